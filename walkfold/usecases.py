"""The analyses: each states its specification; ``solve`` fuses it, admits it and runs it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkfold.exec import models
from walkfold.exec.metrics import RunMetrics
from walkfold.exec.vertexops import solve_rounds
from walkfold.fuse.engine import fuse
from walkfold.kernels.library import Kernels, page_rank as page_rank_kernels
from walkfold.spec.terms import ArgPath, ArgsPaths, BinOp, Card, Lit, OverSources, PathReduce, Paths, SourcePaths, Term, Vertex, VertexReduce
from walkfold.spec.types import typecheck
from walkfold.kernels.exprs import to_column
from walkfold.synth.conditions import admit_kernels

# -- specifications ------------------------------------------------------------------------------------------------


def spec_reduce(r: str, f: str, source: int | None = None) -> Term:
    return PathReduce(r, f, Paths(source))


def spec_wsp(source: int, by: str = "length") -> Term:
    return PathReduce("max", "capacity", ArgsPaths("min", by, Paths(source)))


def spec_swp(source: int, by: str = "weight") -> Term:
    """The shortest of the widest paths: its tuple does not distribute, so it runs on fronts of trade-offs."""
    return PathReduce("min", by, ArgsPaths("max", "capacity", Paths(source)))


def spec_nsp(source: int, by: str = "weight") -> Term:
    return Card(ArgsPaths("min", by, Paths(source)))


def spec_nwr(source: int) -> Term:
    return BinOp("/", spec_reduce("min", "capacity", source), spec_reduce("max", "capacity", source))


def spec_bfs(source: int) -> Term:
    return ArgPath("min", "length", "penult", Paths(source))


def spec_trust(sources: tuple[int, ...]) -> Term:
    p = SourcePaths("s")
    return OverSources("max", "s", sources, BinOp("/", PathReduce("max", "capacity", p), PathReduce("min", "length", p)))


def spec_eccentricity(source: int) -> Term:
    return VertexReduce("max", spec_reduce("min", "length", source))


def _over(r: str, sources: tuple[int, ...]) -> Term:
    return OverSources(r, "s", sources, VertexReduce("max", PathReduce("min", "length", SourcePaths("s"))))


def spec_radius(sources: tuple[int, ...]) -> Term:
    return _over("min", sources)


def spec_diameter(sources: tuple[int, ...]) -> Term:
    return _over("max", sources)


def spec_drr(sources: tuple[int, ...]) -> Term:
    return BinOp("/", _over("max", sources), _over("min", sources))


def spec_distant(source: int, bound: int = 7, op: str = ">", by: str = "weight") -> Term:
    return VertexReduce("union", Vertex(), where=BinOp(op, spec_reduce("min", by, source), Lit(bound)))


def spec_rds(source: int, sources: tuple[int, ...], distance: str = "length") -> Term:
    near = BinOp("<", spec_reduce("min", distance, source), spec_radius(sources))
    return VertexReduce("min", spec_reduce("max", "capacity", source), where=near)


# -- running -------------------------------------------------------------------------------------------------------


def solve(graph, spec: Term, model: str = "auto", fused: bool = True, metrics: RunMetrics | None = None, disable=(), max_iter: int | None = None, keep_firsts: bool = False) -> DataFrame:
    """Check the types, fuse, admit, run. ``fused=False`` runs each path reduction in a loop of its own."""
    typecheck(spec, set(graph.edges.columns))
    off = set(disable) | (set() if fused else {"pair_paths", "pair_vertex_reductions", "share_common"})
    rounds, _ = fuse(spec, off)
    return solve_rounds(graph, rounds, model, metrics, max_iter, keep_firsts)


def _named(df: DataFrame, name: str) -> DataFrame:
    return df.select("id", F.col("value").alias(name))


def sssp(graph, source: int, **how) -> DataFrame:
    return _named(solve(graph, spec_reduce("min", "weight", source), **how), "dist")


def hop_distance(graph, source: int, **how) -> DataFrame:
    return _named(solve(graph, spec_reduce("min", "length", source), **how), "hops")


def connected_components(graph, **how) -> DataFrame:
    return _named(solve(graph, spec_reduce("min", "head"), **how), "component")


def bfs_tree(graph, source: int, **how) -> DataFrame:
    out = solve(graph, spec_bfs(source), keep_firsts=True, **how)
    return out.select("id", F.col("first").alias("hops"), F.col("value").alias("parent"))


def widest_path(graph, source: int, **how) -> DataFrame:
    return _named(solve(graph, spec_reduce("max", "capacity", source), **how), "cap")


def narrowest_path(graph, source: int, **how) -> DataFrame:
    return _named(solve(graph, spec_reduce("min", "capacity", source), **how), "cap")


def widest_shortest(graph, source: int, by: str = "length", **how) -> DataFrame:
    out = solve(graph, spec_wsp(source, by), keep_firsts=True, **how)
    return out.select("id", F.col("first").alias("dist"), F.col("value").alias("cap"))


def shortest_widest(graph, source: int, by: str = "weight", **how) -> DataFrame:
    out = solve(graph, spec_swp(source, by), keep_firsts=True, **how)
    return out.select("id", F.col("first").alias("cap"), F.col("value").alias("dist"))


def count_shortest(graph, source: int, by: str = "weight", **how) -> DataFrame:
    out = solve(graph, spec_nsp(source, by), keep_firsts=True, **how)
    return out.select("id", F.col("first").alias("dist"), F.col("value").alias("n"))


def narrow_wide_ratio(graph, source: int, **how) -> DataFrame:
    return _named(solve(graph, spec_nwr(source), **how), "ratio")


def trust(graph, sources, **how) -> DataFrame:
    return _named(solve(graph, spec_trust(tuple(sources)), **how), "trust")


def eccentricity(graph, source: int, **how) -> DataFrame:
    return solve(graph, spec_eccentricity(source), **how)


def radius(graph, sources, **how) -> DataFrame:
    return solve(graph, spec_radius(tuple(sources)), **how)


def diameter(graph, sources, **how) -> DataFrame:
    return solve(graph, spec_diameter(tuple(sources)), **how)


def diameter_radius_ratio(graph, sources, **how) -> DataFrame:
    return solve(graph, spec_drr(tuple(sources)), **how)


def distant_set(graph, source: int, bound: int = 7, op: str = ">", **how) -> DataFrame:
    return solve(graph, spec_distant(source, bound, op), **how)


def distant_members(graph, source: int, bound: int = 7, op: str = ">", by: str = "weight", **how) -> DataFrame:
    """The same set as rows (id): the comparison is a map over vertices, and nothing is gathered."""
    far = solve(graph, BinOp(op, spec_reduce("min", by, source), Lit(bound)), **how)
    return far.where("value").select("id")


def radius_trust_floor(graph, source: int, sources, distance: str = "length", **how) -> DataFrame:
    return solve(graph, spec_rds(source, tuple(sources), distance), **how)


def reachable(graph, source: int, **how) -> DataFrame:
    return _named(solve(graph, spec_reduce("or", "true", source), **how), "reached")


def all_paths(graph, source: int, predicate: str = "weight>1", **how) -> DataFrame:
    """Whether every path to a vertex has only edges for which a comparison of weight or capacity holds."""
    return _named(solve(graph, spec_reduce("and", f"all:{predicate}", source), **how), "ok")


def all_paths_heavy(graph, source: int, **how) -> DataFrame:
    return all_paths(graph, source, **how)


def count_paths(graph, source: int, **how) -> DataFrame:
    return _named(solve(graph, spec_reduce("sum", "one", source), **how), "n")


def longest_path(graph, source: int | None = None, by: str = "length", **how) -> DataFrame:
    return _named(solve(graph, spec_reduce("max", by, source), **how), "len")


def page_rank(graph, gamma: float = 0.85, tol: float | None = None, iters: int = 20, dangling: str = "drop", model: str = "pull", metrics=None) -> DataFrame:
    out = models.fixed_point(graph, page_rank_kernels(gamma), model, iters, tol, metrics, dangling)
    return out.select("id", F.col("value").alias("rank"))


def run_kernels(graph, kernels: Kernels, model: str = "pull", iters: int = 20, tol: float | None = None, metrics: RunMetrics | None = None) -> DataFrame:
    """Kernels without a specification: id, value.

    A sum runs its epilogue for a number of rounds (or until it moves by no more than ``tol``). Any other reduction runs
    to its fixed point, by push, pull or both, after its kernels were checked: the reduction's laws, and that propagation
    distributes over it. Whether it stops is the caller's statement; a run that goes on after |V| + 1 steps is ended.
    """
    if kernels.reduce == "sum":
        return models.fixed_point(graph, kernels, model, iters, tol, metrics)
    admit_kernels(kernels)
    part = models.Part(((kernels.reduce, "value"),), hand=kernels)
    out = models.push_idem(graph, (part,), metrics, direction="auto" if model == "auto_switch" else model if model in ("push", "pull") else "push")
    return out.select("id", to_column(kernels.epilogue, {"n": F.col("s0_0")}).alias("value"))
