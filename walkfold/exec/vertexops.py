"""Maps and reductions over vertices, and the evaluation of fused rounds."""

from __future__ import annotations

from functools import partial, reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from walkfold.exec import blocks, models
from walkfold.exec.metrics import RunMetrics
from walkfold.kernels.codec import shown
from walkfold.spec.terms import BinOp, Factored, Lit, Rounds, Term, TripleLet, UnOp, Var, Vertex
from walkfold.synth.conditions import admit, certificate

_MERGE = {"min": F.least, "max": F.greatest}


def expression(t: Term, env: dict[str, Column]) -> Column:
    """Arithmetic and comparison pass none on; min, max, and, or skip it."""
    if isinstance(t, Lit):
        return F.lit(t.value)
    if isinstance(t, Vertex):
        return F.col("id")
    if isinstance(t, Var):
        return env[t.name]
    if isinstance(t, UnOp):
        a = expression(t.arg, env)
        return -a if t.op == "-" else ~a
    assert isinstance(t, BinOp), t
    a, b = expression(t.left, env), expression(t.right, env)
    if t.op == "if":
        return F.when(a, b)
    if t.op in ("union", "intersect"):
        return F.array_sort((F.array_union if t.op == "union" else F.array_intersect)(a, b))
    if t.op in _MERGE:
        return _MERGE[t.op](a, b)
    if t.op == "and":
        return F.coalesce(a & b, a, b)
    if t.op == "or":
        return F.coalesce(a | b, a, b)
    if t.op == "/":
        return F.try_divide(a.cast("double"), b.cast("double"))
    return {"+": lambda: a + b, "-": lambda: a - b, "*": lambda: a * b, "=": lambda: a == b, "<": lambda: a < b, ">": lambda: a > b, "<=": lambda: a <= b, ">=": lambda: a >= b}[t.op]()


def reduction(r: str, value: Column) -> Column:
    if r == "union":
        return F.array_sort(F.collect_set(value))
    if r == "intersect":  # of singletons: what all have in common
        return F.when(F.min(value) == F.max(value), F.array(F.min(value))).otherwise(F.array().cast("array<bigint>"))
    return {"min": F.min, "max": F.max, "sum": F.sum, "or": F.bool_or, "and": F.bool_and}[r](value)


_RUN = {
    "pull_nonidem": models.pull_nonidem,
    "push_nonidem": models.push_nonidem,
    "rollback": models.push_rollback,
    "front": models.front,
    "async_push": partial(blocks.async_block, direction="push"),
    "async_pull": partial(blocks.async_block, direction="pull"),
    "async_push_sum": partial(blocks.async_sum, direction="push"),
    "async_pull_sum": partial(blocks.async_sum, direction="pull"),
}


def run_loop(graph, loop: tuple[Factored, ...], model: str, metrics: RunMetrics | None, max_iter: int | None) -> DataFrame:
    """id and a column for each factored reduction of the loop. What needs a front of trade-offs runs in a loop of its own."""
    kind = dict(graph.edges.dtypes).get("weight", "bigint")
    parts = tuple(models.Part(f.keys, f.source, "double" if kind in ("double", "float") else "long") for f in loop)
    if len(parts) > 1:
        alone = [i for i, p in enumerate(parts) if certificate(graph, p.keys, p.source).front or model.startswith("async")]
        if alone:
            rest = tuple(f for i, f in enumerate(loop) if i not in alone)
            groups = [(loop[i],) for i in alone] + ([rest] if rest else [])
            return reduce(lambda a, b: a.join(b, "id", "full_outer"), [run_loop(graph, x, model, metrics, max_iter) for x in groups])
    chosen = admit(graph, parts, model)
    if chosen in ("push", "pull", "auto"):
        state = models.push_idem(graph, parts, metrics, max_iter, direction=chosen)
    else:
        state = _RUN[chosen](graph, parts, metrics, max_iter=max_iter)
    columns = []
    for i, (p, f) in enumerate(zip(parts, loop, strict=True)):
        value = F.col(p.names(i)[-1])
        columns.append((shown(value) if p.keys[-1][1] == "capacity" else value).alias(f.name))
        if len(p.keys) > 1:
            first = F.col(p.names(i)[0])
            columns.append((shown(first) if p.keys[0][1] == "capacity" else first).alias(f"{f.name}_first"))
    return state.select("id", *columns)


def solve_triple(graph, t: TripleLet, scalars: dict[str, Column], model: str = "auto", metrics: RunMetrics | None = None, max_iter: int | None = None, keep_firsts: bool = False, extra: DataFrame | None = None) -> DataFrame:
    """m: id and value of every vertex; r: one row with value. ``extra`` is a one-row table with earlier rounds' scalars."""
    states = [run_loop(graph, loop, model, metrics, max_iter) for loop in t.loops]
    rows = reduce(lambda a, b: a.join(b, "id", "full_outer"), states) if states else graph.held_vertices()
    if not t.passes:
        rows = graph.held_vertices().join(rows, "id", "left") if states else rows
    elif not states:
        rows = graph.held_vertices()
    if extra is not None:
        rows = rows.crossJoin(F.broadcast(extra))  # one row
    env = {f.name: F.col(f.name) for loop in t.loops for f in loop} | scalars
    maps = [expression(body, env).alias(name) for name, body in t.maps]
    firsts = [c for c in rows.columns if c.endswith("_first")] if keep_firsts else []
    if not t.passes:
        named = rows.select("id", *maps, *firsts)
        return named.select("id", expression(t.body, {n: F.col(n) for n, _ in t.maps}).alias("value"), *[F.col(c).alias("first") for c in firsts[:1]])
    mapped = rows.select(*maps, *([c for c in extra.columns] if extra is not None else []))
    passes = [mapped.agg(*[reduction(r, F.col(name)).alias(out) for out, r, name in p.items]) for p in t.passes]
    one = reduce(lambda a, b: a.crossJoin(F.broadcast(b)), passes)  # one-row tables
    if extra is not None:
        one = one.crossJoin(F.broadcast(extra))
    env = {out: F.col(f"`{out}`") for p in t.passes for out, _, _ in p.items} | scalars
    return one.select(expression(t.body, env).alias("value"))


def solve_rounds(graph, rounds: Rounds, model: str = "auto", metrics: RunMetrics | None = None, max_iter: int | None = None, keep_firsts: bool = False) -> DataFrame:
    """Rounds in order; a round's scalar is a one-row table that the next ones read."""
    extra, scalars = None, {}
    for name, t in zip(rounds.names, rounds.lets[:-1], strict=True):
        one = models.cut(solve_triple(graph, t, scalars, model, metrics, max_iter, extra=extra).select(F.col("value").alias(name)))
        extra = one if extra is None else extra.crossJoin(F.broadcast(one))
        scalars[name] = F.col(f"`{name}`")
    return solve_triple(graph, rounds.lets[-1], scalars, model, metrics, max_iter, keep_firsts, extra)
