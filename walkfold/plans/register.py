"""The SQL surface: graphs as views, path reductions as views, walks as a table function."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from walkfold import usecases as U
from walkfold.spec.parser import parse
from walkfold.spec.terms import PathReduce, Paths


def register(spark: SparkSession, graph, prefix: str = "") -> None:
    """Views <prefix>edges and <prefix>vertices, and the table function expand_paths."""
    graph.edges.createOrReplaceTempView(f"{prefix}edges")
    graph.held_vertices().createOrReplaceTempView(f"{prefix}vertices")
    spark.udtf.register("expand_paths", expand_paths)


def path_reduce(graph, reduce: str, fn: str, source: int | None, view: str) -> DataFrame:
    """The result of a path reduction as a view of that name."""
    out = U.solve(graph, PathReduce(reduce, fn, Paths(source)))
    out.createOrReplaceTempView(view)
    return out


def solve_text(graph, text: str, view: str | None = None, **how) -> DataFrame:
    """A specification in text form, run; its result as a view if a name is given."""
    out = U.solve(graph, parse(text), **how)
    if view:
        out.createOrReplaceTempView(view)
    return out


@udtf(returnType="end: bigint, length: int, walk: array<bigint>")
class expand_paths:  # noqa: N801 - an SQL function's name
    """All walks of at most ``most`` edges from a source over an edge list 'a>b,c>d'; for tiny graphs."""

    def eval(self, edges: str, source: int, most: int):
        pairs = [tuple(map(int, e.split(">"))) for e in edges.split(",") if e]
        walks = [[source]]
        while walks:
            for w in walks:
                yield w[-1], len(w) - 1, w
            walks = [[*w, b] for w in walks if len(w) <= most for a, b in pairs if a == w[-1]]
