"""Unfused versions: each path reduction in a loop of its own; nested ones in two passes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkfold import usecases as U
from walkfold.graphs import Graph


def _tight(graph, source: int, by: str, metrics) -> tuple[DataFrame, Graph]:
    """Distances, and the sub-graph of the edges that lie on shortest paths."""
    first = U.sssp(graph, source, metrics=metrics) if by == "weight" else U.hop_distance(graph, source, metrics=metrics).withColumnRenamed("hops", "dist")
    step = F.col("weight") if by == "weight" else F.lit(1)
    a, b = first.select(F.col("id").alias("src"), F.col("dist").alias("_a")), first.select(F.col("id").alias("dst"), F.col("dist").alias("_b"))
    edges = graph.held().join(a, "src").join(b, "dst").where(F.col("_a") + step == F.col("_b")).select(*graph.edges.columns)
    return first, Graph(edges, graph.held_vertices(), f"{graph.name}_tight")


def widest_shortest(graph, source: int, by: str = "length", metrics=None) -> DataFrame:
    first, tight = _tight(graph, source, by, metrics)
    second = U.widest_path(tight, source, metrics=metrics)
    return first.join(second, "id", "left").select("id", "dist", "cap")


def count_shortest(graph, source: int, by: str = "weight", metrics=None) -> DataFrame:
    first, tight = _tight(graph, source, by, metrics)
    return first.join(U.count_paths(tight, source, metrics=metrics), "id", "left").select("id", "dist", "n")


def narrow_wide_ratio(graph, source: int, metrics=None) -> DataFrame:
    return U.narrow_wide_ratio(graph, source, fused=False, metrics=metrics)


def trust(graph, sources, metrics=None) -> DataFrame:
    return U.trust(graph, sources, fused=False, metrics=metrics)


def radius(graph, sources, metrics=None) -> DataFrame:
    return U.radius(graph, sources, fused=False, metrics=metrics)


def diameter_radius_ratio(graph, sources, metrics=None) -> DataFrame:
    return U.diameter_radius_ratio(graph, sources, fused=False, metrics=metrics)


def radius_trust_floor(graph, source, sources, distance="length", metrics=None) -> DataFrame:
    return U.radius_trust_floor(graph, source, sources, distance, fused=False, metrics=metrics)
