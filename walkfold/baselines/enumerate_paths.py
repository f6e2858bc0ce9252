"""Explicit enumeration of walks by a recursive query: exponential, for tiny graphs and as an oracle."""

from __future__ import annotations

from pyspark.sql import DataFrame


def walks(graph, source: int, most_edges: int) -> DataFrame:
    """v, len, weight, cap of every walk of at most ``most_edges`` edges from a source."""
    spark = graph.edges.sparkSession
    graph.edges.createOrReplaceTempView("walkfold_edges")
    return spark.sql(f"""
      WITH RECURSIVE w(v, len, weight, cap) AS (
        SELECT CAST({source} AS BIGINT), CAST(0 AS BIGINT), CAST(0 AS BIGINT), CAST({2**63 - 1} AS BIGINT)
        UNION ALL
        SELECT e.dst, w.len + 1, w.weight + e.weight, least(w.cap, e.capacity) FROM w JOIN walkfold_edges e ON e.src = w.v WHERE w.len < {most_edges})
      SELECT v, len, weight, cap FROM w""")


def sssp(graph, source: int, most_edges: int) -> DataFrame:
    found = walks(graph, source, most_edges).groupBy("v").agg({"weight": "min"}).toDF("id", "dist")
    return graph.held_vertices().join(found, "id", "left").select("id", "dist")
