"""Scalar helpers over arrays, maps and JSON that graph users need."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def degree_map(edges: DataFrame) -> DataFrame:
    """One row: out-degree to number of vertices, as a map. The number of distinct degrees is at most the root of twice the edges."""
    hist = edges.groupBy("src").agg(F.count(F.lit(1)).alias("n")).groupBy("n").agg(F.count(F.lit(1)).alias("c"))
    pairs = F.array_sort(F.collect_list(F.struct("n", "c")))
    return hist.agg(F.map_from_arrays(F.transform(pairs, lambda x: x["n"]), F.transform(pairs, lambda x: x["c"])).alias("degrees"))


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: ((x - y) * (x - y)).cast("double")), F.lit(0.0), lambda s, x: s + x)


def edge_properties(props: Column, schema: str = "k INT") -> Column:
    return F.from_json(props, schema)
