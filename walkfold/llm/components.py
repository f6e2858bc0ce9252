"""Connected components of an edge table, by alternating large and small stars.

Each round sends every node's neighbours to the smallest of them; a hub's rows are only
aggregated (partial sums first) and joined, never gathered. Rounds are written to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkfold.llm.common import cut


def _star(edges: DataFrame, small: bool) -> DataFrame:
    both = edges if small else edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    # small: b < a, so a's neighbours are its smaller ones
    least = both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("m", "a"))
    joined = both.join(least, "a")
    if small:
        out = joined.where("b != m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.where("a != m").select("a", F.col("m").alias("b")))
    else:
        out = joined.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return out.distinct()


def components(edges: DataFrame, a: str, b: str, most_rounds: int = 60) -> DataFrame:
    """node, root (the smallest node of its component) of every node with an edge to another one."""
    now = cut(edges.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).where("a != b").distinct(), "edges")
    said = None
    for _ in range(most_rounds):
        now = cut(_star(_star(now, small=False), small=True), "edges")
        state = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state == said:
            break
        said = state
    else:
        raise RuntimeError(f"components: not stable after {most_rounds} rounds")
    roots = now.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())
