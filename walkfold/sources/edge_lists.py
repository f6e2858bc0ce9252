"""Edge lists as files, bucketed tables, and dictionaries of vertex names."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

SCHEMA = "src long, dst long, weight long, capacity long"


def _folder(spark: SparkSession) -> str:
    return f"{(spark.conf.get('spark.checkpoint.dir', None) or 'file:///tmp/walkfold-checkpoints').rstrip('/')}/edges-{uuid.uuid4().hex}"


def read(spark: SparkSession, path: str, form: str = "parquet") -> DataFrame:
    """An edge list in parquet, csv or json, or text with blanks between."""
    if form == "text":
        parts = F.split("value", r"\s+")
        return spark.read.text(path).select(*[parts[i].cast("long").alias(n) for i, n in enumerate(("src", "dst", "weight", "capacity"))])
    return spark.read.schema(SCHEMA).format(form).load(path)


def write(edges: DataFrame, path: str, form: str = "parquet") -> None:
    if form == "text":
        edges.select(F.concat_ws(" ", *[F.col(c).cast("string") for c in ("src", "dst", "weight", "capacity")]).alias("value")).write.text(path)
    else:
        edges.write.format(form).save(path)


def write_bucketed(edges: DataFrame, name: str, buckets: int) -> None:
    """A table bucketed and sorted by source: supersteps join it without moving an edge."""
    edges.write.bucketBy(buckets, "src").sortBy("src").mode("overwrite").saveAsTable(name)


def round_trip(edges: DataFrame) -> DataFrame:
    """Through csv, json and text; rows that survive all three."""
    spark, at = edges.sparkSession, edges.select("src", "dst", "weight", "capacity")
    for form in ("csv", "json", "text"):
        path = _folder(spark)
        write(at, path, form)
        at = read(spark, path, form)
    return at


def dictionary(names: DataFrame, column: str) -> DataFrame:
    """Dense numbers of distinct names in their order: ranges are numbered from the sizes of the ranges before."""
    distinct = names.select(column).distinct().repartitionByRange(column).withColumn("_p", F.spark_partition_id())
    from walkfold.exec.checkpoint import cut

    distinct = cut(distinct)
    sizes = distinct.groupBy("_p").agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.select("_p", F.coalesce(F.sum("_n").over(W.orderBy("_p").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_b"))
    rank = F.row_number().over(W.partitionBy("_p").orderBy(column)) - 1
    return distinct.withColumn("_r", rank).join(before, "_p").select(column, (F.col("_b") + F.col("_r")).cast("long").alias("id"))
