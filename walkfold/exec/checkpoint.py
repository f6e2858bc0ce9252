"""Lineage cuts of loops: reliable checkpoints in the shared folder, old ones deleted.

Plans of loops are made in a session of their own (``Quiet``) that shares the context with the caller's session but does
not adapt plans at run time: only then does a checkpoint know how it is partitioned and sorted. The caller's settings are
never touched, so its other queries are planned as before.
"""

from __future__ import annotations

import uuid
from functools import cache
from types import SimpleNamespace

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Without one, only a local master gets a folder of its own."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where:
        return where.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return "file:///tmp/walkfold"


def ensure_dir(spark: SparkSession) -> None:
    """The context's checkpoint folder, set from the shared one if it has none."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(shared_dir(spark))


class Quiet:
    """A clone of a session without run-time adaptation; data frames move between the two by their logical plans."""

    def __init__(self, spark: SparkSession) -> None:
        self.outer = spark
        self.inner = SparkSession(spark.sparkContext, spark._jsparkSession.cloneSession())
        self.inner.conf.set("spark.sql.adaptive.enabled", "false")
        # what is dealt alike is joined where it lies; only marked sides of a known size are broadcast
        self.inner.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")

    @staticmethod
    def _move(df: DataFrame, to: SparkSession) -> DataFrame:
        made = to._jvm.org.apache.spark.sql.classic.Dataset.ofRows(to._jsparkSession, df._jdf.queryExecution().logical())
        return DataFrame(made, to)

    def take(self, df: DataFrame) -> DataFrame:
        return self._move(df, self.inner)

    def give(self, df: DataFrame) -> DataFrame:
        return self._move(df, self.outer)


def cut(df: DataFrame) -> DataFrame:
    """An eager reliable checkpoint; in a quiet session it keeps the partitioning and order that its plan has."""
    ensure_dir(df.sparkSession)
    return _forgetful(df.checkpoint(eager=True))


#: Beyond this estimate of bytes a checkpoint's size is as good as unknown.
MOST_BYTES = 2**62


@cache
def _classes(jvm) -> SimpleNamespace:
    """What a checkpoint's plan is made of; a name costs a call for each of its parts, so it is looked up once."""
    sql = jvm.org.apache.spark.sql
    return SimpleNamespace(
        none=getattr(getattr(jvm.scala, "None$"), "MODULE$"),
        some=jvm.scala.Some,
        seq=jvm.org.apache.spark.api.python.PythonUtils.toSeq,
        scan=sql.execution.LogicalRDD,
        hashed=sql.catalyst.plans.physical.HashPartitioning,
        order=sql.catalyst.expressions.SortOrder,
        dataset=sql.classic.Dataset,
    )


def _each(seq) -> list:
    return [seq.apply(i) for i in range(seq.size())]


def _forgetful(df: DataFrame) -> DataFrame:
    """A checkpoint without what its plan inherits from the plan before it.

    A join's estimated bytes are the product of its sides'. State that meets itself in each step would double the number's
    digits each time, until the driver does nothing but multiply; the inferred conditions on its columns pile up too.
    Partitioning and order are told in the very columns that the checkpoint shows: a table that is read twice in a plan gets
    new columns, and Spark carries the partitioning over to them only if the old ones are equal to the last detail.
    """
    spark, rdd = df.sparkSession, df._jdf.queryExecution().logical()
    of = _classes(spark._jvm)
    stats = rdd.stats()
    known = of.some(stats) if stats.sizeInBytes() <= MOST_BYTES else of.none
    columns = [c.withQualifier(of.seq([])) for c in _each(rdd.output())]
    shown = {c.exprId().id(): c for c in columns}

    def column(e):
        return shown.get(e.exprId().id()) if e.getClass().getSimpleName() == "AttributeReference" else None

    dealt = rdd.outputPartitioning()
    if dealt.getClass().getSimpleName() == "HashPartitioning":
        by = [column(e) for e in _each(dealt.expressions())]
        if None not in by:
            dealt = of.hashed(of.seq(by), dealt.numPartitions())
    order = []
    for o in _each(rdd.outputOrdering()):
        if (c := column(o.child())) is None:
            break
        order.append(of.order(c, o.direction(), o.nullOrdering(), of.seq([])))
    bare = of.scan(of.seq(columns), rdd.rdd(), dealt, of.seq(order), rdd.isStreaming(), rdd.stream(), spark._jsparkSession, known, of.none)
    return DataFrame(of.dataset.ofRows(spark._jsparkSession, bare), spark)


def written(df: DataFrame, name: str) -> DataFrame:
    """A table in the shared folder: readers get its columns pruned and its statistics, and the lineage ends there."""
    path = f"{shared_dir(df.sparkSession)}/walkfold/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    back = df.sparkSession.read.schema(df.schema).parquet(path)
    back._walkfold_path = path
    return back


def remove(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def drop(df: DataFrame | None) -> None:
    """Delete the files of a checkpoint or written table that nothing reads any more."""
    if df is None:
        return
    spark = df.sparkSession
    try:
        path = getattr(df, "_walkfold_path", None)
        if path is None:
            at = df._jdf.queryExecution().analyzed().rdd().getCheckpointFile()
            path = at.get() if at.isDefined() else None
        if path is not None:
            remove(spark, path)
    except Exception as e:  # a file that stays costs disk, not results
        print(f"walkfold: a checkpoint was not deleted: {str(e)[:200]}")


def shuffled_records(df: DataFrame) -> int:
    """Rows that the exchanges of a finished plan have written, after partial aggregation."""
    total, todo = 0, [df._jdf.queryExecution().executedPlan()]
    while todo:
        node = todo.pop()
        if node.nodeName() == "Exchange":
            found = node.metrics().get("shuffleRecordsWritten")
            total += found.get().value() if found.isDefined() else 0
        under = node.children()
        todo += [under.apply(i) for i in range(under.size())]
    return total
