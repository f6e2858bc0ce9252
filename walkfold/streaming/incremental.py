"""Streaming maintenance: arriving edges update the values of a path reduction that is kept as tables.

Inserts, idempotent: each new walk is one more reduced element. New edges are first relaxed alone, from the sources that
have a value; then only what changes moves on, along all edges.
Inserts, sums: on graphs where paths end, counts change by what the new edges bring; differences move on, as in the
model with rollback.
Deletions: values that may rest on a deleted edge (its target, if the edge gave the target's value, and what follows along
edges that give values) are withdrawn, then computed again from the vertices that keep theirs.

Edges are kept in pieces dealt by source, one for each batch, put together when there are many: a batch is dealt, not the
whole graph. With a folder, a batch's edges and the state after it are written under its number; a batch that comes again
is skipped, and a new object goes on from the last batch that was finished.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkfold.exec import models
from walkfold.exec.checkpoint import Quiet, cut, drop
from walkfold.exec.metrics import RunMetrics
from walkfold.graphs import Dealt, Graph
from walkfold.kernels.exprs import edge_columns, to_sql
from walkfold.synth.conditions import Refused, certificate


class _Pieces:
    """What a loop asks of a graph, over edges that grow."""

    MOST = 8

    def __init__(self, spark: SparkSession, used: tuple[str, ...]) -> None:
        self.quiet, self.used = Quiet(spark), used
        self.dealt = Dealt(())

    def add(self, batch: DataFrame) -> None:
        new = cut(self.quiet.take(batch).select("src", "dst", *self.used).repartition("src").sortWithinPartitions("src"))
        self.dealt = Dealt((*self.dealt.lights, new))
        if len(self.dealt.lights) > self.MOST:
            whole = cut(self.dealt.all().repartition("src").sortWithinPartitions("src"))
            self.dealt.drop()
            self.dealt = Dealt((whole,))

    def prepared(self, _: tuple[str, ...]) -> Dealt:
        return self.dealt

    def bounds(self):
        return None

    def order(self) -> int:
        return 2**62  # batches always reach their fixed point: the reduction was admitted

    def held_vertices(self) -> DataFrame:
        ends = self.quiet.give(self.dealt.all().selectExpr("explode(array(src, dst)) AS id"))
        return ends.distinct()


class Maintained:
    """The state of one path reduction under edge arrivals and deletions."""

    def __init__(self, spark: SparkSession, reduce: str, fn: str, source: int | None, folder: str | None = None) -> None:
        self.spark, self.part, self.folder = spark, models.Part(((reduce, fn),), source), folder
        if not self.part.idempotent and (fn != "one" or source is None):
            raise Refused(f"streaming sums count the paths from a source; not {reduce} of {fn}")
        self.metrics = RunMetrics()
        (self.prop,) = self.part.extends()
        self.used = tuple(sorted(edge_columns(self.prop) - {"src", "dst"}))
        self.graph = _Pieces(spark, self.used)
        self.loop: models.Loop | None = None
        self.edges: DataFrame | None = None  # all columns, for deletions and checks
        self.last = -1
        if folder is not None:
            self._recover()

    @property
    def edges_processed(self) -> int:
        return self.metrics.edges_processed

    # -- batches

    def insert(self, batch: DataFrame, number: int | None = None) -> None:
        """Add edges (src, dst, weight, capacity) and relax until nothing changes. A batch number seen before is skipped."""
        if number is not None and number <= self.last:
            return
        batch = cut(batch)
        edges = batch if self.edges is None else cut(self.edges.unionByName(batch))
        self._admit(edges)
        if self.edges is not None:
            drop(self.edges)
        self.edges = edges
        self.graph.add(batch)
        if self.loop is None:
            self._start()
            self._relax()
        else:
            self.loop.see_edges()
            self._meet(batch)
        if number is not None:
            self.last = number
            self._save(batch, number)
        drop(batch if batch is not edges else None)

    def _admit(self, edges: DataFrame) -> None:
        graph = Graph(edges)
        certificate(graph, self.part.keys, self.part.source)

    def _start(self) -> None:
        if self.part.idempotent:
            self.loop = models.Loop(self.graph, (self.part,), self.metrics)
            self.loop.first(self._starts())
        else:
            self.loop = models.rollback_loop(self.graph, (self.part,), self.metrics, starts=self._starts())

    def _starts(self) -> DataFrame:
        """The starts of the vertices so far; a named source has its value from the first batch on."""
        ids = self.graph.held_vertices() if self.part.source is None else self.spark.range(self.part.source, self.part.source + 1).select("id")
        return models.initial(ids, (self.part,))

    def _relax(self) -> None:
        if self.part.idempotent:
            models.relax(self.loop)
        else:
            while models.rollback_step(self.loop, (self.part,), self.loop.frontier()):
                pass

    def _meet(self, batch: DataFrame) -> None:
        """The new edges alone, from sources with a value; then whatever that changed."""
        loop, new = self.loop, self.loop.lights[-1]
        if self.part.source is None:  # vertices that were not there yet start with their own value
            starts = loop.view("fresh", loop.quiet.take(models.initial(batch.selectExpr("explode(array(src, dst)) AS id").distinct(), (self.part,))))
            loop.step(f"SELECT id AS dst, {loop.cols()} FROM {starts}", "sum(0)", lambda sent: loop.improved(f"SELECT * FROM {sent}"), "start")
        if self.part.idempotent:
            text = f"SELECT e.dst, {', '.join(models.messages(loop.parts))} FROM ({loop.state()}) r JOIN {new} e ON r.id = e.src"
            changed = loop.step(text, models.ROWS, lambda sent: loop.improved(models.reduced(sent, loop.parts)), "push")
        else:
            rows = f"SELECT id, s0_0, CAST(NULL AS {models.DECIMAL}) AS p_s0_0 FROM ({loop.state()})"
            changed = models.rollback_step(loop, (self.part,), rows, pieces=[new])
        if changed:
            self._relax()

    # -- deletions

    def delete(self, gone: DataFrame) -> None:
        """Remove edges (src, dst). A sum, and a graph without edges left, is computed anew."""
        gone = cut(gone.select("src", "dst").distinct())
        kept = cut(self.edges.join(gone, ["src", "dst"], "left_anti"))
        if not self.part.idempotent or not kept.limit(1).count():
            self._reset(kept)
            return
        loop, quiet = self.loop, self.graph.quiet
        state = cut(loop.sql(f"SELECT id, s0_0 FROM ({loop.state()})"))
        values, out = loop.view("values", state), loop.view("gone", quiet.take(gone))
        edges = loop.view("every", quiet.take(self.edges))
        step = to_sql(self.prop, {"n": "a.s0_0"})
        # the edges that give their target its value
        tight = cut(loop.sql(f"SELECT e.src, e.dst FROM {edges} e JOIN {values} a ON e.src = a.id JOIN {values} b ON e.dst = b.id WHERE {step} <=> b.s0_0"))
        gives = loop.view("tight", tight)
        doubt = cut(loop.sql(f"SELECT DISTINCT t.dst AS id FROM {gives} t LEFT SEMI JOIN {out} g ON t.src = g.src AND t.dst = g.dst"))
        front = doubt
        while front.limit(1).count():
            seen, now = loop.view("doubt", doubt), loop.view("front", front)
            nexts = cut(loop.sql(f"SELECT DISTINCT t.dst AS id FROM {gives} t LEFT SEMI JOIN {now} f ON t.src = f.id LEFT ANTI JOIN {seen} d ON t.dst = d.id"))
            whole = cut(doubt.unionByName(nexts))
            if front is not doubt:
                drop(front)
            drop(doubt)
            doubt, front = whole, nexts
        lost = loop.view("doubt", doubt)
        starts = loop.view("starts", loop.quiet.take(self._starts()))
        rest = f"SELECT id, s0_0 FROM {values} v LEFT ANTI JOIN {lost} d ON v.id = d.id UNION ALL SELECT s.id, s.s0_0 FROM {starts} s LEFT SEMI JOIN {lost} d ON s.id = d.id"
        # what keeps its value and has an edge into what lost it sends again
        sends = f"SELECT DISTINCT e.src AS id FROM {edges} e LEFT SEMI JOIN {lost} d ON e.dst = d.id"
        rows = cut(loop.sql(f"SELECT r.id, r.s0_0, s.id IS NOT NULL AS changed FROM ({rest}) r LEFT JOIN ({sends}) s ON r.id = s.id"))
        self._reset(kept, quiet.give(rows))
        for x in (state, tight, doubt, rows):
            drop(x)

    def _reset(self, kept: DataFrame, rows: DataFrame | None = None) -> None:
        """All edges anew, and the state from the start or from these rows."""
        if self.loop is not None:
            self.loop.result()
        self.graph.dealt.drop()
        self.graph = _Pieces(self.spark, self.used)
        self.edges, self.loop = kept, None
        self.graph.add(kept)
        if rows is None:
            self._start()
        else:
            self.loop = models.Loop(self.graph, (self.part,), self.metrics)
            self.loop.first(rows)
        self._relax()

    # -- the folder

    def _save(self, batch: DataFrame, number: int) -> None:
        if self.folder is None:
            return
        batch.write.mode("overwrite").parquet(f"{self.folder}/edges/batch={number}")
        self.values().write.mode("overwrite").parquet(f"{self.folder}/state/batch={number}")  # its _SUCCESS file ends the batch

    def _recover(self) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/state")
        files = path.getFileSystem(self.spark._jsc.hadoopConfiguration())
        done = files.globStatus(self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/state/batch=*/_SUCCESS")) or []
        numbers = [int(x.getPath().getParent().getName().partition("=")[2]) for x in done]
        if not numbers:
            return
        self.last = max(numbers)
        edges = self.spark.read.option("basePath", f"{self.folder}/edges").parquet(f"{self.folder}/edges").where(F.col("batch") <= self.last).drop("batch")
        rows = self.spark.read.parquet(f"{self.folder}/state/batch={self.last}").withColumnRenamed("value", "s0_0")
        rows = rows.withColumn("s0_0", F.col("s0_0").cast(self.part.kinds()[0]))
        if not self.part.idempotent:
            rows = rows.withColumn("p_s0_0", F.col("s0_0"))
        self.edges = cut(edges)
        self.graph.add(self.edges)
        if self.part.idempotent:
            self.loop = models.Loop(self.graph, (self.part,), self.metrics)
        else:
            self.loop = models.rollback_loop(self.graph, (self.part,), self.metrics, starts=rows.drop("p_s0_0"))
        self.loop.first(rows.withColumn("changed", F.lit(False)))

    def values(self) -> DataFrame:
        """id and value after the last batch, as a table of its own."""
        out = cut(self.loop.sql(f"SELECT id, s0_0 AS value FROM ({self.loop.state()}) WHERE s0_0 IS NOT NULL"))
        return self.graph.quiet.give(out)


def maintain(stream: DataFrame, kept: Maintained, checkpoint: str):
    """A streaming query that feeds each micro-batch of edges to ``kept``, under its number."""

    def apply(batch: DataFrame, number: int) -> None:
        if batch.limit(1).count():
            kept.insert(batch, number)

    return stream.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def late_rows(query) -> int:
    """How many rows a streaming query's watermark has dropped so far, from its progress reports."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in p.get("stateOperators", []))
