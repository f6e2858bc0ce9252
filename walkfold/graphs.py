"""Graphs as DataFrames, their builders on the given tables, and graph preparation."""

from __future__ import annotations

import weakref
from dataclasses import dataclass
from functools import reduce

from pyspark import SparkContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkfold.exec import onetask
from walkfold.exec.checkpoint import Quiet, cut, drop, written
from walkfold.exec.nearest import nearest


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Loops deal a graph into one partition for each so many of its edges or vertices, up to the session's number.
PART_ROWS = 20_000

#: A dealt edge's column with the number of edges that have its target; loops that pull read it.
INTO = "_into"

#: A source is a hub if it has over a fourth of an even partition's edges, and over this many: its edges are then dealt apart.
HUB_LEAST = 1_000


@dataclass
class Dealt:
    """Edges as a loop reads them: those of light sources dealt and sorted by src, those of hubs dealt by dst.

    There are fewer than four hubs for each partition, so ``hubs`` and any one value for each of them can be broadcast.
    """

    lights: tuple[DataFrame, ...]
    heavy: DataFrame | None = None
    hubs: DataFrame | None = None

    @property
    def columns(self) -> list[str]:
        return self.lights[0].columns

    def all(self) -> DataFrame:
        return reduce(DataFrame.unionByName, [*self.lights, *([self.heavy] if self.heavy is not None else [])])

    def along(self, rows: DataFrame) -> DataFrame:
        """Rows (id, ...) of the quiet session joined to their outgoing edges."""
        leave = F.col("id") == F.col("src")
        parts = [rows.join(e, leave) for e in self.lights]
        if self.heavy is not None:
            few = rows.join(F.broadcast(self.hubs), leave, "left_semi")
            parts.append(F.broadcast(few).join(self.heavy, leave))
        return reduce(DataFrame.unionByName, parts)

    def drop(self) -> None:
        for df in (*self.lights, self.heavy, self.hubs):
            drop(df)


class Graph:
    """Edges (src, dst, weight, capacity) and vertices (id). A graph is directed; ``symmetrise`` gives both ways.

    The edge plan is run once, when a loop first needs it, and kept as a table in the shared folder; that table and what
    is dealt from it are deleted when the graph is no longer used. Results rest on vertices and final states alone.
    """

    def __init__(self, edges: DataFrame, vertices: DataFrame | None = None, name: str = "graph", hub_least: int = HUB_LEAST) -> None:
        missing = {"src", "dst"} - set(edges.columns)
        if missing:
            raise ValueError(f"an edge table needs {', '.join(sorted(missing))}")
        self.edges, self.name, self.hub_least = edges, name, hub_least
        ids = edges.select(F.col("src").alias("id")).unionByName(edges.select(F.col("dst").alias("id")))
        self._own_vertices = vertices is None
        self.vertices = vertices if vertices is not None else ids.distinct()
        self.quiet = Quiet(edges.sparkSession)
        self._held: DataFrame | None = None
        self._prepared: dict[tuple[str, ...], Dealt] = {}
        self._numbers: dict[object, object] = {}
        self._vertices_cut = self._fitted = False
        self._files: list = []
        weakref.finalize(self, _drop_all, self._files)

    def held(self) -> DataFrame:
        """The edges as a written table."""
        if self._held is None:
            self._held = written(self.edges, "edges")
            self._files.append(self._held)
        return self._held

    def held_vertices(self) -> DataFrame:
        if not self._vertices_cut:
            if self._own_vertices:
                e = self.held()
                self.vertices = e.select(F.col("src").alias("id")).unionByName(e.select(F.col("dst").alias("id"))).distinct()
            self.vertices, self._vertices_cut = cut(self.vertices), True
        return self.vertices

    def prepared(self, columns: tuple[str, ...] = ()) -> Dealt:
        """src, dst and what the kernels read, dealt by src once: a step shuffles its frontier and never the edges."""
        if columns not in self._prepared:
            self._fit()
            degrees = {"outdeg", "indeg", "order", INTO}
            lacking = set(columns) - set(self.edges.columns) - degrees
            if lacking:
                raise ValueError(f"the edges of {self.name} have no {', '.join(sorted(lacking))}")
            edges = self.quiet.take(self.held()).select("src", "dst", *[c for c in columns if c not in degrees])
            if "indeg" in columns:
                edges = edges.join(edges.groupBy("dst").agg(F.count(F.lit(1)).alias("indeg")), "dst")
            if "outdeg" in columns:
                edges = edges.join(edges.groupBy("src").agg(F.count(F.lit(1)).alias("outdeg")), "src")
            if "order" in columns:
                edges = edges.withColumn("order", F.lit(float(self.order())))
            if INTO in columns:  # edges without a target count as having the same one
                into = edges.where("dst IS NOT NULL").groupBy("dst").agg(F.count(F.lit(1)).alias(INTO))
                edges = edges.join(into, "dst", "left").fillna(self._measured()["open"], [INTO])
            edges = edges.select("src", "dst", *columns)
            parts = int(self.quiet.inner.conf.get("spark.sql.shuffle.partitions"))
            most = max(self.hub_least, self.size() // (4 * parts))
            hubs = cut(edges.groupBy("src").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > most).select("src"))
            if hubs.limit(1).count():
                few = F.broadcast(hubs)  # under 4 rows for each partition
                light, heavy = edges.join(few, "src", "left_anti"), cut(edges.join(few, "src", "left_semi").repartition("dst"))
                dealt = Dealt((cut(light.repartition("src").sortWithinPartitions("src")),), heavy, hubs)
            else:
                drop(hubs)
                dealt = Dealt((cut(edges.repartition("src").sortWithinPartitions("src")),))
            self._prepared[columns] = dealt
            self._files.append(dealt)
        return self._prepared[columns]

    def _fit(self) -> None:
        """A step over few rows costs what its tasks cost to start, so a small graph is dealt into few partitions."""
        if not self._fitted:
            rows = self.size() if self._own_vertices else max(self.size(), self.order())
            most = int(self.quiet.inner.conf.get("spark.sql.shuffle.partitions"))
            self.quiet.inner.conf.set("spark.sql.shuffle.partitions", str(min(most, 2 + rows // PART_ROWS)))
            self._fitted = True

    def order(self) -> int:
        if "order" not in self._numbers:
            self._numbers["order"] = self.held_vertices().count()
        return self._numbers["order"]

    def _measured(self) -> dict:
        """Size, least and greatest values: one pass over the held edges."""
        if "measured" not in self._numbers:
            wanted = [c for c in ("weight", "capacity") if c in self.edges.columns]
            ends = [F.max(F.greatest("src", "dst")).alias("id"), F.min(F.least("src", "dst")).alias("low"), F.count(F.lit(1)).alias("n"), F.count_if(F.col("dst").isNull()).alias("open")]
            self._numbers["measured"] = self.held().agg(*[F.min(c).alias(f"lo_{c}") for c in wanted], *[F.max(c).alias(f"hi_{c}") for c in wanted], *ends).first().asDict()
        return self._numbers["measured"]

    def size(self) -> int:
        return self._measured()["n"]

    def bounds(self) -> tuple[int, int] | None:
        """Greatest path weight and greatest code of a second key; none if they cannot be told."""
        if "bounds" not in self._numbers:
            got = self._measured()
            low = [v for k, v in got.items() if k == "low" or k.startswith("lo_")]
            whole = all(isinstance(x, int) and x >= 0 for x in low)
            n = self.order() if whole else 0
            self._numbers["bounds"] = (max(n, n * max(got.get("hi_weight") or 0, 1)), max(got["id"], got.get("hi_capacity") or 0)) if whole else None
        return self._numbers["bounds"]

    def least_weight(self):
        return self._measured().get("lo_weight")

    def _peels(self, left: DataFrame) -> bool:
        """Whether peeling vertices without incoming edges, round by round, leaves no edge."""
        n, now = left.count(), None
        if n <= onetask.MOST:
            return onetask.peels(left)
        while n:
            ends = left.select(F.col("dst").alias("src")).distinct()
            rest = cut(left.join(ends, "src", "left_semi"))
            m = rest.count()
            drop(now)
            if m == n:
                drop(rest)
                return False
            left, now, n = rest, rest, m
        drop(now)
        return True

    def is_acyclic(self) -> bool:
        if "acyclic" not in self._numbers:
            self._numbers["acyclic"] = self._peels(self.held().select("src", "dst"))
        return self._numbers["acyclic"]

    def _reached(self, source: int) -> DataFrame:
        """The edges that leave what the source reaches, itself included."""
        key = ("reached", source)
        if key not in self._numbers:
            from walkfold.exec import models

            ids = models.push_idem(self, (models.Part((("or", "true"),), source),)).select(F.col("id").alias("src"))
            found = cut(self.held().select("src", "dst").join(ids, "src", "left_semi"))
            self._files.append(found)
            self._numbers[key] = found
        return self._numbers[key]

    def source_on_cycle(self, source: int) -> bool:
        """Whether a path leads from the source back to it."""
        return not self._numbers.get("acyclic", False) and bool(self._reached(source).where(F.col("dst") == source).limit(1).count())

    def acyclic_from(self, source: int) -> bool:
        """Whether only finitely many paths start at the source: what it reaches has no cycle."""
        key = ("acyclic", source)
        if key not in self._numbers:
            self._numbers[key] = self._numbers.get("acyclic", False) or self._peels(self._reached(source))
        return self._numbers[key]


def _drop_all(files: list) -> None:
    """Called when a graph is garbage, or at the end of the program, when the context may be gone."""
    if SparkContext._active_spark_context is None:
        return
    for x in files:
        x.drop() if isinstance(x, Dealt) else drop(x)


# -- preparation ---------------------------------------------------------------------------------------------------


def symmetrise(edges: DataFrame) -> DataFrame:
    """Both directions, each edge once."""
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *[c for c in edges.columns if c not in ("src", "dst")])
    return edges.unionByName(back).distinct()


def drop_self_loops(edges: DataFrame) -> DataFrame:
    return edges.where("src != dst")


def merge_parallel(edges: DataFrame) -> DataFrame:
    """One edge for each pair: least weight, greatest capacity."""
    return edges.groupBy("src", "dst").agg(F.min("weight").alias("weight"), F.max("capacity").alias("capacity"))


def reverse(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *[c for c in edges.columns if c not in ("src", "dst")])


def induced(edges: DataFrame, keep: Column) -> DataFrame:
    """Edges whose two ends satisfy ``keep``, a condition on id."""
    ends = edges.select(F.col("src").alias("id")).unionByName(edges.select(F.col("dst").alias("id"))).distinct().where(keep)
    return edges.join(ends.withColumnRenamed("id", "src"), "src", "left_semi").join(ends.withColumnRenamed("id", "dst"), "dst", "left_semi")


def unit(graph: Graph) -> Graph:
    """The unweighted variant: weight and capacity are 1."""
    made = Graph(graph.held().select("src", "dst", F.lit(1).cast("long").alias("weight"), F.lit(1).cast("long").alias("capacity")), graph.held_vertices(), f"{graph.name}_unit")
    made.rests_on = graph  # whose table must stay until this one's is written
    return made


def top_sources(graph: Graph, k: int) -> list[int]:
    """The k vertices with the most outgoing edges, ties by smaller id; k is a small parameter."""
    rows = graph.held().groupBy("src").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "src").limit(k).collect()
    return [r["src"] for r in rows]


# -- builders ------------------------------------------------------------------------------------------------------


def part_hop(spark: SparkSession, sf_dir: str) -> Graph:
    """Part to the part on the next line of the same order, returned lines only."""
    line = table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'").select("l_orderkey", "l_linenumber", "l_partkey", "l_quantity")
    a = line.select("l_orderkey", (F.col("l_linenumber") + 1).alias("l_linenumber"), F.col("l_partkey").alias("src")).distinct()
    b = line.select("l_orderkey", "l_linenumber", F.col("l_partkey").alias("dst"), F.col("l_quantity").cast("long").alias("q"))
    pairs = a.join(b, ["l_orderkey", "l_linenumber"]).where("src != dst")
    return Graph(pairs.groupBy("src", "dst").agg(F.min("q").alias("weight"), F.max("q").alias("capacity")), name="part_hop")


def nation_trade(spark: SparkSession, sf_dir: str) -> Graph:
    """Supplier nation to customer nation, the two with most lines for each source."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    customer = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").cast("long").alias("dst"))
    supplier = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").cast("long").alias("src"))
    flow = line.join(supplier, "l_suppkey").join(orders, "l_orderkey").join(customer, "o_custkey").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight"), F.sum("l_quantity").cast("long").alias("capacity"))
    rank = F.row_number().over(W.partitionBy("src").orderBy(F.desc("weight"), "dst"))
    return Graph(flow.withColumn("_r", rank).where("_r <= 2").drop("_r"), name="nation_trade")


def cust_supp(spark: SparkSession, sf_dir: str) -> Graph:
    """Customers and suppliers (offset 10^9) of large returned lines, both directions."""
    line = table(spark, sf_dir, "lineitem").where("l_returnflag = 'R' AND l_quantity >= 49").select("l_orderkey", (F.col("l_suppkey") + 1_000_000_000).alias("dst"), F.col("l_quantity").cast("long").alias("q"))
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("src"))
    one_way = line.join(orders, "l_orderkey").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight"), F.max("q").alias("capacity"))
    return Graph(symmetrise(one_way), name="cust_supp")


def relay_edges(events: DataFrame) -> DataFrame:
    """Purchaser to the next purchaser in time: one row for each purchase but the last. A global order is part of the definition: purchases are ranked by day first."""
    buys = events.where("event_type = 'purchase'").select("event_id", F.unix_micros(F.to_timestamp("ts")).alias("us"), "user_id", "value")
    day = F.expr("us div 86400000000")
    inside = W.partitionBy("_day").orderBy("us", "event_id")
    rows = buys.withColumn("_day", day)
    # within a day by window; across days each day's last purchase meets the first of the next day that has one
    nexts = rows.select("*", F.lead("user_id").over(inside).alias("_u"), F.lead("us").over(inside).alias("_t"))
    first = rows.groupBy("_day").agg(F.min(F.struct("us", "event_id", "user_id")).alias("_f"))
    first = first.select("_day", "_f", F.lead("_f").over(W.orderBy("_day")).alias("_n")).select("_day", F.col("_n.user_id").alias("_nu"), F.col("_n.us").alias("_nt"))
    nexts = nexts.join(first, "_day")
    minute = F.expr("us div 60000000")
    t = F.coalesce("_t", "_nt")
    return nexts.select(F.col("user_id").alias("src"), F.coalesce("_u", "_nu").alias("dst"), F.col("us"), (1 + F.floor(t / 60000000) - minute).cast("long").alias("weight"), "value").where("dst IS NOT NULL")


def user_relay(spark: SparkSession, sf_dir: str) -> Graph:
    """User to the next purchaser; weight: minute boundaries to it plus 1."""
    pairs = relay_edges(table(spark, sf_dir, "events")).where("src != dst")
    return Graph(pairs.groupBy("src", "dst").agg(F.min("weight").alias("weight"), F.floor(F.max("value")).cast("long").alias("capacity")), name="user_relay")


def catalog_dag(spark: SparkSession, sf_dir: str) -> Graph:
    """Region, nation, customer, order, part in five layers; id = layer * 10^10 + key."""
    layer = lambda n, c: (F.lit(n * 10_000_000_000) + F.col(c)).cast("long")
    fixed = lambda w, c: [F.lit(w).cast("long").alias("weight"), c.cast("long").alias("capacity")]
    nation, customer, orders = (table(spark, sf_dir, t) for t in ("nation", "customer", "orders"))
    parts = [
        nation.select(layer(0, "n_regionkey").alias("src"), layer(1, "n_nationkey").alias("dst"), *fixed(1, F.lit(1000))),
        customer.select(layer(1, "c_nationkey").alias("src"), layer(2, "c_custkey").alias("dst"), *fixed(1, F.lit(1000))),
        orders.select(layer(2, "o_custkey").alias("src"), layer(3, "o_orderkey").alias("dst"), *fixed(1, 1 + F.floor(F.col("o_totalprice") / 10000))),
        table(spark, sf_dir, "lineitem").groupBy(layer(3, "l_orderkey").alias("src"), layer(4, "l_partkey").alias("dst")).agg(F.min("l_quantity").cast("long").alias("weight"), F.max("l_quantity").cast("long").alias("capacity")),
    ]
    return Graph(reduce(DataFrame.unionByName, parts), name="catalog_dag")


def turn_chain(spark: SparkSession, sf_dir: str) -> Graph:
    """A conversation's turn to its next; id = conversation * 1000 + turn."""
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    nexts = rows.select("conv_id", (F.col("turn") - 1).alias("turn"))
    ident = F.col("conv_id") * 1000 + F.col("turn")
    edges = rows.join(nexts, ["conv_id", "turn"]).select(ident.alias("src"), (ident + 1).alias("dst"), F.lit(1).cast("long").alias("weight"), F.lit(1).cast("long").alias("capacity"))
    return Graph(edges, rows.select(ident.alias("id")), name="turn_chain")


def page_link(spark: SparkSession, sf_dir: str) -> Graph:
    """Pages and the targets of their links, numbered from 10^9 by their digest; both directions."""
    href = F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), F.lit(1)))
    links = table(spark, sf_dir, "pages").select("page_id", href.alias("href")).distinct()
    target = F.lit(1_000_000_000) + F.conv(F.substring(F.md5("href"), 1, 12), 16, 10).cast("long")
    one = [F.lit(1).cast("long").alias("weight"), F.lit(1).cast("long").alias("capacity")]
    return Graph(symmetrise(links.select(F.col("page_id").alias("src"), target.alias("dst"), *one)), name="page_link")


def doc_line(spark: SparkSession, sf_dir: str) -> Graph:
    """Documents and the lines of 20 characters or more that at least two of them have (numbered from 10^9 by digest); both directions."""
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") >= 20)
    lines = lines.select("doc_id", F.md5("line").alias("line")).distinct()
    shared = lines.groupBy("line").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    ident = F.lit(1_000_000_000) + F.conv(F.substring("line", 1, 12), 16, 10).cast("long")
    one = [F.lit(1).cast("long").alias("weight"), F.lit(1).cast("long").alias("capacity")]
    return Graph(symmetrise(lines.join(shared, "line").select(F.col("doc_id").alias("src"), ident.alias("dst"), *one)), name="doc_line")


#: Vectors that meet in one task of vec_knn: queries, and rows that they are compared with; numbers of each at most.
KNN_QUERIES, KNN_ROWS, KNN_NUMBERS = 40_000, 40_000, 5_000_000


def vec_knn(spark: SparkSession, sf_dir: str, k: int = 3, every: int = 1) -> Graph:
    """The k nearest vectors by squared distance, from each vector whose id is divisible by ``every``, against all rows.

    Queries and rows are cut into blocks of bounded size; each pair of blocks meets in one task and leaves its k best.
    """
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding").where("vec_id IS NOT NULL")
    asked = F.col("vec_id") % every == 0
    n, m, width = vectors.agg(F.count(F.lit(1)), F.count_if(asked), F.max(F.size("embedding"))).first()
    most = max(1, KNN_NUMBERS // max(1, width or 1))
    across, down = 1 + m // min(KNN_QUERIES, most), 1 + n // min(KNN_ROWS, most)
    block = lambda parts: F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int")
    each = lambda parts: F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    query = vectors.where(asked).select(block(across).alias("_a"), each(down).alias("_b"), F.col("vec_id").alias("src"), F.col("embedding").alias("_q"))
    other = vectors.select(each(across).alias("_a"), block(down).alias("_b"), F.col("vec_id").alias("dst"), F.col("embedding").alias("_x"))
    met = query.groupBy("_a", "_b").cogroup(other.groupBy("_a", "_b")).applyInArrow(nearest(k), "src long, dst long, d double")
    best = met.withColumn("_r", F.row_number().over(W.partitionBy("src").orderBy(F.asc_nulls_last("d"), "dst"))).where(F.col("_r") <= k)
    return Graph(best.select("src", "dst", F.round(F.col("d") * 1000).cast("long").alias("weight"), F.lit(1).cast("long").alias("capacity")), name="vec_knn")


#: The nine edges of the hand-made test graph: src, dst, weight, capacity.
MICRO = [(1, 2, 4, 10), (1, 3, 1, 3), (3, 2, 3, 8), (2, 4, 2, 5), (3, 4, 5, 9), (4, 5, 1, 7), (5, 3, 1, 2), (6, 6, 1, 1), (7, 1, 2, 6)]


def micro(spark: SparkSession) -> Graph:
    return Graph(spark.createDataFrame(MICRO, "src long, dst long, weight long, capacity long"), name="micro")
