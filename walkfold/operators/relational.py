"""Relational operators around the graph methods, each with its DuckDB form."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkfold import graphs as G
from walkfold import usecases as U
from walkfold.plans import oracles as O
from walkfold.sources import edge_lists
from walkfold.streaming import windows

QUERIES: dict[str, tuple] = {}


def query(sql: str | None = None):
    def take(f):
        QUERIES[f.__name__] = (f, sql)
        return f

    return take


def _graph(name: str, builder) -> None:
    QUERIES[name] = (lambda spark, d: builder(spark, d).edges.select("src", "dst", "weight", "capacity"), None)


for _name, _b, _key in (("edges_part", G.part_hop, "part_hop"), ("edges_trade", G.nation_trade, "nation_trade"), ("edges_cust_supp", G.cust_supp, "cust_supp"), ("edges_relay", G.user_relay, "user_relay"), ("edges_catalog", G.catalog_dag, "catalog_dag"), ("edges_turns", G.turn_chain, "turn_chain"), ("edges_links", G.page_link, "page_link"), ("edges_lines", G.doc_line, "doc_line")):
    QUERIES[_name] = ((lambda b: lambda spark, d: b(spark, d).edges.select("src", "dst", "weight", "capacity"))(_b), f"SELECT src, dst, weight, capacity FROM ({O.GRAPHS[_key]})")

_E = f"WITH e AS MATERIALIZED ({O.PART_HOP})"


def _part(spark, d) -> DataFrame:
    return G.part_hop(spark, d).edges


@query(f"{_E} SELECT src, dst, weight, capacity FROM e UNION SELECT dst, src, weight, capacity FROM e")
def symmetrise(spark, d):
    return G.symmetrise(_part(spark, d))


@query(f"{_E} SELECT least(src, dst) AS src, greatest(src, dst) AS dst, min(weight) AS weight, max(capacity) AS capacity FROM e GROUP BY 1, 2")
def merge_parallel(spark, d):
    return G.merge_parallel(_part(spark, d).select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "weight", "capacity"))


@query(f"SELECT src, dst, weight FROM ({O.RELAY}) WHERE src <> dst")
def drop_self_loops(spark, d):
    return G.drop_self_loops(G.relay_edges(G.table(spark, d, "events"))).select("src", "dst", "weight")


@query(f"{_E} SELECT dst AS src, src AS dst, weight, capacity FROM e")
def reverse_edges(spark, d):
    return G.reverse(_part(spark, d))


@query(f"{_E} SELECT * FROM e WHERE src % 2 = 0 AND dst % 2 = 0")
def induced_subgraph(spark, d):
    return G.induced(_part(spark, d), F.col("id") % 2 == 0).select("src", "dst", "weight", "capacity")


@query(f"{_E} SELECT src, dst FROM e INTERSECT SELECT dst, src FROM e")
def mutual_edges(spark, d):
    e = _part(spark, d)
    return e.select("src", "dst").intersect(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


@query(f"{_E} SELECT src, dst FROM e EXCEPT SELECT dst, src FROM e")
def one_way_edges(spark, d):
    e = _part(spark, d)
    return e.select("src", "dst").subtract(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


@query(f"{_E} SELECT a.src, b.dst, min(a.weight + b.weight)::BIGINT AS weight FROM e a JOIN e b ON a.dst = b.src GROUP BY a.src, b.dst")
def two_hop_part(spark, d):
    e = _part(spark, d).select("src", "dst", "weight")
    a, b = e.select("src", F.col("dst").alias("mid"), F.col("weight").alias("w1")), e.select(F.col("src").alias("mid"), "dst", F.col("weight").alias("w2"))
    return a.join(b, "mid").groupBy("src", "dst").agg(F.min(F.col("w1") + F.col("w2")).alias("weight"))


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_custkey IS NOT NULL)")
def isolated_customers(spark, d):
    return G.table(spark, d, "customer").select("c_custkey").join(G.table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


@query("SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R'")
def scan_lineitem(spark, d):
    return G.table(spark, d, "lineitem").where("l_quantity >= 45 AND l_returnflag = 'R'").select("l_orderkey", "l_partkey", "l_quantity")


@query(f"{_E} SELECT src, dst, weight FROM e WHERE capacity >= 45")
def edges_heavy(spark, d):
    return _part(spark, d).where("capacity >= 45").select("src", "dst", "weight")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS q FROM lineitem WHERE l_returnflag IN ('R', 'A') GROUP BY ALL")
def edges_by_flag(spark, d):
    return G.table(spark, d, "lineitem").where(F.col("l_returnflag").isin("R", "A")).groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q"))


@query(f"{_E} SELECT dst AS id, count(*) AS n, sum(weight)::BIGINT AS w FROM e GROUP BY dst")
def indegree(spark, d):
    return _part(spark, d).groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("n"), F.sum("weight").alias("w"))


@query(f"{_E} SELECT src AS id, count(*) AS n, max(capacity) AS c FROM e GROUP BY src")
def outdegree(spark, d):
    return _part(spark, d).groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("n"), F.max("capacity").alias("c"))


@query(f"{_E}, g AS (SELECT src, count(*) AS n FROM e GROUP BY src) SELECT n, count(*) AS vertices FROM g GROUP BY n")
def degree_hist(spark, d):
    return _part(spark, d).groupBy("src").agg(F.count(F.lit(1)).alias("n")).groupBy("n").agg(F.count(F.lit(1)).alias("vertices"))


@query(f"{_E}, g AS (SELECT src, count(*) AS n FROM e GROUP BY src), h AS (SELECT n, count(*) AS c FROM g GROUP BY n) SELECT n, (sum(c) OVER (ORDER BY n ROWS UNBOUNDED PRECEDING))::BIGINT AS upto FROM h")
def degree_cdf(spark, d):
    return degree_hist(spark, d).select("n", F.sum("vertices").over(W.orderBy("n").rowsBetween(W.unboundedPreceding, W.currentRow)).alias("upto"))


@query(f"{_E} SELECT src, count(DISTINCT dst) AS n, list_sort(list(DISTINCT dst))[1] AS least FROM e GROUP BY src")
def distinct_neighbours(spark, d):
    return _part(spark, d).groupBy("src").agg(F.count_distinct("dst").alias("n"), F.element_at(F.array_sort(F.collect_set("dst")), 1).alias("least"))


@query()
def approx_neighbours(spark, d):
    return _part(spark, d).groupBy("src").agg(F.approx_count_distinct("dst").alias("n"))


@query(f"{_E}, g AS (SELECT src, count(*) AS n FROM e GROUP BY src) SELECT count(*) AS vertices, max(n) AS most, min(n) AS fewest FROM g")
def degree_summary(spark, d):
    return _part(spark, d).groupBy("src").agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)).alias("vertices"), F.max("n").alias("most"), F.min("n").alias("fewest"))


@query(f"{_E} SELECT dst, min_by(src, weight * 10000000000 + src) AS parent, max_by(src, capacity * 10000000000 - src) AS widest FROM e GROUP BY dst")
def best_parent(spark, d):
    return _part(spark, d).groupBy("dst").agg(F.min_by("src", F.struct("weight", "src")).alias("parent"), F.max_by("src", F.struct("capacity", -F.col("src"))).alias("widest"))


@query(f"{_E} SELECT src, dst, weight, rank() OVER w AS r, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY src ORDER BY weight DESC, dst) AS rn, ntile(4) OVER (PARTITION BY src ORDER BY weight DESC, dst) AS q FROM e WINDOW w AS (PARTITION BY src ORDER BY weight DESC) QUALIFY rn <= 3")
def top_edges_per_src(spark, d):
    w, t = W.partitionBy("src").orderBy(F.desc("weight")), W.partitionBy("src").orderBy(F.desc("weight"), "dst")
    return _part(spark, d).select("src", "dst", "weight", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.row_number().over(t).alias("rn"), F.ntile(4).over(t).alias("q")).where("rn <= 3")


@query(f"SELECT id, cap FROM ({O.per_vertex('part_hop', O.WIDE, 'cap', f'nullif(d, {O.TOP})')}) WHERE cap IS NOT NULL ORDER BY cap DESC, id LIMIT 10")
def top10_widest(spark, d):
    g = G.part_hop(spark, d)
    return U.widest_path(g, G.top_sources(g, 1)[0]).where("cap IS NOT NULL").orderBy(F.desc("cap"), "id").limit(10)


@query("SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def edges_rollup(spark, d):
    c, n, r = (G.table(spark, d, t) for t in ("customer", "nation", "region"))
    return c.join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT event_type, hour(ts)::INT AS h, count(*) AS n FROM events GROUP BY CUBE (event_type, hour(ts)::INT)")
def edges_cube(spark, d):
    return G.table(spark, d, "events").withColumn("h", F.hour("ts")).cube("event_type", "h").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def edges_grouping_sets(spark, d):
    rows = G.table(spark, d, "lineitem")
    return rows.groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")).select("l_returnflag", "l_linestatus", "n")


_BUY = "(SELECT event_id, user_id, epoch_us(ts) AS us FROM events WHERE event_type = 'purchase')"


@query(f"SELECT a.event_id AS a, b.event_id AS b FROM {_BUY} a JOIN {_BUY} b ON b.us > a.us AND b.us <= a.us + 3600000000")
def relay_interval(spark, d):
    """Purchases within an hour of each other: each hour meets itself and the next one, an equi-join on the hour."""
    rows = G.table(spark, d, "events").where("event_type = 'purchase'").select("event_id", F.unix_micros(F.to_timestamp("ts")).alias("us")).withColumn("h", F.expr("us div 3600000000"))
    a = rows.select(F.col("event_id").alias("a"), F.col("us").alias("ua"), F.explode(F.array("h", F.col("h") + 1)).alias("h"))
    b = rows.select(F.col("event_id").alias("b"), F.col("us").alias("ub"), "h")
    return a.join(b, "h").where("ub > ua AND ub <= ua + 3600000000").select("a", "b")


@query("SELECT event_id, max_by(p, us) AS last_click FROM (SELECT a.event_id, b.event_id AS p, epoch_us(b.ts) AS us FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts < a.ts AND b.event_type = 'click' WHERE a.event_type = 'purchase') GROUP BY event_id")
def relay_asof(spark, d):
    """The last earlier click of the same user, by one window over both kinds."""
    rows = G.table(spark, d, "events").where("event_type IN ('purchase', 'click')").select("event_id", "user_id", "event_type", "ts")
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1))
    return rows.withColumn("last_click", last).where("event_type = 'purchase' AND last_click IS NOT NULL").select("event_id", "last_click")


_DAY = 86_400_000_000


@query(f"SELECT us // {_DAY} * {_DAY} AS start_us, count(*) AS n, min(user_id) AS least_user FROM {_BUY} GROUP BY 1")
def relay_tumbling(spark, d):
    return windows.tumbling(G.table(spark, d, "events"))


@query(f"SELECT (us // {_DAY} - o) * {_DAY} AS start_us, count(*) AS n FROM {_BUY}, (SELECT unnest([0, 1]) AS o) GROUP BY 1")
def relay_sliding(spark, d):
    return windows.sliding(G.table(spark, d, "events"))


@query(f"SELECT user_id, min(us) AS start_us, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY us, event_id) AS g FROM (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY user_id ORDER BY us, event_id) < 43200000000 THEN 0 ELSE 1 END AS fresh FROM {_BUY})) GROUP BY user_id, g")
def relay_session(spark, d):
    return windows.sessions(G.table(spark, d, "events"))


@query(f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY us RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM {_BUY}")
def user_rate_1h(spark, d):
    rows = G.table(spark, d, "events").where("event_type = 'purchase'").select("event_id", "user_id", F.unix_micros(F.to_timestamp("ts")).alias("us"))
    return rows.select("event_id", F.count(F.lit(1)).over(W.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("n"))


@query("SELECT props->>'$.k' AS k, count(*) AS n FROM events GROUP BY 1")
def props_json(spark, d):
    return G.table(spark, d, "events").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_hints_same_result(spark, d):
    """The same join by broadcast, shuffled hash and sort-merge: what all three agree on."""
    c, n = G.table(spark, d, "customer").select("c_nationkey"), G.table(spark, d, "nation").select("n_nationkey", "n_name")
    found = [c.join(n.hint(h), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count(F.lit(1)).alias("n")) for h in ("broadcast", "shuffle_hash", "merge")]
    return reduce(DataFrame.intersect, found)


@query(O.start("part_hop") + O.rounds("q", *O.HOPS, most=2) + ", x AS (SELECT r, max(d) AS m FROM q GROUP BY r) SELECT src, dst FROM e WHERE weight < (SELECT min(m) FROM x)")
def within_radius(spark, d):
    g = G.part_hop(spark, d)
    one = U.radius(g, G.top_sources(g, 2))
    return g.edges.crossJoin(F.broadcast(one)).where("weight < value").select("src", "dst")  # one row


@query(f"{_E} SELECT DISTINCT dst AS id FROM e WHERE src IN (SELECT src FROM e WHERE weight = 1)")
def changed_preds(spark, d):
    e = _part(spark, d)
    return e.join(e.where("weight = 1").select("src").distinct(), "src", "left_semi").select(F.col("dst").alias("id")).distinct()


@query(O.start("part_hop") + O.rounds("q", *O.HOPS) + " SELECT v.id, coalesce(d, -1) AS hops FROM v LEFT JOIN q ON q.id = v.id")
def state_or_bottom(spark, d):
    g = G.part_hop(spark, d)
    return U.hop_distance(g, G.top_sources(g, 1)[0]).select("id", F.coalesce("hops", F.lit(-1).cast("long")).alias("hops"))


@query(O.start("part_hop") + O.rounds("a", *O.HOPS) + O.rounds("b", *O.DIST) + " SELECT coalesce(a.id, b.id) AS id, a.d AS hops, b.d AS dist FROM a FULL JOIN b ON a.id = b.id")
def compare_runs(spark, d):
    g = G.part_hop(spark, d)
    s = G.top_sources(g, 1)[0]
    a, b = U.hop_distance(g, s).where("hops IS NOT NULL"), U.sssp(g, s).where("dist IS NOT NULL")
    return a.join(b, "id", "full_outer").select("id", "hops", "dist")


@query(f"{_E} SELECT src, dst, weight, capacity FROM e")
def edgelist_roundtrip(spark, d):
    return edge_lists.round_trip(_part(spark, d))


@query("SELECT c_mktsegment, (dense_rank() OVER (ORDER BY c_mktsegment) - 1)::BIGINT AS id FROM customer GROUP BY c_mktsegment")
def vertex_dictionary(spark, d):
    return edge_lists.dictionary(G.table(spark, d, "customer").select("c_mktsegment"), "c_mktsegment")


@query("WITH e AS (" + O.PART_HOP + ") SELECT src, dst, o AS out_src, i AS in_dst FROM e JOIN (SELECT src, count(*) AS o FROM e GROUP BY src) USING (src) JOIN (SELECT dst, count(*) AS i FROM e GROUP BY dst) USING (dst)")
def degree_join(spark, d):
    """Every edge with the out-degree of its source and the in-degree of its target."""
    e = _part(spark, d).select("src", "dst")
    out = e.groupBy("src").agg(F.count(F.lit(1)).alias("out_src"))
    into = e.groupBy("dst").agg(F.count(F.lit(1)).alias("in_dst"))
    return e.join(out, "src").join(into, "dst").select("src", "dst", "out_src", "in_dst")


@query("WITH e AS (" + O.PAGES + "), o AS (SELECT src, count(*) AS n FROM e GROUP BY src) SELECT src AS id, n FROM o ORDER BY n DESC, src LIMIT 10")
def top10_degree(spark, d):
    """The ten vertices with the most links: a heap for each partition and one merge, not a global sort."""
    return G.page_link(spark, d).edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "id").limit(10)


@query("WITH e AS (" + O.PART_HOP + ") SELECT DISTINCT src, TRUE AS close FROM e")
def approx_neighbours_close(spark, d):
    """Whether each approximate count of neighbours is within 5 % and one of the exact one."""
    e = G.part_hop(spark, d).edges
    both = e.groupBy("src").agg(F.approx_count_distinct("dst", 0.02).alias("a"), F.count_distinct("dst").alias("n"))
    return both.select("src", (F.abs(F.col("a") - F.col("n")) <= F.col("n") * 0.05 + 1).alias("close"))


@query("WITH e AS (" + O.PART_HOP + ") SELECT p, TRUE AS close FROM (VALUES (10), (50), (90)) AS t(p)")
def percentile_close(spark, d):
    """Approximate percentiles of weights against the share of edges at or under them."""
    marks = _part(spark, d).agg(F.percentile_approx("weight", F.array(F.lit(0.1), F.lit(0.5), F.lit(0.9)), F.lit(10_000))).first()[0]  # three numbers
    shares = [F.struct(F.lit(p).alias("p"), F.avg((F.col("weight") <= w).cast("double")).alias("s"), F.avg((F.col("weight") < w).cast("double")).alias("t")) for p, w in zip((10, 50, 90), marks, strict=True)]
    rows = _part(spark, d).agg(F.array(*shares).alias("x")).select(F.inline("x"))
    return rows.select("p", ((F.col("s") * 100 >= F.col("p") - 0.1) & (F.col("t") * 100 <= F.col("p") + 0.1)).alias("close"))
