"""Every analysis, model, baseline, measure and workload as a query on the given tables, with its DuckDB form."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkfold import graphs as G
from walkfold import usecases as U
from walkfold.baselines import enumerate_paths, handwritten, unfused
from walkfold.exec.metrics import RunMetrics
from walkfold.fuse.engine import fuse
from walkfold.operators import relational
from walkfold.plans import oracles as O
from walkfold.plans import surface
from walkfold.spec.types import typecheck
from walkfold.synth.enumerate import derive, forget

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, run: Query, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql is not None:
        ORACLES[name] = sql


def _on(builder, use, k: int = 1):
    """A query that builds a graph, picks its k sources and runs ``use(graph, sources)``."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = builder(spark, sf_dir)
        return use(g, G.top_sources(g, k) if k else [])

    return run


def _value(df: DataFrame, name: str = "value") -> DataFrame:
    return df.select(F.round(F.col("value").cast("double"), 6).alias(name))


def _rounded(df: DataFrame, name: str) -> DataFrame:
    return df.withColumn(name, F.round(F.col(name), 6))


# -- path reductions -----------------------------------------------------------------------------------------------

_B = {"part": (G.part_hop, "part_hop"), "nation": (G.nation_trade, "nation_trade"), "users": (G.user_relay, "user_relay"), "cust_supp": (G.cust_supp, "cust_supp"), "pages": (G.page_link, "page_link"), "doc_line": (G.doc_line, "doc_line"), "catalog": (G.catalog_dag, "catalog_dag"), "turns": (G.turn_chain, "turn_chain")}

for _g in ("part", "nation", "users"):
    _add(f"sssp_{_g}", _on(_B[_g][0], lambda g, s: U.sssp(g, s[0])), O.per_vertex(_B[_g][1], O.DIST, "dist"))
for _g in ("part", "users"):
    _add(f"widest_{_g}", _on(_B[_g][0], lambda g, s: U.widest_path(g, s[0])), O.per_vertex(_B[_g][1], O.WIDE, "cap", f"nullif(d, {O.TOP})"))
_add("hops_part", _on(G.part_hop, lambda g, s: U.hop_distance(g, s[0])), O.per_vertex("part_hop", O.HOPS, "hops"))
_add("narrowest_part", _on(G.part_hop, lambda g, s: U.narrowest_path(g, s[0])), O.per_vertex("part_hop", O.THIN, "cap", f"nullif(d, {O.TOP})"))
_add("reach_part", _on(G.part_hop, lambda g, s: U.reachable(g, s[0])), O.per_vertex("part_hop", O.HOPS, "reached", "CASE WHEN d IS NOT NULL THEN TRUE END"))
_add("all_paths_positive", _on(G.part_hop, lambda g, s: U.all_paths_heavy(g, s[0])), O.per_vertex("part_hop", ("TRUE", "t.d AND e.weight > 1", "bool_and"), "ok"))

# -- components ----------------------------------------------------------------------------------------------------

for _g in ("cust_supp", "doc_line", "pages"):
    _add(f"cc_{_g}", _on(_B[_g][0], lambda g, s: U.connected_components(g), 0), O.start(_B[_g][1]) + O.rounds("q", "id", "t.d", "min", source=False) + " SELECT id, d AS component FROM q")

# -- pairs ---------------------------------------------------------------------------------------------------------

_PAIR = {
    "length": ("{'a': 0::BIGINT, 'b': -" + str(O.TOP) + "::BIGINT}", "{'a': t.d.a + 1, 'b': greatest(t.d.b, -e.capacity)}", "min"),
    "weight": ("{'a': 0::BIGINT, 'b': -" + str(O.TOP) + "::BIGINT}", "{'a': t.d.a + e.weight, 'b': greatest(t.d.b, -e.capacity)}", "min"),
}
_WSP = f" SELECT v.id, d.a AS dist, nullif(-d.b, {O.TOP}) AS cap FROM v LEFT JOIN q ON q.id = v.id"
_add("wsp_len_part", _on(G.part_hop, lambda g, s: U.widest_shortest(g, s[0])), O.start("part_hop") + O.rounds("q", *_PAIR["length"]) + _WSP)
_add("wsp_weight_part", _on(G.part_hop, lambda g, s: U.widest_shortest(g, s[0], "weight")), O.start("part_hop") + O.rounds("q", *_PAIR["weight"]) + _WSP)
_BFS = O.rounds("q", "{'a': 0::BIGINT, 'b': id}", "{'a': t.d.a + 1, 'b': e.src}", "min") + " SELECT v.id, d.a AS hops, d.b AS parent FROM v LEFT JOIN q ON q.id = v.id"
_add("bfs_cust_supp", _on(G.cust_supp, lambda g, s: U.bfs_tree(g, s[0])), O.start("cust_supp") + _BFS)
_add("bfs_part", _on(G.part_hop, lambda g, s: U.bfs_tree(g, s[0])), O.start("part_hop") + _BFS)
_NWR = O.rounds("a", *O.THIN) + O.rounds("b", *O.WIDE) + f" SELECT v.id, round(nullif(a.d, {O.TOP})::DOUBLE / nullif(b.d, {O.TOP}), 6) AS ratio FROM v LEFT JOIN a ON a.id = v.id LEFT JOIN b ON b.id = v.id"
for _n, _g in (("part", "part"), ("catalog", "catalog")):
    _add(f"nwr_{_n}", _on(_B[_g][0], lambda g, s: _rounded(U.narrow_wide_ratio(g, s[0]), "ratio")), O.start(_B[_g][1]) + _NWR)

# -- counting ------------------------------------------------------------------------------------------------------

_COUNT = """, c(k, id, n) AS (SELECT 0, id, 1::HUGEINT FROM s WHERE r = 1 UNION ALL SELECT k + 1, {e}.dst, sum(n)::HUGEINT FROM c JOIN {e} ON {e}.src = c.id GROUP BY k, {e}.dst)"""
_NSP = O.rounds("q", *O.DIST) + ", h AS MATERIALIZED (SELECT e.src, e.dst FROM e JOIN q a ON a.id = e.src JOIN q b ON b.id = e.dst WHERE a.d + e.weight = b.d)" + _COUNT.format(e="h") + " SELECT v.id, q.d AS dist, n::BIGINT AS n FROM v LEFT JOIN q ON q.id = v.id LEFT JOIN (SELECT id, sum(n) AS n FROM c GROUP BY id) c ON c.id = v.id"
for _g in ("part", "cust_supp"):
    _add(f"nsp_{_g}", _on(_B[_g][0], lambda g, s: U.count_shortest(g, s[0]).withColumn("n", F.col("n").cast("long"))), O.start(_B[_g][1]) + _NSP)


def _catalog_from(g, model="auto", metrics=None):
    return U.count_paths(g, 0, model=model, metrics=metrics).withColumn("n", F.col("n").cast("long"))


_PATHS = O.start("catalog_dag") + _COUNT.format(e="e").replace("SELECT 0, id, 1::HUGEINT FROM s WHERE r = 1", "SELECT 0, 0::BIGINT, 1::HUGEINT") + " SELECT v.id, n::BIGINT AS n FROM v LEFT JOIN (SELECT id, sum(n) AS n FROM c GROUP BY id) c ON c.id = v.id"
_add("path_count_catalog", _on(G.catalog_dag, lambda g, s: _catalog_from(g), 0), _PATHS)
_add("longest_turns", _on(G.turn_chain, lambda g, s: U.longest_path(g), 0), "SELECT conv_id * 1000 + turn AS id, turn - min(turn) OVER (PARTITION BY conv_id, g) AS len FROM (SELECT DISTINCT conv_id, turn, turn - dense_rank() OVER (PARTITION BY conv_id ORDER BY turn) AS g FROM conversations)")

# -- several sources, vertex reductions ----------------------------------------------------------------------------

_ECC = ", x AS (SELECT r, max(d) AS m FROM q GROUP BY r)"
_add("ecc_nation", _on(G.nation_trade, lambda g, s: _value(U.eccentricity(g, s[0]))), O.scalar("nation_trade", O.HOPS, 1, "max(d)::DOUBLE AS value"))


def _over(graph: str, most: int, select: str) -> str:
    return O.start(graph) + O.rounds("q", *O.HOPS, most=most) + _ECC + f" SELECT round(({select})::DOUBLE, 6) AS value FROM x"


_add("radius_part", _on(G.part_hop, lambda g, s: _value(U.radius(g, s)), 2), _over("part_hop", 2, "min(m)"))
_add("radius_cust_supp", _on(G.cust_supp, lambda g, s: _value(U.radius(g, s)), 2), _over("cust_supp", 2, "min(m)"))
_add("diameter_nation", _on(G.nation_trade, lambda g, s: _value(U.diameter(g, s)), 4), _over("nation_trade", 4, "max(m)"))
_add("drr_cust_supp", _on(G.cust_supp, lambda g, s: _value(U.diameter_radius_ratio(g, s)), 2), _over("cust_supp", 2, "max(m) / min(m)"))
_add("drr_part", _on(G.part_hop, lambda g, s: _value(U.diameter_radius_ratio(g, s)), 2), _over("part_hop", 2, "max(m) / min(m)"))
for _k in (1, 2, 4, 8, 16):
    _add(f"radius_k{_k}", _on(G.part_hop, lambda g, s: _value(U.radius(g, s)), _k), _over("part_hop", _k, "min(m)"))
_TRUST = O.rounds("a", *O.WIDE, most=2) + O.rounds("b", *O.HOPS, most=2) + f" SELECT v.id, round(max(nullif(a.d, {O.TOP})::DOUBLE / nullif(b.d, 0)), 6) AS trust FROM v LEFT JOIN a ON a.id = v.id LEFT JOIN b ON b.id = a.id AND b.r = a.r GROUP BY v.id"
_add("trust_users", _on(G.user_relay, lambda g, s: _rounded(U.trust(g, s), "trust"), 2), O.start("user_relay") + _TRUST)
_add("ds_part", _on(G.part_hop, lambda g, s: U.distant_members(g, s[0])), O.start("part_hop") + O.rounds("q", *O.DIST) + " SELECT id FROM q WHERE d > 7")


def _rds(graph: str, distance: tuple) -> str:
    return O.start(graph) + O.rounds("q", *O.HOPS, most=2) + _ECC + O.rounds("a", *distance) + O.rounds("b", *O.WIDE) + f" SELECT round(min(nullif(b.d, {O.TOP}))::DOUBLE, 6) AS value FROM a JOIN b USING (id) WHERE a.d < (SELECT min(m) FROM x)"


_add("rds_cust_supp", _on(G.cust_supp, lambda g, s: _value(U.radius_trust_floor(g, s[0], s)), 2), _rds("cust_supp", O.HOPS))
_add("rds_part", _on(G.part_hop, lambda g, s: _value(U.radius_trust_floor(g, s[0], s)), 2), _rds("part_hop", O.HOPS))
_add("rds_users_weight", _on(G.user_relay, lambda g, s: _value(U.radius_trust_floor(g, s[0], s, "weight")), 2), _rds("user_relay", O.DIST))

# -- raw kernels ---------------------------------------------------------------------------------------------------


def _pr_sql(graph: str, n: int = 20) -> str:
    return O.start(graph) + f""", o AS MATERIALIZED (SELECT src, count(*) AS od FROM e GROUP BY src), c AS (SELECT count(*) AS n FROM v),
 t(k, id, p) AS (SELECT 0, id, 1.0::DOUBLE / (SELECT n FROM c) FROM v UNION ALL
  SELECT k + 1, id, 0.85 * sum(x) + 0.15 / (SELECT n FROM c) FROM (SELECT t.k, t.id, 0.0::DOUBLE AS x FROM t UNION ALL SELECT t.k, e.dst, t.p / o.od FROM t JOIN e ON e.src = t.id JOIN o ON o.src = t.id) WHERE k < {n} GROUP BY k, id)
 SELECT id, round(p, 6) AS rank FROM t WHERE k = {n}"""


_add("pagerank_nation", _on(G.nation_trade, lambda g, s: _rounded(U.page_rank(g), "rank"), 0), _pr_sql("nation_trade"))
_add("pagerank_pages", _on(G.page_link, lambda g, s: _rounded(U.page_rank(g), "rank"), 0), _pr_sql("page_link"))
_add("pagerank_rollback", _on(G.nation_trade, lambda g, s: _rounded(U.page_rank(g, model="rollback"), "rank"), 0), _pr_sql("nation_trade"))

# -- models, baselines ---------------------------------------------------------------------------------------------

for _m in ("pull", "push", "auto_switch"):
    _add(f"sssp_{_m.split('_')[0]}", _on(G.part_hop, lambda g, s, m=_m: U.sssp(g, s[0], model=m)), ORACLES["sssp_part"])
for _m in ("pull_nonidem", "push_nonidem", "rollback"):
    _add(f"path_count_{_m.split('_')[0]}", _on(G.catalog_dag, lambda g, s, m=_m: _catalog_from(g, m), 0), _PATHS)
_add("hand_sssp", _on(G.part_hop, lambda g, s: handwritten.sssp(g, s[0])), ORACLES["sssp_part"])
_add("hand_wp", _on(G.part_hop, lambda g, s: handwritten.wp(g, s[0])), ORACLES["widest_part"])
_add("hand_bfs", _on(G.cust_supp, lambda g, s: handwritten.bfs(g, s[0])), ORACLES["bfs_cust_supp"])
_add("hand_cc", _on(G.cust_supp, lambda g, s: handwritten.cc(g), 0), ORACLES["cc_cust_supp"])
_add("hand_cc_init_in_step", _on(G.cust_supp, lambda g, s: handwritten.cc(g, init_in_step=True), 0), ORACLES["cc_cust_supp"])
_add("hand_pr", _on(G.nation_trade, lambda g, s: _rounded(handwritten.pr(g), "rank"), 0), ORACLES["pagerank_nation"])
_add("unfused_wsp", _on(G.part_hop, lambda g, s: unfused.widest_shortest(g, s[0], "weight")), ORACLES["wsp_weight_part"])
_add("unfused_nwr", _on(G.part_hop, lambda g, s: _rounded(unfused.narrow_wide_ratio(g, s[0]), "ratio")), ORACLES["nwr_part"])
_add("unfused_trust", _on(G.user_relay, lambda g, s: _rounded(unfused.trust(g, s), "trust"), 2), ORACLES["trust_users"])
_add("unfused_radius", _on(G.part_hop, lambda g, s: _value(unfused.radius(g, s)), 2), ORACLES["radius_part"])
_add("unfused_drr", _on(G.cust_supp, lambda g, s: _value(unfused.diameter_radius_ratio(g, s)), 2), ORACLES["drr_cust_supp"])
_add("unfused_rds", _on(G.part_hop, lambda g, s: _value(unfused.radius_trust_floor(g, s[0], s)), 2), ORACLES["rds_part"])
_add("unfused_nsp", _on(G.part_hop, lambda g, s: unfused.count_shortest(g, s[0]).withColumn("n", F.col("n").cast("long"))), ORACLES["nsp_part"])
_add("enumerate_paths_nation", _on(G.nation_trade, lambda g, s: enumerate_paths.sssp(g, s[0], 10)), O.per_vertex("nation_trade", O.DIST, "dist"))

# -- accounting ----------------------------------------------------------------------------------------------------


def _one_row(spark: SparkSession, schema: str, *rows: tuple) -> DataFrame:
    return spark.createDataFrame(list(rows), schema)


def _sssp_work(spark: SparkSession, sf_dir: str) -> tuple[RunMetrics, DataFrame]:
    g, m = G.part_hop(spark, sf_dir), RunMetrics()
    U.sssp(g, G.top_sources(g, 1)[0], metrics=m)
    return m


def _frontier_sql(select: str) -> str:
    """Frontier counting: each round's changed vertices and their outgoing edges."""
    return O.start("part_hop") + O.rounds("q", *O.DIST) + f""",
 ch AS (SELECT k, id FROM (SELECT k, id, d, lag(d) OVER (PARTITION BY id ORDER BY k) AS was FROM q_t) WHERE was IS NULL OR d < was),
 od AS (SELECT src, count(*) AS n FROM e GROUP BY src)
 SELECT {select} FROM ch LEFT JOIN od ON od.src = ch.id"""


_add("edge_work_sssp", lambda spark, d: _one_row(spark, "edges long", (_sssp_work(spark, d).edges_processed,)), _frontier_sql("coalesce(sum(n), 0)::BIGINT AS edges"))
_add("steps_sssp", lambda spark, d: _one_row(spark, "steps long", (_sssp_work(spark, d).n_steps,)), _frontier_sql("(max(k) + 1)::BIGINT AS steps"))


def _wsp_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of the fused and the two-pass program for the widest of the shortest paths."""
    g, a, b = G.part_hop(spark, sf_dir), RunMetrics(), RunMetrics()
    source = G.top_sources(g, 1)[0]
    U.widest_shortest(g, source, "weight", metrics=a)
    unfused.widest_shortest(g, source, "weight", metrics=b)
    return _one_row(spark, "fused long, unfused long", (a.edges_processed, b.edges_processed))


_WSP_WORK = (
    O.start("part_hop") + O.rounds("q", *_PAIR["weight"]) + O.rounds("w", *O.DIST)
    + ", od AS (SELECT src, count(*) AS n FROM e GROUP BY src)"
    + ", fc AS (SELECT k, id FROM (SELECT k, id, d, lag(d) OVER (PARTITION BY id ORDER BY k) AS was FROM q_t) WHERE was IS NULL OR d <> was)"
    + ", h AS MATERIALIZED (SELECT e.* FROM e JOIN w a ON a.id = e.src JOIN w b ON b.id = e.dst WHERE a.d + e.weight = b.d)"
    + O.rounds("z", f"{O.TOP}::BIGINT", "least(t.d, h.capacity)", "max", edges="h")
    + ", ht AS (SELECT src, count(*) AS n FROM h GROUP BY src)"
    + ", c1 AS (SELECT k, id FROM (SELECT k, id, d, lag(d) OVER (PARTITION BY id ORDER BY k) AS was FROM w_t) WHERE was IS NULL OR d <> was)"
    + ", c2 AS (SELECT k, id FROM (SELECT k, id, d, lag(d) OVER (PARTITION BY id ORDER BY k) AS was FROM z_t) WHERE was IS NULL OR d <> was)"
    + " SELECT (SELECT sum(n) FROM fc JOIN od ON src = id)::BIGINT AS fused, ((SELECT sum(n) FROM c1 JOIN od ON src = id) + (SELECT sum(n) FROM c2 JOIN ht ON src = id))::BIGINT AS unfused"
)
_add("edge_work_wsp", _wsp_work, _WSP_WORK)

# -- programs only -------------------------------------------------------------------------------------------------


def specs(a: int, b: int) -> dict:
    """The use cases' specifications for two sources."""
    return {"bfs": U.spec_bfs(a), "cc": U.spec_reduce("min", "head"), "sssp": U.spec_reduce("min", "weight", a), "wp": U.spec_reduce("max", "capacity", a), "wsp": U.spec_wsp(a), "nsp": U.spec_nsp(a), "nwr": U.spec_nwr(a), "radius": U.spec_radius((a, b)), "ds": U.spec_distant(a), "drr": U.spec_drr((a, b)), "trust": U.spec_trust((a, b)), "rds": U.spec_rds(a, (a, b))}


SPECS = specs(1, 2)


def _part_specs(spark: SparkSession, sf_dir: str) -> dict:
    """The use cases for the two sources of the part graph, their types checked against its columns."""
    g = G.part_hop(spark, sf_dir)
    found = specs(*G.top_sources(g, 2))
    for spec in found.values():
        typecheck(spec, set(g.edges.columns))
    return found


def _fusion_traces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of each use case on the part graph its reductions, loops and rounds, and the sources that its loops start from."""
    rows = []
    for name, spec in _part_specs(spark, sf_dir).items():
        done, trace = fuse(spec)
        sources = {x.source for let in done.lets for loop in let.loops for x in loop} - {None}
        rows.append((name, trace.n_before, trace.n_after, len(done.lets), min(sources, default=None), max(sources, default=None)))
    return spark.createDataFrame(rows, "use_case string, reductions long, loops long, rounds long, least_source long, greatest_source long")


def _analysis_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fusion and the synthesis that runs the program, each from nothing; kernels tried."""
    rows = []
    for name, spec in _part_specs(spark, sf_dir).items():
        done, trace = fuse(spec)
        forget()
        found = [derive(x.keys, x.source is not None) for t in done.lets for loop in t.loops for x in loop]
        rows.append((name, trace.n_before, round(trace.ms, 3), round(sum(x.ms for x in found), 3), sum(x.tried for x in found)))
    return spark.createDataFrame(rows, "use_case string, reductions long, fusion_ms double, synthesis_ms double, tried long")


_TRACES = surface.values("use_case, reductions, loops, rounds", *[(n, before, loops, rounds) for n, (before, loops, rounds) in surface.WANT_TRACES.items()])
_SOURCES = {n: 0 if n == "cc" else 2 if n in ("radius", "drr", "trust", "rds") else 1 for n in surface.WANT_TRACES}  # how many
_SOURCES = surface.values("use_case, n", *_SOURCES.items())
_add("fusion_traces", _fusion_traces, O.start("part_hop") + f" SELECT t.*, min(s.id)::BIGINT AS least_source, max(s.id)::BIGINT AS greatest_source FROM ({_TRACES}) t JOIN ({_SOURCES}) k USING (use_case) LEFT JOIN s ON s.r <= k.n GROUP BY ALL")
_add("analysis_time", _analysis_time)
_KNN = """WITH p AS (SELECT a.vec_id AS src, b.vec_id AS dst, list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda x: ((x[1] - x[2]) * (x[1] - x[2]))::DOUBLE)) AS d
 FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id)
 SELECT src, dst, round(d * 1000)::BIGINT AS weight FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY d, dst) AS r FROM p) WHERE r <= 3"""
_add("knn_vectors", lambda spark, d: G.vec_knn(spark, d).edges.select("src", "dst", "weight"), _KNN)

# -- graph preparation and relational operators --------------------------------------------------------------------

for _n, (_run, _sql) in relational.QUERIES.items():
    _add(_n, _run, _sql)

surface.register_all(_add, ORACLES)
