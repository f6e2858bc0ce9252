"""DuckDB SQL: the graphs, and round-by-round forms of path reductions."""

from __future__ import annotations

ROUNDS = 60
TOP = 2**63 - 1

_SYM = "SELECT src, dst, weight, capacity FROM ({0}) UNION SELECT dst, src, weight, capacity FROM ({0})"

PART_HOP = """SELECT src, dst, min(q)::BIGINT AS weight, max(q)::BIGINT AS capacity FROM
 (SELECT DISTINCT l_orderkey, l_linenumber + 1 AS ln, l_partkey AS src FROM lineitem WHERE l_returnflag = 'R') a
 JOIN (SELECT l_orderkey, l_linenumber AS ln, l_partkey AS dst, l_quantity::BIGINT AS q FROM lineitem WHERE l_returnflag = 'R') b USING (l_orderkey, ln)
 WHERE src <> dst GROUP BY src, dst"""

NATION_TRADE = """SELECT src, dst, weight, capacity FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY weight DESC, dst) AS rn FROM
 (SELECT s_nationkey::BIGINT AS src, c_nationkey::BIGINT AS dst, count(*) AS weight, sum(l_quantity)::BIGINT AS capacity
  FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey GROUP BY 1, 2)) WHERE rn <= 2"""

CUST_SUPP = _SYM.format("""SELECT o_custkey AS src, l_suppkey + 1000000000 AS dst, count(*) AS weight, max(l_quantity)::BIGINT AS capacity
 FROM lineitem JOIN orders ON o_orderkey = l_orderkey WHERE l_returnflag = 'R' AND l_quantity >= 49 GROUP BY 1, 2""")

RELAY = """SELECT user_id AS src, nu AS dst, us, (1 + nt // 60000000 - us // 60000000)::BIGINT AS weight, value FROM
 (SELECT user_id, value, epoch_us(ts) AS us, lead(user_id) OVER w AS nu, lead(epoch_us(ts)) OVER w AS nt FROM events WHERE event_type = 'purchase' WINDOW w AS (ORDER BY ts, event_id)) WHERE nu IS NOT NULL"""

USER_RELAY = f"SELECT src, dst, min(weight)::BIGINT AS weight, floor(max(value))::BIGINT AS capacity FROM ({RELAY}) WHERE src <> dst GROUP BY src, dst"

CATALOG = """SELECT n_regionkey::BIGINT AS src, 10000000000 + n_nationkey AS dst, 1::BIGINT AS weight, 1000::BIGINT AS capacity FROM nation
 UNION ALL SELECT 10000000000 + c_nationkey, 20000000000 + c_custkey, 1, 1000 FROM customer
 UNION ALL SELECT 20000000000 + o_custkey, 30000000000 + o_orderkey, 1, 1 + floor(o_totalprice / 10000)::BIGINT FROM orders
 UNION ALL SELECT 30000000000 + l_orderkey, 40000000000 + l_partkey, min(l_quantity)::BIGINT, max(l_quantity)::BIGINT FROM lineitem GROUP BY 1, 2"""

TURNS = """SELECT a.conv_id * 1000 + a.turn AS src, a.conv_id * 1000 + a.turn + 1 AS dst, 1::BIGINT AS weight, 1::BIGINT AS capacity
 FROM (SELECT DISTINCT conv_id, turn FROM conversations) a JOIN (SELECT DISTINCT conv_id, turn FROM conversations) b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1"""

PAGES = _SYM.format("""SELECT DISTINCT page_id AS src, 1000000000 + ('0x' || substr(md5(href), 1, 12))::BIGINT AS dst, 1::BIGINT AS weight, 1::BIGINT AS capacity
 FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)""")

LINES = _SYM.format("""SELECT doc_id AS src, 1000000000 + ('0x' || substr(h, 1, 12))::BIGINT AS dst, 1::BIGINT AS weight, 1::BIGINT AS capacity FROM
 (SELECT *, count(*) OVER (PARTITION BY h) AS n FROM (SELECT DISTINCT doc_id, md5(line) AS h FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20)) WHERE n > 1""")

GRAPHS = {"part_hop": PART_HOP, "nation_trade": NATION_TRADE, "cust_supp": CUST_SUPP, "user_relay": USER_RELAY, "catalog_dag": CATALOG, "turn_chain": TURNS, "page_link": PAGES, "doc_line": LINES}


def start(graph: str) -> str:
    """CTEs e (edges), v (vertices), s (sources by rank: most outgoing edges, least id)."""
    return f"""WITH RECURSIVE e AS MATERIALIZED ({GRAPHS[graph]}),
 v AS MATERIALIZED (SELECT src AS id FROM e UNION SELECT dst FROM e),
 s AS MATERIALIZED (SELECT src AS id, row_number() OVER (ORDER BY count(*) DESC, src) AS r FROM e GROUP BY src)"""


def rounds(name: str, init: str, step: str, agg: str, most: int = 1, source: bool = True, n: int = ROUNDS, edges: str = "e") -> str:
    """CTEs: rows (r, id, d) in ``name``, for each source rank up to ``most`` (or from every vertex, r = 0)."""
    begin = f"SELECT 0, r, id, {init} FROM s WHERE r <= {most}" if source else f"SELECT 0, 0, id, {init} FROM v"
    return f""", {name}_t(k, r, id, d) AS ({begin}
  UNION ALL SELECT k + 1, r, id, {agg}(d) FROM (SELECT t.k, t.r, t.id, t.d FROM {name}_t t UNION ALL SELECT t.k, t.r, {edges}.dst, {step} FROM {name}_t t JOIN {edges} ON {edges}.src = t.id) WHERE k < {n} GROUP BY k, r, id),
 {name} AS MATERIALIZED (SELECT r, id, d FROM {name}_t WHERE k = {n})"""


DIST = ("0::BIGINT", "t.d + e.weight", "min")
HOPS = ("0::BIGINT", "t.d + 1", "min")
WIDE = (f"{TOP}::BIGINT", "least(t.d, e.capacity)", "max")
THIN = (f"{TOP}::BIGINT", "least(t.d, e.capacity)", "min")


def per_vertex(graph: str, kernel: tuple[str, str, str], column: str, value: str = "d") -> str:
    return start(graph) + rounds("q", *kernel) + f" SELECT v.id, {value} AS {column} FROM v LEFT JOIN q ON q.id = v.id"


def scalar(graph: str, kernel, most: int, select: str) -> str:
    return start(graph) + rounds("q", *kernel, most=most) + f" SELECT {select} FROM q"
