"""Benchmark decontamination by a positional inverted index, with DataFrame operations only.

1. The index is stored once in the shared folder: the postings (term, text, position) of all tokens of all training texts.
   It is dealt by text as the input is, so building it shuffles nothing, and any benchmark can be looked up in it: a look-up
   is a hash join of the postings with its terms.
2. Frequencies of the benchmark's terms come from the index. Windows with a term that no training text has cannot occur.
3. Every other window of ``window`` consecutive item words is looked up from its rarest terms: the position lists of the
   two rarest are adjusted by the terms' offsets in the item and intersected, which leaves few diagonals (a text, an item,
   and the difference of their positions).
4. On these, the lists of all the item's terms are intersected: each diagonal asks for a posting of every term at its
   adjusted position. A window whose words are all there is an exact phrase match, and all its words are hit.
5. Proximity: texts where an item's rarest terms lie within ``SPAN`` words of each other (``n_near`` counts the items).

Terms are 64-bit hashes in the index: among 10^8 terms two clash with a chance of about 0.0003. No set of terms
reaches the driver, and a table is broadcast only if its row count is checked to be small.

Defined cases: null texts have no words; an item without words has no window; items of fewer words than a window
are one window; rows with the same doc_id and text get the same figures; a null item_id is written as the empty
string; an empty benchmark hits nothing; an empty table gives an empty result; extra columns are ignored
(``drop_contaminated`` carries them, whatever they are called).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from walkfold.llm.common import cut, lower_ascii, unused

#: What stands between words once A-Z are lower-case.
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
WINDOW = 10
NEAR_TERMS, SPAN = 2, 20
#: Look-up rows (each under 200 bytes) up to this many are broadcast; more are joined by shuffle.
BROADCAST_ROWS = 50_000


def words(text: Column) -> Column:
    return F.array_remove(F.split(lower_ascii(text), BETWEEN), "")


def _small(df: DataFrame, most: int = BROADCAST_ROWS) -> DataFrame:
    return F.broadcast(df) if df.count() <= most else df


def item_words(benchmark: DataFrame) -> DataFrame:
    """One row for each word of each distinct item: item_id, _item (hash of id and words), at, term, h (its hash), n."""
    items = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item_id"), words(F.col("text")).alias("ws")).distinct()
    items = items.where(F.size("ws") > 0).withColumn("_item", F.sha1(F.concat_ws(" ", "item_id", F.array_join("ws", " "))))
    items = items.select("item_id", "_item", F.size("ws").alias("n"), F.posexplode("ws").alias("at", "term"))
    return items.withColumn("at", F.col("at") + 1).withColumn("h", F.xxhash64("term"))


#: A text is known by its doc_id and this hash; rows that repeat both share their postings.
TEXT = ("doc_id", "_text")


def positional_index(docs: DataFrame) -> DataFrame:
    """h (term hash), doc_id, _text, pos: one row for each token."""
    rows = docs.select("doc_id", F.xxhash64("text").alias("_text"), F.posexplode(words(F.col("text"))).alias("pos", "term"))
    return rows.select(F.xxhash64("term").alias("h"), "doc_id", "_text", (F.col("pos") + 1).alias("pos"))


def term_frequencies(index: DataFrame, terms: DataFrame) -> DataFrame:
    """h, df: occurrences in the training texts of those of ``terms`` that occur."""
    return index.select("h").join(_small(terms), "h").groupBy("h").agg(F.count(F.lit(1)).alias("df"))


def windows(items: DataFrame, frequencies: DataFrame, window: int = WINDOW) -> DataFrame:
    """_item, need, rare: the windows that can occur, with their two rarest terms (df, at, h); equal pairs of terms once."""
    known = items.join(frequencies, "h")
    length = F.least(F.col("n"), F.lit(window))
    start = F.explode(F.sequence(F.greatest(F.lit(1), F.col("at") - length + 1), F.least(F.col("at"), F.col("n") - length + 1)))
    placed = known.select("_item", length.alias("need"), "at", "h", "df", start.alias("start"))
    whole = placed.groupBy("_item", "start", "need").agg(F.sort_array(F.collect_list(F.struct("df", "at", "h"))).alias("all")).where(F.size("all") == F.col("need"))
    return whole.select("_item", "need", F.slice("all", 1, 2).alias("rare")).distinct()


def diagonals(index: DataFrame, wins: DataFrame) -> DataFrame:
    """doc_id, _text, _item, diag: where the adjusted lists of a window's two rarest terms meet (pos = at + diag for both)."""
    looked = wins.select("_item", F.inline("rare").alias("_df", "at", "h")).select("_item", "at", "h").distinct()
    met = index.join(_small(looked), "h").select(*TEXT, "_item", (F.col("pos") - F.col("at")).alias("diag"), "at")
    met = met.groupBy(*TEXT, "_item", "diag").agg(F.collect_set("at").alias("ats"))
    pairs = wins.select("_item", F.col("rare.at").alias("_pair")).distinct()
    met = met.join(_small(pairs), "_item").where(F.size(F.array_except("_pair", "ats")) == 0)
    return met.select(*TEXT, "_item", "diag").distinct()


def _same_text(a: DataFrame, b: DataFrame) -> Column:
    return a["doc_id"].eqNullSafe(b["_d"]) & (a["_text"] == b["_t"])


def phrase_matches(index: DataFrame, items: DataFrame, found: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, _text, item_id, places: exact occurrences of an item's windows on these diagonals, as the hit positions."""
    asked = found.join(_small(items.select("_item", "item_id", "n", "at", "h")), "_item")
    asked = asked.select(F.col("doc_id").alias("_d"), F.col("_text").alias("_t"), "item_id", "_item", "n", "diag", "at", F.col("h").alias("_h"), (F.col("at") + F.col("diag")).alias("_pos"))
    asked = _small(cut(asked, "decon-asked"), 10 * BROADCAST_ROWS)
    met = index.join(asked, (index["h"] == asked["_h"]) & (index["pos"] == asked["_pos"]) & _same_text(index, asked))
    met = met.groupBy(*TEXT, "item_id", "_item", "n", "diag").agg(F.collect_set("at").alias("there"))
    need = F.least(F.col("n"), F.lit(window))
    starts = F.filter("there", lambda s: (s + need - 1 <= F.col("n")) & (F.size(F.filter("there", lambda i: (i >= s) & (i < s + need))) == need))
    met = met.withColumn("starts", starts).where(F.size("starts") > 0)
    places = F.array_distinct(F.flatten(F.transform("starts", lambda s: F.sequence(s + F.col("diag"), s + F.col("diag") + need - 1))))
    return met.select(*TEXT, "item_id", places.alias("places"))


def near_matches(index: DataFrame, items: DataFrame, frequencies: DataFrame, terms: int = NEAR_TERMS, span: int = SPAN) -> DataFrame:
    """doc_id, _text, item_id: texts that hold an item's ``terms`` rarest known terms within ``span`` words of its rarest one."""
    known = items.select("item_id", "term", "h").distinct().join(frequencies, "h")
    rare = known.groupBy("item_id").agg(F.slice(F.sort_array(F.collect_set(F.struct("df", "term", "h"))), 1, terms).alias("_t")).where(F.size("_t") == terms)
    rare = cut(rare.select("item_id", F.posexplode("_t.h").alias("rank", "h")), "near-terms")
    lists = index.join(_small(rare), "h").groupBy(*TEXT, "item_id", "rank").agg(F.collect_set("pos").alias("at"))
    met = lists.groupBy(*TEXT, "item_id").agg(F.collect_list(F.struct("rank", "at")).alias("_m")).where(F.size("_m") == terms)
    by_rank = F.transform(F.sort_array("_m"), lambda x: x["at"])
    near = F.exists(by_rank[0], lambda p: F.forall(by_rank, lambda more: F.exists(more, lambda q: F.abs(p - q) <= span)))
    return met.where(near).select(*TEXT, "item_id")


def _looked_up(docs: DataFrame, benchmark: DataFrame, window: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """The index, the items' words, their frequencies, and the phrase matches."""
    items = cut(item_words(benchmark), "decon-items")
    index = cut(positional_index(docs), "decon-index")
    frequencies = cut(term_frequencies(index, items.select("h").distinct()), "decon-frequencies")
    wins = cut(windows(items, frequencies, window), "decon-windows")
    found = cut(diagonals(index, wins), "decon-found")
    return index, items, frequencies, cut(phrase_matches(index, items, found, window), "decon-phrases")


def hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated, n_near of every row."""
    index, items, frequencies, found = _looked_up(docs, benchmark, window)
    per = found.groupBy(*TEXT).agg(F.size(F.array_distinct(F.flatten(F.collect_list("places")))).cast("long").alias("n_hit"), F.sort_array(F.collect_set("item_id")).alias("items"))
    near = near_matches(index, items, frequencies).groupBy(*TEXT).agg(F.count(F.lit(1)).alias("n_near")).withColumnsRenamed({"doc_id": "_d", "_text": "_t"})
    both = per.join(near, _same_text(per, near), "full_outer")
    both = both.select(F.coalesce("doc_id", "_d").alias("_d"), F.coalesce("_text", "_t").alias("_t"), "n_hit", "items", "n_near")
    both = _small(cut(both, "decon-rows"), 10 * BROADCAST_ROWS)
    rows = docs.select("doc_id", F.xxhash64("text").alias("_text"), F.size(words(F.col("text"))).cast("long").alias("n_words"))
    out = rows.join(both, _same_text(rows, both), "left")
    named = F.coalesce("items", F.array().cast("array<string>"))
    none = F.lit(0).cast("long")
    n_hit = F.coalesce("n_hit", none)
    return out.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size(named).cast("long").alias("n_items"), F.sha2(F.concat_ws(",", named).cast("binary"), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"), F.coalesce("n_near", none).alias("n_near"))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """The rows of ``docs``, all columns, without a phrase of the benchmark."""
    found = _looked_up(docs, benchmark, window)[3]
    ident, mark = unused(docs.columns, "_id"), unused(docs.columns, "_hash")
    bad = _small(cut(found.select(F.col("doc_id").alias(ident), F.col("_text").alias(mark)).distinct(), "decon-bad"), 10 * BROADCAST_ROWS)
    return docs.join(bad, docs["doc_id"].eqNullSafe(bad[ident]) & (F.xxhash64(docs["text"]) == bad[mark]), "left_anti")


def proximity_matches(docs: DataFrame, benchmark: DataFrame, terms: int = NEAR_TERMS, span: int = SPAN) -> DataFrame:
    """doc_id, item_id: texts that hold an item's ``terms`` rarest terms within ``span`` words of the rarest one."""
    items = cut(item_words(benchmark), "near-items")
    index = cut(positional_index(docs), "near-index")
    frequencies = cut(term_frequencies(index, items.select("h").distinct()), "near-frequencies")
    return near_matches(index, items, frequencies, terms, span).select("doc_id", "item_id").distinct()


_W = "regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+')"
SQL = f"""
WITH d AS (SELECT doc_id, {_W} AS w FROM documents),
b AS (SELECT item_id, w, least(len(w), 10) AS l FROM (SELECT item_id, {_W} AS w FROM benchmark) WHERE len(w) > 0),
bw AS (SELECT DISTINCT item_id, l, array_to_string(w[i : i + l - 1], ' ') AS g FROM (SELECT *, unnest(range(1, len(w) - l + 2)) AS i FROM b)),
ls AS (SELECT DISTINCT l FROM b),
dw AS (SELECT doc_id, l, i, array_to_string(w[i : i + l - 1], ' ') AS g FROM (SELECT doc_id, w, l, unnest(range(1, len(w) - l + 2)) AS i FROM d, ls WHERE len(w) >= l)),
h AS (SELECT DISTINCT doc_id, i, l, item_id FROM dw JOIN bw USING (l, g)),
p AS (SELECT doc_id, count(DISTINCT pl) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + l)) AS pl FROM h) GROUP BY doc_id),
k AS (SELECT doc_id, count(*) AS n_items, sha256(string_agg(x, ',' ORDER BY x)) AS s FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS x FROM h) GROUP BY doc_id),
dt AS (SELECT doc_id, unnest(w) AS t, unnest(range(1, len(w) + 1)) AS pos FROM d),
bt AS (SELECT DISTINCT item_id::VARCHAR AS x, unnest(w) AS t FROM b),
df AS (SELECT t, count(*) AS df FROM dt WHERE t IN (SELECT t FROM bt) GROUP BY t),
rk AS (SELECT x, t, row_number() OVER (PARTITION BY x ORDER BY df, t) AS r FROM bt JOIN df USING (t)),
pp AS (SELECT dt.doc_id, rk.x, rk.r, dt.pos FROM dt JOIN rk USING (t) WHERE rk.r <= 2),
nr AS (SELECT doc_id, count(DISTINCT x) AS n_near FROM (SELECT a.doc_id, a.x FROM pp a JOIN pp c ON a.doc_id = c.doc_id AND a.x = c.x AND a.r = 1 AND c.r = 2 AND abs(a.pos - c.pos) <= 20) GROUP BY doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       coalesce(s, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated,
       coalesce(n_near, 0)::BIGINT AS n_near
FROM d LEFT JOIN p USING (doc_id) LEFT JOIN k USING (doc_id) LEFT JOIN nr USING (doc_id)
"""
