"""Mixing sources to target weights, with DataFrame operations only.

Each document gets a hash-random key; a source's documents are dealt into ranges of
that key. Sums of sizes by range and a running sum over the ranges of a source give
each range its place in the source; only the range that holds the cut is sorted row by
row. What comes out is one small row for each source (whole epochs, cut key, words
taken at the cut key), so texts are never shuffled.

Defined cases: a null text has size 0; null sources are one source, the last in the
order of weights; documents with one and the same id share a key, and the words left
at the cut are shared among them in proportion to their sizes (rounded down); an empty table
gives an empty result; columns of the input named like a column of the result are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkfold.llm.common import count_words, cut, unused

#: Sources' rows up to this many are broadcast (under 100 bytes each); more are joined by shuffle.
BROADCAST_SOURCES = 20_000
#: Hex digits of the key in the ranges: a source of 10^12 documents has under 10^5 in one of the last ranges.
PREFIXES = (3, 6)
ADDED = ("size", "source_size", "target", "taken")


def _source_key(source: Column) -> Column:
    return F.when(source.isNull(), F.lit("n")).otherwise(F.concat(F.lit("s"), source))


def _document_key(doc_id: Column) -> Column:
    return F.md5(F.coalesce(doc_id.cast("string"), F.lit("")))


def source_targets(sized: DataFrame, weights=(5, 2, 1), share=1.5, most=2.0) -> DataFrame:
    """One row for each source: _src, source_size, target.

    Targets in proportion to the weights that no source may exceed ``most`` times its size: sources
    are taken by rising cap per weight, and the level is the first at which the rest fit under their caps.
    """
    per = sized.groupBy("_src").agg(F.sum("size").alias("source_size"))
    order = W.orderBy(F.col("_src").startswith("n"), "_src")
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("_rank") % len(weights) + 1).cast("int"))
    per = per.withColumn("_rank", F.row_number().over(order) - 1).withColumn("_w", weight).withColumn("_cap", F.col("source_size") * F.lit(float(most)))
    by_cap, whole = W.orderBy(F.col("_cap") / F.col("_w"), "_rank"), W.partitionBy()
    before = by_cap.rowsBetween(W.unboundedPreceding, -1)
    level = (F.sum("source_size").over(whole) * F.lit(float(share)) - F.coalesce(F.sum("_cap").over(before), F.lit(0.0))) / (
        F.sum("_w").over(whole) - F.coalesce(F.sum("_w").over(before), F.lit(0.0))
    )
    per = per.withColumn("_level", level)
    fits = F.when(F.col("_level") <= F.col("_cap") / F.col("_w"), F.col("_level"))
    per = per.withColumn("_at", F.max(fits).over(whole))  # the levels fall after the first that fits
    target = F.round(F.least(F.col("_cap"), F.coalesce(F.col("_at") * F.col("_w"), F.col("_cap"))), 6)
    return per.select("_src", "source_size", target.alias("target"))


def source_cuts(sized: DataFrame, weights=(5, 2, 1), share=1.5, most=2.0) -> DataFrame:
    """One row for each source: _src, source_size, target, epochs, cut_key, cut_words, cut_group.

    ``sized`` has _src, _key, size. Keys under cut_key are taken once more than ``epochs`` times; the
    documents at cut_key (cut_group words) share cut_words.
    """
    targets = source_targets(sized, weights, share, most)
    budget = F.floor("target").cast("long")
    epochs = F.when(F.col("source_size") > 0, F.expr("CAST(floor(target) AS BIGINT) div source_size")).otherwise(F.lit(0)).cast("long")
    targets = cut(targets.withColumn("epochs", epochs).withColumn("_rest", budget - epochs * F.col("source_size")), "mix-targets")
    # the range of keys that holds the cut, found by ever longer prefixes of the key: none is sorted row by row but the last
    inside = sized.select("_src", "_key", "size")
    start = targets.where("_rest > 0").select("_src", F.lit(0).cast("long").alias("_start"), "_rest")
    for digits in PREFIXES:
        inside = inside.withColumn("_range", F.substring("_key", 1, digits))
        ranges = inside.groupBy("_src", "_range").agg(F.sum("size").alias("_sum")).join(start, "_src")
        place = W.partitionBy("_src").orderBy("_range").rowsBetween(W.unboundedPreceding, 0)
        ranges = ranges.withColumn("_end", F.col("_start") + F.sum("_sum").over(place))
        holds = ranges.where((F.col("_end") >= F.col("_rest")) & (F.col("_end") - F.col("_sum") < F.col("_rest")))
        holds = cut(holds.select("_src", "_range", (F.col("_end") - F.col("_sum")).alias("_start"), "_rest"), "mix-ranges")
        inside = cut(inside.join(holds.select("_src", "_range"), ["_src", "_range"]).select("_src", "_key", "size"), "mix-inside")
        start = holds.drop("_range")
    inside = inside.join(start, "_src").groupBy("_src", "_key", "_start", "_rest").agg(F.sum("size").alias("_group"))
    inside = inside.withColumn("_upto", F.col("_start") + F.sum("_group").over(W.partitionBy("_src").orderBy("_key")))
    at = (
        inside.where(F.col("_upto") >= F.col("_rest"))
        .groupBy("_src")
        .agg(F.min_by(F.struct("_key", "_group", (F.col("_rest") - (F.col("_upto") - F.col("_group"))).alias("words")), "_key").alias("_at"))
    )
    return (
        targets.join(at, "_src", "left")
        .select("_src", "source_size", "target", "epochs", F.col("_at._key").alias("cut_key"), F.col("_at.words").alias("cut_words"), F.col("_at._group").alias("cut_group"))
    )


def _taken(size: Column, key: Column, cuts: Column) -> Column:
    """Whole epochs, and what the cut adds: the size under the cut key, a share at it, nothing above it."""
    at = cuts["cut_key"]
    part = F.when(at.isNull() | (key > at), F.lit(0)).when(key < at, size).otherwise(F.floor(cuts["cut_words"] * size / F.greatest(cuts["cut_group"], F.lit(1))))
    return (cuts["epochs"] * size + part).cast("long")


def sized_documents(docs: DataFrame, doc_id="doc_id", text="text", source="source") -> DataFrame:
    return docs.select(F.col(doc_id).alias("doc_id"), count_words(F.col(text)).alias("size"), _source_key(F.col(source)).alias("_src"), _document_key(F.col(doc_id)).alias("_key"))


def apply_cuts(docs: DataFrame, cuts: DataFrame, text: Column, doc_id: Column, source: Column) -> DataFrame:
    """``docs`` with size, source_size, target and taken; whatever its columns are called."""
    cuts = cut(cuts, "mix-cuts")
    own, word = unused(docs.columns, "_mix"), unused(docs.columns, "_mix_words")
    rows = docs.withColumn(word, F.struct(count_words(text).alias("size"), _source_key(source).alias("src"), _document_key(doc_id).alias("key")))
    cuts = cuts.select(F.struct(*cuts.columns).alias(own))
    if cuts.count() <= BROADCAST_SOURCES:
        cuts = F.broadcast(cuts)
    rows = rows.join(cuts, F.col(f"{word}.src") == F.col(f"{own}._src"))
    taken = _taken(F.col(f"{word}.size"), F.col(f"{word}.key"), F.col(own))
    added = {"size": F.col(f"{word}.size"), "source_size": F.col(f"{own}.source_size"), "target": F.col(f"{own}.target"), "taken": taken}
    kept = [F.col(f"`{c}`") for c in docs.columns if c.lower() not in ADDED]
    return rows.select(*kept, *[v.alias(k) for k, v in added.items()])


def mix(docs: DataFrame, weights=(5, 2, 1), share=1.5, most=2.0, doc_id="doc_id", text="text", source="source") -> DataFrame:
    """All rows of ``docs`` with size, source_size, target and taken (words the mix takes, repeats counted)."""
    slim = cut(sized_documents(docs, doc_id, text, source), "mix-sizes")
    return apply_cuts(docs, source_cuts(slim, weights, share, most), F.col(text), F.col(doc_id), F.col(source))


def mix_report(docs: DataFrame, weights=(5, 2, 1), share=1.5, most=2.0) -> DataFrame:
    """doc_id, size, source_size, target, taken of every document; the texts are read once."""
    slim = cut(sized_documents(docs), "mix-sizes")
    cuts = cut(source_cuts(slim, weights, share, most), "mix-cuts")
    if cuts.count() <= BROADCAST_SOURCES:
        cuts = F.broadcast(cuts)
    own = F.struct(*cuts.columns)
    rows = slim.join(cuts.select("_src", own.alias("_mix")), "_src")
    return rows.select("doc_id", "size", "_mix.source_size", "_mix.target", _taken(F.col("size"), F.col("_key"), F.col("_mix")).alias("taken"))


SQL = """
WITH d AS (
  SELECT doc_id, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size,
         CASE WHEN source IS NULL THEN 'n' ELSE 's' || source END AS src, md5(coalesce(doc_id::VARCHAR, '')) AS k
  FROM documents),
s AS (SELECT src, sum(size)::BIGINT AS source_size FROM d GROUP BY src),
r AS (SELECT *, row_number() OVER (ORDER BY (src LIKE 'n%'), src) - 1 AS rk FROM s),
w AS (SELECT *, ([5.0, 2.0, 1.0])[(rk % 3 + 1)::INT]::DOUBLE AS w, source_size * 2.0::DOUBLE AS cap FROM r),
l AS (SELECT *, (sum(source_size) OVER () * 1.5::DOUBLE - coalesce(sum(cap) OVER b, 0.0)) / (sum(w) OVER () - coalesce(sum(w) OVER b, 0.0)) AS lev
      FROM w WINDOW b AS (ORDER BY cap / w, rk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
t AS (SELECT src, source_size, round(least(cap, coalesce((max(CASE WHEN lev <= cap / w THEN lev END) OVER ()) * w, cap)), 6) AS target FROM l),
e AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target)::BIGINT // source_size ELSE 0 END AS ep FROM t),
f AS (SELECT *, floor(target)::BIGINT - ep * source_size AS rest FROM e),
g AS (SELECT src, k, sum(size)::BIGINT AS grp FROM d GROUP BY src, k),
c AS (SELECT *, (sum(grp) OVER (PARTITION BY src ORDER BY k))::BIGINT AS upto FROM g)
SELECT d.doc_id, d.size, f.source_size, f.target,
       (f.ep * d.size + CASE WHEN c.upto <= f.rest THEN d.size WHEN c.upto - c.grp >= f.rest THEN 0
          ELSE floor((f.rest - (c.upto - c.grp)) * d.size / greatest(c.grp, 1)) END)::BIGINT AS taken
FROM d JOIN f USING (src) JOIN c ON c.src = d.src AND c.k = d.k
"""
