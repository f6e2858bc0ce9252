"""N-gram Jaccard join by a token-group matrix, exact, by classes of equal shingle sets.

1. Each document's shingles become a set of 64-bit hashes; equal sets are one class.
2. Partition into groups of similar documents. Two sets that link differ in at most
   (1-t)/t times the smaller set's size many shingles. Each class deals its shingles into one segment more than
   that: two linked sets agree on a whole segment. Of classes that agree on a segment's hash, those stay
   candidates of each other whose parity sketches allow it: the sketches of two sets differ in at most as many bits as
   the sets differ in shingles. Candidates make families; every link lies inside a family.
3. In a family, classes are ordered by how many of their shingles no other has, and cut into groups.
   A row of the matrix is a group's union of shingles. The shingles that a query has in a group's union bound its
   overlap with any member; only groups whose bound reaches what a link needs are opened, and none whose
   members are already known to be in the query's component. Opened members are compared exactly.
   A family of over ``BLOCK`` shingles is worked on in pairs of blocks.
4. Links (enough to connect each component) give components; a class passes its to its documents.

Defined cases: a null or blank text has no shingles, no links, and is its own component; a text of fewer words
than a shingle is one shingle; repeated rows and equal sets are linked; a null doc_id is no component's id unless all of the
component's are null; an empty table gives an empty result; extra columns are ignored (``keep_one`` carries them).
"""

from __future__ import annotations

from math import ceil, floor, log

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkfold.llm.common import WORD, cut, tidy, trim, unused
from walkfold.llm.components import components

GROUP = 64
BLOCK = 3_000_000
BUCKET = 20_000
BITS = 1 << 25
#: A row is known by its doc_id and this hash of its text: neither a null id nor one id on two texts hides a row.
TEXT = "xxhash64(text)"
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def _mix(x: np.ndarray) -> np.ndarray:
    """The splitmix64 finaliser."""
    x = (x ^ (x >> np.uint64(30))) * _M1
    x = (x ^ (x >> np.uint64(27))) * _M2
    return x ^ (x >> np.uint64(31))


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 500_000:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


def shingles(text: bytes | None, k: int, cache: _Hashes) -> np.ndarray:
    """The sorted distinct hashes of the k-word shingles."""
    words = (text or b"").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    w = np.fromiter(map(cache.__getitem__, words), np.uint64, len(words))
    k = min(k, len(w))
    h = np.full(len(w) - k + 1, k, np.uint64)
    for i in range(k):
        h = _mix(h * np.uint64(0x9E3779B97F4A7C15) + w[i : len(w) - k + 1 + i])
    return np.unique(h)


def _space(n: int, t: float) -> int:
    """The class of sizes that n is in: sizes of one class differ by less than 1/t."""
    return int(floor(log(n) / -log(t) + 1e-9))


def _segments(space: int, t: float) -> tuple[int, int]:
    """How many segments a space has, and how many of them two linked sets agree on at least.

    A twentieth more than needed: a set of few empty segments then agrees with its partner on one that is not empty.
    """
    most = int(floor((1 - t) / t * (t ** -(space + 1) + 1) + 1e-9))
    spare = 1 + ceil(most / 20)
    return most + spare, spare


def signatures(h: np.ndarray, t: float) -> np.ndarray:
    """Hashes of the set's segments in the spaces of its size and of the next smaller sizes.

    Empty segments count only for a set that has as many as linked sets must agree on: only two
    such sets may agree on empty segments alone.
    """
    if len(h) * (1 - t) < t - 1e-9 and len(h) * (1 - t) / t < 1 - 1e-9:  # no other set is near enough
        return np.zeros(0, np.int64)
    mixed, out = _mix(h + np.uint64(77)), []
    content = _mix(h + np.uint64(1234567))
    here = _space(len(h), t)
    for space in (here, here - 1):
        if space < 0:
            continue
        m, spare = _segments(space, t)
        seg = (mixed % np.uint64(m)).astype(np.int64)
        sums = np.zeros(m, np.uint64)
        np.add.at(sums, seg, content)
        full = np.bincount(seg, minlength=m) > 0
        use = np.flatnonzero(full) if m - full.sum() < spare else np.arange(m)
        out.append(_mix(sums[use] + np.uint64(space * 1_000_003) + _mix(use.astype(np.uint64))))
    return np.concatenate(out).view(np.int64)


def sketch(h: np.ndarray) -> bytes:
    """For each of 1,024 bits or more (by the set's size), whether an odd number of shingles fall on it."""
    bits = 1024
    while bits < 2 * len(h) and bits < 1 << 17:
        bits *= 2
    at = (_mix(h) & np.uint64(bits - 1)).astype(np.int64)
    return np.packbits(np.bincount(at, minlength=bits).astype(np.uint8) & 1).tobytes()


def folded(sketches: list[bytes], width: int) -> np.ndarray:
    """Rows of ``width`` bytes: longer sketches are folded, which keeps parities."""
    out = np.zeros((len(sketches), width), np.uint8)
    for i, b in enumerate(sketches):
        row = np.frombuffer(b, np.uint8)
        out[i] = row if len(row) == width else np.bitwise_xor.reduce(row.reshape(-1, width), axis=0)
    return out.view(np.uint64)


def _key(h: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(h.tobytes()) - (1 << 63)


def classes(docs: DataFrame, k: int, t: float) -> DataFrame:
    """doc_id, _text (hash), key (of the class), n_shingles; sigs and sketch, null where the partition has had that class before."""

    def run(batches):
        cache, seen = _Hashes(), set()
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                keys, sizes, sigs, bits = [], [], [], []
                for text in part.column(1).cast(pa.binary()):
                    h = shingles(text.as_py(), k, cache)
                    key = _key(h)
                    keys.append(key)
                    sizes.append(len(h))
                    if key in seen or not len(h):
                        sigs.append(None)
                        bits.append(None)
                    else:
                        if len(seen) > 1_000_000:
                            seen.clear()
                        seen.add(key)
                        sigs.append(signatures(h, t))
                        bits.append(sketch(h))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(keys, pa.int64()), pa.array(sizes, pa.int64()), pa.array(sigs, pa.list_(pa.int64())), pa.array(bits, pa.binary())], ["doc_id", "_text", "key", "n_shingles", "sigs", "sketch"])

    return docs.select("doc_id", "text", F.expr(TEXT).alias("_text")).mapInArrow(tidy(run), "doc_id long, _text long, key long, n_shingles long, sigs array<long>, sketch binary")


def needed(a: np.ndarray, b, percent: int) -> np.ndarray:
    """The smallest overlap with which sets of sizes a and b link."""
    return -(-(percent * (a + b)) // (100 + percent))


def link_family(keys: np.ndarray, sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Pairs of keys that link, enough of them to connect what links connect."""
    order = np.argsort(keys)
    keys, sets = keys[order], [sets[i] for i in order]
    sizes = np.array([len(x) for x in sets], np.int64)
    tokens, inverse, often = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    of = np.repeat(np.arange(len(sets)), sizes)
    shared = often[inverse] > 1
    common = np.bincount(of[shared], minlength=len(sets))
    able = np.flatnonzero(common * 100 >= percent * sizes)  # the whole family as one group
    if len(able) < 2:
        return []
    able = able[np.lexsort((keys[able], sizes[able] - common[able]))]
    starts = np.concatenate([[0], np.cumsum(sizes)])
    rows = [inverse[starts[i] : starts[i + 1]][shared[starts[i] : starts[i + 1]]] for i in able]
    keys, sizes, n = keys[able], sizes[able], len(able)
    lengths = np.array([len(x) for x in rows])
    flat, ends = np.concatenate(rows), np.concatenate([[0], np.cumsum(lengths)])
    component, links = np.arange(n), []
    union = np.zeros(len(tokens), bool)
    one = np.zeros(len(tokens), bool)
    for g in range(0, n, GROUP):
        members = np.arange(g, min(g + GROUP, n))
        low, high = sizes[members].min(), sizes[members].max()
        span = flat[ends[g] : ends[members[-1] + 1]]
        union[span] = True
        # queries: this group's members and all that come after it
        bound = np.add.reduceat(union[flat[ends[g] :]], ends[g:n] - ends[g])
        union[span] = False
        size = sizes[g:]
        least = np.maximum(low, -(-percent * size // 100))
        opens = np.flatnonzero((bound >= needed(size, least, percent)) & (size * 100 >= percent * low) & (high * 100 >= percent * size)) + g
        inside = component[members]
        if (inside == inside[0]).all():
            opens = opens[component[opens] != inside[0]]
        if len(opens) < 1:
            continue
        query = np.concatenate([flat[ends[i] : ends[i + 1]] for i in opens])
        at = np.concatenate([[0], np.cumsum(lengths[opens])[:-1]])
        for y in members:
            if (component[opens] == component[y]).all():
                continue
            mine = flat[ends[y] : ends[y + 1]]
            one[mine] = True
            overlap = np.add.reduceat(one[query], at)
            one[mine] = False
            linked = opens[(overlap * (100 + percent) >= percent * (sizes[opens] + sizes[y])) & (component[opens] != component[y])]
            fresh = np.unique(component[linked], return_index=True)[1]
            links += [(int(keys[y]), int(keys[linked[i]])) for i in fresh]
            if len(linked):
                joined = np.append(component[linked], component[y])
                component[np.isin(component, joined)] = joined.min()
    return links


def near(n: np.ndarray, bits: np.ndarray, i: int, others: np.ndarray, percent: int) -> np.ndarray:
    """Which of ``others`` may link with row i, by their sketches."""
    differ = np.bitwise_count(bits[others] ^ bits[i]).sum(1, dtype=np.int64)
    return others[differ * (100 + percent) <= (100 - percent) * (n[others] + n[i])]


def cluster(n: np.ndarray, bits: np.ndarray, percent: int) -> list[tuple[int, int]]:
    """Pairs of rows that connect all that may link. A row is compared with rows that no cluster has yet."""
    left, out = np.arange(len(n)), []
    while len(left):
        wave, left = [int(left[0])], left[1:]
        while wave and len(left):
            i = wave.pop()
            found = near(n, bits, i, left, percent)
            if len(found):
                left = np.setdiff1d(left, found, assume_unique=True)
                wave += found.tolist()
                out += [(i, int(j)) for j in found]
    return out


def _candidates(found: DataFrame, percent: int) -> DataFrame:
    """a, b: classes that agree on a segment and may link by their sketches; enough pairs to connect them.

    A segment's classes are dealt into pairs of parts when they are over ``BUCKET``.
    """
    # a class comes once for each partition that holds a copy: here each class counts once
    rows = found.where("sigs IS NOT NULL").select("key", F.explode("sigs").alias("sig")).repartition("sig").dropDuplicates(["sig", "key"])
    whole = W.partitionBy("sig")
    stated = {"_a": F.min("key"), "_z": F.max("key"), "_x": F.bit_xor(F.xxhash64("key")), "_c": F.count(F.lit(1))}
    shared = rows.select("sig", "key", *[x.over(whole).alias(k) for k, x in stated.items()]).where("_a != _z")
    shared = cut(shared, "jaccard-shared")
    # near copies agree on many segments: of segments with the same classes one is enough
    one = cut(shared.groupBy(*stated).agg(F.min("sig").alias("sig")).select("sig"), "jaccard-segments")
    shared = cut(shared.join(one, "sig", "left_semi").select("sig", "key").distinct(), "jaccard-shared")
    hot = shared.groupBy("sig").agg(F.count(F.lit(1)).alias("_c")).where(F.col("_c") > BUCKET).select("sig", F.ceil(F.col("_c") / BUCKET).cast("int").alias("_parts"))
    hot = cut(hot, "jaccard-hot")
    about = found.where("sketch IS NOT NULL").groupBy("key").agg(F.first("n_shingles").alias("n"), F.first("sketch").alias("sketch"))
    rows = shared.join(about, "key").join(hot, "sig", "left").withColumn("_parts", F.coalesce("_parts", F.lit(1)))
    part = F.pmod(F.xxhash64("key"), F.col("_parts")).cast("int")
    other = F.explode(F.sequence(F.lit(0), F.col("_parts") - 1))
    rows = rows.withColumn("_p", part).withColumn("_o", other).select("sig", F.least("_p", "_o").alias("_p1"), F.greatest("_p", "_o").alias("_p2"), "key", "n", "sketch")
    rows = rows.repartition("sig", "_p1", "_p2").sortWithinPartitions("sig", "_p1", "_p2", "key")

    def run(batches):
        seen: set[tuple[int, int]] = set()
        held: pa.Table | None = None

        def work(table: pa.Table, bounds: np.ndarray):
            key, n = table["key"].to_numpy(), table["n"].to_numpy()
            sketches, pairs = table["sketch"].to_pylist(), []
            bits = folded(sketches, 128)
            at, size = bounds[:-1], np.diff(bounds)
            width = np.minimum.reduceat(np.array([len(x) for x in sketches]), at)
            two = at[(size == 2) & (width == 128)]
            differ = np.bitwise_count(bits[two] ^ bits[two + 1]).sum(1, dtype=np.int64)
            good = two[differ * (100 + percent) <= (100 - percent) * (n[two] + n[two + 1])]
            pairs += zip(key[good].tolist(), key[good + 1].tolist(), strict=True)
            rest = np.flatnonzero((size > 2) | (width > 128))
            for b, k, w in zip(at[rest].tolist(), size[rest].tolist(), width[rest].tolist(), strict=True):
                own = bits[b : b + k] if w == 128 else folded(sketches[b : b + k], w)
                pairs += [(int(key[b + i]), int(key[b + j])) for i, j in cluster(n[b : b + k], own, percent)]
            fresh = [p for p in dict.fromkeys(pairs) if p not in seen]
            if len(seen) < 500_000:
                seen.update(fresh)
            return pa.RecordBatch.from_arrays([pa.array([p[0] for p in fresh], pa.int64()), pa.array([p[1] for p in fresh], pa.int64())], ["a", "b"])

        for batch in batches:
            table = pa.Table.from_batches([batch])
            held = table if held is None else pa.concat_tables([held, table])
            names = [held[c].to_numpy() for c in ("sig", "_p1", "_p2")]
            new = np.flatnonzero(np.logical_or.reduce([x[1:] != x[:-1] for x in names])) + 1
            if len(new):  # all groups but the last are whole
                yield work(held.slice(0, new[-1]), np.concatenate([[0], new]))
                held = held.slice(new[-1])
        if held is not None and held.num_rows:
            yield work(held, np.array([0, held.num_rows]))

    return rows.mapInArrow(tidy(run), "a long, b long").distinct()


def _maybe(docs: DataFrame, reps: DataFrame) -> DataFrame:
    """doc_id, text and _text of the rows whose bit is set by a row of ``reps``: few others, so few texts are moved.

    The bit set has ``BITS`` bits, whatever the input: at most BITS / 64 rows reach the driver.
    """
    bit = F.pmod(F.xxhash64("doc_id", "_text"), F.lit(BITS))
    rows = reps.select(F.shiftright(bit, 6).alias("w"), F.call_function("shiftleft", F.lit(1).cast("long"), bit.bitwiseAND(63).cast("int")).alias("b"))
    held = rows.groupBy("w").agg(F.bit_or("b").alias("b")).toPandas()
    table = np.zeros(BITS // 64, np.uint64)
    table[held["w"].to_numpy(np.int64)] = held["b"].to_numpy(np.int64).view(np.uint64)
    sent = docs.sparkSession.sparkContext.broadcast(table)

    def run(batches):
        for batch in batches:
            at = batch.column(3).to_numpy()
            good = (sent.value[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1)
            yield pa.RecordBatch.from_arrays(batch.columns[:3], ["doc_id", "text", "_text"]).filter(pa.array(good.astype(bool)))

    rows = docs.select("doc_id", "text", F.expr(TEXT).alias("_text")).withColumn("_bit", bit)
    return rows.mapInArrow(tidy(run), "doc_id long, text string, _text long")


def links(docs: DataFrame, found: DataFrame, k: int, percent: int) -> DataFrame:
    """a, b: keys of classes that link."""
    family = components(cut(_candidates(found, percent), "jaccard-near"), "a", "b").withColumnRenamed("node", "key")
    sizes = found.where("n_shingles > 0").groupBy("key").agg(F.first("n_shingles").alias("_n"))
    family = family.join(sizes, "key")
    family = family.join(family.groupBy("root").agg(F.ceil(F.sum("_n") / BLOCK).cast("int").alias("_blocks")), "root")
    # the class's row with the least id stands for it, a row without id only where no row has one
    least = F.min(F.struct(F.col("doc_id").isNull(), F.col("doc_id"), F.col("_text"))).alias("_r")
    reps = family.join(found.where("n_shingles > 0").groupBy("key").agg(least), "key")
    reps = reps.select("_r.doc_id", "_r._text", F.col("key").alias("_key"), F.col("root").alias("_root"), "_blocks")
    mine = F.pmod(F.xxhash64("_key"), F.col("_blocks")).cast("int")
    reps = cut(reps, "jaccard-classes")
    texts = _maybe(docs, reps)
    named = texts.where("doc_id IS NOT NULL").join(reps.where("doc_id IS NOT NULL"), ["doc_id", "_text"])
    nameless = texts.where("doc_id IS NULL").dropDuplicates(["_text"]).join(reps.where("doc_id IS NULL").drop("doc_id"), "_text")
    texts = named.unionByName(nameless.select(*named.columns))
    texts = texts.withColumn("_b", mine).withColumn("_o", F.explode(F.sequence(F.lit(0), F.col("_blocks") - 1)))
    texts = texts.select("_root", F.least("_b", "_o").alias("_b1"), F.greatest("_b", "_o").alias("_b2"), "_key", "text")

    def run(table: pa.Table) -> pa.Table:
        cache, held = _Hashes(), {}
        for key, text in zip(table["_key"].to_pylist(), table["text"].cast(pa.binary()), strict=True):
            if key not in held:
                h = shingles(text.as_py(), k, cache)
                if _key(h) == key:  # another text with this hash
                    held[key] = h
        out = link_family(np.array(list(held), np.int64), list(held.values()), percent) if len(held) > 1 else []
        if table.nbytes > 8 << 20:
            held.clear()
            trim()
        return pa.table({"a": pa.array([x for x, _ in out], pa.int64()), "b": pa.array([x for _, x in out], pa.int64())})

    return texts.groupBy("_root", "_b1", "_b2").applyInArrow(run, "a long, b long")


def _components(docs: DataFrame, k: int, percent: int) -> tuple[DataFrame, DataFrame]:
    """The rows (doc_id, _text, n_shingles, key), and of each class of rows with shingles its root."""
    found = cut(classes(docs, k, percent / 100), "jaccard-sets")
    roots = components(links(docs, found, k, percent), "a", "b")
    of_class = found.where("n_shingles > 0").select("key").distinct().join(roots.withColumnRenamed("node", "key"), "key", "left")
    return found, of_class.withColumn("root", F.coalesce("root", "key"))


def component_ids(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    found, of_class = _components(docs, k, percent)
    of_class = of_class.join(found.where("n_shingles > 0").groupBy("key").agg(F.min("doc_id").alias("least")), "key")
    ids = of_class.groupBy("root").agg(F.min("least").alias("component_id"))
    of_class = cut(of_class.join(ids, "root").select("key", "component_id"), "jaccard-ids")
    out = found.select("doc_id", "n_shingles", "key").join(of_class, "key", "left")
    own = F.when(F.col("n_shingles") == 0, F.col("doc_id")).otherwise(F.col("component_id"))
    return out.select("doc_id", "n_shingles", own.alias("component_id"))


def keep_one(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """Of each component the row that comes first (by doc_id, null ids last, then by text hash), all columns.

    Rows repeated whole stay once; rows without words link with nothing and all stay. One doc_id on two texts of a
    component keeps one of them.
    """
    found, of_class = _components(docs, k, percent)
    first = F.min(F.struct(F.col("doc_id").isNull().alias("n"), "doc_id", "_text")).alias("_r")
    per_class = found.where("n_shingles > 0").groupBy("key").agg(first)
    kept = of_class.join(per_class, "key").groupBy("root").agg(F.min("_r").alias("_r"))
    ident, mark = unused(docs.columns, "_id"), unused(docs.columns, "_hash")
    kept = cut(kept.select(F.col("_r.doc_id").alias(ident), F.col("_r._text").alias(mark)), "jaccard-kept")
    blank = F.regexp_count(F.coalesce("text", F.lit("")), F.lit(WORD)) == 0
    chosen = docs.where(~blank).join(kept, docs["doc_id"].eqNullSafe(kept[ident]) & (F.xxhash64(docs["text"]) == kept[mark]), "left_semi")
    return chosen.dropDuplicates(["doc_id", "text"]).unionByName(docs.where(blank))


SQL = """
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
s AS (
  SELECT DISTINCT doc_id, array_to_string(w[i : i + 2], ' ') AS g
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 2, 1) + 1)) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS (SELECT x, y FROM p JOIN n q ON q.doc_id = x JOIN n r ON r.doc_id = y WHERE 100 * c >= 90 * (q.n + r.n - c)),
t AS (SELECT doc_id AS x, doc_id AS y FROM d UNION SELECT t.x, e.y FROM t JOIN e ON t.y = e.x)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, min(t.y) AS component_id
FROM d JOIN t ON t.x = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id GROUP BY ALL
"""
