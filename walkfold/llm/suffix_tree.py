"""Language-model scoring with a probabilistic suffix tree.

A text is lower-cased (A-Z), cut into words, and read as a string of symbols: the words' bytes, a
blank between words, an end mark. Words and strings determine each other, so the
probability of the string is a probability of the sequence of words and its end.

1. Counts: all documents that are learned from, every position, contexts up to ``DEPTH`` symbols.
2. Every context that occurs is a candidate. The tree grows with the corpus, so it is a table dealt into pieces by the
   contexts' most recent symbols, joined to the distinct contexts of each block of documents, and never in one place.
3. A candidate is retained if its next symbols diverge from what its parent predicts (log-likelihood
   gain over ``GAIN`` per log of all symbols), or if a deeper retained context ends with it.
4. A retained context's distribution is smoothed towards its parent's, down to the root and the uniform one.
5. Each symbol is scored by the state of the longest retained suffix of what precedes it.
6. A text's score is the tree's own log10 probability of it: the sum over its symbols. The unigram base is reported
   beside it and does not enter it.

The unigram base needs each word's count over the whole training set. The vocabulary grows
with the corpus, so it is joined to each block's distinct words, by 64-bit hashes, and never broadcast.

Defined cases: a null or empty text is its end alone; a null doc_id counts as the empty string for the held-out
rule; repeated rows count as often as they occur; an empty table gives an empty result; with no training document the
tree is the uniform root; extra columns are ignored.
"""

from __future__ import annotations

import pickle
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import xxhash
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkfold.llm.common import cut, tidy, trim

DEPTH = 6
GAIN = 0.25
#: How many symbols' worth of its parent's distribution a context borrows; chosen on a split inside the training fold.
STRENGTH = 16.0
END = 10  # the line end: no word holds it
CHUNK = 1 << 20
PIECE = 1 << 24  # characters of text for one piece of the tree
BLOCK_ROWS = 4_500


def held_out(doc_id: int | None, folds: int = 10) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % folds == 0


def words(text: bytes | None) -> list[bytes]:
    """bytes.lower and bytes.split know A-Z and the six blanks alone."""
    return (text or b"").lower().split()


def stream(parts: list[list[bytes]], depth: int = DEPTH) -> tuple[np.ndarray, np.ndarray]:
    """Symbols of the documents with ``depth`` end marks before each, and where each begins."""
    pad = bytes([END]) * depth
    texts = [b" ".join(x) for x in parts]
    sizes = np.array([len(x) + 1 for x in texts], np.int64)
    symbols = np.frombuffer(pad + (bytes([END]) + pad).join(texts) + bytes([END]), np.uint8)
    starts = np.concatenate([[0], np.cumsum(sizes + depth)[:-1]]) + depth
    return symbols, starts


def chunks(docs: Iterator[list[bytes]]) -> Iterator[list[list[bytes]]]:
    group, held = [], 0
    for x in docs:
        group.append(x)
        held += sum(map(len, x)) + len(x)
        if held >= CHUNK:
            yield group
            group, held = [], 0
    if group:
        yield group


def codes_of(symbols: np.ndarray, starts: np.ndarray, depth: int = DEPTH) -> np.ndarray:
    """For every symbol of a document: itself in the low byte, what precedes it in the bytes above."""
    real = np.ones(len(symbols), bool)
    for d in range(1, depth + 1):
        real[starts - d] = False
    at = np.flatnonzero(real)
    wide = symbols.astype(np.uint64)
    code = wide[at]
    for d in range(1, depth + 1):
        code |= wide[at - d] << np.uint64(8 * d)
    return code


def count_codes(groups: Iterator[list[list[bytes]]], depth: int = DEPTH) -> tuple[np.ndarray, np.ndarray]:
    """Distinct codes and their counts; chunks merge pairwise, so each code is sorted a logarithm of times."""
    ladder: list[tuple[np.ndarray, np.ndarray]] = []
    for group in groups:
        new = np.unique(codes_of(*stream(group, depth), depth), return_counts=True)
        while ladder and len(ladder[-1][0]) < 2 * len(new[0]):
            new = _merge(ladder.pop(), new)
        ladder.append(new)
    out = (np.zeros(0, np.uint64), np.zeros(0, np.int64))
    for x in reversed(ladder):
        out = _merge(x, out)
    return out


def _merge(a, b):
    codes, inverse = np.unique(np.concatenate([a[0], b[0]]), return_inverse=True)
    return codes, np.bincount(inverse, weights=np.concatenate([a[1], b[1]]), minlength=len(codes)).astype(np.int64)


class SuffixTree:
    """The whole tree of a small corpus in memory; the tests hold the table's scores against it. States, their children by the next older symbol, and log10 probabilities of the next symbol."""

    def __init__(self, rows: np.ndarray, total: int, depth: int = DEPTH, gain: float = GAIN, strength: float = STRENGTH) -> None:
        """``rows``: depth, code (context above the symbol's byte), count; of candidates and the root."""
        self.depth = depth
        d, code, n = rows["depth"], rows["code"].astype(np.uint64), rows["count"].astype(np.float64)
        used = np.unique(np.concatenate([(code & np.uint64(255)).astype(np.int64), [END]]))
        self.classes = np.full(256, len(used), np.uint8 if len(used) < 255 else np.int16)
        self.classes[used] = np.arange(len(used))
        size = self.size = len(used) + 1
        unseen = 256 - len(used)
        base = np.full(size, 1 / 256)
        base[-1] = 1 / 256 if unseen else 0.0
        root = np.zeros(size)
        top = d == 0
        root[self.classes[(code[top] & np.uint64(255)).astype(np.int64)]] = n[top]
        levels = [{"ctx": np.zeros(1, np.uint64), "p": ((root + 256 * base * 0.01) / (root.sum() + 2.56))[None, :], "up": np.zeros(1, np.int64), "keep": np.ones(1, bool)}]
        bar = gain * np.log(max(total, 2))
        for k in range(1, depth + 1):
            here = d == k
            ctx, inverse = np.unique(code[here] >> np.uint64(8), return_inverse=True)
            above = levels[-1]
            parent = ctx & np.uint64((1 << (8 * (k - 1))) - 1)
            up = np.searchsorted(above["ctx"], parent)
            up = np.minimum(up, len(above["ctx"]) - 1)
            known = above["ctx"][up] == parent
            counts = np.zeros((len(ctx), size), np.float32)
            np.add.at(counts, (inverse, self.classes[(code[here] & np.uint64(255)).astype(np.int64)]), n[here])
            counts, ctx, up = counts[known], ctx[known], up[known]
            sums = counts.sum(1, keepdims=True)
            before = above["p"][up]
            p = (counts + strength * before) / (sums + strength)
            with np.errstate(divide="ignore", invalid="ignore"):
                won = np.where(counts > 0, counts * np.log(counts / sums / before), 0).sum(1)
            levels.append({"ctx": ctx, "p": p.astype(np.float32), "up": up, "keep": won > bar})
        for k in range(depth, 0, -1):
            levels[k - 1]["keep"][levels[k]["up"][levels[k]["keep"]]] = True
        number = np.zeros(1, np.int64)
        tables, children, states = [levels[0]["p"]], [], 1
        for k in range(1, depth + 1):
            lv = levels[k]
            kept = np.flatnonzero(lv["keep"])
            fresh = np.full(len(lv["ctx"]), -1)
            fresh[kept] = np.arange(states, states + len(kept))
            oldest = (lv["ctx"][kept] >> np.uint64(8 * (k - 1))).astype(np.int64)
            children.append((number[lv["up"][kept]], self.classes[oldest].astype(np.int64), fresh[kept]))
            # a retained context's parent is retained, so its smoothing is the parent state's
            tables.append(lv["p"][kept])
            number, states = fresh, states + len(kept)
        self.logp = np.log10(np.maximum(np.concatenate(tables), 1e-30)).astype(np.float32).ravel()
        self.child = np.zeros(states * size, np.int32)
        for parents, symbols, ids in children:
            self.child[parents * size + symbols] = ids
        self.states = states

    def score(self, parts: list[list[bytes]]) -> np.ndarray:
        """log10 probability of each document (a list of words) and its end."""
        symbols, starts = stream(parts, self.depth)
        x = self.classes[symbols].astype(np.int32)
        node = np.zeros(len(x), np.int32)
        active = np.arange(self.depth, len(x))
        for d in range(1, self.depth + 1):
            found = self.child[node[active] * self.size + x[active - d]]
            good = found > 0
            active = active[good]
            node[active] = found[good]
            if not len(active):
                break
        value = self.logp[node * self.size + x].astype(np.float64)
        for d in range(1, self.depth + 1):
            value[starts - d] = 0.0
        return np.add.reduceat(value, starts)


# -- the tree as a table: contexts dealt by their most recent symbols ----------------------------------------------
#
# A key holds a context and its next symbol, the most recent symbol of the context on top, so all contexts that end
# alike are one range of keys. Pieces are ranges of keys: whatever lies below a suffix is in one piece, but for the few
# suffixes that hold a cut between pieces ("upper" ones, at most DEPTH a cut), whose counts are added up beforehand.


def keys_of(symbols: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For every symbol of a document its key; and where each document's first key is."""
    code = codes_of(symbols, starts)
    key = code & np.uint64(255)
    for d in range(1, DEPTH + 1):
        key |= ((code >> np.uint64(8 * d)) & np.uint64(255)) << np.uint64(8 * (DEPTH + 1 - d))
    return key, starts - DEPTH * np.arange(1, len(starts) + 1)


def shrink(x: np.ndarray) -> bytes:
    """Bytes of equal weight side by side, which compress well."""
    return pa.compress(np.ascontiguousarray(x).view(np.uint8).reshape(len(x), x.itemsize).T.tobytes(), "zstd", asbytes=True)


def grow(data: bytes, size: int, kind) -> np.ndarray:
    width = np.dtype(kind).itemsize
    planes = np.frombuffer(pa.decompress(data, size * width, "zstd", asbytes=True), np.uint8).reshape(width, size)
    return np.ascontiguousarray(planes.T).view(kind).reshape(size)


def steps(sorted_keys: np.ndarray) -> np.ndarray:
    return np.diff(sorted_keys, prepend=np.uint64(0))


def hashes(terms) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, terms), np.uint64, len(terms))


class Cuts:
    """Cuts between pieces: contexts for the keys, hashes for the words; and the suffixes that hold a cut."""

    def __init__(self, contexts: np.ndarray, term_pieces: int) -> None:
        self.contexts = np.unique(contexts.astype(np.uint64))
        self.terms = np.array([i * (1 << 64) // term_pieces for i in range(1, term_pieces)], np.uint64)
        self.upper = [np.unique(np.append(self.contexts >> np.uint64(8 * (DEPTH - k)), [] if k else np.uint64(0)).astype(np.uint64)) for k in range(DEPTH)]
        self.up = [np.zeros(1, np.int64)] + [np.searchsorted(self.upper[k - 1], self.upper[k] >> np.uint64(8)) for k in range(1, DEPTH)]

    @property
    def pieces(self) -> int:
        return len(self.contexts) + len(self.terms) + 2

    def split(self, keys: np.ndarray, terms: np.ndarray) -> list[tuple[np.ndarray, int, int]]:
        """Of sorted keys and sorted hashes: each piece's part."""
        out = []
        for x, cuts in ((keys, self.contexts << np.uint64(8)), (terms, self.terms)):
            ends = [0, *np.searchsorted(x, cuts).tolist(), len(x)]
            out += [(x, a, b) for a, b in zip(ends, ends[1:], strict=False)]
        return out

    def find(self, k: int, contexts: np.ndarray) -> np.ndarray:
        """The number among the upper suffixes of length k of these ones, -1 where it is none."""
        if not len(self.upper[k]):
            return np.full(len(contexts), -1)
        at = np.minimum(np.searchsorted(self.upper[k], contexts), len(self.upper[k]) - 1)
        return np.where(self.upper[k][at] == contexts, at, -1)


class Upper:
    """Distributions of the upper suffixes over all 256 symbols, and which of them diverge from their parent's."""

    def __init__(self, cuts: Cuts, key: np.ndarray, n: np.ndarray) -> None:
        self.cuts, self.counts, self.p, self.diverges = cuts, [], [], []
        for k in range(DEPTH):
            here = key[(key >> 56) == k] & ((1 << 56) - 1)
            counts = np.zeros((len(cuts.upper[k]), 256))
            counts[cuts.find(k, (here >> 8).astype(np.uint64)), here & 255] = n[(key >> 56) == k]
            sums = counts.sum(1, keepdims=True)
            if k == 0:
                self.total = int(sums[0, 0])
                self.bar = GAIN * np.log(max(self.total, 2))
                p, won = (counts + 0.01) / (sums + 2.56), np.array([np.inf])
            else:
                before = self.p[-1][cuts.up[k]]
                p = (counts + STRENGTH * before) / (sums + STRENGTH)
                with np.errstate(divide="ignore", invalid="ignore"):
                    won = np.where(counts > 0, counts * np.log(counts / sums / before), 0).sum(1)
            self.counts.append(counts)
            self.p.append(p)
            self.diverges.append(won > self.bar)

    def retained(self, flags: np.ndarray) -> list[np.ndarray]:
        """``flags``: length << 48 | number of upper suffixes with a retained context right below."""
        keep = [x.copy() for x in self.diverges]
        for k in range(DEPTH - 1, -1, -1):
            keep[k][flags[(flags >> 48) == k] & ((1 << 48) - 1)] = True
            if k:
                keep[k - 1][self.cuts.up[k][keep[k]]] = True
        return keep

    def answers(self, keys: np.ndarray, keep: list[np.ndarray]) -> np.ndarray:
        """Probabilities where no context below the upper suffixes is retained."""
        best, out, symbol = None, None, (keys & np.uint64(255)).astype(np.int64)
        for k in range(DEPTH):
            best = np.where(keep[k][:, None], self.p[k], best[self.cuts.up[k]]) if k else self.p[0]
            at = self.cuts.find(k, keys >> np.uint64(8 * (DEPTH + 1 - k)))
            found = best[np.maximum(at, 0), symbol] if len(best) else np.zeros(len(keys))
            out = found if out is None else np.where(at >= 0, found, out)
        return out


def tree_piece(keys: np.ndarray, n: np.ndarray, upper: Upper) -> tuple[np.ndarray, np.ndarray]:
    """log10 probability of each distinct key under its longest retained context (nan: an upper one), and flags for ``retained``."""
    pairs, ups, counts = [None] * (DEPTH + 1), [None] * (DEPTH + 1), [None] * (DEPTH + 1)
    pairs[DEPTH], counts[DEPTH] = keys, n.astype(float)
    for k in range(DEPTH, 0, -1):
        # the oldest symbol of a context is next to the symbol's byte
        less = ((pairs[k] >> np.uint64(16)) << np.uint64(8)) | (pairs[k] & np.uint64(255))
        pairs[k - 1], ups[k] = np.unique(less, return_inverse=True)
        counts[k - 1] = np.bincount(ups[k], weights=counts[k], minlength=len(pairs[k - 1]))
    p, levels = [], []
    for k in range(DEPTH + 1):
        context, of = np.unique(pairs[k] >> np.uint64(8), return_inverse=True)
        high = upper.cuts.find(k, context) if k < DEPTH else np.full(len(context), -1)
        sums = np.bincount(of, weights=counts[k], minlength=len(context))
        if k:
            before = p[-1][ups[k]]
            here = (counts[k] + STRENGTH * before) / (sums[of] + STRENGTH)
            with np.errstate(divide="ignore", invalid="ignore"):
                won = np.bincount(of, weights=np.where(counts[k] > 0, counts[k] * np.log(counts[k] / sums[of] / before), 0), minlength=len(context))
        else:
            here, won = np.zeros(len(pairs[0])), np.zeros(len(context))
        if k < DEPTH and (high >= 0).any():
            top = high[of] >= 0
            here[top] = upper.p[k][high[of][top], (pairs[k][top] & np.uint64(255)).astype(np.int64)]
        p.append(here)
        levels.append((context, of, high, (won > upper.bar) & (high < 0)))
    flags = []
    for k in range(DEPTH, 0, -1):
        context, _, _, keep = levels[k]
        above = np.searchsorted(levels[k - 1][0], context[keep] >> np.uint64(8))
        high = levels[k - 1][2][above]
        levels[k - 1][3][above[high < 0]] = True
        flags.append(np.unique(high[high >= 0]) | ((k - 1) << 48))
    # a retained context's parent is retained, so the last that is found is the longest
    value = np.where(levels[0][3][levels[0][1]], p[0], np.nan)
    for k in range(1, DEPTH + 1):
        value = np.where(levels[k][3][levels[k][1]], p[k], value[ups[k]])
    return np.log10(np.maximum(value, 1e-30)).astype(np.float32), np.concatenate(flags).astype(np.int64)


def union(parts: list[np.ndarray]) -> np.ndarray:
    return np.unique(np.concatenate(parts)) if parts else np.zeros(0, np.uint64)


def sample(docs: DataFrame) -> Cuts:
    """Cuts of about even pieces, from every 64th text; results do not depend on where they are."""

    def run(batches):
        size, parts, at = 0, [], 0
        for batch in batches:
            text = batch.column(0).cast(pa.binary())
            size += pa.compute.sum(pa.compute.binary_length(text)).as_py() or 0
            picked = [words(text[i].as_py()) for i in range(-at % 64, len(text), 64)]
            at += len(text)
            if picked:
                parts.append(np.unique(keys_of(*stream(picked))[0]))
        found = union(parts)
        found = (found[:: max(1, len(found) // 256)] >> np.uint64(8)).view(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array([size]), pa.array([found.tobytes()], pa.binary())], ["size", "contexts"])

    rows = docs.select("text").mapInArrow(tidy(run), "size long, contexts binary").collect()
    size = sum(r["size"] for r in rows)
    found = np.sort(np.concatenate([np.frombuffer(r["contexts"], np.uint64) for r in rows] or [np.zeros(0, np.uint64)]))
    pieces = min(1 + size // PIECE, 1 + len(found))
    return Cuts(found[np.arange(1, pieces) * len(found) // pieces], 1 + size // (4 * PIECE))


def pack(docs: DataFrame, cuts: Cuts, folds: int) -> DataFrame:
    """For each block and piece the block's distinct keys (or words' hashes) with their training counts; and the upper suffixes' counts."""

    def rows(block: int, learnt: list, other: list, terms: dict):
        keys, n = count_sorted(learnt)
        more = np.setdiff1d(union(other), keys, assume_unique=True)
        order = np.argsort(all_keys := np.concatenate([keys, more]), kind="stable")
        all_n = np.concatenate([n, np.zeros(len(more), np.int64)])[order]
        all_keys = all_keys[order]
        hashed, inverse = np.unique(hashes(terms), return_inverse=True)
        often = np.bincount(inverse, weights=np.fromiter(terms.values(), np.int64, len(terms)), minlength=len(hashed)).astype(np.int64)
        for piece, (x, a, b) in enumerate(cuts.split(all_keys, hashed)):
            count = (all_n if x is all_keys else often)[a:b]
            yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in ((block, pa.int64()), (piece, pa.int32()), (b - a, pa.int64()), (shrink(steps(x[a:b])), pa.binary()), (shrink(count), pa.binary()), (None, pa.int64()), (None, pa.int64()))], PACKED)
        top = []
        for k in range(DEPTH):
            context = keys >> np.uint64(8 * (DEPTH + 1 - k))
            here = cuts.find(k, context) >= 0
            if here.any():
                pair, inverse = np.unique((context[here] << np.uint64(8)) | (keys[here] & np.uint64(255)), return_inverse=True)
                top.append((pair.astype(np.int64) | (k << 56), np.bincount(inverse, weights=n[here]).astype(np.int64)))
        if top:
            key, n = np.concatenate([x[0] for x in top]), np.concatenate([x[1] for x in top])
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(key), block)), *[pa.nulls(len(key), t) for t in (pa.int32(), pa.int64(), pa.binary(), pa.binary())], pa.array(key), pa.array(n)], PACKED)

    def run(batches):
        now, learnt, other, terms, texts = None, [], [], {}, ([], [])
        held = [0, 0]

        def close(which):
            if texts[which]:
                keys = keys_of(*stream(texts[which]))[0]
                if which:
                    other.append(np.unique(keys))
                    if len(other) > 8:
                        other[:] = [union(other)]
                else:
                    add_sorted(learnt, np.unique(keys, return_counts=True))
                texts[which].clear()
                held[which] = 0

        def block_rows():
            close(0), close(1)
            yield from rows(now, learnt, other, terms)

        for batch in batches:
            for block, doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).cast(pa.binary()), strict=True):
                if block != now:
                    if now is not None:
                        yield from block_rows()
                    now, learnt, other, terms = block, [], [], {}
                got, which = words(text.as_py()), int(held_out(doc_id, folds))
                for w in got:
                    terms[w] = terms.get(w, 0) + 1 - which
                terms[b"\n"] = terms.get(b"\n", 0) + 1 - which
                texts[which].append(got)
                held[which] += sum(map(len, got)) + len(got)
                if held[which] >= CHUNK:
                    close(which)
        if now is not None:
            yield from block_rows()

    return docs.mapInArrow(tidy(run), "block long, piece int, size long, keys binary, counts binary, key long, n long")


def add_sorted(ladder: list, new: tuple[np.ndarray, np.ndarray]) -> None:
    while ladder and len(ladder[-1][0]) < 2 * len(new[0]):
        new = _merge(ladder.pop(), new)
    ladder.append(new)


def count_sorted(ladder: list) -> tuple[np.ndarray, np.ndarray]:
    out = (np.zeros(0, np.uint64), np.zeros(0, np.int64))
    for x in reversed(ladder):
        out = _merge(x, out)
    return out


def answer(packed: DataFrame, cuts: Cuts, upper) -> DataFrame:
    """For each block and piece what the block's keys (or words) score in the whole, in the keys' order."""
    first_term = len(cuts.contexts) + 1

    def run(batches):
        rows = [x for batch in batches for x in batch.to_pylist()]
        if not rows:
            return
        sizes = [r["size"] for r in rows]
        keys, of = np.unique(np.concatenate([np.cumsum(grow(r["keys"], r["size"], np.uint64), dtype=np.uint64) for r in rows]), return_inverse=True)
        n = np.bincount(of, weights=np.concatenate([grow(r["counts"], r["size"], np.int64) for r in rows]), minlength=len(keys)).astype(np.int64)
        tree = rows[0]["piece"] < first_term
        values, flags = tree_piece(keys, n, pickle.loads(upper.value)) if tree else (n, np.zeros(0, np.int64))
        at, seen, total = 0, 0 if tree else int((n > 0).sum()), 0 if tree else int(n.sum())
        for r, size in zip(rows, sizes, strict=True):
            data = shrink(values[of[at : at + size]])
            at += size
            yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in ((r["block"], pa.int64()), (r["piece"], pa.int32()), (size, pa.int64()), (data, pa.binary()), (flags.tobytes(), pa.binary()), (seen, pa.int64()), (total, pa.int64()))], ANSWER)

    packed = packed.where("piece IS NOT NULL").select("block", "piece", "size", "keys", "counts").repartitionById(cuts.pieces, F.col("piece"))
    return packed.mapInArrow(tidy(run), "block long, piece int, size long, data binary, flags binary, seen long, total long")


def score_documents(docs: DataFrame, folds: int = 10) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row."""
    spark, row = docs.sparkSession, F.monotonically_increasing_id()
    docs = docs.select("doc_id", "text")
    cuts = sample(docs)
    # rows of one partition, BLOCK_ROWS at a time
    docs = docs.select((F.shiftright(row, 33) * (1 << 20) + F.floor(row.bitwiseAND(F.lit((1 << 33) - 1)) / BLOCK_ROWS)).cast("long").alias("block"), "doc_id", "text")
    packed = cut(pack(docs, cuts, folds), "lm-packed")
    rows = packed.where("key IS NOT NULL").groupBy("key").agg(F.sum("n").alias("n")).toPandas()
    # sent with its code, so that no executor needs this package
    upper = spark.sparkContext.broadcast(cloudpickle.dumps(Upper(cuts, rows["key"].to_numpy(np.int64), rows["n"].to_numpy(np.int64))))
    first_term = len(cuts.contexts) + 1

    def block(texts: pa.Table, answers: pa.Table) -> pa.Table:
        try:
            return _block(texts, answers)
        finally:
            trim()

    def _block(texts: pa.Table, answers: pa.Table) -> pa.Table:
        rows = sorted(answers.to_pylist(), key=lambda r: r["piece"])
        values = np.concatenate([grow(r["data"], r["size"], np.float32) for r in rows[:first_term]])
        counts = np.concatenate([grow(r["data"], r["size"], np.int64) for r in rows[first_term:]])
        above = pickle.loads(upper.value)
        keep = above.retained(np.concatenate([np.frombuffer(r["flags"], np.int64) for r in rows]))
        seen, n_all = sum(r["seen"] for r in rows), sum(r["total"] for r in rows)
        ids = texts["doc_id"].to_pylist()
        vocabulary: defaultdict = defaultdict()
        vocabulary.default_factory = vocabulary.__len__
        parts, sizes, terms = [], [], []
        for group in chunks(words(t.as_py()) for t in texts["text"].cast(pa.binary())):
            keys, starts = keys_of(*stream(group))
            found, of = np.unique(keys, return_inverse=True)
            parts.append((found, of.astype(np.int32), starts))
            for got in group:
                terms.append(np.fromiter(map(vocabulary.__getitem__, [*got, b"\n"]), np.int32, len(got) + 1))
                sizes.append(len(got) + 1)
        keys = union([x[0] for x in parts])
        hashed, inverse = np.unique(hashes(vocabulary), return_inverse=True)
        if len(keys) != len(values) or len(hashed) != len(counts):
            raise ValueError("the table's rows came in another order when they were read again")
        upper_ones = np.flatnonzero(np.isnan(values))
        values[upper_ones] = np.log10(np.maximum(above.answers(keys[upper_ones], keep), 1e-30))
        tree = np.concatenate([np.add.reduceat(values[np.searchsorted(keys, found)].astype(np.float64)[of], starts) for found, of, starts in parts])
        sizes = np.array(sizes)
        at = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        count = counts[inverse][np.concatenate(terms)]
        base = np.add.reduceat(np.log10(count + 0.1), at) - sizes * np.log10(n_all + 0.1 * (seen + 1))
        known = np.add.reduceat((count > 0).astype(np.int64), at)
        columns = (pa.array(ids, pa.int64()), pa.array([held_out(i, folds) for i in ids], pa.bool_()), pa.array(sizes), pa.array(known), pa.array(np.full(len(ids), n_all)), pa.array(base), pa.array(tree))
        return pa.table(dict(zip(("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"), columns, strict=True)))

    both = docs.groupBy("block").cogroup(answer(packed, cuts, upper).groupBy("block"))
    return both.applyInArrow(block, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


PACKED = ["block", "piece", "size", "keys", "counts", "key", "n"]
ANSWER = ["block", "piece", "size", "data", "flags", "seen", "total"]
