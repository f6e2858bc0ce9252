r"""Document fingerprints: invertible Bloom lookup sketches of paragraph digests.

A text is cut into paragraphs (lines); a paragraph of over ``LONG`` characters is cut after its sentence ends, so
that a one-line text has several, and what is still longer is cut where its characters say so (a hash of the last
``WINDOW`` of them), so that texts without sentence marks have several too. The repeats of a paragraph are numbered, each
with a digest of its own. Each digest goes into one cell of each of three sub-tables; a cell holds a count, the digests' sum by xor and a check's sum by xor. Subtracting two texts' cells
leaves only what differs, and peeling cells that hold one digest recovers it. Where peeling stalls, both
texts are sketched anew with twice the cells.

The fingerprint is the sketch of ``CELLS`` cells in base64, so equal texts have equal fingerprints. The likeness of two
fingerprints is the share of their digests that both have: (a + b - d) / (a + b + d) for a and b
digests of which d differ.

Defined cases: a null text is the empty one, and has no digest; two texts without digests are alike (1), and one of them and
another text are not (0); rows are ordered by doc_id (nulls first), then by text, and the row after the last is the first; a
table of one row is followed by itself; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkfold.llm.common import input_partitions, tidy

CELLS = 12
WAYS = 3
LONG = 120
WINDOW, LEAST, MOST = 8, 24, 128
_END = re.compile(r"(?<=[.!?])\s+")
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)

_STEPS = {1: np.uint64(0x100000001B3), 2: np.uint64(0x9E3779B97F4A7C15), 4: np.uint64(0xC2B2AE3D27D4EB4F)}


def _mix(x: np.ndarray, salt: int) -> np.ndarray:
    x = x + np.uint64((salt * 0x9E3779B97F4A7C15) & (2**64 - 1))
    x = (x ^ (x >> np.uint64(30))) * _M1
    x = (x ^ (x >> np.uint64(27))) * _M2
    return x ^ (x >> np.uint64(31))


def paragraphs(text: str) -> list[str]:
    out: list[str] = []
    long: list[str] = []
    for line in text.split("\n"):
        line = line.strip()
        if len(line) > LONG:
            for piece in _END.split(line):
                (long if len(piece) > LONG else out).append(piece)
        elif line:
            out.append(line)
    return out + content_pieces(long) if long else out


def content_pieces(long: list[str]) -> list[str]:
    """Cut after about every 32nd place, chosen by the characters before it, but into LEAST to MOST characters; a piece's last part may be shorter."""
    whole = "".join(long)
    h = np.frombuffer(whole.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    for width in (1, 2, 4):  # in the end of WINDOW characters, and none of another piece's as LEAST is more
        h = h[:-width] * _STEPS[width] + h[width:]
    ends = (np.flatnonzero((h * _M1) >> np.uint64(59) == 0) + WINDOW).tolist()
    out, at, k, stop = [], 0, 0, 0
    for piece in long:
        stop += len(piece)
        while at < stop:
            while k < len(ends) and ends[k] < at + LEAST:
                k += 1
            end = min(ends[k] if k < len(ends) else stop, at + MOST, stop)
            out.append(whole[at:end])
            at = end
    return out


def digests(text: str) -> np.ndarray:
    """Distinct 64-bit digests of the text's paragraphs; the k-th repeat of one is hashed with seed k."""
    often: dict[str, int] = {}
    found = set()
    for p in paragraphs(text):
        k = often[p] = often.get(p, -1) + 1
        found.add(xxhash.xxh3_64_intdigest(p, k))
    return np.fromiter(found, np.uint64)


class Sketches:
    """The sketches of several texts: row i of each array belongs to text i."""

    def __init__(self, of: np.ndarray, found: np.ndarray, n: int, cells: int) -> None:
        """``found[k]`` is a digest of text ``of[k]``."""
        self.n, self.cells = n, cells
        self.count = np.zeros(n * cells, np.int32)
        self.key = np.zeros(n * cells, np.uint64)
        self.check = np.zeros(n * cells, np.uint64)
        for at in self._places(of, found):
            np.add.at(self.count, at, 1)
            np.bitwise_xor.at(self.key, at, found)
            np.bitwise_xor.at(self.check, at, _mix(found, 99) & np.uint64(0xFFFF))

    def _places(self, of: np.ndarray, found: np.ndarray) -> list[np.ndarray]:
        part = self.cells // WAYS
        return [of * self.cells + way * part + (_mix(found, way + 1) % np.uint64(part)).astype(np.int64) for way in range(WAYS)]

    def fingerprints(self) -> list[str]:
        packed = np.zeros((self.n, self.cells), [("n", "<u2"), ("key", "<u8"), ("check", "<u2")])
        packed["n"], packed["key"], packed["check"] = (x.reshape(self.n, -1) for x in (self.count, self.key, self.check))
        return [base64.b64encode(x.tobytes()).decode() for x in packed]

    def subtract(self, other: Sketches) -> Sketches:
        out = object.__new__(Sketches)
        out.n, out.cells = self.n, self.cells
        out.count, out.key, out.check = self.count - other.count, self.key ^ other.key, self.check ^ other.check
        return out

    def peel(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(text, digest, sign) of what was recovered, and which texts are empty after it."""
        texts, keys, signs = [], [], []
        while True:
            at = np.flatnonzero(np.abs(self.count) == 1)
            at = at[(_mix(self.key[at], 99) & np.uint64(0xFFFF)) == self.check[at]]
            pair = np.stack([(at // self.cells).astype(np.uint64), self.key[at]])
            _, first = np.unique(pair, axis=1, return_index=True)
            at = at[first]
            # a chance cell that passes the check sits where its digest would not
            home = np.zeros(len(at), bool)
            for place in self._places(at // self.cells, self.key[at]):
                home |= place == at
            at = at[home]
            if not len(at) or len(texts) > 200:
                break
            of, key, sign = at // self.cells, self.key[at], self.count[at]
            for place in self._places(of, key):
                np.subtract.at(self.count, place, sign)
                np.bitwise_xor.at(self.key, place, key)
                np.bitwise_xor.at(self.check, place, _mix(key, 99) & np.uint64(0xFFFF))
            texts.append(of)
            keys.append(key)
            signs.append(sign)
        left = (self.count != 0).reshape(self.n, -1).any(1) | (self.key != 0).reshape(self.n, -1).any(1)
        join = lambda parts, kind: np.concatenate(parts) if parts else np.zeros(0, kind)
        return join(texts, np.int64), join(keys, np.uint64), join(signs, np.int32), ~left


def _flat(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    return np.repeat(np.arange(len(sets)), [len(x) for x in sets]), np.concatenate(sets) if sets else np.zeros(0, np.uint64)


def differences(a: list[np.ndarray], b: list[np.ndarray], cells: int = CELLS) -> list[tuple[set[int], set[int]]]:
    """Per pair the digests that only the first and only the second text has, recovered from sketches alone."""
    out: list = [None] * len(a)
    todo = np.arange(len(a))
    while len(todo):
        left = Sketches(*_flat([a[i] for i in todo]), len(todo), cells)
        rest = left.subtract(Sketches(*_flat([b[i] for i in todo]), len(todo), cells))
        texts, keys, signs, done = rest.peel()
        for k in np.flatnonzero(done):
            out[todo[k]] = (set(), set())
        for t, key, sign in zip(texts.tolist(), keys.tolist(), signs.tolist(), strict=True):
            if done[t]:
                out[todo[t]][sign < 0].add(key)
        todo, cells = todo[~done], cells * 2
    return out


def likeness(a: list[np.ndarray], b: list[np.ndarray], cells: int = CELLS) -> np.ndarray:
    """The share of digests that both texts of a pair have, from the count of recovered differences."""
    sizes = np.array([len(x) + len(y) for x, y in zip(a, b, strict=True)], float)
    differ = np.zeros(len(a))
    todo = np.arange(len(a))
    while len(todo):
        left = Sketches(*_flat([a[i] for i in todo]), len(todo), cells)
        texts, _, _, done = left.subtract(Sketches(*_flat([b[i] for i in todo]), len(todo), cells)).peel()
        differ[todo[done]] = np.bincount(texts, minlength=len(todo))[done]
        todo, cells = todo[~done], cells * 2
    return np.where(sizes > 0, (sizes - differ) / np.maximum(sizes + differ, 1), 1.0)


def edited(text: str, following: str) -> str:
    """The last quarter of the text's characters replaced by as many of the next text's first."""
    n = len(text) // 4
    return text[: len(text) - n] + following[:n]


def _ranges(docs: DataFrame, parts: int) -> tuple[list[int], list]:
    """Cuts between ranges of ids, and the least doc_id of each range (null: it holds a null); about ``parts`` even ranges; at most ``parts`` + 1 values."""
    probabilities = [i / parts for i in range(1, parts)]
    ids = docs.select("doc_id")
    cuts = sorted(set(ids.approxQuantile("doc_id", probabilities, 0.2 / parts))) if probabilities else []
    found = ids.withColumn("_range", _range_of([int(x) for x in cuts])).groupBy("_range").agg(F.min(F.struct("doc_id")).alias("least")).orderBy("_range").collect()
    return [int(x) for x in cuts], found


def _range_of(cuts: list[int]):
    """How many of the sorted cuts are at most doc_id; nulls are in the first range. Found in two steps of about the root of their number."""
    if not cuts:
        return F.lit(0)
    step = max(1, int(len(cuts) ** 0.5))
    groups = [cuts[i : i + step] for i in range(0, len(cuts), step)]
    array = lambda xs: F.array(*[F.lit(x).cast("long") for x in xs])
    below = lambda xs: F.size(F.filter(xs, lambda c: c <= F.col("doc_id")))
    group = below(array([g[0] for g in groups]))
    inner = F.element_at(F.array(*[array(g) for g in groups]), group)
    return F.when(F.col("doc_id").isNull() | (group == 0), F.lit(0)).otherwise((group - 1) * step + below(inner)).cast("int")


def fingerprint_versions(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next of every row.

    Texts are dealt into ranges of doc_id once; the first row of each range also goes to the range before it.
    """
    cuts, ranges = _ranges(docs, parts or 2 * input_partitions(docs.sparkSession))
    numbers = [r["_range"] for r in ranges]
    dealt = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("_range", _range_of(cuts))
    if numbers:
        before = F.create_map(*[F.lit(x) for pair in zip(numbers, [numbers[-1], *numbers[:-1]], strict=True) for x in pair])
        firsts = {r["_range"]: r["least"]["doc_id"] for r in ranges}
        # rows that share a range's least id are all sent: which of them is first is found where they meet
        is_first = F.col("doc_id").eqNullSafe(F.element_at(F.create_map(*[F.lit(x).cast("long") if k % 2 else F.lit(x) for pair in firsts.items() for k, x in enumerate(pair)]), F.col("_range")))
        copies = F.when(is_first, F.array(F.struct(F.col("_range").alias("to"), F.lit(False).alias("ahead")), F.struct(F.element_at(before, F.col("_range")).alias("to"), F.lit(True).alias("ahead")))).otherwise(
            F.array(F.struct(F.col("_range").alias("to"), F.lit(False).alias("ahead")))
        )
        dealt = dealt.withColumn("_copy", F.explode(copies)).select("doc_id", "text", F.col("_copy.to").alias("_to"), F.col("_copy.ahead").alias("_ahead"))
        most = max(numbers) + 1
    else:
        dealt, most = dealt.select("doc_id", "text", F.col("_range").alias("_to"), F.lit(False).alias("_ahead")), 1
    dealt = dealt.repartitionById(most, F.col("_to")).sortWithinPartitions("_to", "_ahead", "doc_id", "text")

    def run(batches):
        held: list[tuple] = []  # rows whose next row is not known yet, and the last one's digests
        ended = False
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                rows = list(zip(part.column(0).to_pylist(), part.column(1).to_pylist(), part.column(3).to_pylist(), strict=True))
                own = [r for r in rows if not r[2]]
                ahead = next((r for r in rows if r[2]), None)
                if not ended:
                    held += own
                    if ahead is not None:
                        if held:
                            yield _report(held, ahead[1])
                        held, ended = [], True
                    elif len(held) > 1:
                        yield _report(held[:-1], held[-1][1])
                        held = held[-1:]

    def _report(rows, following):
        texts = [r[1] for r in rows]
        nexts = [*texts[1:], following]
        versions = [edited(t, f) for t, f in zip(texts, nexts, strict=True)]
        a, b = [digests(t) for t in texts], [digests(t) for t in versions]
        c = [*a[1:], digests(following)]
        columns = [
            pa.array([r[0] for r in rows], pa.int64()),
            pa.array([len(t) for t in texts], pa.int64()),
            pa.array([hashlib.sha256(t.encode()).hexdigest() for t in versions]),
            pa.array(Sketches(*_flat(a), len(a), CELLS).fingerprints()),
            pa.array(Sketches(*_flat(b), len(b), CELLS).fingerprints()),
            pa.array(likeness(a, b)),
            pa.array(likeness(a, c)),
        ]
        return pa.RecordBatch.from_arrays(columns, ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

    return dealt.mapInArrow(tidy(run), "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
