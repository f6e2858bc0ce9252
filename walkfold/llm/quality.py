"""Quality classifier: Bradley-Terry ranking from preference pairs.

Pairs set a labelled good document against a labelled bad one. The chance that the first is preferred is the
logistic of the difference of two scores, each linear in a document's features (what bytes it has, which kinds of
character follow which, how its words repeat, over its whole text). The threshold is the quantile of the labelled scores
at the share of bad labels; a logistic curve through it maps scores to 0..1.

Labelled rows: all but those of a held-out fold. They are dealt into blocks, and all pairs of a good and a bad one inside a
block count; each Newton step is one pass over the blocks. Features of every document come from its whole text, once.

Defined cases: a null or empty text has the features of no character and gets a score like any other;
without labelled rows every score is 0.5, and with labels of one class their share; labels that are null or not 0 or 1 are not
learned from; repeated labels count as often; an empty table gives an empty result; extra columns are ignored (``keep_good`` carries them).
"""

from __future__ import annotations

import zlib
from collections import Counter
from dataclasses import dataclass, field
from itertools import islice
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkfold.llm.common import cut, tidy

#: Rows of the commoner class in a block, and of the rarer one at least (copies, if it is rare): all their pairs are learned from.
BLOCK, RARE = 192, 16

#: A step's sums come to the driver in at most so many parts (1 MB each); Newton steps at most; weight of the squared weights.
PARTIALS, MOST_STEPS, RIDGE = 32, 30, 3e-3

#: Kinds of byte: other, blank, line end, digit, upper, lower, part of a non-ASCII letter, sentence mark, symbol.
_KINDS = np.zeros(256, np.int64)
for _kind, _bytes in enumerate((b" \t", b"\n\r\x0b\x0c", b"0123456789", bytes(range(65, 91)), bytes(range(97, 123)), bytes(range(128, 256)), b".,;:!?'\"-()", b"#$%&*+/<=>@[\\]^_`{|}~"), 1):
    _KINDS[list(_bytes)] = _kind
N_KINDS = 9
N_FEATURES = 256 + N_KINDS * N_KINDS + 5


def features(texts: list[bytes | None]) -> np.ndarray:
    """Roots of the shares of bytes, pairs of kinds, words that repeat the one before, the commonest word, and distinct words; the log of the length."""
    out = np.zeros((len(texts), N_FEATURES), np.float32)
    for i, text in enumerate(texts):
        if not text:
            continue
        data = np.frombuffer(text, np.uint8)
        kinds = _KINDS[data]
        out[i, :256] = np.bincount(data, minlength=256) / len(data)
        if len(data) > 1:
            out[i, 256:-5] = np.bincount(kinds[:-1] * N_KINDS + kinds[1:], minlength=N_KINDS * N_KINDS) / (len(data) - 1)
        words = text.split()
        if words:
            counts = Counter(words)
            out[i, -5] = sum(map(eq, words, islice(words, 1, None))) / len(words)
            out[i, -4] = max(counts.values()) / (len(words) + 20)
            out[i, -3] = len(counts) / len(words)
        out[i, -2] = min(np.log1p(len(data)) / 12, 1.5) ** 2
        out[i, -1] = 1.0
    return np.sqrt(out)


@dataclass
class Ranker:
    """Weights and the curve from scores to 0..1."""

    weights: np.ndarray = field(default_factory=lambda: np.zeros(N_FEATURES))
    at: float = 0.0
    scale: float = 0.0
    shift: float = 0.0

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip((x @ self.weights - self.at) * self.scale + self.shift, -50, 50)))


def is_held_out(doc_id: int | None) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % 3 == 1


def _featured(docs: DataFrame) -> DataFrame:
    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 2000):
                part = batch.slice(at, 2000)
                x = features(part.column(1).cast(pa.binary()).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array([r.tobytes() for r in x], pa.binary())], ["doc_id", "x"])

    return docs.select("doc_id", "text").mapInArrow(tidy(run), "doc_id long, x binary")


def _matrix(column) -> np.ndarray:
    """A row of features for each element."""
    return np.frombuffer(b"".join(column.to_pylist()), np.float32).reshape(-1, N_FEATURES)


def _blocks(rows: DataFrame, known: DataFrame, counts: dict[int, int]) -> DataFrame:
    """Labelled rows dealt into blocks by a hash of their ids, a block in a row: x, y, and which rows are no copies.

    Rows of the rarer class stand in several blocks if they are few, so that every block has about RARE of them: each
    labelled row meets rows of the other class.
    """
    common, rare = (0, 1) if counts[0] >= counts[1] else (1, 0)
    blocks = -(-counts[common] // BLOCK)
    copies = min(blocks, max(1, -(-RARE * blocks // counts[rare])))
    dealt = known.withColumn("h", F.xxhash64("doc_id")).withColumn("k", F.explode(F.when(F.col("label") == rare, F.sequence(F.lit(0), F.lit(copies - 1))).otherwise(F.array(F.lit(0)))))
    dealt = dealt.withColumn("block", F.pmod(F.col("h") + F.col("k"), F.lit(blocks)))

    def gather(t: pa.Table) -> pa.Table:
        x, y, h, k = _matrix(t["x"]), t["label"].to_numpy(), t["h"].to_numpy(), t["k"].to_numpy()
        order = np.lexsort((*x[:, ::40].T, k, y, h))
        return pa.table({"x": pa.array([x[order].tobytes()], pa.binary()), "y": pa.array([y[order].astype(np.int8).tobytes()], pa.binary()), "own": pa.array([(k[order] == 0).tobytes()], pa.binary())})

    packed = rows.join(dealt, "doc_id").select("block", "x", "label", "h", "k").groupBy("block").applyInArrow(gather, "x binary, y binary, own binary")
    return cut(packed, "quality-blocks")


def _over(blocks: DataFrame, use) -> list[bytes]:
    """``use(list of (x, y, own))`` of at most PARTIALS parts of the blocks."""

    def run(batches):
        def each():
            for batch in batches:
                for x, y, own in zip(*(batch.column(c).to_pylist() for c in ("x", "y", "own")), strict=True):
                    yield np.frombuffer(x, np.float32).reshape(-1, N_FEATURES).astype(np.float64), np.frombuffer(y, np.int8), np.frombuffer(own, bool)

        yield pa.RecordBatch.from_arrays([pa.array([use(each())], pa.binary())], ["part"])

    return [bytes(r.part) for r in blocks.coalesce(PARTIALS).mapInArrow(tidy(run), "part binary").collect()]


def _summed(parts: list[bytes]) -> np.ndarray:
    total = np.frombuffer(parts[0]).copy()
    for p in parts[1:]:
        total += np.frombuffer(p)
    return total


def _moments(blocks) -> bytes:
    out = np.zeros(1 + 2 * N_FEATURES)
    for x, _, _ in blocks:
        out += np.concatenate([[len(x)], x.sum(0), (x**2).sum(0)])
    return out.tobytes()


def _slopes(blocks, w: np.ndarray, spread: np.ndarray) -> bytes:
    """Over all pairs of a block: their number, the loss, its gradient and its second derivatives."""
    n, loss, slope, bend = 0.0, 0.0, np.zeros(N_FEATURES), np.zeros((N_FEATURES, N_FEATURES))
    for x, y, _ in blocks:
        good, bad = x[y == 1] / spread, x[y == 0] / spread
        if not len(good) or not len(bad):
            continue
        ahead = (good @ w)[:, None] - (bad @ w)[None, :]
        lost = 1 / (1 + np.exp(np.clip(ahead, -50, 50)))
        n, loss = n + ahead.size, loss + np.logaddexp(0, -ahead).sum()
        slope += lost.sum(0) @ bad - lost.sum(1) @ good
        curved = lost * (1 - lost)
        cross = good.T @ (curved @ bad)
        bend += (good * curved.sum(1)[:, None]).T @ good + (bad * curved.sum(0)[:, None]).T @ bad - cross - cross.T
    return np.concatenate([[n, loss], slope, bend.ravel()]).tobytes()


def _fitted(blocks: DataFrame) -> np.ndarray:
    """The weights with the least mean loss over all pairs inside blocks, by damped Newton steps."""
    m = _summed(_over(blocks, _moments))
    mean = m[1 : 1 + N_FEATURES] / m[0]
    spread = np.sqrt(np.maximum(m[1 + N_FEATURES :] / m[0] - mean**2, 0)) + 1e-3
    w, was, before = np.zeros(N_FEATURES), np.zeros(N_FEATURES), np.inf
    for _ in range(MOST_STEPS):
        got = _summed(_over(blocks, lambda b: _slopes(b, w, spread)))  # noqa: B023  it is run at once
        n = got[0]
        loss = got[1] / n + RIDGE / 2 * (w @ w)
        if loss > before:  # the step was too long
            w = (w + was) / 2
            continue
        slope = got[2 : 2 + N_FEATURES] / n + RIDGE * w
        step = np.linalg.solve(got[2 + N_FEATURES :].reshape(N_FEATURES, N_FEATURES) / n + RIDGE * np.eye(N_FEATURES), slope)
        was, before = w, loss
        if slope @ step < 1e-8:
            break
        w = w - step
    return was / spread


def _learn(rows: DataFrame, labels: DataFrame, label: str = "quality", skip_held_out: bool = True) -> Ranker:
    """Learn from every labelled row outside the held-out fold; ``rows`` has each document's features."""
    known = labels.select(F.col("doc_id"), F.col(label).cast("int").alias("label")).where(F.col("label").isin(0, 1) & F.col("doc_id").isNotNull())
    if skip_held_out:
        known = known.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 != 1)
    counts = {0: 0, 1: 0} | {r.label: r["count"] for r in rows.select("doc_id").join(known, "doc_id").groupBy("label").count().collect()}
    n = counts[0] + counts[1]
    if not counts[0] or not counts[1]:
        share = counts[1] / n if n else 0.5
        return Ranker(shift=max(-20.0, min(20.0, float(np.log((share + 1e-9) / (1 - share + 1e-9))))))
    blocks = _blocks(rows, known, counts)
    weights = _fitted(blocks)
    # 8 bytes for each labelled row
    raw = np.frombuffer(b"".join(_over(blocks, lambda b: b"".join((x @ weights)[own].tobytes() for x, _, own in b))))
    at = float(np.quantile(raw, counts[0] / n))
    return Ranker(weights, at, 4.0 / (float(np.median(np.abs(raw - at))) + 1e-9))


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", skip_held_out: bool = True) -> Ranker:
    """Learn from every labelled row outside the held-out fold."""
    return _learn(_kept(docs), labels, label, skip_held_out)


def _kept(docs: DataFrame) -> DataFrame:
    return cut(_featured(docs), "quality-features")


def score_documents(docs: DataFrame, labels: DataFrame, label: str = "quality") -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    rows = _kept(docs)
    model = _learn(rows, labels, label)

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 2000):
                part = batch.slice(at, 2000)
                ids = part.column(0).to_pylist()
                score = model.score(_matrix(part.column(1)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([is_held_out(i) for i in ids]), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return rows.mapInArrow(tidy(run), "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, labels: DataFrame, label: str = "quality") -> DataFrame:
    """The rows of ``docs``, all columns, that the classifier predicts to be good."""
    model = train(docs, labels, label)

    def run(batches):
        for batch in batches:
            text = batch.schema.get_field_index("text")
            for at in range(0, batch.num_rows, 2000):
                part = batch.slice(at, 2000)
                yield part.filter(pa.array(model.score(features(part.column(text).cast(pa.binary()).to_pylist())) >= 0.5))

    return docs.mapInArrow(tidy(run), docs.schema)
