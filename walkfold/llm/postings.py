"""Per-block postings: which terms each document of a block holds, and how often.

Terms are 64-bit hashes: rows stay short, and among 10^8 terms a clash has a chance of about 0.0003.
A block is a run of whole documents of one input partition, closed after ``BLOCK_TERMS`` terms, so
a term has one row in a block however hot it is, and a block's rows fit one task.
Rows are of two kinds: of a term (term, cells: pairs of document number and frequency) and of a
document (doc_id, idx, and what the caller adds).
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import xxhash

BLOCK_TERMS = 3_000_000
SCHEMA = "block long, term long, trained long, cells binary, wide boolean, doc_id long, idx int, size long, held_out boolean, score double"
_TYPES = {"long": pa.int64(), "binary": pa.binary(), "boolean": pa.bool_(), "int": pa.int32(), "double": pa.float64()}
FIELDS = pa.schema([pa.field(name, _TYPES[kind]) for name, kind in (x.split() for x in SCHEMA.split(", "))])


def _batch(n: int, **columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([columns[f.name] if f.name in columns else pa.nulls(n, f.type) for f in FIELDS], schema=FIELDS)


class BlockWriter:
    """Collects documents' terms; ``flush`` gives a block's rows."""

    def __init__(self, partition: int) -> None:
        self.partition, self.number = partition, 0
        self._clear()

    def _clear(self) -> None:
        self.vocabulary: defaultdict = defaultdict()
        self.vocabulary.default_factory = self.vocabulary.__len__
        self.ids: list[np.ndarray] = []
        self.docs: list[tuple] = []
        self.held = 0

    def add(self, terms: list[bytes], doc_id: int | None, size: int, held_out: bool, score: float | None = None) -> None:
        ids = np.fromiter(map(self.vocabulary.__getitem__, terms), np.int64, len(terms))
        self.ids.append(ids)
        self.docs.append((doc_id, len(self.docs), size, held_out, score))
        self.held += len(ids)

    @property
    def full(self) -> bool:
        return self.held >= BLOCK_TERMS or len(self.docs) >= 50_000

    def flush(self) -> Iterator[pa.RecordBatch]:
        if not self.docs:
            return
        block, n = (self.partition << 24) + self.number, len(self.docs)
        self.number += 1
        ids = np.concatenate(self.ids)
        of = np.repeat(np.arange(n), [len(x) for x in self.ids])
        codes, often = np.unique(ids * n + of, return_counts=True)
        term, doc = codes // n, codes % n
        trained = np.bincount(term, weights=often * ~np.array([d[3] for d in self.docs], bool)[doc], minlength=len(self.vocabulary)).astype(np.int64)
        wide = bool(len(often) and often.max() > 65_535)
        kind = "<u4" if wide else "<u2"
        cells = np.stack([doc, often], 1).astype(kind)
        ends = np.concatenate([[0], np.cumsum(np.bincount(term, minlength=len(self.vocabulary)))]) * (2 * cells.itemsize)
        terms = np.fromiter(map(xxhash.xxh3_64_intdigest, self.vocabulary), np.uint64, len(self.vocabulary)).view(np.int64)
        for at in range(0, len(terms), 50_000):
            to = min(at + 50_000, len(terms))
            data = cells.tobytes()[ends[at] : ends[to]]
            held = pa.Array.from_buffers(pa.binary(), to - at, [None, pa.py_buffer((ends[at : to + 1] - ends[at]).astype("<i4").tobytes()), pa.py_buffer(data)])
            yield _batch(to - at, block=pa.array(np.full(to - at, block)), term=pa.array(terms[at:to]), trained=pa.array(trained[at:to]), cells=held, wide=pa.array([wide] * (to - at)))
        columns = dict(zip(("doc_id", "idx", "size", "held_out", "score"), zip(*self.docs, strict=True), strict=True))
        yield _batch(n, block=pa.array(np.full(n, block)), **{k: pa.array(v, FIELDS.field(k).type) for k, v in columns.items()})
        self._clear()


def add_up(table: pa.Table, weights: Callable[[pa.Table], list[np.ndarray]]) -> tuple[pa.Table, list[np.ndarray]]:
    """A block's documents and, for each weight of a term, the sums over each document's terms."""
    docs = table.filter(pa.compute.is_valid(table["idx"])).sort_by("idx")
    rows = table.filter(pa.compute.is_null(table["idx"]))
    n, sums = docs.num_rows, None
    for batch in rows.to_batches():
        if not batch.num_rows:
            continue
        one = pa.Table.from_batches([batch])
        cells = batch.column(batch.schema.get_field_index("cells"))
        wide = bool(batch.column(batch.schema.get_field_index("wide"))[0].as_py())
        lengths = np.asarray(pa.compute.binary_length(cells)) // (8 if wide else 4)
        offsets = np.frombuffer(cells.buffers()[1], "<i4", len(cells) + 1, cells.offset * 4)
        pairs = np.frombuffer(cells.buffers()[2], "<u4" if wide else "<u2", int(lengths.sum()) * 2, int(offsets[0])).reshape(-1, 2)
        parts = [np.bincount(pairs[:, 0], weights=np.repeat(w, lengths) * pairs[:, 1], minlength=n) for w in weights(one)]
        sums = parts if sums is None else [a + b for a, b in zip(sums, parts, strict=True)]
    return docs, sums if sums is not None else [np.zeros(n)] * len(weights(rows))
