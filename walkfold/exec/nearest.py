"""The nearest rows of each query in one block of queries and one of rows.

A matrix product gives every pair a distance that is off by a known bound at most. Only the pairs that can be among the
nearest by that bound are measured as the query states it (float32 differences, squares added in order as doubles) and
ranked, so the result is that of measuring every pair.
"""

from __future__ import annotations

import sys
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import cloudpickle

# functions sent to executors carry their code
cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Queries of one matrix product, rows of which the least value is kept, numbers that are measured at once.
TILE, GROUP, AT_ONCE = 256, 64, 2_000_000

#: Vectors with larger numbers are measured pair by pair: their products may leave float32.
LARGEST = 1e15


class Vectors:
    """A column of vectors; the length of a null is -1."""

    def __init__(self, column: pa.ChunkedArray):
        lists = column.combine_chunks()
        self.sizes = pc.fill_null(pc.list_value_length(lists), -1).to_numpy(zero_copy_only=False).astype(np.int64)
        flat = lists.flatten()
        self.first = np.cumsum(np.maximum(self.sizes, 0)) - np.maximum(self.sizes, 0)
        self.numbers = flat.to_numpy(zero_copy_only=False).astype(np.float32)
        self.holes = flat.is_null().to_numpy(zero_copy_only=False) if flat.null_count else None

    def of(self, rows: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray | None]:
        """The vectors of rows that have n numbers, and which of the numbers are null."""
        at = self.first[rows][:, None] + np.arange(n)
        return self.numbers[at], None if self.holes is None else self.holes[at]


def distances(a: np.ndarray, b: np.ndarray, gone: np.ndarray | None = None) -> np.ndarray:
    """Of each row of a and b. Nulls add nothing; what has no finite distance is infinitely far."""
    with np.errstate(over="ignore", invalid="ignore"):
        step = a - b
        step *= step
        if gone is not None:
            step[gone] = 0
        d = np.cumsum(step, axis=1, dtype=np.float64)[:, -1]
    d[~np.isfinite(d)] = np.inf
    if gone is not None:
        d[gone.all(axis=1)] = np.inf
    return d


def _pairs(a, b, a_holes, b_holes, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The distances of pairs of rows of a and b, some at once."""
    out, most = np.empty(len(i)), max(1, AT_ONCE // a.shape[1])
    for at in range(0, len(i), most):
        x, y = i[at : at + most], j[at : at + most]
        gone = [h[z] for h, z in ((a_holes, x), (b_holes, y)) if h is not None]
        out[at : at + most] = distances(a[x], b[y], np.logical_or.reduce(gone) if gone else None)
    return out


def _first(kind: np.ndarray) -> np.ndarray:
    """Of each entry of a sorted array its place among its equals."""
    starts = np.flatnonzero(np.r_[True, kind[1:] != kind[:-1]])
    return np.arange(len(kind)) - np.repeat(starts, np.diff(np.r_[starts, len(kind)]))


class Near:
    """Rows without nulls, prepared for products with queries. Of equal vectors only those stay that can be among the k first."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, k: int):
        """ids: in order."""
        n, self.k = x.shape[1], k
        equal = np.unique(np.ascontiguousarray(x).view(np.dtype((np.void, 4 * n))).ravel(), return_inverse=True)[1].ravel()
        order = np.argsort(equal, kind="stable")
        rows = order[_first(equal[order]) < k + np.unique(ids, return_counts=True)[1].max()]
        self.centre = x[rows].mean(axis=0, dtype=np.float64).astype(np.float32)
        x = x[rows] - self.centre
        squares = np.square(x, dtype=np.float64).sum(axis=1)
        order = np.argsort(squares, kind="stable")  # long vectors, whose bounds are wide, share their groups with each other
        self.rows, self.ids, extra = rows[order], ids[rows[order]], -len(rows) % GROUP
        self.matrix = np.zeros((len(rows) + extra, n + 1), np.float32)
        self.matrix[: len(rows), :n], self.matrix[: len(rows), n] = x[order], squares[order]
        self.longest = np.sqrt(np.r_[squares[order], np.full(extra, squares[order[-1]])]).reshape(-1, GROUP)[:, -1:]
        self.by_id = np.argsort(self.ids, kind="stable")
        self.in_order = self.ids[self.by_id]

    def own(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rows with the id of a query, and which query."""
        low, high = (np.searchsorted(self.in_order, ids, side) for side in ("left", "right"))
        i = np.repeat(np.arange(len(ids)), high - low)
        return self.by_id[np.arange(len(i)) - np.repeat(np.cumsum(high - low) - (high - low), high - low) + np.repeat(low, high - low)], i

    def candidates(self, q: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pairs of a query and a row: all that can be among the query's k nearest.

        Centring, the product's sum of n + 1 terms and the stated distance are each off by a few float32 roundings of the
        square of both lengths' sum; products below float32 vanish.
        """
        n = q.shape[1]
        q = q - self.centre
        length = np.sqrt(np.square(q, dtype=np.float64).sum(axis=1))
        value = self.matrix @ np.ascontiguousarray(np.c_[-2 * q, np.ones(len(q), np.float32)].T)
        value[len(self.rows) :] = np.inf
        value[self.own(ids)] = np.inf
        value = value.reshape(-1, GROUP, len(q))
        least = value.min(axis=1).astype(np.float64)
        off = 1.01 * (n + 16) * 2.0**-24 * (self.longest + length) ** 2 + (n + 16) * 1e-37
        most = np.partition(least + off, self.k - 1, axis=0)[self.k - 1] if len(least) >= self.k else np.full(len(q), np.inf)
        g, i = np.nonzero(least - off <= most)
        inside = value[g, :, i]
        p, o = np.nonzero((inside - off[g, i][:, None] <= most[i][:, None]) & np.isfinite(inside))
        return i[p], self.rows[g[p] * GROUP + o]


def _class(src, a, a_holes, dst, b, b_holes, k: int) -> tuple[np.ndarray, list[tuple[np.ndarray, np.ndarray, np.ndarray]]]:
    """Of queries and rows of one length: which queries have k rows at a finite distance, and of those the query, row and distance."""
    plain_a, plain_b = ((np.abs(x) < LARGEST).all(axis=1) for x in (a, b))  # not so for what is not a number
    rows, odd = np.flatnonzero(plain_b), np.flatnonzero(~plain_b)
    ids = dst[rows]
    done = plain_a & (len(rows) - np.searchsorted(ids, src, "right") + np.searchsorted(ids, src, "left") >= k)
    out, asked = [], np.flatnonzero(done)
    near = Near(b[rows], ids, k) if len(asked) else None
    for at in range(0, len(asked), TILE):
        some = asked[at : at + TILE]
        i, j = near.candidates(a[some], src[some])
        far_i, far_j = np.repeat(np.arange(len(some)), len(odd)), np.tile(odd, len(some))
        i, j = some[np.r_[i, far_i]], np.r_[rows[j], far_j]
        other = src[i] != dst[j]
        i, j = i[other], j[other]
        d = _pairs(a, b, a_holes, b_holes, i, j)
        order = np.lexsort((dst[j], d, i))
        order = order[_first(i[order]) < k]
        out.append((i[order], j[order], d[order]))
    return done, out


def nearest(k: int) -> Callable[[pa.Table, pa.Table], pa.Table]:
    """Of queries (src, _q) and rows (dst, _x) the k nearest rows of each query that have another id: src, dst, d.

    Where a vector is null or empty, or its length is not its query's, the distance is null and ranks last.
    """

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        right = right.sort_by("dst")
        src, dst = left.column("src").to_numpy(), right.column("dst").to_numpy()
        q, x = Vectors(left.column("_q")), Vectors(right.column("_x"))
        best = [(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))]
        for n in np.unique(q.sizes).tolist():
            asked = np.flatnonzero(q.sizes == n)
            same = np.flatnonzero(x.sizes == n) if n > 0 else np.empty(0, np.int64)
            (a, a_holes), (b, b_holes) = q.of(asked, max(n, 0)), x.of(same, max(n, 0))
            done = np.zeros(len(asked), bool)
            if len(same):
                done, found = _class(src[asked], a, a_holes, dst[same], b, b_holes, k)
                best += [(src[asked[i]], dst[same[j]], d) for i, j, d in found]
            for i in np.flatnonzero(~done):
                d = np.full(len(dst), np.inf)
                if len(same):
                    d[same] = _pairs(a, b, a_holes, b_holes, np.full(len(same), i), np.arange(len(same)))
                rows = np.flatnonzero(dst != src[asked[i]])
                if len(rows) > k:  # rows are in order of their ids
                    last = np.partition(d[rows], k - 1)[k - 1]
                    less = rows[d[rows] < last]
                    rows = np.r_[less, rows[d[rows] == last][: k - len(less)]]
                best.append((np.full(len(rows), src[asked[i]]), dst[rows], d[rows]))
        s, t, d = (np.concatenate(x) for x in zip(*best, strict=True))
        return pa.table({"src": pa.array(s, pa.int64()), "dst": pa.array(t, pa.int64()), "d": pa.array(d, pa.float64(), mask=np.isinf(d))})

    return run
