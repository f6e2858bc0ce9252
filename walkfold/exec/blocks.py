"""The asynchronous models: a block of vertices takes several local rounds before it exchanges values.

A block holds its vertices and, pushing, their outgoing edges, or, pulling, their incoming ones. Local rounds run the
same synthesised kernels over arrays. Idempotent reductions may fold a value in as often as it comes, so stale and
intermediate values do no harm. Sums move differences instead (push), or are computed anew from all predecessors (pull),
on graphs where paths end. Fixed points are those of the synchronous models; the values of single steps are not.

There are as many blocks as shuffle partitions, so what a block holds shrinks as the cluster grows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkfold.exec.checkpoint import cut, drop
from walkfold.exec.models import Loop, reduced, start_columns
from walkfold.kernels.exprs import evaluate_arrays

MOST = 2**62


def _blocks(loop: Loop, blocks: int | None) -> int:
    return blocks or int(loop.quiet.outer.conf.get("spark.sql.shuffle.partitions"))


def _dealt(loop: Loop, by: str, blocks: int) -> DataFrame:
    """Edges with the number of the block that holds them."""
    return cut(loop.edges.all().withColumn("_b", F.pmod(F.xxhash64(by), F.lit(blocks)).cast("int")).repartition("_b"))


def _best(keys: tuple[tuple[str, str], ...], ids: np.ndarray, values: list[np.ndarray]) -> tuple[np.ndarray, list[np.ndarray]]:
    """Of rows with equal ids the lexicographic best (booleans: or and and are the greatest and the least)."""
    signs = [x if r in ("min", "and") else -x.astype(np.int64) if x.dtype == bool else -x for (r, _), x in zip(keys, values, strict=True)]
    order = np.lexsort([*signs[::-1], ids])
    first = order[np.flatnonzero(np.diff(ids[order], prepend=ids[order][:1] - 1))] if len(ids) else order
    return ids[first], [x[first] for x in values]


def _beats(keys, new: list[np.ndarray], old: list[np.ndarray], known: np.ndarray) -> np.ndarray:
    wins, ties = np.zeros(len(known), bool), np.ones(len(known), bool)
    for (r, _), x, y in zip(keys, new, old, strict=True):
        wins |= ties & ((x < y) if r in ("min", "and") else (x > y))
        ties &= x == y
    return wins | ~known


def async_block(graph, parts, metrics=None, max_iter=None, direction: str = "push", local_rounds: int = 4, blocks: int | None = None) -> DataFrame:
    """Asynchronous relaxation of one idempotent reduction, lexicographic or not.

    push: a block relaxes its own outgoing edges, then sends the last values along those that leave it.
    pull: a block is sent the changed values of its vertices' predecessors and relaxes its incoming edges.
    """
    (part,) = parts
    if not part.idempotent:
        raise ValueError("async_block: a reduction that is not idempotent would count a contribution twice")
    loop = Loop(graph, parts, metrics, max_iter)
    n, names, keys, props, used = _blocks(loop, blocks), part.names(0), part.keys, part.extends(), loop.used
    edges = _dealt(loop, "src" if direction == "push" else "dst", n)
    loop.first()
    kinds = {f.name: f.dataType.simpleString() for f in loop.recent.schema.fields if f.name in names}
    schema = "dst long, " + ", ".join(f"{c} {t}" for c, t in kinds.items()) + ", edges long"
    arrow = [loop.recent.schema[c].dataType for c in names]

    def relax(left: pa.Table, right: pa.Table) -> pa.Table:
        from pyspark.sql.pandas.types import to_arrow_type

        src, dst = right["src"].to_numpy(), right["dst"].to_numpy()
        attr = {c: right[c].to_numpy() for c in used} | {"src": src, "dst": dst}
        ids = np.unique(np.concatenate([left["id"].to_numpy(), src, dst]))
        row = np.searchsorted(ids, left["id"].to_numpy())
        value = []
        for c in names:
            got = left[c].combine_chunks()
            x = np.zeros(len(ids), bool if pa.types.is_boolean(got.type) else np.float64 if pa.types.is_floating(got.type) else np.int64)
            x[row] = got.cast(pa.int64()).to_numpy() if pa.types.is_decimal(got.type) else got.to_numpy(zero_copy_only=False)
            value.append(x)
        known, active, told = (np.zeros(len(ids), bool) for _ in range(3))
        known[row] = True
        active[row] = left["changed"].to_numpy(zero_copy_only=False)
        at, to, count = np.searchsorted(ids, src), np.searchsorted(ids, dst), 0
        for _ in range(local_rounds):
            go = active[at]
            if not go.any():
                break
            count += int(go.sum())
            env = {c: x[go] for c, x in attr.items()}
            sent = [np.broadcast_to(evaluate_arrays(p, env | {"n": x[at[go]]}), (int(go.sum()),)) for p, x in zip(props, value, strict=True)]
            where, sent = _best(keys, to[go], [np.asarray(x).astype(v.dtype) for x, v in zip(sent, value, strict=True)])
            wins = _beats(keys, sent, [v[where] for v in value], known[where])
            where = where[wins]
            for v, x in zip(value, sent, strict=True):
                v[where] = x[wins]
            active = np.zeros(len(ids), bool)
            active[where] = known[where] = told[where] = True
            # what lies in another block is only sent to, and goes on from there
        out = np.flatnonzero(told)
        columns = {"dst": pa.array(np.append(ids[out], -1), pa.int64(), mask=np.append(np.zeros(len(out), bool), True))}
        for c, v, t in zip(names, value, arrow, strict=True):
            columns[c] = pa.array(np.append(v[out], v.dtype.type(0)), mask=np.append(np.zeros(len(out), bool), True)).cast(to_arrow_type(t))
        return pa.table(columns | {"edges": pa.array(np.append(np.zeros(len(out), np.int64), count))})

    changed = 1
    while changed and not loop.over():
        mine = loop.sql(f"SELECT *, CAST(pmod(xxhash64(id), {n}) AS INT) AS _b FROM ({loop.marked()})")
        if direction == "pull":
            # a block's own values, and the changed ones of its vertices' predecessors
            ghosts = loop.sql(loop.frontier()).join(edges.select("src", "_b").distinct(), F.col("id") == F.col("src")).select("id", *names, F.lit(True).alias("changed"), "_b")
            every = mine.withColumn("changed", F.lit(False)).unionByName(ghosts).groupBy("id", "_b").agg(F.max_by(F.struct(*names), "changed").alias("_v"), F.max("changed").alias("changed"))
            mine = every.select("id", *[F.col(f"_v.{c}").alias(c) for c in names], "changed", "_b")
        got = loop.view("got", mine.groupBy("_b").cogroup(edges.groupBy("_b")).applyInArrow(relax, schema))
        changed = loop.step(f"SELECT * FROM {got}", "sum(edges)", lambda sent: loop.improved(reduced(f"(SELECT * FROM {sent} WHERE dst IS NOT NULL)", parts, loop.bounds)), f"async_{direction}")
    drop(edges)
    return loop.result()


def async_sum(graph, parts, metrics=None, max_iter=None, direction: str = "push", local_rounds: int = 4, blocks: int | None = None) -> DataFrame:
    """Asynchronous sums over graphs where paths end: differences move (push), or sums are computed anew (pull).

    Values are whole numbers under 2^62 inside a block; a block that would pass that fails instead of wrapping round.
    """
    (part,) = parts
    if part.idempotent or len(part.keys) != 1:
        raise ValueError("async_sum: one sum at a time")
    loop = Loop(graph, parts, metrics, max_iter)
    (name,), (prop,), n, used = part.names(0), part.extends(), _blocks(loop, blocks), loop.used
    edges = _dealt(loop, "src" if direction == "push" else "dst", n)
    pend = f"p_{name}"  # push: what has come and was not sent on; pull: the vertex's own start
    loop.names = [name, pend]
    loop.first(loop.graph.held_vertices().select("id", *_start(part, name, pend)).where(F.col(name).isNotNull()))

    def numbers(t: pa.Table, c: str) -> np.ndarray:
        return np.array([0 if x is None else int(x) for x in t[c].to_pylist()], np.int64)

    def relax(left: pa.Table, right: pa.Table) -> pa.Table:
        src, dst = right["src"].to_numpy(), right["dst"].to_numpy()
        attr = {c: right[c].to_numpy() for c in used} | {"src": src, "dst": dst}
        mine = left["_own"].to_numpy(zero_copy_only=False)
        ids = np.unique(np.concatenate([left["id"].to_numpy(), src, dst]))
        row = np.searchsorted(ids, left["id"].to_numpy())
        acc, wait, own = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64), np.zeros(len(ids), bool)
        acc[row], wait[row], own[row] = numbers(left, name), numbers(left, pend), mine
        at, to, count = np.searchsorted(ids, src), np.searchsorted(ids, dst), 0
        before, start = acc.copy(), wait.copy()
        active = np.zeros(len(ids), bool)
        active[row] = left["changed"].to_numpy(zero_copy_only=False)
        got = np.zeros(len(ids), np.int64)  # what arrived for vertices of other blocks
        for _ in range(local_rounds):
            if direction == "push":
                go = (wait[at] != 0) & own[at]
            else:
                hit = np.zeros(len(ids), bool)
                hit[to[active[at]]] = True
                go = hit[to]
            if not go.any():
                break
            count += int(go.sum())
            env = {c: x[go] for c, x in attr.items()}
            value = wait if direction == "push" else acc
            sent = np.asarray(np.broadcast_to(evaluate_arrays(prop, env | {"n": value[at[go]]}), (int(go.sum()),)))
            total = np.zeros(len(ids), np.int64)
            np.add.at(total, to[go], sent)
            if np.abs(total.astype(float)).max(initial=0) > MOST or np.abs(acc.astype(float)).max(initial=0) > MOST:
                raise OverflowError("async_sum: a sum passed 2^62; run a synchronous model")
            if direction == "push":
                wait = np.where(own & (wait != 0), 0, wait)
                wait = wait + np.where(own, total, 0)
                acc = acc + np.where(own, total, 0)
                got += np.where(own, 0, total)
            else:
                fresh = np.where(hit & own, total + start, acc)
                active, acc = fresh != acc, fresh
        if direction == "push":
            out = np.flatnonzero((own & ((acc != before) | (wait != start))) | (got != 0))
            first, second = np.where(own, acc - before, got)[out], np.where(own, wait - start, got)[out]
        else:
            out = np.flatnonzero(own & (acc != before))
            first, second = acc[out], start[out]
        gone = np.append(np.zeros(len(out), bool), True)
        add = lambda x: pa.array(np.append(x, 0), pa.int64(), mask=gone)
        return pa.table({"dst": add(ids[out]), name: add(first), pend: add(second), "edges": pa.array(np.append(np.zeros(len(out), np.int64), count))})

    schema, whole = f"dst long, {name} long, {pend} long, edges long", "decimal(38,0)"

    def then(sent: str) -> str:
        rows = f"SELECT * FROM {sent} WHERE dst IS NOT NULL"
        if direction == "pull":
            return loop.replaced(f"SELECT dst, CAST({name} AS {whole}) AS {name}, CAST({pend} AS {whole}) AS {pend} FROM ({rows})")
        added = f"SELECT dst, CAST(sum({name}) AS {whole}) AS {name}, CAST(sum({pend}) AS {whole}) AS {pend} FROM ({rows}) GROUP BY dst"
        plus = ", ".join(f"CAST(coalesce(o_{c}, 0) + {c} AS {whole}) AS {c}" for c in (name, pend))
        return f"SELECT dst AS id, {plus} FROM ({loop.with_old(added)}) WHERE {name} <> 0 OR {pend} <> 0"

    changed = 1
    while changed and not loop.over():
        mine = loop.sql(f"SELECT id, {name}, {pend}, changed, CAST(pmod(xxhash64(id), {n}) AS INT) AS _b, TRUE AS _own FROM ({loop.marked()})")
        if direction == "pull":
            # every vertex belongs to its block, with or without a value; and predecessors' values are sent along
            wanted = edges.select("src", "_b").distinct()
            ghosts = mine.drop("_b", "_own").join(wanted, F.col("id") == F.col("src")).select("id", name, F.lit(0).cast(whole).alias(pend), "changed", "_b", F.lit(False).alias("_own"))
            empty = edges.select(F.col("dst").alias("id"), F.lit(None).cast(whole).alias(name), F.lit(0).cast(whole).alias(pend), F.lit(False).alias("changed"), "_b", F.lit(True).alias("_own")).distinct()
            every = mine.unionByName(ghosts).unionByName(empty)
            mine = every.groupBy("id", "_b").agg(F.max(name).alias(name), F.max(pend).alias(pend), F.max("changed").alias("changed"), F.max("_own").alias("_own"))
        got = loop.view("got", mine.groupBy("_b").cogroup(edges.groupBy("_b")).applyInArrow(relax, schema))
        changed = loop.step(f"SELECT * FROM {got}", "sum(edges)", then, f"async_{direction}_sum")
    drop(edges)
    return loop.result().select("id", name)


def _start(part, name: str, pend: str) -> list:
    value = start_columns((part,))[0]
    return [value.alias(name), value.alias(pend)]
