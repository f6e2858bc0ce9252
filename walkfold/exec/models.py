"""The iteration models: each superstep is one SQL plan over edges and state.

State has a row (id, one or more columns for each part of the tuple) for every vertex with a value. It is kept as a base
and the rows that changed since the base was written (``recent``, with a mark on those of the last step): a step writes
what changed lately and not all vertices, and the two are put together when the recent rows are many. Base, recent
rows and edges are dealt and sorted by vertex, so what moves in a step is partially aggregated messages alone. Edges of
hubs are dealt apart from their sources; the few rows of hubs are broadcast to them.

A step is written as two SQL texts (the messages, which are counted, and what they change), so its cost on the driver is
two analyses whatever the tuple's width. Kernels come from the synthesis (``synth/enumerate.py``); hand kernels can be
given with a part.

The fixed points of a bounded graph run in one task (``onetask.py``), with the same steps.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from walkfold.exec import onetask
from walkfold.exec.checkpoint import cut, drop, shuffled_records
from walkfold.exec.metrics import RunMetrics
from walkfold.graphs import INTO
from walkfold.kernels import codec
from walkfold.kernels.exprs import KExpr, edge_columns, to_column, to_sql
from walkfold.kernels.library import Kernels
from walkfold.synth.enumerate import Derived, derive, result_kind

IDEMPOTENT = {"min", "max", "or", "and"}
AGGREGATE = {"min": "min", "max": "max", "or": "bool_or", "and": "bool_and", "sum": "sum"}
DECIMAL = "decimal(38,0)"


@dataclass(frozen=True)
class Part:
    """One factored path reduction: ((R, F), ...) compared lexicographically, the last one is the value.

    ``hand`` gives kernels instead of the synthesised ones; F is then a name only.
    """

    keys: tuple[tuple[str, str], ...]
    source: int | None = None
    weight_type: str = "long"
    hand: Kernels | None = None

    def names(self, i: int) -> list[str]:
        return [f"s{i}_{j}" for j in range(len(self.keys))]

    @property
    def idempotent(self) -> bool:
        return self.keys[-1][0] in IDEMPOTENT

    def kernels(self) -> Derived:
        found = derive(self.keys, self.source is not None)
        if found is None:
            raise ValueError(f"no kernels were found for {self.keys}")
        return found

    def extends(self) -> tuple[KExpr, ...]:
        return (self.hand.prop,) if self.hand else self.kernels().props

    def inits(self) -> tuple[KExpr, ...]:
        return (self.hand.init,) if self.hand else self.kernels().inits

    def rollback(self) -> KExpr | None:
        return self.hand.rollback if self.hand else self.kernels().rollback

    def kinds(self) -> list[str]:
        return [self._kind(r, f) for r, f in self.keys]

    def _kind(self, r: str, f: str) -> str:
        if self.hand is not None or f in ("weight", "capacity"):
            return self.weight_type
        if f == "one":
            return DECIMAL
        return "boolean" if result_kind(f) == "bool" else "long"


Parts = tuple[Part, ...]


def names_of(parts: Parts) -> list[str]:
    return [n for i, p in enumerate(parts) for n in p.names(i)]


def read_by(parts: Parts) -> tuple[str, ...]:
    """The edges' own columns that the kernels read."""
    return tuple(sorted(set().union(*(edge_columns(e) for p in parts for e in p.extends())) - {"src", "dst"}))


def state_bytes(parts: Parts) -> int:
    return sum({"long": 8, "double": 8, "boolean": 1}.get(k, 16) for p in parts for k in p.kinds())


def start_columns(parts: Parts) -> list[Column]:
    out = []
    for i, p in enumerate(parts):
        for name, kind, init in zip(p.names(i), p.kinds(), p.inits(), strict=True):
            out.append(to_column(init, {"id": F.col("id"), "source": F.lit(p.source), "order": F.lit(None)}).cast(kind).alias(name))
    return out


def initial(vertices: DataFrame, parts: Parts) -> DataFrame:
    """The vertices that have a value of a path without edges."""
    return vertices.select("id", *start_columns(parts)).where(" OR ".join(f"{n} IS NOT NULL" for n in names_of(parts)))


def messages(parts: Parts, prefix: str = "") -> list[str]:
    """The tuple that an edge carries; a missing slot stays missing (the none guard)."""
    out = []
    for i, p in enumerate(parts):
        first = prefix + p.names(i)[0]
        for name, kind, e in zip(p.names(i), p.kinds(), p.extends(), strict=True):
            out.append(f"CAST(CASE WHEN {first} IS NOT NULL THEN {to_sql(e, {'n': prefix + name})} END AS {kind}) AS {prefix + name}")
    return out


def rank(keys, names: list[str]) -> str:
    """A struct whose least is the lexicographic best."""
    code = {"min": "{}", "max": "-{}", "and": "{}", "or": "NOT {}"}
    return "struct(" + ", ".join(code[r].format(n) for n, (r, _) in zip(names, keys, strict=True)) + ")"


def _packable(part: Part, bounds: tuple[int, int] | None) -> bool:
    keys = part.keys
    return bounds is not None and len(keys) == 2 and keys[0][0] == "min" and keys[0][1] in ("length", "weight") and part.weight_type == "long" and keys[1][0] in ("min", "max") and result_kind(keys[1][1]) != "bool" and codec.fits(*bounds)


def reduced(sent: str, parts: Parts, bounds: tuple[int, int] | None = None, also: tuple[tuple[str, str], ...] = ()) -> str:
    """dst and the reduced tuple of messages; ``also`` are further columns with the aggregate that joins them.

    A sum behind a comparison sums by (dst, first keys), then keeps the best keys' sum: both aggregations are partial first.
    """
    more = "".join(f", {agg}({c}) AS {c}" for agg, c in also)
    kept = "".join(f", {c}" for _, c in also)
    if any(len(p.keys) > 1 and not p.idempotent for p in parts):
        (part,) = parts
        *firsts, last = part.names(0)
        by = f"SELECT dst, {', '.join(firsts)}, CAST(sum({last}) AS {DECIMAL}) AS {last}{more} FROM {sent} GROUP BY dst, {', '.join(firsts)}"
        best = f"SELECT dst, min_by(struct({', '.join(part.names(0))}), CASE WHEN {firsts[0]} IS NOT NULL THEN {rank(part.keys[:-1], firsts)} END) AS _b{more} FROM ({by}) GROUP BY dst"
        return f"SELECT dst, {', '.join(f'_b.{n} AS {n}' for n in part.names(0))}{kept} FROM ({best})"
    aggs, outs = [], []
    for i, p in enumerate(parts):
        names = p.names(i)
        if len(names) == 1:
            aggs.append(f"CAST({AGGREGATE[p.keys[0][0]]}({names[0]}) AS {p.kinds()[0]}) AS {names[0]}")
            outs.append(names[0])
        elif _packable(p, bounds):
            most = p.keys[1][0] == "max"
            aggs.append(f"min({codec.pack_sql(*names, most)}) AS _p{i}")
            outs += [f"{x} AS {n}" for x, n in zip(codec.unpack_sql(f"_p{i}", most), names, strict=True)]
        else:
            aggs.append(f"min_by(struct({', '.join(names)}), CASE WHEN {names[0]} IS NOT NULL THEN {rank(p.keys, names)} END) AS _p{i}")
            outs += [f"_p{i}.{n} AS {n}" for n in names]
    return f"SELECT dst, {', '.join(outs)}{kept} FROM (SELECT dst, {', '.join(aggs)}{more} FROM {sent} GROUP BY dst)"


def combine(part: Part, i: int, old: str = "o_", new: str = "") -> list[str]:
    """R of the old value and the new one; none is neutral."""
    names = part.names(i)
    if len(names) == 1:
        a, b, (r, _) = old + names[0], new + names[0], part.keys[0]
        joined = {"min": "least({a}, {b})", "max": "greatest({a}, {b})", "or": "coalesce({a} OR {b}, {a}, {b})", "and": "coalesce({a} AND {b}, {a}, {b})", "sum": "coalesce({a} + {b}, {a}, {b})"}[r]
        return [f"{joined.format(a=a, b=b)} AS {names[0]}"]
    better = "FALSE"
    for n, (r, _) in reversed(list(zip(names, part.keys, strict=True))):
        a, b = old + n, new + n
        better = f"({b} {'<' if r in ('min', 'and') else '>'} {a} OR ({a} = {b} AND {better}))"
    take = f"{new}{names[0]} IS NOT NULL AND ({old}{names[0]} IS NULL OR {better})"
    return [f"CASE WHEN {take} THEN {new}{n} ELSE {old}{n} END AS {n}" for n in names]


def differs(names: list[str], old: str = "o_") -> str:
    return " OR ".join(f"NOT ({n} <=> {old}{n})" for n in names)


def observed(seen: Observation, name: str = "n"):
    """What was counted; a plan that the optimiser found empty has counted nothing."""
    try:
        return seen.get.get(name) or 0
    except Exception as e:
        if "assertion failed" in str(e):
            return 0
        raise


class Plan:
    """Dealt edges as views of the quiet session, and SQL over them."""

    def __init__(self, graph, used: tuple[str, ...], metrics: RunMetrics | None, more: tuple[str, ...] = ()) -> None:
        self.graph, self.quiet, self.used, self.more = graph, graph.quiet, used, more
        self.metrics = metrics if metrics is not None else RunMetrics()
        self.tag = f"wf_{uuid.uuid4().hex}"
        self.views: set[str] = set()
        self.see_edges()
        self.done = 0

    def see_edges(self) -> None:
        self.edges = self.graph.prepared((*self.used, *self.more))
        self.lights = [self.view(f"e{k}", x) for k, x in enumerate(self.edges.lights)]
        if self.edges.heavy is not None:
            self.view("heavy", self.edges.heavy), self.view("hubs", self.edges.hubs)

    def view(self, name: str, df: DataFrame) -> str:
        df._jdf.createOrReplaceTempView(f"{self.tag}_{name}")
        self.views.add(f"{self.tag}_{name}")
        return f"{self.tag}_{name}"

    def sql(self, text: str) -> DataFrame:
        return self.quiet.inner.sql(text)

    def unsee(self) -> None:
        for v in self.views:
            self.quiet.inner._jsparkSession.catalog().dropTempView(v)
        self.views.clear()

    def along(self, rows: str, select: list[str]) -> str:
        """Columns of rows (r, by id) joined to their outgoing edges (e)."""
        chosen = ", ".join(select)
        parts = [f"SELECT {chosen} FROM ({rows}) r JOIN {e} e ON r.id = e.src" for e in self.lights]
        if self.edges.heavy is not None:
            few = f"SELECT /*+ BROADCAST(u) */ x.* FROM ({rows}) x LEFT SEMI JOIN {self.tag}_hubs u ON x.id = u.src"
            parts.append(f"SELECT /*+ BROADCAST(r) */ {chosen} FROM {self.tag}_heavy e JOIN ({few}) r ON r.id = e.src")
        return " UNION ALL ".join(parts)

    def write(self, rows: DataFrame, sent: Observation, model: str, at: float) -> tuple[DataFrame, int]:
        got = Observation()
        rows = rows.observe(got, F.expr("count_if(changed)").alias("n"))
        out = cut(rows)
        changed = observed(got)
        self.done += 1
        records = shuffled_records(rows) if self.metrics.count_records else 0
        self.metrics.add(observed(sent), changed, time.perf_counter() - at, model, records)
        return out, changed


class Loop(Plan):
    """What the models share: state, its view names, step accounting."""

    #: The recent rows join the base after so many steps at the latest.
    COMPACT = 16

    def __init__(self, graph, parts: Parts, metrics: RunMetrics | None = None, max_iter: int | None = None, pulls: bool = False) -> None:
        super().__init__(graph, read_by(parts), metrics, (INTO,) if pulls else ())
        self.parts, self.max_iter = parts, max_iter
        self.names = names_of(parts)
        self.bounds = graph.bounds() if any(len(p.keys) == 2 for p in parts) else None
        self.metrics.vertex_bytes, self.metrics.edge_bytes = state_bytes(parts), 8 * len(self.used)
        self.base: DataFrame | None = None
        self.recent: DataFrame | None = None
        self.start: DataFrame | None = None

    def limit(self) -> int:
        """A fixed point needs at most one step more than the longest simple path has edges."""
        return self.max_iter if self.max_iter is not None else self.graph.order() + 1

    def over(self) -> bool:
        """The step bound is looked up only when a run is long."""
        if self.max_iter is not None:
            return self.done >= self.max_iter
        if self.done > 64 and self.done > self.limit() + 1:
            raise RuntimeError(f"no fixed point after {self.done} steps")
        return False

    # -- state

    def _keep(self, base: DataFrame | None, recent: DataFrame) -> None:
        self.base, self.recent = base, recent
        self.view("recent", recent)
        if base is not None:
            self.view("base", base)

    def first(self, starts: DataFrame | None = None) -> None:
        """Every vertex that has a value of a path without edges (or the rows given) is new."""
        if starts is None:
            starts = initial(self.graph.held_vertices(), self.parts)
        rows = self.quiet.take(starts if "changed" in starts.columns else starts.withColumn("changed", F.lit(True)))
        self.start = cut(rows.repartition("id").sortWithinPartitions("id"))
        self.view("start", self.start)
        self._keep(None, self.start)

    def cols(self, prefix: str = "") -> str:
        return ", ".join(f"{prefix}{n}" for n in self.names)

    def frontier(self) -> str:
        return f"SELECT id, {self.cols()} FROM {self.tag}_recent WHERE changed"

    def state(self, key: str = "id") -> str:
        """All rows: the recent ones and those of the base that none replaces. Under another ``key`` they stay dealt as both are.

        A union is known to be dealt only if each side's columns are made in it: a column that is merely passed on may be
        nullable on one side and not on the other.
        """
        rows = f"SELECT id AS {key}, {self.cols()} FROM {self.tag}_recent"
        if self.base is None:
            return rows
        return f"SELECT id AS {key}, {self.cols()} FROM {self.tag}_base b LEFT ANTI JOIN {self.tag}_recent r ON b.id = r.id UNION ALL {rows}"

    def marked(self) -> str:
        """All rows, and whether they changed in the last step."""
        return f"SELECT k AS id, {self.cols('s.')}, f.id IS NOT NULL AS changed FROM ({self.state('k')}) s LEFT JOIN (SELECT id FROM {self.tag}_recent WHERE changed) f ON k = f.id"

    def with_old(self, news: str) -> str:
        """Rows by dst with the vertex's present values as o_<name>."""
        old = ", ".join(f"CASE WHEN r.id IS NOT NULL THEN r.{n} ELSE b.{n} END AS o_{n}" if self.base is not None else f"r.{n} AS o_{n}" for n in self.names)
        base = f"LEFT JOIN {self.tag}_base b ON m.dst = b.id" if self.base is not None else ""
        return f"SELECT m.*, {old} FROM ({news}) m LEFT JOIN {self.tag}_recent r ON m.dst = r.id {base}"

    def improved(self, news: str) -> str:
        """Of reduced messages the vertices that they change, with R(old, new)."""
        values = ", ".join(c for i, p in enumerate(self.parts) for c in combine(p, i))
        old = self.cols("o_")
        return f"SELECT id, {self.cols()} FROM (SELECT dst AS id, {values}, {old} FROM ({self.with_old(news)})) WHERE {differs(self.names)}"

    def replaced(self, news: str) -> str:
        """Of rows by dst those that differ from the vertex's present values; the new ones stand."""
        return f"SELECT dst AS id, {self.cols()} FROM ({self.with_old(news)}) WHERE {differs(self.names)}"

    # -- steps

    def _counted(self, text: str, count: str, at: float) -> tuple[Observation, float]:
        sent = Observation()
        self.view("sent", self.sql(text).observe(sent, F.expr(count).alias("n")))
        return sent, at

    def step(self, text: str, count: str, then: Callable[[str], str], model: str) -> int:
        """``then(messages)`` selects the rows that change (id, names); they become recent rows. The count of changes."""
        sent, at = self._counted(text, count, time.perf_counter())
        news = then(f"{self.tag}_sent")
        if self.base is None:  # all that is known so far becomes the base
            rows = self.sql(f"SELECT id, {self.cols()}, TRUE AS changed FROM ({news}) SORT BY id")
        else:
            both = f"SELECT id AS k, {self.cols()}, 0 AS _t FROM {self.tag}_recent UNION ALL SELECT id AS k, {self.cols()}, 1 AS _t FROM ({news})"
            last = f"SELECT k, max_by(struct({self.cols()}), _t) AS _v, max(_t) AS _t FROM ({both}) GROUP BY k"
            rows = self.sql(f"SELECT k AS id, {', '.join(f'_v.{n} AS {n}' for n in self.names)}, _t = 1 AS changed FROM ({last})")
        out, changed = self.write(rows, sent, model, at)
        old = self.recent if self.base is not None else None
        self._keep(self.base if self.base is not None else self.recent, out)
        self._drop(old)
        if changed and self.done % self.COMPACT == 0:
            self.compact()
        return changed

    def compact(self) -> None:
        whole = cut(self.sql(f"SELECT k AS id, {self.cols()} FROM (SELECT * FROM ({self.state('k')}) SORT BY k)"))
        lately, olds = cut(self.sql(f"SELECT * FROM {self.tag}_recent WHERE changed")), (self.base, self.recent)
        self._keep(whole, lately)
        for x in olds:
            self._drop(x)

    def replace(self, text: str, count: str, then: Callable[[str], str], model: str) -> int:
        """``then(messages)`` selects the whole new state (id, names, changed)."""
        sent, at = self._counted(text, count, time.perf_counter())
        out, changed = self.write(self.sql(f"SELECT id, {self.cols()}, changed FROM ({then(f'{self.tag}_sent')}) SORT BY id"), sent, model, at)
        olds = (self.base, self.recent)
        self._keep(None, out)
        for x in olds:
            self._drop(x)
        return changed

    def _drop(self, df: DataFrame | None) -> None:
        if df is not None and df is not self.start:
            drop(df)

    def close(self, text: str) -> DataFrame:
        """The result as one table of the caller's session; the loop's own files and views go."""
        out = cut(self.sql(text))
        for x in (self.base, self.recent):
            self._drop(x)
        drop(self.start)
        self.unsee()
        return self.quiet.give(out)

    def result(self) -> DataFrame:
        """The vertices that have a value."""
        return self.close(f"SELECT id, {self.cols()} FROM ({self.state()}) WHERE {' OR '.join(f'{n} IS NOT NULL' for n in self.names)}")


ROWS = "count(1)"


def push_step(loop: Loop) -> int:
    text = loop.along(loop.frontier(), ["e.dst", *messages(loop.parts)])
    return loop.step(text, ROWS, lambda sent: loop.improved(reduced(sent, loop.parts, loop.bounds)), "push")


def _pulled(loop: Loop, start: bool) -> str:
    """Reduced messages of the vertices with a changed predecessor, from all their predecessors and, with ``start``, their start.

    Every edge is looked at where it lies and its message aggregated there: no edge is shuffled, and no message is made
    for a source without a row. All edges into vertices with a changed predecessor count as processed; their number lies
    with each of them.
    """
    sent = loop.along(loop.marked(), ["e.dst", *messages(loop.parts), "changed AS _hit", f"e.{INTO} AS _edges"])
    if start:
        sent += f" UNION ALL SELECT id AS dst, {loop.cols()}, FALSE AS _hit, 0L AS _edges FROM {loop.tag}_start"
    return f"SELECT * FROM ({reduced(f'({sent})', loop.parts, loop.bounds, (('bool_or', '_hit'), ('max', '_edges')))}) WHERE _hit"


def pull_step(loop: Loop) -> int:
    return loop.step(_pulled(loop, False), "sum(_edges)", lambda sent: loop.improved(f"SELECT dst, {loop.cols()} FROM {sent}"), "pull")


def in_one_task(graph, parts: Parts, model: str, metrics: RunMetrics | None, max_iter: int | None, base: str = "init") -> DataFrame | None:
    """The fixed point of a bounded graph, or none if its supersteps have to run over many tasks."""
    used = read_by(parts)
    if not onetask.suits(graph, parts, used, metrics):
        return None
    out = onetask.run(graph, parts, used, initial(graph.held_vertices(), parts), model, metrics, max_iter, base)
    if out is not None and metrics is not None:
        metrics.vertex_bytes, metrics.edge_bytes = state_bytes(parts), 8 * len(used)
    return out


def push_idem(graph, parts, metrics=None, max_iter=None, direction: str = "push") -> DataFrame:
    """Changed vertices send; ``direction='auto'`` pulls while the frontier's edges are over a twentieth of all."""
    if not all(p.idempotent for p in parts):
        raise ValueError("push_idem: a reduction that is not idempotent would count a contribution twice")
    if (out := in_one_task(graph, parts, direction, metrics, max_iter)) is not None:
        return out
    loop = Loop(graph, parts, metrics, max_iter, pulls=direction != "push")
    loop.first()
    relax(loop, direction)
    return loop.result()


def relax(loop: Loop, direction: str = "push") -> None:
    """Steps until nothing changes."""
    changed, edges = 1, 0
    while changed and not loop.over():
        pull = direction == "pull" or (direction == "auto" and edges > loop.graph.size() / 20)
        changed = pull_step(loop) if pull else push_step(loop)
        edges = loop.metrics.steps[-1]["edges"]


def pull_idem(graph, parts, metrics=None, max_iter=None) -> DataFrame:
    return push_idem(graph, parts, metrics, max_iter, direction="pull")


def pull_nonidem(graph, parts, metrics=None, max_iter=None, base: str = "init") -> DataFrame:
    """A vertex with a changed predecessor is computed anew from all its predecessors and its own start."""
    if (out := in_one_task(graph, parts, "pull_nonidem", metrics, max_iter, base)) is not None:
        return out
    loop = Loop(graph, parts, metrics, max_iter, pulls=True)
    loop.first()
    changed = 1
    while changed and not loop.over():
        changed = loop.step(_pulled(loop, base == "init"), "sum(_edges)", lambda sent: loop.replaced(f"SELECT dst, {loop.cols()} FROM {sent}"), "pull")
    return loop.result()


def push_nonidem(graph, parts, metrics=None, max_iter=None, base: str = "init") -> DataFrame:
    """Every vertex sends in every step; targets start again, from their own start unless ``base='printed'``."""
    loop = Loop(graph, parts, metrics, max_iter)
    loop.first()

    def then(sent: str) -> str:
        every = f"(SELECT * FROM {sent}" + (f" UNION ALL SELECT id AS dst, {loop.cols()} FROM {loop.tag}_start)" if base == "init" else ")")
        return f"SELECT dst AS id, {loop.cols()}, {differs(loop.names)} AS changed FROM ({loop.with_old(reduced(every, loop.parts, loop.bounds))})"

    changed = 1
    while changed and not loop.over():
        changed = loop.replace(loop.along(loop.state(), ["e.dst", *messages(loop.parts)]), ROWS, then, "push")
    return loop.result()


def rollback_step(loop: Loop, parts: Parts, rows: str, pieces: list[str] | None = None) -> int:
    """Changed vertices send what they have and what they had (p_): the target takes the latter back with kernel B."""
    kinds = dict(zip(names_of(parts), [k for p in parts for k in p.kinds()], strict=True))

    def then(sent: str) -> str:
        totals = ", ".join(f"CAST({AGGREGATE[p.keys[0][0]]}({pre}{n}) AS {kinds[n]}) AS {pre}{n}" for i, p in enumerate(parts) for n in p.names(i) for pre in ("", "p_"))
        met = loop.with_old(f"SELECT dst, {totals} FROM {sent} GROUP BY dst")
        left, new = [], []
        for i, p in enumerate(parts):
            (n,) = p.names(i)
            left.append(f"CASE WHEN p_{n} IS NULL THEN o_{n} ELSE {to_sql(p.rollback(), {'acc': f'o_{n}', 'old': f'p_{n}'})} END AS k_{n}, {n} AS n_{n}, o_{n}")
            new += combine(p, i, "k_", "n_")
        values = ", ".join(f"CAST({c.rsplit(' AS ', 1)[0]} AS {kinds[n]}) AS {n}" for c, n in zip(new, kinds, strict=True))
        was = ", ".join(f"o_{n} AS p_{n}" for n in kinds)
        return f"SELECT id, {loop.cols()} FROM (SELECT dst AS id, {values}, {was} FROM (SELECT dst, {', '.join(left)} FROM ({met}))) WHERE {differs(list(kinds), 'p_')}"

    select = ["e.dst", *messages(parts), *messages(parts, "p_")]
    text = loop.along(rows, select) if pieces is None else " UNION ALL ".join(f"SELECT {', '.join(select)} FROM ({rows}) r JOIN {e} e ON r.id = e.src" for e in pieces)
    return loop.step(text, ROWS, then, "rollback")


def rollback_loop(graph, parts: Parts, metrics=None, max_iter=None, starts: DataFrame | None = None) -> Loop:
    if not all(len(p.keys) == 1 and p.rollback() is not None for p in parts):
        raise ValueError("push_rollback: only a sum can be rolled back; a minimum or maximum has no inverse")
    loop = Loop(graph, parts, metrics, max_iter)
    values = names_of(parts)
    kinds = [k for p in parts for k in p.kinds()]
    loop.names = [*values, *[f"p_{n}" for n in values]]  # and what was sent last
    starts = initial(graph.held_vertices(), parts) if starts is None else starts
    loop.first(starts.select("*", *[F.lit(None).cast(k).alias(f"p_{n}") for n, k in zip(values, kinds, strict=True)]))
    return loop


def push_rollback(graph, parts, metrics=None, max_iter=None) -> DataFrame:
    """Only changed vertices send; targets take the old contribution back."""
    loop = rollback_loop(graph, parts, metrics, max_iter)
    changed = 1
    while changed and not loop.over():
        changed = rollback_step(loop, parts, loop.frontier())
    return loop.result().select("id", *names_of(parts))


def front(graph, parts, metrics=None, max_iter=None) -> DataFrame:
    """For a pair whose tuple does not distribute: each vertex keeps the front of its best trade-offs of both keys.

    A row is dropped if another one of its vertex is as good in the first key and as good in the second. Each key
    distributes alone, so what extends a dropped row is dropped too; the pair's best is on the final front. A front has
    at most as many rows as the first key has values.
    """
    (part,) = parts
    loop = Loop(graph, parts, metrics, max_iter)
    a, b = part.names(0)
    (r0, _), (r1, _) = part.keys
    first, second = a if r0 == "min" else f"-{a}", b if r1 == "min" else f"-{b}"
    loop.first()

    def then(sent: str) -> str:
        news = f"SELECT dst AS id, {a}, {AGGREGATE[r1]}({b}) AS {b}, TRUE AS changed FROM {sent} GROUP BY dst, {a}"
        rows = f"SELECT id, {a}, {b}, FALSE AS changed FROM {loop.tag}_recent UNION ALL {news}"
        best = f"SELECT *, min({second}) OVER (PARTITION BY id ORDER BY {first}, {second}, changed ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS _best FROM ({rows})"
        return f"SELECT * FROM ({best}) WHERE _best IS NULL OR {second} < _best"

    changed = 1
    while changed and not loop.over():
        changed = loop.replace(loop.along(loop.frontier(), ["e.dst", *messages(parts)]), ROWS, then, "front")
    best = f"SELECT id, min_by(struct({a}, {b}), {rank(part.keys, [a, b])}) AS _p FROM ({loop.state()}) GROUP BY id"
    return loop.close(f"SELECT id, _p.{a} AS {a}, _p.{b} AS {b} FROM ({best})")


def fixed_point(graph, kernels: Kernels, model: str = "pull", iters: int = 20, tol: float | None = None, metrics=None, dangling: str = "drop") -> DataFrame:
    """Raw kernels with a sum and an epilogue (page-rank): id, value. Push and pull do the same work each round.

    ``model='rollback'``: only vertices whose value changed send, and they send the change.
    """
    plan = Plan(graph, tuple(sorted((edge_columns(kernels.prop) | edge_columns(kernels.epilogue)) - {"src", "dst", "order"})), metrics)
    order = float(graph.order())
    names = {"order": f"{order!r}D"}
    start = to_column(kernels.init, {"order": F.lit(order), "id": F.col("id")}).cast("double")
    rows = plan.quiet.take(graph.held_vertices()).select("id", start.alias("n"), F.lit(0.0).alias("acc"), F.lit(0.0).alias("was"), F.lit(True).alias("changed"))
    state = cut(rows.repartition("id").sortWithinPartitions("id"))
    lost_sql = "0.0D"
    if dangling == "spread":
        sources = cut(plan.edges.all().select("src").distinct())
        plan.view("sources", sources)
    for _ in range(iters):
        at, sent = time.perf_counter(), Observation()
        plan.view("state", state)
        rows = f"SELECT id, n - was AS n FROM {plan.tag}_state WHERE changed" if model == "rollback" else f"SELECT id, n FROM {plan.tag}_state"
        plan.view("sent", plan.sql(plan.along(rows, ["e.dst", f"{to_sql(kernels.prop, names)} AS v"])).observe(sent, F.expr(ROWS).alias("n")))
        acc = "acc + coalesce(v, 0.0D)" if model == "rollback" else "coalesce(v, 0.0D)"
        extra = ""
        if dangling == "spread":  # one row
            lost_sql = f"lost / {order!r}D"
            extra = f" CROSS JOIN (SELECT coalesce(sum(n), 0.0D) AS lost FROM {plan.tag}_state s LEFT ANTI JOIN {plan.tag}_sources o ON s.id = o.src) l"
        total = f"SELECT dst, sum(v) AS v FROM {plan.tag}_sent GROUP BY dst"
        met = f"SELECT id, n AS was, {acc} + {lost_sql} AS acc FROM {plan.tag}_state s LEFT JOIN ({total}) t ON s.id = t.dst{extra}"
        new = f"SELECT id, {to_sql(kernels.epilogue, names | {'n': 'acc'})} AS n, acc, was FROM ({met})"
        done, changed = plan.write(plan.sql(f"SELECT *, n <> was AS changed FROM ({new})"), sent, model, at)
        drop(state)
        state = done
        if tol is not None and (not changed or state.selectExpr("max(abs(n - was))").first()[0] <= tol):
            break
    if dangling == "spread":
        drop(sources)
    plan.unsee()
    return plan.quiet.give(state).select("id", F.col("n").alias("value"))
