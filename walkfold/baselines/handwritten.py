"""Handwritten programs: direct DataFrame loops for five analyses, without specifications, fusion or synthesis."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from walkfold.exec.checkpoint import cut, drop
from walkfold.exec.metrics import RunMetrics
from walkfold.exec.models import observed


def _edges(graph, columns: tuple[str, ...] = ()) -> DataFrame:
    """What a program reads of the edges, kept by source."""
    return cut(graph.held().select("src", "dst", *columns).repartition("src"))


def _relax(graph, start: DataFrame, extend, best, better, columns: tuple[str, ...], metrics: RunMetrics | None, init_in_step: bool = False) -> DataFrame:
    """``init_in_step``: every vertex is active in the first step, as programs do that initialise inside it."""
    metrics = metrics if metrics is not None else RunMetrics()
    edges = graph.prepared(columns)
    state = cut(graph.quiet.take(start.withColumn("changed", F.lit(True))).repartition("id"))
    changed, first = 1, True
    while changed:
        at = time.perf_counter()
        sent, got = Observation(), Observation()
        active = state.where("changed").select("id", "v")
        if init_in_step and first:
            active = graph.quiet.take(graph.held_vertices()).select("id").join(active, "id", "left")
        first = False
        messages = edges.along(active).observe(sent, F.count(F.lit(1)).alias("n")).select(F.col("dst").alias("id"), F.lit(None).cast(state.schema["v"].dataType).alias("v"), extend(F.col("v")).alias("m"))
        # old values and messages meet in one shuffle by id, which leaves the state dealt like the edges
        joined = state.select("id", "v", F.lit(None).cast(state.schema["v"].dataType).alias("m")).unionByName(messages).groupBy("id").agg(best(F.col("v")).alias("v"), best(F.col("m")).alias("m"))
        take = F.col("m").isNotNull() & (F.col("v").isNull() | better(F.col("m"), F.col("v")))
        new = joined.select("id", F.when(take, F.col("m")).otherwise(F.col("v")).alias("v"), take.alias("changed")).where("v IS NOT NULL")
        new = cut(new.observe(got, F.count_if("changed").alias("n")))
        drop(state)
        state, changed = new, observed(got)
        metrics.add(observed(sent), changed, time.perf_counter() - at, "hand")
    return graph.quiet.give(state.select("id", "v"))


def _all(graph, found: DataFrame, name: str) -> DataFrame:
    return graph.held_vertices().join(found, "id", "left").select("id", F.col("v").alias(name))


def sssp(graph, source: int, metrics=None, **how) -> DataFrame:
    start = graph.held_vertices().where(F.col("id") == source).select("id", F.lit(0).cast("long").alias("v"))
    return _all(graph, _relax(graph, start, lambda v: v + F.col("weight"), F.min, lambda m, v: m < v, ("weight",), metrics, **how), "dist")


def wp(graph, source: int, metrics=None, **how) -> DataFrame:
    """SSSP with another path function."""
    top = 2**63 - 1
    start = graph.held_vertices().where(F.col("id") == source).select("id", F.lit(top).alias("v"))
    found = _relax(graph, start, lambda v: F.when(v.isNotNull(), F.least(v, F.col("capacity"))), F.max, lambda m, v: m > v, ("capacity",), metrics, **how)
    return _all(graph, found.withColumn("v", F.when(F.col("v") != top, F.col("v"))), "cap")


def cc(graph, metrics=None, **how) -> DataFrame:
    start = graph.held_vertices().select("id", F.col("id").alias("v"))
    return _all(graph, _relax(graph, start, lambda v: v, F.min, lambda m, v: m < v, (), metrics, **how), "component")


def bfs(graph, source: int, metrics: RunMetrics | None = None) -> DataFrame:
    """Frontier by frontier: what was visited is left out by an anti-join; least parent on ties."""
    metrics = metrics if metrics is not None else RunMetrics()
    edges = graph.prepared()
    start = graph.held_vertices().where(F.col("id") == source).select("id", F.lit(0).cast("long").alias("hops"), F.col("id").alias("parent"))
    seen = cut(graph.quiet.take(start).repartition("id"))
    hops, n = 0, 1
    while n:
        at = time.perf_counter()
        sent, got = Observation(), Observation()
        front = seen.where(F.col("hops") == hops).select("id")
        hops += 1
        met = edges.along(front).observe(sent, F.count(F.lit(1)).alias("n")).groupBy("dst").agg(F.min("src").alias("parent"))
        fresh = met.join(seen, F.col("dst") == F.col("id"), "left_anti").select(F.col("dst").alias("id"), F.lit(hops).cast("long").alias("hops"), "parent")
        new = cut(seen.unionByName(fresh).observe(got, F.count_if(F.col("hops") == hops).alias("n")))
        drop(seen)
        seen, n = new, observed(got)
        metrics.add(observed(sent), n, time.perf_counter() - at, "hand")
    return graph.held_vertices().join(graph.quiet.give(seen), "id", "left").select("id", "hops", "parent")


def pr(graph, gamma: float = 0.85, iters: int = 20, metrics: RunMetrics | None = None) -> DataFrame:
    metrics = metrics if metrics is not None else RunMetrics()
    n = graph.order()
    edges = _edges(graph)
    edges = cut(edges.join(edges.groupBy("src").agg(F.count(F.lit(1)).alias("outdeg")), "src"))
    rank = cut(graph.held_vertices().select("id", F.lit(1.0 / n).alias("rank")))
    for _ in range(iters):
        at = time.perf_counter()
        sent = Observation()
        got = rank.join(edges, F.col("id") == F.col("src")).observe(sent, F.count(F.lit(1)).alias("n")).groupBy("dst").agg(F.sum(F.col("rank") / F.col("outdeg")).alias("v"))
        new = cut(rank.select("id").join(got, F.col("id") == F.col("dst"), "left").select("id", (F.lit(gamma) * F.coalesce("v", F.lit(0.0)) + (1 - gamma) / n).alias("rank")))
        drop(rank)
        rank = new
        metrics.add(observed(sent), n, time.perf_counter() - at, "hand")
    drop(edges)
    return rank
