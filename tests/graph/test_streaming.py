import pytest
from pyspark.sql import functions as F

from walkfold import graphs as G
from walkfold import usecases as U
from walkfold.streaming import incremental, windows
from walkfold.synth.conditions import Refused

EVENTS = "/root/testdata/sf0.001/events.parquet"


@pytest.fixture
def folder(spark, tmp_path):
    """Events dealt by day into files of a directory."""
    rows = spark.read.parquet(EVENTS).withColumn("_d", F.dayofmonth("ts") % 3)
    for k in range(3):
        rows.where(F.col("_d") == k).drop("_d").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    return str(tmp_path)


def test_inserts_equal_a_recomputation(spark):
    kept = incremental.Maintained(spark, "min", "weight", 1)
    edges = spark.createDataFrame(G.MICRO, "src long, dst long, weight long, capacity long")
    for k in range(3):
        kept.insert(edges.where(F.pmod(F.xxhash64("src", "dst"), F.lit(3)) == k))
    want = {r.id: r.dist for r in U.sssp(G.micro(spark), 1).collect() if r.dist is not None}
    assert {r.id: r.value for r in kept.values().collect()} == want
    kept.delete(edges.where("src = 2"))
    assert {r.id: r.value for r in kept.values().collect()}[4] == 6
    with pytest.raises(Refused):
        incremental.Maintained(spark, "sum", "length", 1)


def test_sums_take_new_edges(spark):
    """Counts of paths by differences; a cycle is refused when its last edge comes."""
    edges = spark.createDataFrame(G.MICRO, "src long, dst long, weight long, capacity long").where("src <> 6 AND NOT (src = 5 AND dst = 3)")
    kept = incremental.Maintained(spark, "sum", "one", 1)
    for k in (2, 0, 1):
        kept.insert(edges.where(F.pmod(F.xxhash64("dst", "src"), F.lit(3)) == k))
    want = {r.id: int(r.n) for r in U.count_paths(G.Graph(edges), 1).collect() if r.n is not None}
    assert {r.id: int(r.value) for r in kept.values().collect()} == want
    kept.delete(edges.where("src = 3 AND dst = 2"))
    assert {r.id: int(r.value) for r in kept.values().collect()}[2] == 1
    with pytest.raises(Refused):
        kept.insert(spark.createDataFrame([(5, 3, 1, 1)], "src long, dst long, weight long, capacity long"))


def test_batches_come_once_and_survive(spark, tmp_path):
    edges = spark.createDataFrame(G.MICRO, "src long, dst long, weight long, capacity long")
    one, two = edges.where("src < 4"), edges.where("src >= 4")
    kept = incremental.Maintained(spark, "max", "capacity", 1, str(tmp_path))
    kept.insert(one, 0)
    kept.insert(one, 0)  # sent again
    assert kept.last == 0 and kept.edges.count() == one.count()
    again = incremental.Maintained(spark, "max", "capacity", 1, str(tmp_path))
    again.insert(two, 1)
    want = {r.id: r.cap for r in U.widest_path(G.micro(spark), 1).collect() if r.cap is not None}
    got = {r.id: r.value for r in again.values().collect()}
    assert {k: v for k, v in got.items() if k != 1} == want


def test_deletions_withdraw_what_rests_on_them(spark):
    """A cycle that gives itself its values loses them with the edge that fed it."""
    rows = [(1, 2, 1, 1), (2, 3, 1, 1), (3, 2, 0, 1), (1, 4, 9, 1), (4, 3, 1, 1), (3, 5, 1, 1)]
    edges = spark.createDataFrame(rows, "src long, dst long, weight long, capacity long")
    kept = incremental.Maintained(spark, "min", "weight", 1)
    kept.insert(edges)
    kept.delete(edges.where("src = 1 AND dst = 2"))
    rest = G.Graph(edges.where("NOT (src = 1 AND dst = 2)"))
    want = {r.id: r.dist for r in U.sssp(rest, 1).collect() if r.dist is not None}
    assert {r.id: r.value for r in kept.values().collect()} == want


def test_late_rows_are_counted(spark, tmp_path):
    at = lambda day: f"2024-01-{day:02d} 12:00:00"
    for k, days in enumerate(((20,), (21,), (3, 22))):  # the last file's first row is 17 days late
        rows = [(10 * k + i, at(d), 1, "purchase", 1.0, "{}") for i, d in enumerate(days)]
        spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = windows.event_stream(spark, str(tmp_path / "in"))
    q = windows.tumbling(stream, late="1 hour").writeStream.outputMode("append").format("memory").queryName("late").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert incremental.late_rows(q) == 1


def test_streamed_edges(spark, folder):
    stream = windows.event_stream(spark, folder + "/in")
    pairs = stream.where("event_type = 'purchase'").select(F.col("user_id").alias("src"), (F.col("user_id") % 5).alias("dst"), F.lit(1).cast("long").alias("weight"), F.lit(1).cast("long").alias("capacity"))
    source = spark.read.parquet(EVENTS).where("event_type = 'purchase'").agg(F.max("user_id")).first()[0]
    kept = incremental.Maintained(spark, "min", "length", source)
    incremental.maintain(pairs, kept, folder + "/cp").awaitTermination(120)
    whole = spark.read.parquet(EVENTS).where("event_type = 'purchase'").select(F.col("user_id").alias("src"), (F.col("user_id") % 5).alias("dst")).distinct()
    want = {r.id: r.hops for r in U.hop_distance(G.Graph(whole), source).collect() if r.hops is not None}
    assert {r.id: r.value for r in kept.values().collect()} == want


@pytest.mark.parametrize("kind", ["tumbling", "sliding", "sessions"])
def test_windows_have_batch_twins(spark, folder, kind):
    use = getattr(windows, kind)
    stream = windows.event_stream(spark, folder + "/in")
    name = f"out_{kind}"
    use(stream).writeStream.outputMode("complete").format("memory").queryName(name).option("checkpointLocation", f"{folder}/cp_{kind}").trigger(availableNow=True).start().awaitTermination(120)
    assert sorted(map(tuple, spark.table(name).collect())) == sorted(map(tuple, use(spark.read.parquet(EVENTS)).collect()))


def test_last_seen_and_deduplication(spark, folder):
    stream = windows.event_stream(spark, folder + "/in")
    windows.last_seen(windows.deduplicated(stream, "40 days")).writeStream.outputMode("update").format("memory").queryName("last_seen").option("checkpointLocation", folder + "/cp_last").trigger(availableNow=True).start().awaitTermination(120)
    got = {r[0]: r[1] for r in spark.sql("SELECT user_id, max(last_us) FROM last_seen GROUP BY user_id").collect()}
    want = {r[0]: r[1] for r in windows.purchases(spark.read.parquet(EVENTS)).groupBy("user_id").agg(F.max(F.unix_micros("ts"))).collect()}
    assert got == want
