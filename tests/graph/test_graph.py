import random

import pytest
from pyspark.sql import functions as F

from walkfold import graphs as G
from walkfold import usecases as U
from walkfold.baselines import enumerate_paths, handwritten, unfused
from walkfold.exec import models, onetask
from walkfold.exec.checkpoint import cut
from walkfold.exec.metrics import RunMetrics
from walkfold.fuse.engine import fuse
from walkfold.kernels import codec
from walkfold.kernels.exprs import call, edge, lit, simplify, slot, to_sql
from walkfold.kernels.library import page_rank
from walkfold.plans.catalog import SPECS
from walkfold.plans.recursive import to_recursive_sql
from walkfold.spec.parser import ParseFault, parse
from walkfold.spec.semantics import evaluate
from walkfold.spec.terms import BinOp, PathReduce, Paths, VertexReduce
from walkfold.spec.types import TypeFault, typecheck
from walkfold.synth.conditions import REDUCE, Refused, check_distributes, check_extends, conditions, explain, reduction_laws
from walkfold.synth.enumerate import find_rollback, synthesize

#: Expected values on the nine-edge graph, from source 1, for vertices 1 to 7.
SSSP = [0, 4, 1, 6, 7, None, None]


@pytest.fixture(scope="module")
def g(spark):
    return G.micro(spark)


@pytest.fixture(scope="module")
def acyclic(g):
    return G.Graph(g.edges.where("NOT (src = 5 AND dst = 3) AND src <> 6"), name="acyclic")


def column(df, name=None):
    rows = sorted(df.collect(), key=lambda r: r[0])
    return [r[name or 1] for r in rows]


@pytest.mark.parametrize(("use", "want", "steps", "edges"), [
    (lambda g, m: U.sssp(g, 1, metrics=m), SSSP, 4, 7),
    (lambda g, m: U.hop_distance(g, 1, metrics=m), [0, 1, 1, 2, 3, None, None], 4, 7),
    (lambda g, m: U.widest_path(g, 1, metrics=m), [None, 10, 3, 5, 5, None, None], 4, 7),
    (lambda g, m: U.narrowest_path(g, 1, metrics=m), [None, 2, 2, 2, 2, None, None], 7, 13),
])
def test_single_reductions(g, use, want, steps, edges):
    m = RunMetrics()
    assert column(use(g, m)) == want
    assert (m.n_steps, m.edges_processed) == (steps, edges)


def test_pairs(g):
    assert [tuple(r)[1:] for r in sorted(U.bfs_tree(g, 1).collect())][:5] == [(0, 1), (1, 1), (1, 1), (2, 2), (3, 4)]
    assert [tuple(r)[1:] for r in sorted(U.widest_shortest(g, 1, "weight").collect())][:5] == [(0, None), (4, 10), (1, 3), (6, 5), (7, 5)]
    assert [tuple(r)[1:] for r in sorted(U.widest_shortest(g, 1).collect())][:5] == [(0, None), (1, 10), (1, 3), (2, 5), (3, 5)]
    assert [(r.dist, r.n and int(r.n)) for r in sorted(U.count_shortest(g, 1).collect())][:5] == [(0, 1), (4, 2), (1, 1), (6, 3), (7, 3)]
    assert column(unfused.widest_shortest(g, 1, "weight"), "cap") == column(U.widest_shortest(g, 1, "weight"), "cap")
    assert column(unfused.count_shortest(g, 1), "n") == column(U.count_shortest(g, 1), "n")


@pytest.mark.parametrize(("spec", "fused", "apart"), [(U.spec_nwr(1), 13, 20), (U.spec_radius((1, 7)), 15, 15), (U.spec_trust((1, 7)), 15, 30), (U.spec_drr((1, 7)), 15, 30)])
def test_fusion_saves_edges_and_keeps_values(g, spec, fused, apart):
    a, b = RunMetrics(), RunMetrics()
    x, y = U.solve(g, spec, metrics=a).collect(), U.solve(g, spec, fused=False, metrics=b).collect()
    assert sorted(map(tuple, x), key=str) == sorted(map(tuple, y), key=str)
    assert (a.edges_processed, b.edges_processed) == (fused, apart)


def test_scalars_and_rounds(g):
    one = lambda df: df.first()[0]
    assert one(U.eccentricity(g, 1)) == 3 and one(U.radius(g, (1, 7))) == 3 and one(U.diameter(g, (1, 7))) == 4
    assert one(U.diameter_radius_ratio(g, (1, 7))) == pytest.approx(4 / 3)
    assert one(U.distant_set(g, 1)) == [] and one(U.distant_set(g, 1, 5)) == [4, 5]
    assert one(U.radius_trust_floor(g, 1, (1, 7))) == 3 and one(U.radius_trust_floor(g, 1, (1, 7), "weight")) == 3
    assert column(U.trust(g, (1, 7)))[:4] == [6, 10, 3, 2.5]


@pytest.mark.parametrize("model", ["push", "pull", "auto_switch", "async"])
def test_models_agree(g, model):
    assert column(U.sssp(g, 1, model=model)) == SSSP


@pytest.mark.parametrize("model", ["pull_nonidem", "push_nonidem", "rollback"])
def test_counting_models_agree(acyclic, model):
    assert [None if x is None else int(x) for x in column(U.count_paths(acyclic, 1, model=model))] == [1, 2, 1, 3, 3, None]


def test_components_and_page_rank(g):
    both = G.Graph(G.symmetrise(g.edges))
    m = RunMetrics()
    assert column(U.connected_components(both, metrics=m)) == [1, 1, 1, 1, 1, 6, 1] and (m.n_steps, m.edges_processed) == (3, 35)
    assert column(handwritten.cc(both)) == [1, 1, 1, 1, 1, 6, 1]
    want = [0.039643, 0.132335, 0.220968, 0.22788, 0.214888, 0.142857, 0.021429]
    for df in (U.page_rank(g), U.page_rank(g, model="rollback"), handwritten.pr(g), U.run_kernels(g, page_rank(), iters=20)):
        assert column(df) == pytest.approx(want, abs=1e-6)
    assert sum(column(U.page_rank(g, dangling="spread"))) == pytest.approx(sum(want), abs=0.5)


def test_handwritten_programs(g):
    assert column(handwritten.sssp(g, 1)) == SSSP and column(handwritten.wp(g, 1)) == column(U.widest_path(g, 1))
    assert sorted(map(tuple, handwritten.bfs(g, 1).collect())) == sorted(map(tuple, U.bfs_tree(g, 1).collect()))
    a, b = RunMetrics(), RunMetrics()
    handwritten.sssp(g, 1, metrics=a)
    handwritten.sssp(g, 1, metrics=b, init_in_step=True)
    assert b.edges_processed > a.edges_processed == 7
    assert column(enumerate_paths.sssp(g, 1, 5)) == SSSP


@pytest.mark.parametrize("k", [1, 2, 3, 4])
def test_each_step_is_the_reduction_over_short_walks(g, k):
    part = (models.Part((("min", "weight"),), 1),)
    want = evaluate(PathReduce("min", "weight", Paths(1)), G.MICRO, k)
    for run in (models.push_idem, models.pull_idem):
        got = {r.id: r.s0_0 for r in run(g, part, max_iter=k).collect()}
        assert got == {v: x for v, x in want.items() if x is not None}
    count = (models.Part((("sum", "one"),), 1),)
    want = evaluate(PathReduce("sum", "one", Paths(1)), G.MICRO, k)
    for run in (models.pull_nonidem, models.push_nonidem):
        got = {r.id: int(r.s0_0) for r in run(g, count, max_iter=k).collect()}
        assert got == {v: x for v, x in want.items() if x is not None}


@pytest.mark.parametrize("seed", range(4))
def test_random_graphs_against_enumeration(spark, seed):
    draw = random.Random(seed)
    n = draw.randint(3, 5)
    edges = [(a, b, draw.randint(0, 3), draw.randint(0, 3)) for a in range(n) for b in range(n) if draw.random() < 0.4] or [(0, 1, 1, 1)]
    graph = G.Graph(spark.createDataFrame(edges, "src long, dst long, weight long, capacity long"), spark.range(n).select("id"))
    for spec in (U.spec_wsp(0, "weight"), U.spec_nwr(0), U.spec_bfs(0), U.spec_trust((0, 1))):
        want = evaluate(spec, edges, n + 2, list(range(n)))
        got = {r.id: r.value for r in U.solve(graph, spec).collect()}
        assert {v: pytest.approx(x) for v, x in want.items()} == got
    for spec in (U.spec_drr((0, 1)), U.spec_rds(0, (0, 1)), U.spec_distant(0, 2)):
        want, got = evaluate(spec, edges, n + 2, list(range(n))), U.solve(graph, spec).first()[0]
        assert got == (pytest.approx(want) if isinstance(want, float) else want)


def test_refusals(g, acyclic, spark):
    with pytest.raises(Refused, match="cycle"):
        U.longest_path(g, 1)
    with pytest.raises(Refused, match="acyclic"):
        U.count_paths(g, 3)
    with pytest.raises(Refused, match="taken back"):
        U.sssp(g, 1, model="rollback")
    with pytest.raises(Refused, match="distribute"):
        U.solve(acyclic, PathReduce("sum", "length", Paths(1)))
    zero = G.Graph(spark.createDataFrame([(1, 2, 0, 1), (2, 1, 0, 1)], "src long, dst long, weight long, capacity long"))
    with pytest.raises(Refused, match="weight zero"):
        U.count_shortest(zero, 1)
    below = G.Graph(spark.createDataFrame([(1, 2, -1, 1), (2, 1, 0, 1)], "src long, dst long, weight long, capacity long"))
    with pytest.raises(Refused, match="negative"):
        U.sssp(below, 1)
    with pytest.raises(ValueError, match="counts? a contribution twice|twice"):
        models.push_idem(acyclic, (models.Part((("sum", "one"),), 1),))
    assert "refused" in explain(g, (models.Part((("max", "length"),), 1),)) and "edge-absorb" in explain(g, (models.Part((("min", "weight"),), 1),))
    assert column(U.longest_path(acyclic, 7)) == [1, 3, 2, 4, 5, 0]


def test_conditions_and_mutants():
    n = slot("n")
    assert check_extends(call("+", n, lit(1)), "length").holds and not check_extends(call("+", n, lit(2)), "length").holds
    assert not check_extends(call("max", n, edge("capacity")), "capacity").holds
    # n*n - 2n + 2 agrees on 1 and 2 only
    mutant = call("+", call("-", call("*", n, n), call("*", lit(2), n)), lit(2))
    assert not check_distributes(mutant, "sum", "one").holds
    assert not reduction_laws(lambda a, b: a)["commutative"] and reduction_laws(REDUCE["min"])["idempotent"] and not reduction_laws(REDUCE["sum"])["idempotent"]
    table = {rf: conditions(*rf) for rf in [("min", "weight"), ("max", "capacity"), ("min", "capacity"), ("max", "length"), ("sum", "one"), ("sum", "length")]}
    assert [table[rf]["edge_absorb"] for rf in table] == [True, True, False, False, False, False]
    assert [table[rf]["distributes"] for rf in table] == [True, True, True, True, True, False]


@pytest.mark.parametrize(("r", "f", "body"), [("min", "length", "+(n, 1)"), ("min", "weight", "+(n, weight)"), ("max", "capacity", "min(n, capacity)"), ("min", "head", "n"), ("min", "penult", "src"), ("sum", "one", "n")])
def test_synthesis(r, f, body):
    got = synthesize(r, f)
    assert repr(got.prop) == body and got.checked == "bounded"
    assert (find_rollback(r) is not None) == (r == "sum")


def test_traces():
    want = {"wsp": ("fuse_nested_paths", 1, 1), "nwr": ("pair_paths", 1, 1), "radius": ("pair_vertex_reductions", 1, 1), "drr": ("share_common", 1, 1), "trust": ("pair_paths", 1, 1), "rds": ("split_rounds", 2, 2), "bfs": ("expand_arg_path", 1, 1)}
    for name, (rule, rounds, loops) in want.items():
        done, trace = fuse(SPECS[name])
        assert rule in trace.fired and (len(done.lets), trace.n_after) == (rounds, loops), name
    assert fuse(SPECS["drr"])[1].n_before == 4 and fuse(SPECS["rds"])[1].n_before == 4
    deep = PathReduce("min", "head", SPECS["wsp"].paths.__class__("max", "capacity", SPECS["wsp"].paths))
    assert len(fuse(deep)[0].lets[0].loops[0][0].keys) == 3


def test_types_and_parser(g):
    assert parse("max capacity best min length paths from 1") == U.spec_wsp(1)
    assert parse("min from {1, 2} of max over v of min length paths from s") == U.spec_radius((1, 2))
    assert parse("count best min weight paths from 1") == U.spec_nsp(1)
    assert parse("union over v of v where min weight paths from 1 > 7") == U.spec_distant(1)
    assert U.solve(g, parse("max over v of min length paths from 7")).first()[0] == 4
    for bad in ("min", "min length", "max over v min", "1 +", "min length paths from 1 )"):
        with pytest.raises(ParseFault):
            parse(bad)
    with pytest.raises(TypeFault, match="weight"):
        typecheck(PathReduce("min", "weight", Paths(1)), {"src", "dst"})
    with pytest.raises(TypeFault):
        typecheck(PathReduce("or", "length", Paths(1)), {"weight"})
    with pytest.raises(TypeFault):
        typecheck(VertexReduce("min", PathReduce("min", "length"), where=BinOp("+", PathReduce("min", "length"), PathReduce("min", "length"))), {"weight"})


def test_codec_and_exprs(spark):
    rows = spark.createDataFrame([(0, 5), (7, 0), (2**31 - 2, 2**31 - 2)], "a long, b long")
    for greatest in (False, True):
        a, b = codec.unpack(codec.pack(F.col("a"), F.col("b"), greatest), greatest)
        assert rows.where((a != F.col("a")) | (b != F.col("b"))).count() == 0
    assert not codec.fits(2**31, 1) and simplify(call("+", slot("n"), lit(0))) == slot("n") and to_sql(call("min", slot("n"), edge("capacity"))) == "least(n, capacity)"


def test_recursive_sql(g):
    import duckdb

    c = duckdb.connect()
    c.execute("CREATE TABLE edges (src BIGINT, dst BIGINT, weight BIGINT, capacity BIGINT)")
    c.executemany("INSERT INTO edges VALUES (?, ?, ?, ?)", G.MICRO)
    got = dict(c.execute(to_recursive_sql(PathReduce("min", "weight", Paths(1)), rounds=10)).fetchall())
    assert got == {v: d for v, d in zip(range(1, 8), SSSP, strict=True) if d is not None}


def test_preparation(spark):
    e = spark.createDataFrame([(1, 2, 3, 4), (1, 2, 1, 9), (2, 1, 5, 5), (3, 3, 1, 1)], "src long, dst long, weight long, capacity long")
    assert sorted(map(tuple, G.merge_parallel(G.drop_self_loops(e)).collect())) == [(1, 2, 1, 9), (2, 1, 5, 5)]
    assert G.symmetrise(e).count() == 7 and G.induced(e, F.col("id") < 3).count() == 3
    assert G.Graph(e.where("src = 1")).is_acyclic() and not G.Graph(e).is_acyclic()
    with pytest.raises(ValueError, match="dst"):
        G.Graph(spark.range(3).withColumnRenamed("id", "src"))
    nothing = G.Graph(e.where("false"))
    assert U.sssp(nothing, 1).count() == 0


def test_plans_keep_edges_in_place(g):
    loop = models.Loop(g, (models.Part((("min", "length"),), 1),))
    assert loop.edges.columns == ["src", "dst"]  # hop counts read no attribute


def test_a_checkpoint_forgets_the_estimates_before_it(spark):
    """State joined with itself step by step: the estimate of its bytes must not double its digits each time."""
    from walkfold.exec.checkpoint import cut

    df = spark.range(4)
    for _ in range(6):
        other = df.withColumnRenamed("id", "other")
        df = cut(df.join(other, df["id"] == other["other"]).select("id"))
    assert int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()) < 2**64
    assert sorted(r.id for r in df.collect()) == [0, 1, 2, 3]


def test_small_graphs_are_dealt_into_few_partitions(spark):
    small = G.micro(spark)
    assert small.prepared().lights[0]._jdf.queryExecution().toRdd().getNumPartitions() == 2
    assert spark.conf.get("spark.sql.shuffle.partitions") == "4"


def test_nearest_vectors_by_blocks(spark, tmp_path, monkeypatch):
    """Several blocks on both sides; equal distances by id; null and shorter vectors rank last."""
    monkeypatch.setattr(G, "KNN_QUERIES", 3), monkeypatch.setattr(G, "KNN_ROWS", 4)
    draw = random.Random(1)
    vectors = {i: [float(draw.randint(0, 2)) for _ in range(3)] for i in range(20)} | {20: None, 21: [1.0]}
    spark.createDataFrame(list(vectors.items()), "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {}
    for r in G.vec_knn(spark, str(tmp_path), k=3, every=5).edges.collect():
        got.setdefault(r.src, []).append((r.dst, r.weight))
    far = lambda a, b: None if a is None or b is None or len(a) != len(b) else sum((x - y) ** 2 for x, y in zip(a, b, strict=True))
    for i in (0, 5, 10, 15, 20):
        d = {j: far(vectors[i], v) for j, v in vectors.items() if j != i}
        want = sorted(d, key=lambda j: (d[j] is None, d[j] or 0, j))[:3]
        assert sorted(got[i]) == sorted((j, None if d[j] is None else round(d[j] * 1000)) for j in want)
    assert set(got) == {0, 5, 10, 15, 20}


def test_every_vector_asks_for_its_nearest(spark, tmp_path):
    """The registered query is that of all vectors, and so is its SQL."""
    import duckdb

    from walkfold.plans import catalog

    draw = random.Random(2)
    rows = [(7 * i + 1, [draw.gauss(0, 1) for _ in range(5)]) for i in range(40)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").coalesce(1).write.parquet(f"{tmp_path}/embeddings.parquet")
    got = sorted(tuple(r) for r in catalog.QUERIES["knn_vectors"](spark, str(tmp_path)).collect())
    assert [r[0] for r in got] == sorted(3 * [i for i, _ in rows])
    db = duckdb.connect()
    db.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    assert got == sorted(db.execute(catalog.ORACLES["knn_vectors"]).fetchall())


@pytest.mark.parametrize("kind", ["spread", "few values", "far from zero", "many lengths", "equal", "odd"])
def test_products_leave_the_nearest(kind, monkeypatch):
    """What the bound of the products leaves out is never among the nearest, measured pair by pair."""
    import numpy as np
    import pyarrow as pa

    from walkfold.exec import nearest

    monkeypatch.setattr(nearest, "TILE", 50), monkeypatch.setattr(nearest, "GROUP", 4), monkeypatch.setattr(nearest, "AT_ONCE", 100)
    draw = np.random.default_rng(3)
    x = {"few values": draw.integers(0, 2, (150, 4)), "far from zero": 1000 + 0.001 * draw.normal(size=(150, 4)), "many lengths": draw.normal(size=(150, 4)) * 10.0 ** draw.integers(-25, 20, (150, 1)), "equal": np.ones((150, 4))}
    x = x.get(kind, draw.normal(size=(150, 4))).astype(np.float32)
    vectors, ids = x.tolist(), draw.permutation(150) // 2 if kind == "few values" else draw.permutation(150)
    if kind == "odd":
        vectors[:8] = [None, [], [1.0], [None] * 4, [None, 0.0, 1.0, 2.0], [float("nan")] * 4, [float("inf"), 0.0, 0.0, 0.0], [3e38, 0.0, 0.0, 0.0]]

    def far(a, b) -> float:
        if a is None or b is None or len(a) != len(b) or all(u is None or v is None for u, v in zip(a, b, strict=True)):
            return np.inf
        with np.errstate(all="ignore"):
            steps = [np.float32(u) - np.float32(v) for u, v in zip(a, b, strict=True) if u is not None and v is not None]
            d = sum(float(s * s) for s in steps)
        return d if np.isfinite(d) else np.inf

    column = pa.array(vectors, pa.list_(pa.float32()))
    got = nearest.nearest(3)(pa.table({"src": ids[:100], "_q": column[:100]}), pa.table({"dst": ids, "_x": column})).to_pylist()
    want = [(i, j, d) for i, a in zip(ids[:100], vectors, strict=False) for d, j in sorted((far(a, b), j) for j, b in zip(ids, vectors, strict=True) if i != j)[:3]]
    assert sorted((r["src"], r["dst"], np.inf if r["d"] is None else r["d"]) for r in got) == sorted(want)


@pytest.mark.parametrize("seed", range(3))
def test_one_task_takes_the_steps_of_many(spark, seed, monkeypatch):
    """Values, steps, edges and changes of each step are those of the supersteps."""
    draw = random.Random(seed)
    n = draw.randint(4, 9)
    edges = [(a, b, draw.randint(1, 3), draw.randint(0, 3)) for a in range(n) for b in range(n) if draw.random() < 0.35] or [(0, 1, 1, 1)]
    graph = G.Graph(spark.createDataFrame(edges, "src long, dst long, weight long, capacity long"), spark.range(n + 1).select("id"))
    hop, wide, pair = ((("min", "length"),), (("max", "capacity"),), (("min", "weight"), ("max", "capacity")))
    cases = [
        *[(models.push_idem, (models.Part(hop, 0), models.Part(wide, 1), models.Part(pair, 2)), {"direction": d}) for d in ("push", "pull", "auto")],
        (models.push_idem, (models.Part((("min", "length"), ("min", "penult")), 0),), {}), (models.push_idem, (models.Part((("min", "head"),)),), {}), (models.push_idem, (models.Part((("and", "all:weight>1"),), 0),), {}),
        (models.pull_nonidem, (models.Part((("min", "weight"), ("sum", "one")), 0),), {}), *[(models.pull_nonidem, (models.Part((("sum", "one"),), 0),), {"max_iter": 4, "base": b}) for b in ("init", "printed")],
    ]
    for run, parts, how in cases:
        seen = []
        for most in (0, 2_000_000):
            monkeypatch.setattr(onetask, "MOST", most)
            m = RunMetrics()
            seen.append((sorted(map(tuple, run(graph, parts, m, **how).collect())), [(s["edges"], s["changed"], s["model"]) for s in m.steps], m.vertex_bytes, m.edge_bytes))
        assert seen[0] == seen[1], (parts, how)


def test_one_task_leaves_what_arrays_cannot_hold(spark):
    """Counts over 2^63 and missing attributes run as supersteps, with exact results."""
    twice = [(k, k + 1, w, 1) for k in range(66) for w in (1, 2)]
    graph = G.Graph(spark.createDataFrame(twice, "src long, dst long, weight long, capacity long"))
    assert max(int(r.n) for r in U.count_paths(graph, 0).collect()) == 2**66
    gaps = G.Graph(spark.createDataFrame([(1, 2, None, 3), (1, 3, 2, 3), (3, 2, 2, 3)], "src long, dst long, weight long, capacity long"))
    assert column(U.sssp(gaps, 1)) == [0, 4, 2]


def test_one_task_runs_few_jobs(spark):
    """A long chain costs no job for each step; as supersteps it had over one each."""
    spark.sparkContext.setJobGroup("one-task", "chain")
    try:
        graph = G.Graph(spark.range(300).selectExpr("id AS src", "id + 1 AS dst", "1L AS weight", "1L AS capacity"))
        m = RunMetrics()
        assert max(column(U.sssp(graph, 0, metrics=m))) == 300 and m.n_steps == 301
        assert graph.is_acyclic()
        assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("one-task")) < 40
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


@pytest.mark.parametrize("hub_least", [1, G.HUB_LEAST])
def test_handwritten_steps_shuffle_once(g, monkeypatch, hub_least):
    """The state stays dealt like the edges: a step moves old values and messages in one shuffle, with hubs too."""
    plans = []
    monkeypatch.setattr(handwritten, "cut", lambda df: (plans.append(df._jdf.queryExecution().executedPlan().toString()), cut(df))[1])
    graph = G.Graph(g.edges, hub_least=hub_least)
    assert column(handwritten.sssp(graph, 1)) == SSSP
    steps = [p for p in plans if "CollectMetrics" in p]
    assert len(steps) == 4
    assert all(p.count(" Exchange ") == 1 for p in steps)
    assert column(handwritten.cc(graph, init_in_step=True)) == [1, 1, 1, 1, 1, 6, 7]
    assert [tuple(r)[1:] for r in sorted(handwritten.bfs(graph, 1).collect())][:5] == [(0, 1), (1, 1), (1, 1), (2, 2), (3, 4)]


@pytest.mark.parametrize("hub_least", [1, G.HUB_LEAST])
def test_supersteps_shuffle_messages_alone(spark, hub_least):
    """State stays dealt, from the first step on and after it was put together (step 16): no record is one of state."""
    edges = spark.range(20).selectExpr("id AS src", "explode(array(id + 1, id + 2)) AS dst", "1L AS capacity").selectExpr("src", "dst", "(dst - src) * (dst - src) AS weight", "capacity")
    graph = G.Graph(edges, hub_least=hub_least)
    push, pair, pull = (RunMetrics(count_records=True) for _ in range(3))
    assert column(U.sssp(graph, 0, metrics=push)) == [*range(21), 23]
    assert [r.dist for r in sorted(U.widest_shortest(graph, 0, "weight", metrics=pair).collect())] == [*range(21), 23]
    assert column(U.sssp(graph, 0, model="pull", metrics=pull)) == [*range(21), 23]
    for m in (push, pair):
        assert m.n_steps > models.Loop.COMPACT + 2
        assert all(0 <= s["records"] <= s["edges"] for s in m.steps), [(s["records"], s["edges"]) for s in m.steps]
    assert pull.n_steps > models.Loop.COMPACT + 2
    assert all(0 < s["records"] <= graph.size() for s in pull.steps), [s["records"] for s in pull.steps]


@pytest.mark.parametrize("hub_least", [1, G.HUB_LEAST])
def test_pull_sends_nothing_for_sources_without_a_value(spark, hub_least):
    """Edges into a hit vertex count, also those from sources without a value and those without a target; only the others' messages move."""
    rows = [(1, 2, 1, 1), (2, 3, 1, 1), (1, None, 1, 1), (9, None, 1, 1), *[(k, 3, 1, 1) for k in range(10, 20)], *[(k, k + 1, 1, 1) for k in range(100, 400)]]
    graph = G.Graph(spark.createDataFrame(rows, "src long, dst long, weight long, capacity long"), hub_least=hub_least)
    m, n = RunMetrics(count_records=True), RunMetrics(count_records=True)
    assert [r.dist for r in U.sssp(graph, 1, model="pull", metrics=m).where("id IN (1, 2, 3)").sort("id").collect()] == [0, 1, 2]
    assert [s["edges"] for s in m.steps][:2] == [3, 11]  # into 2 and into none; into 3
    assert max(s["records"] for s in m.steps) <= 3
    assert [int(r.n) for r in U.count_shortest(graph, 1, metrics=n).where("id IN (1, 2, 3)").sort("id").collect()] == [1, 1, 1]
    assert [s["edges"] for s in n.steps][:2] == [3, 11]
    assert max(s["records"] for s in n.steps) <= 2 * (3 + 1)  # two shuffles, and the start's own row
