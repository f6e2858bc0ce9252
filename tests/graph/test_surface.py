import pytest
from pyspark.sql import functions as F

from walkfold import graphs as G
from walkfold.functions import kernels_udf, scalars
from walkfold.plans import register
from walkfold.sources import edge_lists
from walkfold.synth.conditions import Refused


def test_views_and_table_function(spark):
    g = G.micro(spark)
    register.register(spark, g, "m_")
    register.path_reduce(g, "min", "weight", 1, "m_dist")
    assert spark.sql("SELECT count(*) FROM m_edges JOIN m_dist ON id = dst WHERE value IS NOT NULL").first()[0] == 8  # all edges but the loop of 6 end in a vertex that 1 reaches
    assert register.solve_text(g, "max over v of min length paths from 1", "m_ecc").first()[0] == 3
    rows = spark.sql("SELECT * FROM expand_paths('1>2,2>3,3>1', 1, 3)").collect()
    assert [(r[0], r[1]) for r in rows] == [(1, 0), (2, 1), (3, 2), (1, 3)]


def test_user_kernels(spark):
    e = G.micro(spark).edges
    double = kernels_udf.prop_udf(lambda n, w: n + 2 * w)
    got = e.select(double(F.col("capacity").cast("double"), F.col("weight").cast("double")).alias("x")).agg(F.sum("x")).first()[0]
    assert got == sum(c + 2 * w for _, _, w, c in G.MICRO)
    sums = kernels_udf.reduce_with(e.select("dst", F.col("weight").cast("double").alias("n")), lambda a, b: a + b)
    assert {r.dst: r.n for r in sums.collect()} == {1: 2, 2: 7, 3: 2, 4: 7, 5: 1, 6: 1}
    with pytest.raises(Refused):
        kernels_udf.admit_reduction(lambda a, b: a - b)


def test_scalars_and_edge_files(spark, tmp_path):
    e = G.micro(spark).edges
    assert scalars.degree_map(e).first()[0] == {1: 5, 2: 2}
    for form in ("parquet", "csv", "json", "text"):
        edge_lists.write(e, str(tmp_path / form), form)
        assert sorted(map(tuple, edge_lists.read(spark, str(tmp_path / form), form).collect())) == sorted(G.MICRO)
    names = spark.createDataFrame([("b",), ("a",), ("b",), ("c",)], "n string")
    assert dict(map(tuple, edge_lists.dictionary(names, "n").collect())) == {"a": 0, "b": 1, "c": 2}


def test_programs_are_read_off_a_given_table(spark):
    """Fusion traces, analysis times and the reference evaluator work for the sources of the part graph."""
    from walkfold.plans.catalog import QUERIES

    where = "/root/testdata/sf0.001"
    g = G.part_hop(spark, where)
    a, b = G.top_sources(g, 2)
    got = {r.use_case: (r.least_source, r.greatest_source) for r in QUERIES["fusion_traces"](spark, where).collect()}
    assert got["cc"] == (None, None) and got["sssp"] == (a, a) and got["radius"] == (min(a, b), max(a, b))
    near = g.edges.where(F.col("src") == a).agg(F.count_distinct("dst")).first()[0]
    found = {r.id: r.dist for r in QUERIES["reference_micro"](spark, where).collect()}
    assert found[a] == 0 and len(found) > near


def test_typed_specs_name_the_part_graph_s_sources(spark):
    from walkfold.plans.catalog import QUERIES

    where = "/root/testdata/sf0.001"
    a, b = G.top_sources(G.part_hop(spark, where), 2)
    got = dict(map(tuple, QUERIES["typed_specs"](spark, where).collect()))
    assert got[f"min weight paths from {a}"] == "num" and got[f"max over v of min length paths from {b}"] == "num" and got["1 +"] == "unreadable"


@pytest.mark.parametrize("name", ["congruence_rules", "condition_matrix", "synthesis_table"])
def test_rules_and_conditions_read_a_given_table(spark, name):
    """The rows follow the part graph and not made-up data: the SQL over the same table gives them."""
    import duckdb

    from walkfold.plans import catalog

    sf = "/root/testdata/sf0.001"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{sf}/lineitem.parquet'")
    df = catalog.QUERIES[name](spark, sf)
    want = con.execute(catalog.ORACLES[name])
    at = [[d[0] for d in want.description].index(c) for c in df.columns]
    assert sorted(map(tuple, df.collect()), key=str) == sorted((tuple(r[i] for i in at) for r in want.fetchall()), key=str)
    assert "lineitem" in catalog.ORACLES[name]
