"""Placement, runs, files and streams on Spark."""

import pytest
from pyspark.sql import functions as F

from graphslice.operators.durable import written
from graphslice.operators import graph as gr, measure as me, runs as rl
from graphslice.plans.execute import one_pass
from graphslice.sources import files, generate as ge
from graphslice.sources.tables import graph
from graphslice.streaming import partition as sp

# expected cut, runs and largest block at sf0.001, four blocks
EXPECTED = {("conv", 1.0): (19, 21, 23), ("conv", 20.0): (22, 7, 23), ("event_time", 1.0): (0, 784, 251), ("hierarchy", 20.0): (76, 67, 49), ("part_supp", 1.0): (1417, 208, 53)}


@pytest.mark.parametrize("name,kappa", EXPECTED)
def test_expected_placements(spark, sf, name, kappa):
    g = graph(spark, sf, name)
    r = one_pass(g, 4, kappa=kappa)
    cut = me.edge_cut(g.edges, r.assign).first()["cut_edges"]
    assert (cut, r.stats["runs"], max(r.sizes)) == EXPECTED[name, kappa]
    assert rl.rle_validate(r.runs, g.n).isEmpty()


def test_grid_gains_from_stickiness(spark):
    edges, n = ge.gen_grid(spark, 120, 120)
    g = gr.make_graph(edges, n)
    cuts = {k: (me.edge_cut(g.edges, (r := one_pass(g, 4, kappa=k)).assign).first()["cut_edges"], r.stats["runs"]) for k in (1.0, 20.0)}
    assert cuts == {1.0: (1100, 45), 20.0: (723, 7)}


def labels(r):
    return [x["block"] for x in r.assign.orderBy("id").collect()]


def test_modes_and_stores_agree(spark, sf):
    g = graph(spark, sf, "hierarchy")
    want = labels(one_pass(g, 4, kappa=5.0))
    assert labels(one_pass(g, 4, "relay", kappa=5.0, chunks=3)) == want
    assert labels(one_pass(g, 4, kappa=5.0, store="forward", memory_bytes=512)) == want
    assert labels(one_pass(g, 4, kappa=5.0, beta=17)) == want
    for rounds in (1, 2):
        r = one_pass(g, 4, "sharded", shards=3, rounds=rounds)
        assert len(labels(r)) == g.n and max(r.sizes) <= 49


def test_raw_pairs_are_cleaned(spark):
    raw = spark.createDataFrame([(1, 0), (0, 1), (2, 2), (None, 1), (3, 1)], "src long, dst long")
    assert sorted(map(tuple, gr.simple_graph(raw).collect())) == [(0, 1, 1.0), (1, 3, 1.0)]
    assert gr.simple_graph(raw, "count").filter("src = 0").first()["w"] == 2
    with pytest.raises(ValueError):
        gr.simple_graph(raw, mode="strict")


def test_empty_graph(spark):
    g = gr.make_graph(spark.createDataFrame([], "src long, dst long, w double"), 10)
    assert labels(one_pass(g, 3)) == [0] * 4 + [1] * 4 + [2] * 2
    assert labels(one_pass(g, 3, kappa=20.0)) == labels(one_pass(g, 3))


def test_node_weights(spark):
    nodes = spark.createDataFrame([(i, float(1 + i % 3)) for i in range(12)], "id long, c double")
    g = gr.make_graph(spark.createDataFrame([(0, 1, 2.0), (1, 5, 1.0)], "src long, dst long, w double"), 12, nodes)
    r = one_pass(g, 3)
    assert sum(r.sizes) == 24 and r.stats["overfull"] == 0


def test_lookup_is_no_nested_loop(spark):
    runs = rl.rle_encode(spark.range(1000).withColumn("s", F.expr("id div 7 % 3")), "id", "s")
    for f in (rl.lookup, rl.lookup_few):
        got = f(runs, spark.range(1003), "id", "s", 100)
        plan = got._jdf.queryExecution().toString()
        assert "NestedLoop" not in plan and "Cartesian" not in plan
        assert got.filter("s <> id div 7 % 3").isEmpty() and got.count() == 1000


def test_lookup_makes_no_pairs(spark):
    """Rows inside the plan grow with runs + positions, also where every position is a run."""
    n = 20_000
    runs = written(rl.rle_encode(spark.range(n).withColumn("s", F.expr("id % 2")), "id", "s"))
    got = rl.lookup(runs, spark.range(n).withColumn("p", F.lit(7)), "p", "s", n)  # one hub
    assert "Join" not in got._jdf.queryExecution().toString()
    assert got.groupBy("s").count().collect() == [(1, n)]


def test_parallel_coding_of_long_runs(spark):
    df = spark.range(1000).withColumn("s", F.expr("case when id < 700 then 'x' when id < 701 then null else 'y' end"))
    got = [tuple(r) for r in rl.rle_encode_parallel(df, "id", "s").select("start", "len", "head").orderBy("start").collect()]
    assert got == [(0, 700, "x"), (700, 1, None), (701, 299, "y")]


def test_adjacency_text_round_trip(spark, sf, tmp_path):
    g = graph(spark, sf, "conv")
    files.write_adjacency(g, f"file://{tmp_path}/g")
    back = files.read_adjacency(spark, f"file://{tmp_path}/g")
    assert (back.n, back.m) == (g.n, g.m) and back.edges.exceptAll(g.edges).isEmpty()


def test_weighted_adjacency_text(spark, tmp_path):
    (tmp_path / "w.graph").write_text("% a comment\n3 2 011\n5 2 1.5\n1 1 1.5 3 2\n\n")
    g = files.read_adjacency(spark, f"file://{tmp_path}/w.graph")
    assert sorted(map(tuple, g.edges.collect())) == [(0, 1, 1.5), (1, 2, 2.0)]
    assert sorted(map(tuple, g.nodes.collect())) == [(0, 5.0), (1, 1.0), (2, 1.0)]


def test_generators_do_not_depend_on_chunks(spark):
    for f in (lambda c: ge.gen_ba(spark, 300, 5, chunks=c)[0], lambda c: ge.gen_rgg(spark, 400, 0.08, chunks=c)[0]):
        a, b = f(1), f(7)
        assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty() and a.count() > 100
    assert 800 < ge.gen_rdg(spark, 300)[0].count() < 900 - 3


def test_stream_restarts(spark, sf, tmp_path):
    g = graph(spark, sf, "conv")
    adj = ge.as_adjacency(g.edges, g.n)
    want = labels(one_pass(g, 4))
    first = sp.files_of(adj.filter("id < 40"), "id", 2)
    run = lambda: sp.drained(sp.stream_partition(sp.read_stream(spark, first, adj.schema), 4, g.n, g.weight), checkpoint=f"file://{tmp_path}/c", sink=f"file://{tmp_path}/o")
    run()
    adj.filter("id >= 40").repartition(1).write.mode("append").parquet(first)
    got = [r["block"] for r in run().orderBy("id").collect()]
    assert got == want


def test_profiles(spark):
    rows = [("a", "g", i, "t", v) for i, v in enumerate([1.0, 2.0, 4.0, 3.0])] + [("b", "g", i, "t", v) for i, v in enumerate([2.0, 2.0, 1.0, None])]
    m = spark.createDataFrame(rows, "algo string, graph string, k int, metric string, value double")
    got = {(r["algo"], r["tau"]): r["share"] for r in me.performance_profile(m, [1.0, 2.0, 4.0]).collect()}
    assert got == {("a", 1.0): 0.75, ("b", 1.0): 0.5, ("a", 2.0): 0.75, ("b", 2.0): 0.75, ("a", 4.0): 1.0, ("b", 4.0): 0.75}
    g = me.geomean(spark.createDataFrame([("x", "g", i, "t", v) for i, v in enumerate([1.0, 10.0, 100.0])], m.schema)).first()["geomean"]
    assert g == 10
