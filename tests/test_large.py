"""What kept queries from ending on large tables: a job per buffer, a queue of single messages, runs one after the other."""

import re

import numpy as np
import pyarrow as pa
import pytest

from graphslice.functions.score import LinearPenalty
from graphslice.operators import measure as me
from graphslice.operators.stores import ForwardQueue
from graphslice.plans.execute import one_pass
from graphslice.sources import tables as ta


def labels(r):
    return [tuple(x) for x in r.assign.orderBy("id").collect()]


def jobs(spark, name, f):
    """The result of f and the number of Spark jobs that it ran."""
    spark.sparkContext.setJobGroup(name, name)
    try:
        return f(), len(spark.sparkContext.statusTracker().getJobIdsForGroup(name))
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


@pytest.mark.parametrize("inner", ["sequential", "frozen"])
def test_many_buffers_take_no_job_each(spark, sf, inner):
    g = ta.graph(spark, sf, "conv")
    r, n = jobs(spark, f"buffers-{inner}", lambda: one_pass(g, 4, exec="buffered", buffer=2, inner=inner))
    assert r.stats["buffers"] == -(-g.n // 2) > n
    assert len(labels(r)) == g.n == sum(r.sizes)


@pytest.mark.parametrize("options", [{}, {"kappa": 20.0}, {"objective": LinearPenalty()}, {"eps": 0.0}])
def test_frozen_buffers_in_one_task_equal_the_joins(spark, sf, options):
    g = ta.graph(spark, sf, "hierarchy")
    for k, buffer in ((3, g.n // 3 + 1), (16, 70)):
        a, b = (one_pass(g, k, exec="buffered", buffer=buffer, inner="frozen", joins=j, **options) for j in (False, True))
        assert labels(a) == labels(b) and a.sizes == b.sizes


@pytest.mark.parametrize("memory", [64, 1024, 1 << 20])
def test_queue_takes_and_gives_messages_in_batches(memory):
    rng, q = np.random.default_rng(1), ForwardQueue(memory)
    want = np.zeros((2200, 4))
    for lo in range(0, 2000, 10):
        t, b, w = q.pop_upto(lo + 9)
        got = np.zeros((2200, 4))
        np.add.at(got, (t, b), w)
        assert (np.diff(t) >= 0).all() and (got[: lo + 10] == want[: lo + 10]).all() and not got[lo + 10 :].any()
        want[: lo + 10] = 0
        t, b = rng.integers(lo + 10, lo + 200, 400), rng.integers(0, 4, 400)
        q.push_many(t, b, np.ones(400))
        np.add.at(want, (t, b), 1)
    q.pop_upto(2200)
    assert q.inserts == q.deletes == 80_000 and q.peak >= 400 and (memory > 64 * 400 or q.merges)


@pytest.mark.parametrize("store", ["run", "forward"])
def test_the_kernel_counts_the_cut(spark, sf, store):
    for name in ("conv", "cust_supp_weighted"):
        g = ta.graph(spark, sf, name)
        r = one_pass(g, 4, store=store)
        cut = me.edge_cut(g.edges, r.assign).first()
        assert r.stats["cut"] == cut["cut"] and r.stats["unit"] == (name == "conv")


def test_cosine_blocks_of_any_size_give_the_same_edges(spark, sf):
    one, many = (sorted(map(tuple, ta.emb_cos(spark, sf, **o)[0].collect())) for o in ({}, {"block": 7, "most": 11}))
    assert one == many and len(one) == len(set(one)) > 0


def test_vectors_are_sent_a_bounded_number_of_times(spark, sf, tmp_path):
    """Null vectors link with nothing, and 2000 vectors in blocks of ten at least make 32 blocks, not 200."""
    rng = np.random.default_rng(0)
    rows = [(i, None if i % 100 == 99 else rng.normal(size=4).tolist()) for i in range(2000)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    edges, n = ta.emb_cos(spark, str(tmp_path), block=10)
    plan = edges._jdf.queryExecution().optimizedPlan().toString()
    assert n == 2000 and re.search(r"pmod\(vec_id#\d+L?, 32\)", plan)
    assert edges.filter("src % 100 = 99 or dst % 100 = 99").isEmpty() and not edges.isEmpty()


def test_a_study_sorts_a_stream_once_for_all_its_runs(spark, sf, monkeypatch):
    from graphslice.plans import workloads

    calls = []
    real = workloads.pieces
    monkeypatch.setattr(workloads, "pieces", lambda rows: calls.append(1) or real(rows))
    rows = workloads.study(spark, sf, ("conv",), (4,), {"run": {}, "dense": {"store": "dense"}, "queue": {"store": "forward"}, "small": {"store": "forward", "memory_bytes": 4096}}).collect()
    g = ta.graph(spark, sf, "conv")
    cut = me.edge_cut(g.edges, one_pass(g, 4).assign).first()["cut_edges"]
    assert len(calls) == 2 and [r["value"] for r in rows if r["metric"] == "cut"] == [cut] * 4
    assert [r["algo"] for r in rows if r["metric"] == "cut"] == ["run", "dense", "queue", "small"]


def test_stores_with_equal_labels_are_placed_once(spark, sf, monkeypatch):
    from graphslice.plans import workloads
    from graphslice.plans.execute import Settings, side_by_side

    g = ta.graph(spark, sf, "conv")
    settings = [Settings(4), Settings(4, beta=50), Settings(4, store="dense"), Settings(4, beta=7, delta=16)]
    for s, r in zip(settings, side_by_side(g, settings), strict=True):
        alone = one_pass(g, 4, store=s.store, beta=s.beta, delta=s.delta)
        same = ("runs", "segments", "size_bits", "nbytes", "lookups", "appends", "cut", "sizes", "previous")
        assert labels(r) == labels(alone) and [r.stats[m] for m in same] == [alone.stats[m] for m in same]
        assert sorted(map(tuple, r.runs.collect())) == sorted(map(tuple, alone.runs.collect()))
    with pytest.raises(ValueError):
        side_by_side(g, [Settings(4), Settings(4, kappa=20.0)])
    calls = []
    real = workloads.one_pass
    monkeypatch.setattr(workloads, "one_pass", lambda *a, **o: calls.append(o) or real(*a, **o))
    rows = workloads.store_comparison(spark, sf, ("conv",)).collect()
    assert len(calls) == 2 and len({r["algo"] for r in rows}) == 5  # sticky20 and queue are placed alone


def _streams():
    """Streams (id, nbr, w) of a band, a bipartite, a random and an empty graph, sorted by id."""
    rng, n = np.random.default_rng(5), 1500
    band = [(i, j) for i in range(n) for j in range(max(0, i - 1 - i % 12), i)]
    sides = [(int(rng.integers(0, 1000)), int(rng.integers(1000, n))) for _ in range(4500)]
    mixed = [tuple(sorted(rng.integers(0, n, 2).tolist())) for _ in range(6000)]
    for name, edges in (("band", band), ("sides", sides), ("mixed", mixed), ("none", [])):
        edges = {(max(a, b), min(a, b)) for a, b in edges if a != b}
        rows = np.array(sorted([(i, -1) for i in range(n)] + list(edges)))
        yield name, n, len(edges), rows


def _kernel(rows, rules, size, store="run", beta=None, w=None):
    import json

    from graphslice.operators.kernel import place

    w = np.ones(len(rows)) if w is None else w
    arrays = [pa.array(np.zeros(len(rows), np.int32)), pa.array(rows[:, 0]), pa.array(rows[:, 1]), pa.array(w), pa.array(np.full(len(rows), -1, np.int32))]
    table = pa.RecordBatch.from_arrays(arrays, names=["shard", "id", "nbr", "w", "block"])
    out = [r for b in place((table.slice(i, size) for i in range(0, len(rows), size)), rules, store, beta, 16, 0) for r in b.to_pylist()]
    stats = json.loads(out[-1]["stats"])
    return [tuple(r[m] for m in ("batch", "start", "len", "head")) for r in out[:-1]], {m: stats[m] for m in stats if m not in ("seconds", "peak_rss_kb")}


@pytest.mark.parametrize("size", [701])
@pytest.mark.parametrize("kappa", [1.0, 5.0, 20.0])
def test_stretches_placed_at_once_equal_single_choices(kappa, size, monkeypatch):
    from graphslice.functions.score import PowerPenalty, limit
    from graphslice.operators.kernel import Placer, Rules

    chosen, real = [], Placer.choose
    monkeypatch.setattr(Placer, "choose", lambda *a: chosen.append(1) or real(*a))
    for name, n, m, rows in _streams():
        for k in (1, 4, 16, 70):
            for gamma, cap, store, beta in ((1.5, limit(n, k), "run", None), (1.5, None, "dense", None), (2.0, limit(n, k, 0.0), "run", 7), (1.5, limit(n, k), "plainbits", 50), (1.25, limit(n, k), "run", None)):
                for w in (None, np.where(rows[:, 1] < 0, 1.0, 1.0 + rows[:, 0] % 3)) if k == 4 else (None,):
                    rules = Rules(k, n, m, cap, PowerPenalty(gamma), kappa)
                    got = _kernel(rows, rules, size, store, beta, w)
                    with monkeypatch.context() as c:
                        c.setattr(PowerPenalty, "many", lambda *a: None)
                        chosen.clear()
                        assert got == _kernel(rows, rules, size, store, beta, w), (name, k, gamma, store)
                        assert len(chosen) == n
        chosen.clear()
        _kernel(rows, Rules(4, n, m, limit(n, 4), kappa=kappa), 1 << 14)
        if (name, kappa) in (("band", 20.0), ("sides", 20.0)):
            assert len(chosen) < n * 2 / 3  # before, each node was chosen by itself
        if (name, kappa) == ("sides", 1.0):
            assert len(chosen) < n * 2 / 3


@pytest.mark.parametrize("name", ["dense", "runlist", "plainbits", "run", "auto"])
@pytest.mark.parametrize("beta", [None, 1, 7, 1000])
def test_blocks_that_come_together_are_stored_as_single_ones(name, beta):
    from graphslice.operators.stores import make_store

    rng = np.random.default_rng(2)
    labels = np.repeat(rng.integers(0, 5, 800), rng.integers(1, 9, 800))
    one, many, i = make_store(name, 5, beta, 4), make_store(name, 5, beta, 4), 0
    for b in labels.tolist():
        one.append(b)
    while i < len(labels):
        step = int(rng.integers(0, 40))
        many.extend(labels[i : i + step])
        i += step
    assert many.get_many(np.arange(len(labels))).tolist() == labels.tolist() and len(many) == len(one)
    assert (many.size_bits(), many.nbytes()) == (one.size_bits(), one.nbytes())
    assert all((a == b).all() for a, b in zip(one.heads_and_starts(), many.heads_and_starts()))
    many.append(int(labels[-1]))
    assert len(many.heads_and_starts()[0]) == len(one.heads_and_starts()[0]) + bool(beta and len(labels) % beta == 0)


@pytest.mark.parametrize("later", [False, True])
def test_keys_of_a_stream_sort_and_pack_as_its_rows(spark, sf, later):
    from graphslice.operators import graph as gr
    from graphslice.operators.kernel import unpacked
    from graphslice.plans.execute import pieces

    g = ta.graph(spark, sf, "event_time")
    weighted = ta.graph(spark, sf, "cust_supp_weighted")
    assert g.unit and not weighted.unit and gr.stream_keys(weighted, later).columns == ["id", "nbr", "w"]
    got = []
    for rows in (gr.stream_keys(g, later), gr.stream_rows(g, later)):
        t = pieces(rows).orderBy("id", "nbr").toArrow()
        assert max(len(x) for x in t.column("nbrs").to_pylist()) <= 4 * max(t.column("rows").to_pylist())
        got.append([r for b in unpacked(t.to_batches()) for r in b.to_pylist()])
    assert gr.stream_keys(g, later).columns == ["key"] and got[0] == got[1] and len(got[0]) == g.n + g.m


def test_packed_numbers_beyond_four_bytes():
    from graphslice.operators.kernel import packed, unpacked

    ids, nbr, w = [5, 7, 1 << 40, 1 << 40], [None, 5, None, (1 << 40) - 1], [1.0, 1.0, 2.0, 1.0]
    batch = pa.RecordBatch.from_arrays([pa.array(ids), pa.array(nbr), pa.array(w)], names=["id", "nbr", "w"])
    for most in (2, 3, 100):
        rows = [r for b in unpacked(packed([batch], most)) for r in b.to_pylist()]
        assert [r["id"] for r in rows] == ids and [r["nbr"] for r in rows] == [-1 if x is None else x for x in nbr] and [r["w"] for r in rows] == w


def test_events_meet_across_cells_and_without_repeats(spark, tmp_path):
    import datetime as dt

    rng, t0 = np.random.default_rng(8), dt.datetime(2024, 1, 1)
    ids = [*range(2960, 3040), *range(-3040, -2960), *range(-20, 20), *range(3000, 3010), None, 50, 95]
    rows = [(i, None if n % 37 == 5 else t0 + dt.timedelta(seconds=int(rng.integers(0, 1500)))) for n, i in enumerate(ids)]
    spark.createDataFrame(rows, "event_id long, ts timestamp").write.parquet(str(tmp_path / "events.parquet"))
    edges, n = ta.event_time(spark, str(tmp_path))
    got = [(r["src"], r["dst"]) for r in edges.collect()]
    want = {(a, b) for a, x in rows for b, y in rows if None not in (a, b, x, y) and 0 < b - a <= 30 and abs((y - x).total_seconds()) <= 600}
    assert n == len(rows) and len(got) == len(set(got)) and set(got) == want
    assert "Join" not in edges._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("beta, delta", [(64, 1024), (64, 16), (1000, 100), (7, 1), (1, 1024)])
def test_full_batches_are_looked_up_together(beta, delta, monkeypatch):
    """They give what a store for each batch gives, without a call for each batch that a lookup touches."""
    from graphslice.operators.stores import BatchedStore, RunStore, make_store

    rng, calls = np.random.default_rng(beta), []
    blocks = np.repeat(rng.integers(0, 5, 3000), rng.integers(1, 30, 3000) * rng.integers(0, 2, 3000) + 1)
    new, old = make_store("run", 5, beta, delta), BatchedStore(5, beta, lambda k: RunStore(k, delta))
    at = 0
    while at < len(blocks):
        step = int(rng.integers(1, 5000))
        new.extend(blocks[at : at + step])
        old.extend(blocks[at : at + step])
        at = min(at + step, len(blocks))
        v = rng.integers(0, at, 500)
        assert (new.get_many(v) == blocks[v]).all() and new.get(int(v[0])) == blocks[v[0]]
    for m in ("segments", "nbytes", "size_bits"):
        assert getattr(new, m)() == getattr(old, m)(), m
    assert all((a == b).all() for a, b in zip(new.heads_and_starts(), old.heads_and_starts(), strict=True))
    real = RunStore.get_many
    monkeypatch.setattr(RunStore, "get_many", lambda self, v: calls.append(1) or real(self, v))
    new.get_many(np.arange(len(blocks)))
    assert len(calls) <= 1


def _kept(spark):
    """Tables in the shared folder, and shuffle files with their sizes."""
    from graphslice.operators.durable import shared_folder

    path = spark._jvm.org.apache.hadoop.fs.Path(f"{shared_folder(spark)}/graphslice")
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    tables = {x.getPath().getName() for x in fs.listStatus(path)} if fs.exists(path) else set()
    files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return tables, {x.getName(): x.length() for i in range(files.size()) if (x := files.apply(i)).getName().startswith("shuffle_")}


@pytest.mark.parametrize("query", ["store_comparison", "comparison_profiles", "comparison_means"])
def test_a_comparison_leaves_nothing_on_disk(spark, sf, query):
    from graphslice.operators.durable import CLEANUP
    from graphslice.plans import workloads

    tables, files = _kept(spark)
    assert getattr(workloads, query)(spark, sf, ("conv", "order_supp")).count()
    now = _kept(spark)
    assert not now[0] - tables
    assert sum(size for name, size in now[1].items() if name not in files) < 10_000  # counts of rows at most, no edges or streams
    assert spark.conf.get(CLEANUP, "false") == "false"


def test_a_study_holds_a_few_graphs_at_a_time(spark, sf, monkeypatch):
    """However many graphs there are, only those that are made, or placed by the cores at hand, are on disk."""
    from graphslice.plans import workloads

    before, most = _kept(spark)[0], []
    real = workloads.pieces
    monkeypatch.setattr(workloads, "pieces", lambda rows: most.append(sum(x.startswith("pieces") for x in _kept(spark)[0] - before)) or real(rows))
    names = ("conv", "order_supp", "part_supp", "hierarchy", "cust_order", "event_chain", "cust_part", "order_part")
    rows = workloads.study(spark, sf, names, (4,), {f"kappa_{x}": {"kappa": float(x)} for x in (1, 2, 4, 8)}).collect()
    assert list(dict.fromkeys(r["graph"] for r in rows)) == list(names) and len(most) == len(names)
    assert max(most) <= 4  # with four cores and four runs a graph


def test_a_failed_run_ends_a_study(spark, sf):
    from graphslice.plans import workloads

    with pytest.raises(Exception, match="kappa is at least 1"):
        workloads.study(spark, sf, ("conv", "hierarchy"), (4,), {f"kappa_{x}": {"kappa": x} for x in (1.0, 0.5)})


@pytest.mark.parametrize("apart, blocks, weights, most", [(3, 4, False, 3), (300, 400, False, 5), (1 << 20, 4, True, 14), (1 << 40, 1 << 17, True, 21)])
def test_spilled_messages_are_narrow_and_come_back(apart, blocks, weights, most):
    from graphslice.operators.stores import _Messages

    rng, n = np.random.default_rng(2), 10_000
    target = np.cumsum(rng.integers(0, apart, n))
    block, weight = rng.integers(0, blocks, n).astype(np.int32), rng.random(n) if weights else np.ones(n)
    run = _Messages(0)
    run.write(target, block, weight)
    assert run.handle.tell() < most * n  # 20 bytes each before
    run.rewind()
    got = [run.upto(int(x)) for x in (target[n // 3], target[-1])]
    assert got[0][-1][0][-1] <= target[n // 3] < got[1][0][0][0]
    for want, have in zip((target, block, weight), zip(*(part for some in got for part in some))):
        assert (np.concatenate(have) == want).all() and np.concatenate(have).dtype == want.dtype
    assert run.part is None and run.handle.closed


@pytest.mark.parametrize("name", ["copurchase", "coship"])
def test_lines_are_dealt_by_order_once(spark, name):
    """Both sides of the self-join read one exchange; at sf0.01, with joins that are not broadcast."""
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        edges = ta.BUILDERS[name](spark, "/root/testdata/sf0.01")[0].select("src", "dst")
        got = {tuple(r) for r in edges.collect()}
        plan = edges._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    key = {"copurchase": "l_partkey", "coship": "l_suppkey"}[name]
    orders = {}
    for o, x in ta.read(spark, "/root/testdata/sf0.01", "lineitem").select("l_orderkey", key).collect():
        orders.setdefault(o, set()).add(x)
    assert got == {(a, b) for some in orders.values() for a in some for b in some if a < b}
    assert len(re.findall(r"- Exchange hashpartitioning\(l_orderkey", plan)) == 1
    assert len(re.findall(r"- Exchange hashpartitioning", plan)) == 2  # the other one removes repeated pairs


def test_lines_of_documents_are_dealt_once(spark):
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        edges = ta.doc_lines(spark, "/root/testdata/sf0.01")[0].select("src", "dst")
        got = {tuple(r) for r in edges.collect()}
        plan = edges._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    having = {}
    for i, text in ta.read(spark, "/root/testdata/sf0.01", "documents").select("doc_id", "text").collect():
        for x in (text or "").split("\n"):
            if len(x.strip(" ")) >= 20:
                having.setdefault(x.strip(" "), set()).add(i)
    assert got == {(a, b) for some in having.values() if 2 <= len(some) <= 50 for a in some for b in some if a < b}
    assert len(re.findall(r"- Exchange hashpartitioning", plan)) == 2
