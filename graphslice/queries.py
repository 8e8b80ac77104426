"""Named queries over the given tables, and their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .functions.hashes import hashed_sql
from .functions import table_functions
from .functions.score import LinearPenalty, PowerPenalty
from .operators import bitvector, graph as gr, measure as me, runs as rl
from .operators.durable import folder, written
from .plans import execute as ex, oracles as o, relational, workloads
from .sources import files as fi, generate as ge, tables as ta
from .streaming import partition as sp

QUERIES: dict = {**relational.QUERIES, **workloads.QUERIES}
ORACLES: dict[str, str] = dict(relational.ORACLES)


def _add(name, f, sql=None):
    QUERIES[name] = f
    if sql:
        ORACLES[name] = sql


# --- graphs ------------------------------------------------------------------------------------------

for _n in ta.BUILDERS:
    _add(f"g_{_n}", lambda s, d, n=_n: ta.BUILDERS[n](s, d)[0].select("src", "dst", "w"), f"WITH e AS ({o.edges_sql(_n)}) SELECT src, dst, w FROM e")
_add("g_grid", lambda s, d: ge.gen_grid(s, 20, 20)[0], f"WITH e AS ({o.edges_sql('grid')}) SELECT src, dst, w FROM e")

_add(
    "g_ba",
    lambda s, d: ge.gen_ba(s, 500, 4)[0],
    f"""WITH RECURSIVE chain(e, slot) AS (SELECT e, 2 * e + 1 FROM range(2000) t(e) UNION ALL SELECT e, {hashed_sql('slot', 42)} % slot FROM chain WHERE slot % 2 = 1)
SELECT DISTINCT least(e // 4, slot // 2 // 4)::BIGINT AS src, greatest(e // 4, slot // 2 // 4)::BIGINT AS dst, 1.0::DOUBLE AS w FROM chain WHERE slot % 2 = 0 AND e // 4 <> slot // 2 // 4""",
)
_add(
    "g_rgg",
    lambda s, d: ge.gen_rgg(s, 1000, 0.06)[0],
    f"""WITH p AS (SELECT i, {hashed_sql('2 * i', 42)} / 2147483647.0::DOUBLE AS x, {hashed_sql('2 * i + 1', 42)} / 2147483647.0::DOUBLE AS y FROM range(1000) t(i)),
q AS (SELECT *, row_number() OVER (ORDER BY floor(y * 16), floor(x * 16), i) - 1 AS id FROM p)
SELECT a.id::BIGINT AS src, b.id::BIGINT AS dst, 1.0::DOUBLE AS w FROM q a JOIN q b ON a.id < b.id WHERE (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 0.06::DOUBLE * 0.06::DOUBLE""",
)
_add("g_rhg", lambda s, d: ge.gen_rhg(s, 500, 8.0)[0], o.hyperbolic(500, 8.0))
_add("g_rdg", lambda s, d: ge.gen_rdg(s, 400)[0], o.delaunay(400))
_add("g_meta", lambda s, d: gr.meta(ta.graph(s, d, "order_part")), f"WITH {o.head('order_part')} SELECT n, count(*) AS m, n::DOUBLE AS cw, sum(w) AS ew, (SELECT max(c) FROM (SELECT count(*) AS c FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v)) AS max_degree FROM e, h GROUP BY n")
_add("g_degrees", lambda s, d: gr.degrees(ta.BUILDERS["copurchase"](s, d)[0]), f"WITH e AS ({o.edges_sql('copurchase')}) SELECT v AS id, count(*) AS degree FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v")
_add("g_subgraph", lambda s, d: gr.subgraph(ta.BUILDERS["event_time"](s, d)[0], ta.read(s, d, "events").filter("event_type = 'click'").select(F.col("event_id").alias("id"))), f"WITH e AS ({o.edges_sql('event_time')}), c AS (SELECT event_id FROM events WHERE event_type = 'click') SELECT src, dst, w FROM e WHERE src IN (SELECT event_id FROM c) AND dst IN (SELECT event_id FROM c)")
_add("g_orders_isolated", lambda s, d: ta.read(s, d, "orders").select("o_orderkey").join(ta.read(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_anti"), "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")

# --- placement ---------------------------------------------------------------------------------------


def placed(name, k, **options):
    return lambda s, d: ex.one_pass(ta.graph(s, d, name), k, **options).assign.select("id", "block")


def _greedy_sql(name, k, **options):
    return f"WITH RECURSIVE {o.greedy(name, k, **options)} SELECT id, block FROM a"


for _n in ("conv", "event_time", "part_supp", "emb_cos", "hierarchy", "cust_part"):
    _add(f"p_greedy_{_n}_k4", placed(_n, 4), _greedy_sql(_n, 4))
for _n in ("conv", "emb_cos", "hierarchy", "page_anchor", "doc_lines"):
    _add(f"p_greedy_{_n}_k16", placed(_n, 16), _greedy_sql(_n, 16))
for _kap in (5, 10, 15, 20):
    for _n in ("conv", "event_time", "emb_cos"):
        _add(f"p_sticky{_kap}_{_n}", placed(_n, 4, kappa=float(_kap)), _greedy_sql(_n, 4, kappa=_kap))
for _n in ("conv", "emb_cos"):
    _add(f"p_linear_{_n}", placed(_n, 4, objective=LinearPenalty()), _greedy_sql(_n, 4, linear=True))
_add("p_weighted_cust_supp", placed("cust_supp_weighted", 4), _greedy_sql("cust_supp_weighted", 4))
_add("p_penalty_only_hierarchy", placed("hierarchy", 4, capacity="penalty"), _greedy_sql("hierarchy", 4, capacity="penalty"))
_add("p_gamma2_conv", placed("conv", 4, objective=PowerPenalty(2.0)), _greedy_sql("conv", 4, gamma=2))
_add("p_full_scoring_conv", placed("conv", 16, scoring="full"), _greedy_sql("conv", 16))
for _store in ("dense", "runlist", "plainbits", "learned", "auto", "forward"):
    _add(f"p_{_store}_conv", placed("conv", 4, store=_store), _greedy_sql("conv", 4))
    _add(f"p_{_store}_emb_cos", placed("emb_cos", 4, store=_store), _greedy_sql("emb_cos", 4))
_add("p_forward_spilling_emb_cos", placed("emb_cos", 4, store="forward", memory_bytes=4096), _greedy_sql("emb_cos", 4))
for _n in ("conv", "emb_cos"):
    _add(f"p_batched_{_n}", placed(_n, 4, beta=100), _greedy_sql(_n, 4))
    _add(f"p_relay_{_n}", placed(_n, 4, exec="relay", chunks=3), _greedy_sql(_n, 4))
    _add(f"p_sharded_{_n}", placed(_n, 4, exec="sharded", shards=4), f"WITH RECURSIVE {o.sharded(_n, 4, 4)} SELECT id, block FROM a")
    _add(f"p_sharded_once_{_n}", placed(_n, 4, exec="sharded", shards=4, rounds=1), f"WITH RECURSIVE {o.sharded(_n, 4, 4, 1)} SELECT id, block FROM a")
_add("p_batched_sticky_conv", placed("conv", 4, beta=100, kappa=20.0), _greedy_sql("conv", 4, kappa=20))
_add("p_relay_sticky_hierarchy", placed("hierarchy", 4, exec="relay", chunks=4, kappa=20.0), _greedy_sql("hierarchy", 4, kappa=20))
_add("p_buffered_conv", placed("conv", 4, exec="buffered", buffer=200), _greedy_sql("conv", 4))
_add("p_frozen_conv", placed("conv", 4, exec="buffered", buffer=134, inner="frozen"))
for _n, _by in (("conv", "random"), ("conv", "degree"), ("hierarchy", "bfs")):
    _add(f"p_{_by}_order_{_n}", lambda s, d, n=_n, by=_by: ex.one_pass(gr.reorder(ta.graph(s, d, n), by), 4).assign, _greedy_sql(f"{_n}_{_by}", 4))
_add("p_prefix_stable", lambda s, d: ex.prefix(g := ta.graph(s, d, "conv"), g.n // 2, 4).assign, f"WITH RECURSIVE {o.greedy('conv', 4)} SELECT id, block FROM a WHERE id < (SELECT n // 2 FROM h)")


def _nodes(s, d, name):
    edges, n = ta.BUILDERS[name](s, d)
    return edges, n, s.range(n)


_add("p_hash_mulshift", lambda s, d: ex.hash_blocks(_nodes(s, d, "order_part")[2], 4), f"WITH {o.head('order_part')}, {o.mulshift(4)} SELECT id, block FROM a")
_add("p_hash_mod", lambda s, d: ex.hash_blocks(_nodes(s, d, "order_part")[2], 4, "mod"), f"WITH {o.head('order_part')} SELECT i::BIGINT AS id, (i % 4)::INTEGER AS block FROM h, range(h.n) t(i)")
_add("p_range", lambda s, d: ex.range_blocks(_nodes(s, d, "order_part")[2], _nodes(s, d, "order_part")[1], 4), f"WITH {o.head('order_part')} SELECT i::BIGINT AS id, (i * 4 // n)::INTEGER AS block FROM h, range(h.n) t(i)")
_add("p_hash_xx", lambda s, d: ex.hash_blocks(_nodes(s, d, "order_part")[2], 4, "xxhash64"))

# --- runs --------------------------------------------------------------------------------------------


def sequence(s, d, name):
    if name == "events":
        return ta.read(s, d, "events").select(F.col("event_id").alias("pos"), F.col("event_type").alias("sym"))
    if name == "nation":
        return ta.read(s, d, "customer").select(F.col("c_custkey").alias("pos"), F.col("c_nationkey").alias("sym"))
    x = ta.read(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", F.col("l_returnflag").alias("sym"))
    return gr.dense_ids(x, ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity"], "pos").select("pos", "sym")


_S = {n: f"WITH s AS ({q}), {o.RUNS}" for n, q in o.SEQUENCES.items()}
_ALL = "SELECT batch, run_no, start, len, head FROM r"
for _n in o.SEQUENCES:
    _add(f"r_encode_{_n}", lambda s, d, n=_n: rl.rle_encode_parallel(sequence(s, d, n), "pos", "sym"), f"{_S[_n]} {_ALL}")
_add("r_encode_window", lambda s, d: rl.rle_encode_window(sequence(s, d, "events"), "pos", "sym"), f"{_S['events']} {_ALL}")
_add("r_encode_batched", lambda s, d: rl.rle_encode(sequence(s, d, "events"), "pos", "sym", 64), f"WITH s AS (SELECT pos // 64 AS batch, pos, sym FROM ({o.SEQUENCES['events']})), {o.RUNS} {_ALL}")
_add("r_encode_greedy", lambda s, d: ex.one_pass(ta.graph(s, d, "conv"), 4).runs, f"WITH RECURSIVE {o.greedy('conv', 4)}, s AS (SELECT 0::BIGINT AS batch, id AS pos, block AS sym FROM a), {o.RUNS} {_ALL}")
_add("r_encode_sticky", lambda s, d: ex.one_pass(ta.graph(s, d, "event_time"), 4, kappa=20.0).runs, f"WITH RECURSIVE {o.greedy('event_time', 4, kappa=20)}, s AS (SELECT 0::BIGINT AS batch, id AS pos, block AS sym FROM a), {o.RUNS} {_ALL}")
_runs = lambda s, d: written(rl.rle_encode(sequence(s, d, "events"), "pos", "sym"), "runs")
_add("r_decode", lambda s, d: rl.rle_decode(_runs(s, d)), f"SELECT pos, sym FROM ({o.SEQUENCES['events']})")
_pos = lambda s, d: ta.read(s, d, "events").select(F.col("event_id").alias("pos"))
_add("r_rank1", lambda s, d: rl.rank(_runs(s, d), _pos(s, d), "pos"), f"{_S['events']} SELECT pos, (run_no + 1)::BIGINT AS rank FROM q")
_add("r_rank0", lambda s, d: rl.rank(_runs(s, d), _pos(s, d), "pos", 0), f"{_S['events']} SELECT pos, (pos - run_no)::BIGINT AS rank FROM q")
_add("r_select1", lambda s, d: rl.select(r := _runs(s, d), r.select((F.col("run_no") + 1).alias("x")), "x"), f"{_S['events']} SELECT run_no + 1 AS x, start AS pos FROM r")
_add("r_select0", lambda s, d: rl.select(r := _runs(s, d), s.range(1, ta.size(s, d, "events") - r.count() + 1).withColumnRenamed("id", "x"), "x", 0), f"{_S['events']} SELECT x, pos FROM (SELECT row_number() OVER (ORDER BY pos) AS x, pos FROM q WHERE f = 0)")
_add("r_rank_symbol", lambda s, d: rl.rank_symbol(sequence(s, d, "events"), "pos", "sym"), f"SELECT pos, sym, row_number() OVER (PARTITION BY sym ORDER BY pos) AS rank FROM ({o.SEQUENCES['events']})")
_add("r_select_symbol", lambda s, d: rl.select_symbol(sequence(s, d, "events"), "pos", "sym", sequence(s, d, "events").select("sym").distinct().withColumn("x", F.lit(7).cast("long"))), f"SELECT sym, x, pos FROM (SELECT sym, row_number() OVER (PARTITION BY sym ORDER BY pos) AS x, pos FROM ({o.SEQUENCES['events']})) WHERE x = 7")
for _f in ("lookup", "lookup_few"):
    _add(f"r_{_f}", lambda s, d, f=_f: getattr(rl, f)(_runs(s, d), _pos(s, d), "pos", "head", 100), f"SELECT pos, sym AS head FROM ({o.SEQUENCES['events']})")
_add("r_stats", lambda s, d: rl.run_stats(_runs(s, d)), f"{_S['events']} SELECT count(*) AS runs, sum(len)::BIGINT AS positions, max(len) AS longest, round(avg(len), 6) AS mean_len, quantile_cont(len, 0.5) AS median_len FROM r")
_add("r_validate", lambda s, d: rl.rle_validate(_runs(s, d), ta.size(s, d, "events")), "SELECT 'x' AS kind, 0::BIGINT AS n WHERE false")


def _learned_starts(s, d):
    import pandas as pd

    def back(pdf: pd.DataFrame) -> pd.DataFrame:
        v = bitvector.LearnedBitVector.build(sorted(pdf["start"].tolist()))
        return pd.DataFrame({"rank": range(1, len(v) + 1), "start": v.starts()})

    return _runs(s, d).select("batch", "start").groupBy("batch").applyInPandas(back, "rank long, start long")


_add("r_learned_starts", _learned_starts, f"{_S['events']} SELECT run_no + 1 AS rank, start FROM r")
_add("r_segments_points", lambda s, d: bitvector.learn_segments(_runs(s, d)).agg(F.sum("points").cast("long").alias("starts")), f"{_S['events']} SELECT count(*) AS starts FROM r")
_add("r_segments", lambda s, d: bitvector.learn_segments(_runs(s, d)))

# --- messages ----------------------------------------------------------------------------------------

_M = f"WITH {o.head('order_part')}, {o.mulshift(4)}"
_hash = lambda s, d, k=4: ex.hash_blocks(_nodes(s, d, "order_part")[2], k)
_op = lambda s, d: ta.BUILDERS["order_part"](s, d)[0]
_add("f_messages", lambda s, d: ex.forward_messages(_hash(s, d), _op(s, d)), f"{_M} SELECT dst AS target, block, w FROM e JOIN a ON src = id")
_add("f_queue_profile", lambda s, d: me.queue_profile(ta.BUILDERS["event_time"](s, d)[0]), f"WITH e AS ({o.edges_sql('event_time')}), x AS (SELECT id, sum(x) AS x FROM (SELECT src AS id, 1 AS x FROM e UNION ALL SELECT dst, -1 FROM e) GROUP BY id) SELECT id, (sum(x) OVER (ORDER BY id))::BIGINT AS waiting FROM x")
_add("f_backdegree", lambda s, d: gr.forward_adjacency(_op(s, d)).groupBy("id").agg(F.count("*").alias("back")), f"WITH e AS ({o.edges_sql('order_part')}) SELECT dst AS id, count(*) AS back FROM e GROUP BY dst")

# --- measures ----------------------------------------------------------------------------------------

_add("c_cut", lambda s, d: me.edge_cut(_op(s, d), _hash(s, d)), f"{_M} SELECT sum(CASE WHEN x.block <> y.block THEN w ELSE 0 END)::DOUBLE AS cut, sum((x.block <> y.block)::INT)::BIGINT AS cut_edges, count(*) AS edges FROM e JOIN a x ON src = x.id JOIN a y ON dst = y.id")
_add("c_cut_greedy", lambda s, d: me.edge_cut((g := ta.graph(s, d, "conv")).edges, ex.one_pass(g, 4, kappa=20.0).assign), f"WITH RECURSIVE {o.greedy('conv', 4, kappa=20)} SELECT sum(CASE WHEN x.block <> y.block THEN w ELSE 0 END)::DOUBLE AS cut, sum((x.block <> y.block)::INT)::BIGINT AS cut_edges, count(*) AS edges FROM e JOIN a x ON src = x.id JOIN a y ON dst = y.id")
_add("c_relative_cut", lambda s, d: me.relative_cut(_op(s, d), _hash(s, d)), f"{_M} SELECT sum((x.block <> y.block)::INT) / count(*)::DOUBLE AS relative_cut FROM e JOIN a x ON src = x.id JOIN a y ON dst = y.id")
_add("c_balance", lambda s, d: me.balance(_hash(s, d), 4, _nodes(s, d, "order_part")[1]), f"{_M}, z AS (SELECT max(c)::DOUBLE AS largest FROM (SELECT count(*) AS c FROM a GROUP BY block)) SELECT largest, ceil(103 * n / 400.0)::BIGINT AS allowed, largest <= ceil(103 * n / 400.0) AS feasible, round(largest / (n / 4.0::DOUBLE) - 1, 6) AS imbalance FROM z, h")
_add("c_quotient", lambda s, d: me.quotient(_op(s, d), _hash(s, d)), f"{_M} SELECT least(x.block, y.block) AS a, greatest(x.block, y.block) AS b, count(*) AS edges FROM e JOIN a x ON src = x.id JOIN a y ON dst = y.id GROUP BY ALL")
_add("c_boundary", lambda s, d: me.boundary(_op(s, d), _hash(s, d)), f"{_M}, t AS (SELECT src, dst, x.block AS p, y.block AS q FROM e JOIN a x ON src = x.id JOIN a y ON dst = y.id WHERE x.block <> y.block) SELECT block, count(DISTINCT id) AS nodes FROM (SELECT p AS block, src AS id FROM t UNION ALL SELECT q, dst FROM t) GROUP BY block")
_add("c_sizes", lambda s, d: me.block_sizes(_hash(s, d), 4), f"{_M} SELECT block, count(*)::DOUBLE AS size FROM a GROUP BY block")
_add("c_sizes_bits", lambda s, d: me.structure_sizes((r := ex.one_pass(ta.graph(s, d, "conv"), 4)).runs, 536, 4), f"WITH RECURSIVE {o.greedy('conv', 4)}, s AS (SELECT 0::BIGINT AS batch, id AS pos, block AS sym FROM a), {o.RUNS} SELECT (32 * 536)::BIGINT AS dense32, (536 * 2)::BIGINT AS packed, (536 + count(*) * 2)::BIGINT AS plain, (count(*) * 66)::BIGINT AS runs FROM r")

#: cuts of the stateless rules on three graphs, as measurements
_RULES = {"mulshift": "(((i::HUGEINT * 2654435761) % 4294967296) * {k} // 4294967296)", "mod": "(i % {k})", "range": "(i * {k} // n)"}


def measurements(s, d):
    parts = []
    for name in ("conv", "event_time", "hierarchy"):
        edges, n = ta.BUILDERS[name](s, d)
        edges = written(edges, "edges")
        for k in (4, 16):
            for algo in _RULES:
                a = ex.range_blocks(s.range(n), n, k) if algo == "range" else ex.hash_blocks(s.range(n), k, algo)
                parts.append(me.edge_cut(edges, a).select(F.lit(algo).alias("algo"), F.lit(name).alias("graph"), F.lit(k).alias("k"), F.lit("cut").alias("metric"), F.col("cut").alias("value")))
                parts.append(me.run_bits(a, k).select(F.lit(algo).alias("algo"), F.lit(name).alias("graph"), F.lit(k).alias("k"), F.lit("bits").alias("metric"), F.col("bits").alias("value")))
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return written(out, "measurements")


def _measurements_sql():
    rows, tables = [], []
    for name in ("conv", "event_time", "hierarchy"):
        tables.append(f"e_{name} AS MATERIALIZED ({o.edges_sql(name)}), h_{name} AS (SELECT ({o.GRAPHS[name][1]})::BIGINT AS n)")
        for k in (4, 16):
            for algo, b in _RULES.items():
                x, y = (b.format(k=k).replace("i", c) if algo != "mulshift" else b.format(k=k).replace("i::", f"{c}::") for c in ("src", "dst"))
                rows.append(f"SELECT '{algo}' AS algo, '{name}' AS graph, {k} AS k, 'cut' AS metric, sum(CASE WHEN {x} <> {y} THEN w ELSE 0 END)::DOUBLE AS value FROM e_{name}, h_{name}")
                x, y = (b.format(k=k).replace("i", c) if algo != "mulshift" else b.format(k=k).replace("i::", f"{c}::") for c in ("v", "(v - 1)"))
                rows.append(f"SELECT '{algo}', '{name}', {k}, 'bits', ((1 + count(*)) * {(k - 1).bit_length() + 64})::DOUBLE FROM h_{name}, range(1, n) t(v) WHERE {x} <> {y}")
    return "WITH " + ", ".join(tables) + ", mm AS MATERIALIZED (" + " UNION ALL ".join(rows) + ")"


_MM = _measurements_sql()
_add("c_measurements", measurements, f"{_MM} SELECT * FROM mm")
_add("c_geomean", lambda s, d: me.geomean(measurements(s, d)), f"{_MM} SELECT algo, metric, round(exp(avg(ln(value))), 6) AS geomean FROM mm GROUP BY ALL")
_add("c_relative", lambda s, d: me.relative_value(measurements(s, d), "range", "mod"), f"{_MM} SELECT x.graph, x.k, x.metric, round(x.value / y.value, 6) AS relative FROM mm x JOIN mm y USING (graph, k, metric) WHERE x.algo = 'range' AND y.algo = 'mod'")
_add("c_improvement", lambda s, d: me.improvement(measurements(s, d), "range", "mod"), f"{_MM} SELECT x.graph, x.k, x.metric, round((x.value / y.value - 1) * 100, 6) AS improvement, round((y.value / x.value - 1) * 100, 6) AS quality_gain FROM mm x JOIN mm y USING (graph, k, metric) WHERE x.algo = 'range' AND y.algo = 'mod'")
_add("c_profile", lambda s, d: me.performance_profile(measurements(s, d), [1.0, 1.5, 2.0, 10.0]), f"{_MM}, z AS (SELECT *, value / min(value) OVER (PARTITION BY graph, k, metric) AS ratio FROM mm) SELECT algo, metric, tau, round(avg((ratio <= tau)::INT::DOUBLE), 6) AS share FROM z, (SELECT unnest([1.0, 1.5, 2.0, 10.0])::DOUBLE AS tau) GROUP BY ALL")
_add("c_win_rate", lambda s, d: me.win_rate(measurements(s, d), "range", "mod"), f"{_MM} SELECT x.metric, round(avg((x.value < y.value)::INT::DOUBLE), 6) AS wins, round(avg((x.value = y.value)::INT::DOUBLE), 6) AS ties FROM mm x JOIN mm y USING (graph, k, metric) WHERE x.algo = 'range' AND y.algo = 'mod' GROUP BY x.metric")
_add("c_feasible", lambda s, d: me.feasible(measurements(s, d), 8.0 * (64 << 10)), f"{_MM} SELECT algo, graph, k, value <= 524288 AS feasible FROM mm WHERE metric = 'bits'")
def _counters(s, d, names, **options):
    stats = ex.one_pass(ta.graph(s, d, "emb_cos"), 4, **options).stats
    return s.createDataFrame([tuple(int(stats[n]) for n in names)], ", ".join(f"{n} long" for n in names))


_add("c_counters", lambda s, d: _counters(s, d, ("appends", "lookups", "overfull")), f"WITH {o.head('emb_cos')} SELECT n AS appends, (SELECT count(*) FROM e) AS lookups, 0::BIGINT AS overfull FROM h")
_add("c_queue_counters", lambda s, d: _counters(s, d, ("queue_inserts", "queue_deletes", "queue_peak"), store="forward", memory_bytes=4096), f"WITH e AS MATERIALIZED ({o.edges_sql('emb_cos')}), x AS (SELECT id, sum(x) AS x FROM (SELECT src AS id, 1 AS x FROM e UNION ALL SELECT dst, -1 FROM e) GROUP BY id), y AS (SELECT sum(x) OVER (ORDER BY id) AS waiting FROM x) SELECT (SELECT count(*) FROM e) AS queue_inserts, (SELECT count(*) FROM e) AS queue_deletes, max(waiting)::BIGINT AS queue_peak FROM y")
_add("g_topological", lambda s, d: s.createDataFrame([(gr.check_topological(ta.BUILDERS["copurchase"](s, d)[0]),)], "sound boolean"), f"WITH e AS ({o.edges_sql('copurchase')}) SELECT count(*) FILTER (src >= dst) = 0 AS sound FROM e")

# --- files and table functions -----------------------------------------------------------------------


def _kept(s, save, name):
    path = folder(s, name)
    save(path)
    return path


def _weighted_text(s, d):
    """The weighted graph as adjacency text with edge weights (fmt 1), read again."""
    edges, n = ta.BUILDERS["cust_supp_weighted"](s, d)
    edges = written(edges, "edges")
    near = gr.symmetric(edges).groupBy("id").agg(F.sort_array(F.collect_list(F.struct("nbr", "w"))).alias("x"))
    lines = s.range(n).join(near, "id", "left").select("id", F.array_join(F.transform(F.coalesce("x", F.array().cast("array<struct<nbr: bigint, w: double>>")), lambda y: F.concat_ws(" ", (y.nbr + 1).cast("string"), y.w.cast("long").cast("string"))), " ").alias("value"))
    head = s.createDataFrame([(-1, f"{n} {edges.count()} 1")], "id long, value string")
    path = _kept(s, lambda p: head.union(lines).repartitionByRange("id").sortWithinPartitions("id").select("value").write.text(p), "text")
    return fi.read_adjacency(s, path).edges.select("src", "dst", "w")


def _edge_file(format, **options):
    def query(s, d):
        path = _kept(s, lambda p: fi.write_edges(ta.BUILDERS["part_supp"](s, d)[0], p, format, **options), "edges")
        return fi.read_edges(s, path, format, **options).select("src", "dst", "w")

    return query


_add("s_adjacency", lambda s, d: fi.read_adjacency(s, _kept(s, lambda p: fi.write_adjacency(ta.graph(s, d, "event_chain"), p), "text")).edges.select("src", "dst", "w"), f"WITH e AS ({o.edges_sql('event_chain')}) SELECT src, dst, w FROM e")
_add("s_adjacency_weighted", _weighted_text, f"WITH e AS ({o.edges_sql('cust_supp_weighted')}) SELECT src, dst, w FROM e")
for _f, _opt in (("csv", {"sep": "\t"}), ("json", {}), ("orc", {}), ("parquet", {})):
    _add(f"s_edges_{_f}", _edge_file(_f, **_opt), f"WITH e AS ({o.edges_sql('part_supp')}) SELECT src, dst, w FROM e")
_add("s_assignment", lambda s, d: s.read.parquet(_kept(s, lambda p: fi.write_assignment(_hash(s, d), p, by_block=True), "labels")).select("id", "block"), f"{_M} SELECT id, block FROM a")
_add("s_assignment_text", lambda s, d: s.read.text(_kept(s, lambda p: fi.write_assignment(_hash(s, d), p, "text"), "labels")).groupBy(F.col("value").cast("int").alias("block")).agg(F.count("*").alias("nodes")), f"{_M} SELECT block, count(*) AS nodes FROM a GROUP BY block")
_add("s_runs", lambda s, d: rl.rle_decode(s.read.parquet(_kept(s, lambda p: fi.write_runs(rl.rle_encode(sequence(s, d, "events"), "pos", "sym", 64), p), "runs"))), f"SELECT pos, sym FROM ({o.SEQUENCES['events']})")


def _called(s, sql, **views):
    table_functions.register(s)
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    return s.sql(sql)


def _partition_function(s, d):
    g = ta.graph(s, d, "conv")
    sql = f"SELECT id, block FROM partition_graph(TABLE(graph_nodes) WITH SINGLE PARTITION ORDER BY (id), 4, {g.n}, {g.weight!r}D, 20.0D)"
    return _called(s, sql, graph_nodes=ge.as_adjacency(g.edges, g.n))


_add("q_function_partition", _partition_function, _greedy_sql("conv", 4, kappa=20))
_add("q_function_decode", lambda s, d: _called(s, "SELECT pos, sym FROM decode_runs(TABLE(graph_runs))", graph_runs=_runs(s, d)), f"SELECT pos, sym FROM ({o.SEQUENCES['events']})")
_add("q_function_segments", lambda s, d: _called(s, "SELECT sum(points) AS starts, min(first_pos) AS first FROM learn_segments(TABLE(graph_runs) PARTITION BY batch)", graph_runs=_runs(s, d)), f"{_S['events']} SELECT count(*) AS starts, min(start) AS first FROM r")

# --- streams -----------------------------------------------------------------------------------------


def _stream_partition(s, d):
    g = ta.graph(s, d, "conv")
    adj = ge.as_adjacency(g.edges, g.n)
    nodes = sp.read_stream(s, sp.files_of(adj, "id", 4), adj.schema)
    return sp.drained(sp.stream_partition(nodes, 4, g.n, g.weight)).select("id", "block")


_add("t_stream_partition", _stream_partition, _greedy_sql("conv", 4))


def _event_stream(s, d, files=4, cols=("event_id", "ts", "user_id", "event_type")):
    e = ta.read(s, d, "events").select(*cols).withColumn("ts", F.col("ts").cast("timestamp"))
    return sp.read_stream(s, sp.files_of(e, "event_id", files), e.schema)


def _online_runs(s, d):
    got = sp.drained(sp.online_runs(_event_stream(s, d), "user_id", "event_id", "event_type"))
    return got.groupBy("key", "run_no", "start", "head").agg(F.max("len").alias("len")).select(F.col("key").alias("user_id"), "run_no", "start", "len", "head")


_add("t_online_runs", _online_runs, f"WITH s AS (SELECT user_id AS batch, row_number() OVER (PARTITION BY user_id ORDER BY event_id) - 1 AS pos, event_type AS sym FROM events), {o.RUNS} SELECT batch AS user_id, run_no, start, len, head FROM r")
_add("t_tumbling", lambda s, d: sp.drained(sp.windowed_counts(_event_stream(s, d), "ts", "event_type"), "update").groupBy("start_s", "end_s", "event_type").agg(F.max("n").alias("n")), "SELECT b AS start_s, b + 3600 AS end_s, event_type, count(*) AS n FROM (SELECT event_type, epoch_us(ts) // 3600000000 * 3600 AS b FROM events) GROUP BY ALL")
_add("t_sliding", lambda s, d: sp.drained(sp.windowed_counts(_event_stream(s, d), "ts", "event_type", "sliding"), "update").groupBy("start_s", "end_s", "event_type").agg(F.max("n").alias("n")), "SELECT b AS start_s, b + 3600 AS end_s, event_type, count(*) AS n FROM (SELECT event_type, epoch_us(ts) // 900000000 * 900 - 900 * unnest(range(4)) AS b FROM events) GROUP BY ALL")
_add("t_session", lambda s, d: sp.drained(sp.windowed_counts(_event_stream(s, d), "ts", "user_id", "session", "100 days"), "complete").groupBy("start_s", "end_s", "user_id", "batch").agg(F.max("n").alias("n")).withColumn("_top", F.max("batch").over(Window.partitionBy())).filter("batch = _top").select("start_s", "end_s", "user_id", "n"), "WITH x AS (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 1800000000 THEN 0 ELSE 1 END AS f FROM events), y AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS g FROM x) SELECT min(t) // 1000000 AS start_s, (max(t) + 1800000000) // 1000000 AS end_s, user_id, count(*) AS n FROM y GROUP BY user_id, g")
_add("t_dedup", lambda s, d: sp.drained(_event_stream(s, d).withWatermark("ts", "10 minutes").dropDuplicatesWithinWatermark(["event_id"])).select("event_id", "event_type"), "SELECT event_id, event_type FROM events")
_add("t_interval_join", lambda s, d: sp.drained(sp.near_pairs(_event_stream(s, d), _event_stream(s, d))).select("src", "dst"), f"WITH e AS ({o.edges_sql('event_time')}) SELECT src, dst FROM e")
_add("t_static_join", lambda s, d: sp.drained(_event_stream(s, d).join(ex.hash_blocks(s.range(ta.size(s, d, "events")), 4), F.col("event_id") == F.col("id")).select("event_id", "block")).select("event_id", "block"), "SELECT event_id, (((event_id::HUGEINT * 2654435761) % 4294967296) * 4 // 4294967296)::INTEGER AS block FROM events")


def _late(s, d, late="drop"):
    g = ta.graph(s, d, "conv")
    adj = ge.as_adjacency(g.edges, g.n)
    path = sp.files_of(adj, "id", 2)
    adj.filter("id < 5").repartition(1).write.mode("append").parquet(path)
    return sp.drained(sp.stream_partition(sp.read_stream(s, path, adj.schema), 4, g.n, g.weight, late=late)).groupBy("status").agg(F.count("*").alias("n"))


def _late_error(s, d):
    """Whether a late node ends the stream under the policy 'error'."""
    try:
        _late(s, d, "error")
        ended = False
    except Exception as x:
        ended = "LateNode" in str(x)
    return s.createDataFrame([(ended,)], "ended boolean")


_add("t_late", _late, "SELECT 'placed' AS status, count(*) AS n FROM conversations UNION ALL SELECT 'dropped', 5")
_add("t_late_kept", lambda s, d: _late(s, d, "place_without_run"), "SELECT 'placed' AS status, count(*) AS n FROM conversations UNION ALL SELECT 'late', 5")
_add("t_late_error", _late_error, "SELECT true AS ended")


def _placed_events(s, d):
    labels = ex.hash_blocks(s.range(ta.size(s, d, "events")), 4)
    return _event_stream(s, d, cols=("event_id", "ts")).join(labels, F.col("event_id") == F.col("id")).select("ts", "block")


def _window_cut(s, d):
    """Cut and all proximity edges per hour: edges are found by a join of streams, their windows over what it emitted."""
    a, labels = _event_stream(s, d), ex.hash_blocks(s.range(ta.size(s, d, "events")), 4)
    pairs = sp.drained(sp.near_pairs(a, _event_stream(s, d))).select("src", "dst", F.lit(1.0).alias("w"))
    at = ta.read(s, d, "events").select(F.col("event_id").alias("src"), F.col("ts").cast("timestamp").alias("ts"))
    x = me.edge_blocks(pairs, labels).join(at, "src").groupBy(F.window("ts", "1 hour").alias("w"))
    return x.agg(F.sum((F.col("src_block") != F.col("dst_block")).cast("long")).alias("cut"), F.count("*").alias("edges")).select(F.unix_seconds("w.start").alias("start_s"), "cut", "edges")


_HOUR = "epoch_us(ts) // 3600000000 * 3600"
_EV = f"WITH {o.head('event_time')}, {o.mulshift(4)}"
_add("t_window_placements", lambda s, d: sp.drained(sp.windowed_counts(_placed_events(s, d), "ts", "block"), "update").groupBy("start_s", "end_s", "block").agg(F.max("n").alias("n")), f"{_EV} SELECT b AS start_s, b + 3600 AS end_s, block, count(*) AS n FROM (SELECT block, {_HOUR} AS b FROM events JOIN a ON event_id = id) GROUP BY ALL")
_add("t_window_cut", _window_cut, f"{_EV} SELECT b AS start_s, sum((p <> q)::INT)::BIGINT AS cut, count(*) AS edges FROM (SELECT x.block AS p, y.block AS q, {_HOUR} AS b FROM e JOIN a x ON src = x.id JOIN a y ON dst = y.id JOIN events ON event_id = src) GROUP BY b")
