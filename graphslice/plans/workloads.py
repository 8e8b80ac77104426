"""The experiments as tables of measurements (algo, graph, k, metric, value)."""

from __future__ import annotations

import math
import threading
import time
from concurrent.futures import ThreadPoolExecutor, wait

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.util import inheritable_thread_target

from ..operators import graph as gr, measure as me
from ..operators.bitvector import AppendableBitVector
from ..operators.durable import drop, dropped_after, made, shuffles_dropped, written
from ..sources import generate as ge, tables as ta
from .execute import Settings, hash_block, one_pass, pieces, side_by_side

SCHEMA = "algo string, graph string, k int, metric string, value double"


def _table(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(a, g, k, m, None if v is None else float(v)) for a, g, k, m, v in rows], SCHEMA)


def measured(g: gr.Graph, name: str, k: int, algo: str, **options) -> list[tuple]:
    """One run's cut, relative cut, runs, segments, bits, kernel seconds and feasibility of the balance. With unit weights the
    cut is the one that the kernel counts as it places."""
    return _told(g, name, k, algo, one_pass(g, k, **options))


def _told(g: gr.Graph, name: str, k: int, algo: str, r) -> list[tuple]:
    s = r.stats
    cut = int(s["cut"]) if s.get("unit") else me.edge_cut(g.edges, r.assign).first()["cut_edges"]
    pairs = [("cut", cut), ("relative_cut", cut / max(g.m, 1)), ("runs", s.get("runs")), ("segments", s.get("segments")), ("bits", s.get("size_bits")), ("seconds", s.get("seconds")), ("peak_rss_kb", s.get("peak_rss_kb")), ("largest_block", max(r.sizes))]
    pairs += [(m, s[m]) for m in ("queue_inserts", "queue_deletes", "queue_peak", "spilled_runs") if m in s]
    return [(algo, name, k, m, v) for m, v in pairs if v is not None]


def together(spark: SparkSession, calls: list) -> list:
    """The results of calls that each keep one task busy: as many run at once as there are cores."""
    with ThreadPoolExecutor(max(1, min(len(calls), spark.sparkContext.defaultParallelism))) as pool:
        return [x.result() for x in [pool.submit(inheritable_thread_target(spark)(f)) for f in calls]]


#: graphs that are made at the same time
MAKERS = 2


def in_turn(spark: SparkSession, makers: dict, runs_of) -> dict[str, list[list[tuple]]]:
    """What `measured` gives for the runs (graph, k, algo, options) that runs_of(name, graph) lists, for each graph. A graph's
    stream is sorted once for all its runs, and once more for those with messages to later nodes; the runs stand side by side, so
    their seconds are taken while others run or are sorted. Runs of a graph that differ in the store alone have the same
    labels: one task chooses the blocks once for all of their stores, and a run's seconds are the shared ones and its store's own.

    Graphs are made in turn while those before are placed. A stream is removed when its runs have ended, a graph made here
    when its streams are sorted (where the kernel does not count the cut, when its runs have ended), and no stream is sorted
    while as many runs as there are cores have not ended: the disk holds a few graphs at a time, however many there are."""
    cores = max(1, spark.sparkContext.defaultParallelism)
    half = max(1, cores // 2)  # the others sort streams while there are any to sort
    room, gate = threading.Semaphore(cores), threading.Semaphore(half)

    def place(g: gr.Graph, feed: DataFrame, part: list[tuple]) -> list[list[tuple]]:
        try:
            with gate, dropped_after(spark):
                n, k, algo, o = part[0]
                if len(part) == 1:
                    return [measured(g, n, k, algo, feed=feed, **o)]
                results = side_by_side(g, [Settings(k, **o) for *_, o in part], feed)
                return [_told(g, n, k, algo, r) for (n, k, algo, _), r in zip(part, results)]
        finally:
            room.release()

    def make(name: str) -> list[tuple]:
        """(places of runs in the list, their results to come) of a graph."""
        with dropped_after(spark):
            g = makers[name]()
            runs, alike, out = runs_of(name, g), {}, []
            for i, (_, k, _, o) in enumerate(runs):
                rest = tuple(sorted((key, v) for key, v in o.items() if key not in ("store", "beta", "delta")))
                alike.setdefault((o.get("store") == "forward", k, i if o.get("store") == "forward" else None, rest), []).append(i)
            for later in sorted({x[0] for x in alike}):
                with made() as paths:
                    feed = written(pieces(gr.stream_keys(g, later)), "pieces")
                groups = [members for x, members in alike.items() if x[0] == later]
                waits = [len(groups)]

                def ended(_, waits=waits, paths=paths):
                    with counted:
                        waits[0] -= 1
                    if not waits[0]:
                        for path in paths:
                            drop(spark, path)

                for members in groups:
                    room.acquire()
                    x = placing.submit(inheritable_thread_target(spark)(place), g, feed, [runs[i] for i in members])
                    x.add_done_callback(ended)
                    out.append((members, x))
            if not g.unit:
                wait([x for _, x in out])
        return out

    counted = threading.Lock()
    with shuffles_dropped(spark), ThreadPoolExecutor(cores) as placing, ThreadPoolExecutor(MAKERS) as making:
        making_all = [making.submit(inheritable_thread_target(spark)(make), name) for name in makers]
        wait(making_all)
        if cores > half:
            gate.release(cores - half)
        found = {}
        for name, x in zip(makers, making_all):
            done = dict(pair for members, rows in x.result() for pair in zip(members, rows.result()))
            found[name] = [done[i] for i in range(len(done))]
    return found


def all_measured(spark: SparkSession, graphs: dict, runs: list[tuple]) -> list[list[tuple]]:
    """`in_turn` for graphs that are at hand, large ones first; in the order of the runs."""
    names = sorted({n for n, *_ in runs}, key=lambda n: -graphs[n].m)
    found = in_turn(spark, {n: lambda n=n: graphs[n] for n in names}, lambda name, _: [r for r in runs if r[0] == name])
    each = {n: iter(rows) for n, rows in found.items()}
    return [next(each[n]) for n, *_ in runs]


def study(spark: SparkSession, sf_dir: str, graphs, ks, configs: dict) -> DataFrame:
    def runs_of(name: str, g: gr.Graph) -> list[tuple]:
        return [(name, k, algo, o(g) if callable(o) else o) for k in ks if k <= g.n / 2 for algo, o in configs.items()]

    # large graphs first, so that none is left alone at the end
    found = in_turn(spark, {n: lambda n=n: ta.graph(spark, sf_dir, n) for n in sorted(graphs, key=lambda n: n not in ta.PAIRED)}, runs_of)
    return _table(spark, [row for n in graphs for rows in found[n] for row in rows])


#: the given graphs with unit weights
GIVEN = tuple(n for n in ta.BUILDERS if n != "cust_supp_weighted")


def batch_study(spark, sf_dir, graphs=GIVEN, ks=(16,)):
    """Batch sizes n, n/10, n/100 and 64 at kappa 1: the cut must not move, runs grow by at most a run per batch."""
    return study(spark, sf_dir, graphs, ks, {"beta_n": {}, "beta_n/10": lambda g: {"beta": max(1, g.n // 10)}, "beta_n/100": lambda g: {"beta": max(1, g.n // 100)}, "beta_64": {"beta": 64}})


def kappa_study(spark, sf_dir, graphs=GIVEN, ks=(16,)):
    return study(spark, sf_dir, graphs, ks, {f"kappa_{k}": {"kappa": float(k)} for k in (1, 5, 10, 15, 20)})


def store_comparison(spark, sf_dir, graphs=GIVEN, ks=(4,)):
    """Default runs, batches, stickiness 20, the plain array and the forward queue."""
    return study(spark, sf_dir, graphs, ks, {"run": {}, "batched": lambda g: {"beta": max(1, g.n // 10)}, "sticky20": {"kappa": 20.0}, "dense": {"store": "dense"}, "queue": {"store": "forward"}})


def queue_study(spark, sf_dir, graphs=("event_time",), ks=(4,)):
    return study(spark, sf_dir, graphs, ks, {f"queue_{b}": {"store": "forward", "memory_bytes": b} for b in (1 << 12, 64 << 10, 3 << 20, 64 << 20)})


def sticky_batches(spark, sf_dir, graphs=("conv",), ks=(4,)):
    return study(spark, sf_dir, graphs, ks, {"sticky20": {"kappa": 20.0}, "sticky20_batched": lambda g: {"kappa": 20.0, "beta": max(1, g.n // 10)}})


def delta_study(spark, sf_dir, graph="event_time", k=4, deltas=(1, 16, 256, 4096)):
    """Append time and size of the appendable bit vector over its buffer, on the run starts of one placement."""
    g = ta.graph(spark, sf_dir, graph)
    starts = [r["start"] for r in one_pass(g, k).runs.select("start").orderBy("start").collect()]  # runs, not nodes
    rows = []
    for d in deltas:
        began, v = time.perf_counter(), AppendableBitVector(d)
        for p in starts:
            v.append(p)
        v.flush()
        rows += [(f"delta_{d}", graph, k, m, x) for m, x in (("seconds", time.perf_counter() - began), ("bits", v.size_bits()), ("segments", v.segments()), ("refits", v.closed.refits))]
    return _table(spark, rows)


def locality_study(spark, sf_dir, ks=(4,)):
    """Default against hashed-random order on graphs with local ids, and a row-major mesh."""
    edges, n = ge.gen_grid(spark, 60, 60)
    graphs = {"conv": ta.graph(spark, sf_dir, "conv"), "grid": gr.make_graph(edges, n)}
    rows = []
    for name, g in graphs.items():
        for order in ("default", "random"):
            h = gr.reorder(g, order)
            for k in ks:
                for kappa in (1.0, 20.0):
                    rows += measured(h, f"{name}_{order}", k, f"kappa_{kappa:g}", kappa=kappa)
    return _table(spark, rows)


def massive_study(spark, sf_dir, nodes=100_000, ks=(4, 256), budget_bits_per_node=8.0, given=("event_time", "order_part")):
    """Stickiness 20, the plain array and the hash, with a budget on the store's bits, on given graphs and on generated ones
    at about the published density."""
    rgg, n = ge.gen_rgg(spark, nodes, (30 / (3.141592653589793 * nodes)) ** 0.5)
    ba, _ = ge.gen_ba(spark, nodes, 15)
    graphs = {"rgg": gr.make_graph(rgg, n), "ba": gr.make_graph(ba, nodes)}
    graphs |= dict(zip(given, together(spark, [lambda n=n: ta.graph(spark, sf_dir, n) for n in given])))
    algos = {"sticky20": {"kappa": 20.0}, "dense": {"store": "dense"}}
    sizes = [(name, k) for name, g in graphs.items() for k in ks if k <= g.n / 2]
    got = iter(all_measured(spark, graphs, [(name, k, algo, o) for name, k in sizes for algo, o in algos.items()]))
    rows = []
    for name, k in sizes:
        g = graphs[name]
        for algo in algos:
            part = next(got)
            bits = next(v for *_, m, v in part if m == "bits")
            rows += [*part, (algo, name, k, "feasible", bits <= budget_bits_per_node * g.n)]
        # both ends' blocks come from their ids alone, so no labels are joined
        cut = g.edges.filter(hash_block(F.col("src"), k) != hash_block(F.col("dst"), k)).count()
        rows += [("hash", name, k, "relative_cut", cut / g.m), ("hash", name, k, "bits", 0), ("hash", name, k, "feasible", 1)]
    return _table(spark, rows)


def comparison_profiles(spark, sf_dir, graphs=GIVEN, ks=(4,)):
    """Shares of instances within a factor of the best (cut, seconds, bits) over the comparison of stores."""
    m = store_comparison(spark, sf_dir, graphs, ks).filter("metric in ('cut', 'seconds', 'bits')")
    return me.performance_profile(m, [1.0, 1.1, 1.5, 2.0, 5.0, 10.0, 100.0])


def comparison_means(spark, sf_dir, graphs=GIVEN, ks=(4,)):
    """Geometric means over the comparison of stores. Cuts are counted from one, since some are zero."""
    m = store_comparison(spark, sf_dir, graphs, ks).filter("metric in ('cut', 'seconds', 'bits')")
    return me.geomean(m.withColumn("value", F.col("value") + F.when(F.col("metric") == "cut", 1.0).otherwise(0.0)))


def extrapolation(spark, sf_dir, nodes=(2000, 4000, 8000, 16000), k=4, kappa=20.0, target=2**34):
    """Runs, bits and seconds of generated geometric graphs at a fixed mean degree (30) over growing n, and what a power law
    through them gives at the published largest size (k, kappa as there). The last rows are forecasts, not measurements."""
    rows, seen = [], {}
    for n in nodes:
        edges, _ = ge.gen_rgg(spark, n, (30 / (math.pi * n)) ** 0.5)
        for algo, _, _, metric, value in measured(gr.make_graph(written(edges, "edges"), n), f"rgg_{n}", k, f"sticky{kappa:g}", kappa=kappa):
            if metric in ("runs", "bits", "seconds"):
                rows.append((algo, f"rgg_{n}", k, metric, value))
                seen.setdefault(metric, []).append((math.log(n), math.log(max(value, 1e-9))))
    for metric, points in seen.items():
        x, y = np.array(points).T
        slope, base = np.polyfit(x, y, 1)
        rows += [("power", "rgg", k, metric, slope), ("forecast", f"rgg_{target}", k, metric, math.exp(base + slope * math.log(target)))]
    return _table(spark, rows)


QUERIES = {
    "w_batch_study": batch_study, "w_kappa_study": kappa_study, "w_delta_study": delta_study, "w_store_comparison": store_comparison, "w_queue_study": queue_study,
    "w_sticky_batches": sticky_batches, "w_locality_study": locality_study, "w_massive_study": massive_study,
    "w_comparison_profiles": comparison_profiles, "w_comparison_means": comparison_means, "w_extrapolation": extrapolation,
}
