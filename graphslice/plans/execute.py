"""Ways to run one-pass placement: one ordered task, a relay of chunks, independent shards, buffers, and stateless rules."""

from __future__ import annotations

import json
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.score import LinearPenalty, PowerPenalty, limit, sticky
from ..operators import runs as rl
from ..operators.durable import add, folder, partitions, written
from ..operators.graph import Graph, forward_adjacency, stream_keys, stream_rows
from ..operators.kernel import OUT_DDL, PACKED_DDL, Rules, State, packed, place, place_frozen, place_side, unpacked


@dataclass
class Result:
    """runs (batch, run_no, start, len, head), block sizes and counters. `assign` decodes the runs."""

    runs: DataFrame
    sizes: list[float]
    stats: dict

    @property
    def assign(self) -> DataFrame:
        return rl.rle_decode(self.runs).select(F.col("pos").alias("id"), F.col("sym").alias("block"))


@dataclass(frozen=True)
class Settings:
    k: int
    eps: float = 0.03
    objective: PowerPenalty | LinearPenalty = PowerPenalty()
    store: str = "run"
    kappa: float = 1.0
    beta: int | None = None
    delta: int = 1024
    capacity: str = "hard"  # 'hard': no block beyond the limit; 'penalty': the penalty alone keeps the balance
    scoring: str = "candidates"
    memory_bytes: int = 3 << 20


def rules_of(g: Graph, s: Settings) -> Rules:
    total = float(g.nodes.agg(F.sum("c")).first()[0]) if g.nodes is not None else float(g.n)
    total = int(total) if total.is_integer() else total
    cap = limit(total, s.k, s.eps) if s.capacity == "hard" else None
    return Rules(s.k, total, g.weight, cap, s.objective, s.kappa, s.scoring)


def _typed(df: DataFrame) -> DataFrame:
    have = df.columns
    return df.select(F.col("shard") if "shard" in have else F.lit(0).alias("shard"), "id", "nbr", F.col("w").cast("double").alias("w"), F.col("block").cast("int").alias("block") if "block" in have else F.lit(None).cast("int").alias("block"))


def _run(ordered: DataFrame, rules: Rules, s: Settings, begin: State | None = None, offset: int = 0) -> tuple[DataFrame, list[dict]]:
    """Kernel over sorted rows; its runs as a written table, its statistics on the driver (one short row per shard)."""
    store, beta, delta, memory = s.store, s.beta, s.delta, s.memory_bytes
    return _told(ordered.mapInArrow(lambda b: place(b, rules, store, beta, delta, memory, begin, offset), OUT_DDL))


def _told(placed: DataFrame) -> tuple[DataFrame, list[dict]]:
    out = written(placed, "placed")
    stats = [json.loads(r[0]) | {"shard": r[1]} for r in out.filter("kind = 'stats'").select("stats", "shard").orderBy("shard").collect()]
    return out.filter("kind = 'run'").select("shard", "batch", "run_no", "start", "len", "head"), stats


def pieces(rows: DataFrame) -> DataFrame:
    """The stream (id, nbr, w), or its keys, sorted by all tasks in ranges and packed in pieces of some thousand rows."""
    if rows.columns == ["key"]:
        return rows.repartitionByRange(partitions(rows.sparkSession), "key").sortWithinPartitions("key").mapInArrow(packed, PACKED_DDL)
    rows = rows.select("id", "nbr", F.col("w").cast("double").alias("w"))
    ranged = rows.repartitionByRange(partitions(rows.sparkSession), F.col("id"), F.col("nbr").asc_nulls_first())
    return ranged.sortWithinPartitions("id", F.col("nbr").asc_nulls_first()).mapInArrow(packed, PACKED_DDL)


def _in_order(g: Graph, later: bool, feed: DataFrame | None) -> DataFrame:
    """The stream's pieces in order in one task; only they are sorted there. feed: the written pieces, if they are at hand,
    which the task reads by itself."""
    one = pieces(stream_keys(g, later)).repartition(1) if feed is None else feed.coalesce(1)
    return one.sortWithinPartitions("id", "nbr")


def _one_task(ordered: DataFrame, rules: Rules, s: Settings, k: int) -> Result:
    store, beta, delta, memory = s.store, s.beta, s.delta, s.memory_bytes
    runs, stats = _told(ordered.mapInArrow(lambda b: place(unpacked(b), rules, store, beta, delta, memory), OUT_DDL))
    return Result(runs.drop("shard"), stats[0]["sizes"] if stats else [0.0] * k, stats[0] if stats else {"runs": 0})


def single(g: Graph, s: Settings, feed: DataFrame | None = None) -> Result:
    """Exact, in one task that reads the stream once. feed: its written pieces, if they are at hand."""
    return _one_task(_in_order(g, s.store == "forward", feed), rules_of(g, s), s, s.k)


def side_by_side(g: Graph, settings: list[Settings], feed: DataFrame | None = None) -> list[Result]:
    """What `single` gives for settings that differ in the store alone (store, beta, delta; none is 'forward'): one task
    chooses the blocks once, and each store appends and looks up all of them."""
    s = settings[0]
    if any(x.store == "forward" or replace(x, store=s.store, beta=s.beta, delta=s.delta) != s for x in settings):
        raise ValueError("only the stores may differ")
    rules, kinds = rules_of(g, s), [(x.store, x.beta, x.delta) for x in settings]
    ordered = _in_order(g, False, feed)
    runs, stats = _told(ordered.mapInArrow(lambda b: place_side(unpacked(b), rules, kinds), OUT_DDL))
    return [Result(runs.filter(F.col("shard") == t["shard"]).drop("shard"), t["sizes"], t) for t in stats]


def prefix(g: Graph, upto: int, k: int, **options) -> Result:
    """The first `upto` nodes alone, under the whole graph's n, m and limit: a placed node never moves, so these are the
    labels that the whole stream gives them."""
    s = Settings(k, **options)
    later = s.store == "forward"
    rows = stream_rows(g, later).filter(F.col("id") < upto)
    return _one_task(pieces(rows).repartition(1).sortWithinPartitions("id", "nbr"), rules_of(g, s), s, k)


def relay(g: Graph, s: Settings, chunks: int = 4) -> Result:
    """Exact, chunk after chunk. When a chunk has been placed, its nodes' blocks are joined to the edges that leave it and
    their sums by later node and block are filed under the later node's chunk, so each edge is read and looked up once.
    Only sizes and the previous block pass over the driver; the runs are written chunk by chunk."""
    rules, per = rules_of(g, s), max(1, -(-g.n // chunks))
    if not g.n:
        return single(g, s)
    spark, chunk = g.spark, F.expr(f"id div {per}")
    rows = _typed(stream_rows(g)).withColumn("chunk", chunk).withColumn("from", F.expr(f"nbr div {per}"))
    near = written(rows.filter("nbr is null or from = chunk").drop("from").repartition(partitions(spark), "chunk"), "near", "chunk")
    far = written(rows.filter("from < chunk").select("id", "nbr", "w", "from").repartition(partitions(spark), "from", F.pmod("id", F.lit(8))), "far", "from")
    filed, runs = folder(spark, "gains"), folder(spark, "runs")
    gains = spark.read.schema("id long, block int, w double, chunk long")
    state, total = State([0.0] * s.k), {}
    inner = replace(s, store="run" if s.store == "forward" else s.store, beta=None)
    for c, lo in enumerate(range(0, g.n, per)):
        feed = near.filter(F.col("chunk") == c).select("shard", "id", "nbr", "w", "block")
        if c:
            feed = feed.union(gains.parquet(filed).filter(F.col("chunk") == c).select(F.lit(0), "id", F.lit(None).cast("long"), "w", "block"))
        got, stats = _run(feed.repartition(1).sortWithinPartitions("id", F.col("nbr").asc_nulls_first()), rules, inner, state, lo)
        state = State(stats[0]["sizes"], stats[0]["previous"])
        add(got.select("start", "len", "head"), runs)
        told = rl.lookup(got, far.filter(F.col("from") == c).drop("from"), "nbr", "block").groupBy("id", "block").agg(F.sum("w").alias("w"))
        add(told.withColumn("chunk", chunk), filed, "chunk")
        for key in ("seconds", "lookups", "appends", "overfull"):
            total[key] = total.get(key, 0) + stats[0][key]
    return Result(_stitched(spark.read.schema("start long, len long, head int").parquet(runs), s.beta), state.sizes, total)


def _stitched(cut: DataFrame, beta: int | None) -> DataFrame:
    """Runs joined over the borders of chunks, or cut at batches and joined within each."""
    if not beta:
        return rl.stitch(cut)
    w = Window.partitionBy("batch").orderBy("start")
    x = rl.by_batch(cut, beta).withColumn("_n", ((F.row_number().over(w) == 1) | (F.lag("head").over(w) != F.col("head"))).cast("long"))
    x = x.withColumn("run_no", F.sum("_n").over(w.rowsBetween(Window.unboundedPreceding, 0)) - 1)
    return x.groupBy("batch", "run_no").agg(F.min("start").alias("start"), F.sum("len").alias("len"), F.min_by("head", "start").alias("head"))


def shard_number(n: int, k: int, cap: int | None, wanted: int) -> int:
    """Most shards, up to the wanted number, whose own limits floor(cap / shards) still hold a shard's nodes."""
    for p in range(max(1, min(wanted, n or 1)), 1, -1):
        if cap is None or cap // p >= -(-(-(-n // p)) // k):
            return p
    return 1


def sharded(g: Graph, s: Settings, shards: int = 8, rounds: int = 2) -> Result:
    """Approximate, for 100 TB: id ranges are placed at the same time, each with its part of every block's limit, so the
    global limit holds. From the second round on a node also sees the blocks that earlier ids of other shards got in the
    round before. Each round is one shuffle by shard."""
    if g.nodes is not None:
        raise ValueError("shards need unit node weights")
    rules = rules_of(g, s)
    p = shard_number(g.n, s.k, rules.cap, shards)
    if p == 1:
        return single(g, s)
    per = -(-g.n // p)
    rules = replace(rules, cap=None if rules.cap is None else rules.cap // p, scale=float(p))
    shard = F.expr(f"cast(id div {per} as int)")
    rows = written(_typed(stream_rows(g)).withColumn("shard", shard), "stream")
    own = rows.filter(F.col("nbr").isNull() | (F.expr(f"nbr div {per}") == F.col("shard")))
    far = rows.filter(F.expr(f"nbr div {per}") < F.col("shard")).select("id", "nbr", "w", "shard")
    inner, runs, stats = replace(s, beta=None, store="runlist" if s.store == "forward" else s.store), None, []
    for _ in range(rounds):
        feed = own
        if runs is not None:
            gains = rl.lookup(runs, far, "nbr", "block").groupBy("shard", "id", "block").agg(F.sum("w").alias("w"))
            feed = own.select("shard", "id", "nbr", "w", "block").union(gains.select("shard", "id", F.lit(None).cast("long"), "w", "block"))
        ordered = feed.repartition(p, "shard").sortWithinPartitions("shard", "id", F.col("nbr").asc_nulls_first())
        runs, stats = _run(ordered, rules, inner)
    sizes = [sum(x) for x in zip(*(t["sizes"] for t in stats))]
    total = {key: sum(t[key] for t in stats) for key in ("lookups", "appends", "overfull")} | {"seconds": max(t["seconds"] for t in stats), "shards": p}
    return Result(_stitched(runs.drop("shard"), s.beta), sizes, total)


#: a buffer's table of gains (nodes x blocks) that fits in one task
TABLE = 1 << 23


def buffered(g: Graph, s: Settings, buffer: int, inner: str = "sequential", joins: bool | None = None) -> Result:
    """Buffers of nodes. 'sequential' places a buffer's nodes one after the other, as the stream does without buffers, so one
    task places buffer after buffer without a job for each; 'frozen' scores all of them against the state before the buffer.
    Frozen buffers whose table of gains (nodes x blocks) fits in a task are placed in one ordered task, larger ones as joins
    and an argmax per buffer (`joins` forces either)."""
    count = -(-g.n // buffer)
    if inner == "sequential":
        r = single(g, s)
        return Result(r.runs, r.sizes, r.stats | {"buffers": count})
    if not (buffer * s.k > TABLE if joins is None else joins):
        rules, n = rules_of(g, s), g.n
        ordered = _in_order(g, False, None)
        runs, stats = _told(ordered.mapInArrow(lambda b: place_frozen(unpacked(b), rules, buffer, n), OUT_DDL))
        return Result(_stitched(runs.drop("shard"), s.beta), stats[0]["sizes"], {"buffers": count, "lookups": stats[0]["lookups"]})
    rules, spark = rules_of(g, s), g.spark
    far = written(forward_adjacency(g.edges).withColumn("from", F.expr(f"nbr div {buffer}")).filter(f"from < id div {buffer}"), "far", "from")
    filed, labels = folder(spark, "gains"), folder(spark, "labels")
    sizes, previous = [0.0] * s.k, -1
    for c, lo in enumerate(range(0, g.n, buffer)):
        hi = min(g.n, lo + buffer)
        ids = spark.range(lo, hi)
        blocks = spark.createDataFrame([(b, x) for b, x in enumerate(sizes)], "block int, size double")
        if c:
            near = spark.read.schema("id long, block int, w double, buffer long").parquet(filed).filter(F.col("buffer") == c).groupBy("id", "block").agg(F.sum("w").alias("gain"))
        else:
            near = spark.createDataFrame([], "id long, block int, gain double")
        grid = ids.join(F.broadcast(blocks), F.lit(True)).join(near, ["id", "block"], "left").withColumn("gain", F.coalesce("gain", F.lit(0.0)))
        best = best_block(grid, rules, previous)
        # more nodes than a block has room for: the rest, by id, fill the least loaded blocks
        chosen = written(best, "buffer")
        rows = {b: n for b, n in chosen.groupBy("block").agg(F.count("*")).collect()}
        over = {b: n for b, n in rows.items() if rules.cap is not None and sizes[b] + n > rules.cap}
        if over:
            rank = F.row_number().over(Window.partitionBy("block").orderBy("id"))
            room = g.spark.createDataFrame([(b, float(rules.cap) - x) for b, x in enumerate(sizes)], "block int, room double")
            marked = chosen.withColumn("_r", rank).join(F.broadcast(room), "block")
            stay, rest = marked.filter("_r <= room").select("id", "block"), marked.filter("_r > room").select("id")
            for b, n in rows.items():
                sizes[b] += min(n, max(0, int(rules.cap - sizes[b])))
            spill = [r[0] for r in rest.orderBy("id").collect()]  # at most one buffer
            fill = []
            for v in spill:
                b = min(range(s.k), key=lambda b: (sizes[b], b))
                sizes[b] += 1
                fill.append((v, b))
            chosen = written(stay.union(g.spark.createDataFrame(fill, "id long, block int")), "buffer")
        else:
            for b, n in rows.items():
                sizes[b] += n
        add(chosen.select("id", "block"), labels)
        told = far.filter(F.col("from") == c).join(chosen.select(F.col("id").alias("nbr"), "block"), "nbr").groupBy("id", "block").agg(F.sum("w").alias("w"))
        add(told.withColumn("buffer", F.expr(f"id div {buffer}")), filed, "buffer")
        previous = chosen.filter(F.col("id") == hi - 1).first()["block"]
    runs = rl.rle_encode(spark.read.schema("id long, block int").parquet(labels), "id", "block", s.beta)
    return Result(written(runs, "runs"), sizes, {"buffers": count})


def best_block(scores: DataFrame, rules: Rules, previous: int | None = None) -> DataFrame:
    """(id, block) of the best score per id among (id, block, gain, size); ties go to the lowest block."""
    x = scores if rules.cap is None else scores.filter(F.col("size") + 1 <= F.lit(rules.cap))
    value: Column = rules.objective.column(F.col("gain"), F.col("size"), rules.n, rules.m, rules.k)
    if previous is not None and rules.kappa != 1:
        value = sticky(value, F.col("block"), F.lit(previous), rules.kappa)
    order = F.struct(value.alias("s"), (-F.col("size")).alias("l"), (-F.col("block")).alias("b")) if rules.objective.ties_by_load else F.struct(value.alias("s"), (-F.col("block")).alias("b"))
    return x.groupBy("id").agg(F.max_by("block", order).alias("block"))


MODES = {"single": single, "relay": relay, "sharded": sharded, "buffered": buffered}


def one_pass(g: Graph, k: int, exec: str = "single", *, eps: float = 0.03, objective=PowerPenalty(), store: str = "run", kappa: float = 1.0, beta: int | None = None, delta: int = 1024, capacity: str = "hard", scoring: str = "candidates", memory_bytes: int = 3 << 20, **mode) -> Result:
    """Place all nodes of a graph in k blocks. exec: 'single', 'relay' (chunks=), 'sharded' (shards=, rounds=) or
    'buffered' (buffer=, inner=)."""
    return MODES[exec](g, Settings(k, eps, objective, store, kappa, beta, delta, capacity, scoring, memory_bytes), **mode)


def forward_messages(assign: DataFrame, edges: DataFrame, chunk: int | None = None) -> DataFrame:
    """(target, block, w[, target_chunk]): what each node tells its later neighbours."""
    out = edges.join(assign.select(F.col("id").alias("src"), "block"), "src").select(F.col("dst").alias("target"), "block", "w")
    return out if chunk is None else out.withColumn("target_chunk", F.expr(f"target div {chunk}"))


# --- rules without state -----------------------------------------------------------------------------

def hash_block(i: Column, k: int, method: str = "mulshift") -> Column:
    """A node's block by a hash of its id alone: 'mulshift', 'mod' or 'xxhash64'."""
    if method == "mod":
        b = F.pmod(i, F.lit(k))
    elif method == "xxhash64":
        b = F.pmod(F.xxhash64(i), F.lit(k))
    else:
        # id * 2654435761 modulo 2**32 from halves, which stays within 64 bits
        low, high = i.bitwiseAND(0xFFFF), F.shiftright(i, 16).bitwiseAND(0xFFFF)
        mixed = (low * 2654435761 + F.pmod(high * 2654435761, F.lit(1 << 16)) * 65536) % F.lit(1 << 32)
        b = F.floor(mixed * F.lit(k) / F.lit(float(1 << 32))) if k > (1 << 20) else F.shiftright(mixed * k, 32)
    return b.cast("int")


def hash_blocks(nodes: DataFrame, k: int, method: str = "mulshift") -> DataFrame:
    """(id, block) by `hash_block`. Narrow, no state."""
    return nodes.select(F.col("id").cast("long").alias("id"), hash_block(F.col("id"), k, method).alias("block"))


def range_blocks(nodes: DataFrame, n: int, k: int) -> DataFrame:
    """(id, block) by equal id ranges."""
    return nodes.select(F.col("id").cast("long").alias("id"), F.expr(f"cast(id * {k} div {max(n, 1)} as int)").alias("block"))
