"""Placement, run coding and windows over streams."""

from __future__ import annotations

import pickle
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import IntegerType, StructField, StructType

from ..functions.score import PowerPenalty, limit
from ..operators.durable import shared_folder
from ..operators.kernel import Placer, Rules, State
from ..operators.stores import RunListStore


def files_of(df: DataFrame, order: str, files: int) -> str:
    """df as `files` Parquet files in the order of a column, one after the other in time, for a file stream."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/graphslice/stream-{uuid.uuid4().hex}"
    lo, hi = df.agg(F.min(order), F.max(order)).first()
    if lo is None:
        df.write.parquet(path)
        return path
    step = (hi - lo) // files + 1
    for i in range(files):
        part = df.filter((F.col(order) >= lo + i * step) & (F.col(order) < lo + (i + 1) * step))
        part.repartition(1).sortWithinPartitions(order).write.mode("append").parquet(path)
    return path


def read_stream(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def drained(stream: DataFrame, mode: str = "append", checkpoint: str | None = None, sink: str | None = None) -> DataFrame:
    """What a stream has emitted once all that is available has been read, from a table sink."""
    spark = stream.sparkSession
    base = f"{shared_folder(spark)}/graphslice/sink-{uuid.uuid4().hex}"
    out = sink or f"{base}/out"
    schema = stream.schema

    def save(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

    q = stream.writeStream.outputMode(mode).foreachBatch(save).option("checkpointLocation", checkpoint or f"{base}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(StructType([*schema.fields, StructField("batch", IntegerType())])).option("basePath", out).parquet(out)


class LateNode(ValueError):
    """A node whose id is below one already placed."""


def stream_partition(nodes: DataFrame, k: int, n: int, m: float, kappa: float = 1.0, eps: float = 0.03, objective=PowerPenalty(), late: str = "error", shard: str | None = None) -> DataFrame:
    """(shard, id, block, status) of a stream of (id, nbrs: ids of all neighbours).

    State per shard: the runs so far, the block sizes and the previous block. One shard is exact. n and m have to be
    known. A node below one already placed is an error, is dropped, or is placed without entering the runs
    (late='error', 'drop', 'place_without_run').
    """
    cap = limit(n, k, eps)
    rules = Rules(k, n, m, cap, objective, kappa)

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = pickle.loads(state.get[0]) if state.exists else {"heads": [], "begin": [], "n": 0, "sizes": [0.0] * k, "previous": -1, "ids": []}
        store = RunListStore(k)
        store.heads, store.begin, store.n = held["heads"], held["begin"], held["n"]
        placer = Placer(rules, State(held["sizes"], held["previous"], store.n))
        first = held.get("first", 0)
        rows = pd.concat(list(frames)).sort_values("id", kind="stable")
        out = []
        for v, nbrs in zip(rows["id"].tolist(), rows["nbrs"].tolist()):
            if not store.n:
                first = held["first"] = v
            gains: dict[int, float] = {}
            for u in nbrs if nbrs is not None else ():
                if first <= u < min(v, first + store.n):
                    b = store.get(u - first)
                    gains[b] = gains.get(b, 0) + 1
            if v != first + store.n:
                if v > first + store.n or late == "error":
                    raise LateNode(f"node {v} where {first + store.n} was due")
                if late == "drop":
                    out.append((key[0], v, -1, "dropped"))
                else:
                    previous = placer.s.previous
                    out.append((key[0], v, placer.choose(gains), "late"))
                    placer.s.previous = previous
                continue
            b = placer.choose(gains)
            store.append(b)
            out.append((key[0], v, b, "placed"))
        held |= {"heads": store.heads, "begin": store.begin, "n": store.n, "sizes": placer.s.sizes, "previous": placer.s.previous, "first": first}
        state.update((pickle.dumps(held),))
        yield pd.DataFrame(out, columns=["shard", "id", "block", "status"])

    keyed = nodes.select((F.col(shard) if shard else F.lit(0)).cast("int").alias("shard"), "id", "nbrs")
    return keyed.groupBy("shard").applyInPandasWithState(step, "shard int, id long, block int, status string", "held binary", "append", GroupStateTimeout.NoTimeout)


def online_runs(symbols: DataFrame, key: str, order: str, sym: str) -> DataFrame:
    """(key, run_no, start, len, head, closed) of each key's symbol stream. A closed run is emitted once; the open one, which
    alone is kept in the state, is emitted as it stands after each trigger, with closed = false."""
    kind = symbols.schema[key].dataType.simpleString()

    def step(k, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        number, start, length, head = state.get if state.exists else (-1, 0, 0, None)
        rows = pd.concat(list(frames)).sort_values("o", kind="stable")
        out, pos = [], start + length
        for s in rows["s"].tolist():
            if number < 0 or s != head:
                if number >= 0:
                    out.append((k[0], number, start, length, head, True))
                number, start, length, head = number + 1, pos, 0, s
            length += 1
            pos += 1
        state.update((number, start, length, head))
        out.append((k[0], number, start, length, head, False))
        yield pd.DataFrame(out, columns=["key", "run_no", "start", "len", "head", "closed"])

    x = symbols.select(F.col(key).alias("key"), F.col(order).alias("o"), F.col(sym).alias("s"))
    return x.groupBy("key").applyInPandasWithState(step, f"key {kind}, run_no long, start long, len long, head string, closed boolean", "number long, start long, length long, head string", "append", GroupStateTimeout.NoTimeout)


def windowed_counts(events: DataFrame, ts: str, by: str, kind: str = "tumbling", watermark: str = "10 minutes") -> DataFrame:
    """Counts per window and group: 'tumbling' (1 hour), 'sliding' (1 hour by 15 minutes) or 'session' (gap of 30 minutes)."""
    w = {"tumbling": lambda: F.window(ts, "1 hour"), "sliding": lambda: F.window(ts, "1 hour", "15 minutes"), "session": lambda: F.session_window(ts, "30 minutes")}[kind]()
    return events.withWatermark(ts, watermark).groupBy(w.alias("w"), by).agg(F.count("*").alias("n")).select(F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start_s"), F.unix_seconds(F.col("w.end").cast("timestamp")).alias("end_s"), by, "n")


def near_pairs(events: DataFrame, other: DataFrame) -> DataFrame:
    """Proximity edges online: both sides are streams (event_id, ts), joined on cells of 30 ids within ten minutes."""
    a = events.withWatermark("ts", "20 minutes").select(F.col("event_id").alias("src"), F.col("ts").alias("ta"), F.expr("event_id div 30").alias("cell"))
    b = other.withWatermark("ts", "20 minutes").select(F.col("event_id").alias("dst"), F.col("ts").alias("tb"), F.explode(F.array(F.expr("event_id div 30"), F.expr("event_id div 30 - 1"))).alias("cell_b"))
    on = (F.col("cell") == F.col("cell_b")) & (F.col("dst") > F.col("src")) & (F.col("dst") - F.col("src") <= 30) & (F.col("tb") >= F.col("ta") - F.expr("interval 10 minutes")) & (F.col("tb") <= F.col("ta") + F.expr("interval 10 minutes"))
    return a.join(b, on).select("src", "dst")
