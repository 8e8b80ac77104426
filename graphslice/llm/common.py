"""Helpers shared by the training-data operators: shared-folder tables, byte-level hashing, components."""

from __future__ import annotations

import atexit
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

U64 = np.uint64
SEPARATORS = np.zeros(256, bool)
SEPARATORS[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir of the session. Where none is set and all runs in one process
    (tests) it is a fresh temporary one; on a cluster that raises, since executors would not see it."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = found.get() if found.isDefined() else None
    if not base:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="graphslice-")
        spark.sparkContext.setCheckpointDir(base)
    return base


def _drop(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session may have ended before
        pass


class Durable:
    """Tables written to the shared folder; `release` drops those that later plans no longer read.

    After each write the driver gives back native memory, after every fourth all that `settle` gives back."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths, self.writes = spark, {}, 0

    def __call__(self, df: DataFrame, name: str = "t", codec: str = "zstd") -> DataFrame:
        path = f"{shared_folder(self.spark)}/graphslice/{name}-{uuid.uuid4().hex}"
        df.write.option("compression", codec).parquet(path)
        self.paths[name] = path
        self.writes += 1
        trim_native(self.spark) if self.writes % 4 else settle(self.spark)
        atexit.register(_drop, self.spark, path)
        return self.spark.read.schema(df.schema).parquet(path)

    def release(self, *names: str) -> None:
        for name in names:
            if name in self.paths:
                _drop(self.spark, self.paths.pop(name))


def trim_native(spark: SparkSession) -> bool:
    """Give the free part of the driver JVM's native heap back to the system. Compiling generated code leaves hundreds of MB
    there, which the C library keeps. False where the JVM has no command for it."""
    try:
        jvm, array = spark._jvm, spark.sparkContext._gateway.new_array
        call, values = array(jvm.Class, 4), (jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap", array(jvm.Object, 0), array(jvm.String, 0))
        args = array(jvm.Object, 4)
        for i, x in enumerate(values):
            args[i], call[i] = x, jvm.Class.forName(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")[i])
        # by the interface: the server's own class is not open to reflection
        jvm.Class.forName("javax.management.MBeanServer").getMethod("invoke", call).invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), args)
    except Exception:
        return False
    return True


def settle(spark: SparkSession) -> None:
    """Give back what finished steps hold on the driver. Spark's cleaner drops shuffles and broadcasts only when the driver's
    garbage collector finds their handles unused, which Spark itself forces every half hour."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
        libc.malloc_trim(0)
    spark._jvm.System.gc()
    trim_native(spark)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


# --- bytes, words and polynomial hashes -------------------------------------------------------------

_ODD = 0x9E3779B97F4A7C15 | 1
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit state (xor-shift-multiply), vectorised."""
    x = x.astype(U64, copy=True)
    x ^= x >> U64(30)
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def powers(n: int, base: int = _ODD) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n (kept, grown by doubling)."""
    have = _powers.get(base)
    if have is None or len(have[0]) < n:
        size = 1 << max(12, int(n - 1).bit_length())
        out = []
        for b in (base, pow(base, -1, 1 << 64)):
            p = np.empty(size, U64)
            p[0], filled, step = 1, 1, b
            while filled < size:
                p[filled : 2 * filled] = p[:filled] * U64(step)
                step = step * step & 0xFFFFFFFFFFFFFFFF
                filled *= 2
            out.append(p)
        have = _powers[base] = (out[0], out[1])
    return have[0][:n], have[1][:n]


BYTE_CODES = mix(np.arange(1, 257, dtype=U64) * U64(0xD6E8FEB86659FD93))
BYTE_CODES_2 = mix(np.arange(1001, 1257, dtype=U64) * U64(0xA0761D6478BD642F))


def prefix_hash(codes: np.ndarray, base: int = _ODD) -> np.ndarray:
    """P with P[i] = sum of codes[j] * base**j for j < i, modulo 2**64; length n + 1."""
    p, _ = powers(len(codes) + 1, base)
    out = np.zeros(len(codes) + 1, U64)
    np.cumsum(codes * p[: len(codes)], out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray, base: int = _ODD) -> np.ndarray:
    """Position-independent hash of [start, end) under `prefix_hash`."""
    _, inverse = powers(len(prefix), base)
    return (prefix[end] - prefix[start]) * inverse[start]


def string_slices(column: pa.Array, most_bytes: int = 1 << 20) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Cut a string or binary column into runs of whole values of about `most_bytes` (a longer value stands alone).

    Yields first row, end row, the bytes and the rows' offsets in them; null counts as empty.
    """
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    for base in range(0, len(column), 512):  # copies stay small, however large the batch
        part = pc.fill_null(column.slice(base, 512).cast(pa.large_binary()), b"")
        n = len(part)
        offsets = np.frombuffer(part.buffers()[1], np.int64, n + 1, part.offset * 8)
        data = np.frombuffer(part.buffers()[2], np.uint8) if part.buffers()[2] is not None and part.buffers()[2].size else np.zeros(0, np.uint8)
        row = 0
        while row < n:
            end = max(row + 1, int(np.searchsorted(offsets, offsets[row] + most_bytes, "right")) - 1)
            end = min(end, n)
            yield base + row, base + end, data[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row]
            row = end


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words (runs of bytes outside x20, x09-x0D, never across rows), and words before each row."""
    n = len(data)
    if not n:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(offsets), np.int64)
    inside = ~SEPARATORS[data]
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = inside[:-1]
    filled = offsets[:-1][offsets[1:] > offsets[:-1]]
    before[filled] = False
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = inside[1:]
    after[offsets[1:][offsets[1:] > offsets[:-1]] - 1] = False
    starts, ends = np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, codes: np.ndarray = BYTE_CODES) -> np.ndarray:
    return mix(span_hash(prefix_hash(codes[data]), starts, ends) + (ends - starts).astype(U64))


def sliding_argmin(x: np.ndarray, w: int) -> np.ndarray:
    """Place of the leftmost minimum of each w consecutive values (n - w + 1 of them). Blocks of w values have running
    minima from either end; a window is the end of one block and the beginning of the next."""
    n = len(x)
    if n < w:
        return np.zeros(0, np.int64)
    pad = -n % w
    y = np.concatenate([x, np.full(pad, np.iinfo(x.dtype).max, x.dtype)]).reshape(-1, w)
    place = np.arange(n + pad).reshape(-1, w)
    least = np.minimum.accumulate(y, 1)
    fresh = np.ones(y.shape, bool)
    fresh[:, 1:] = y[:, 1:] < least[:, :-1]
    head = np.maximum.accumulate(np.where(fresh, place, 0), 1).ravel()[w - 1 : n]
    least = least.ravel()[w - 1 : n]
    most = np.minimum.accumulate(y[:, ::-1], 1)[:, ::-1]
    fresh[:, -1] = True
    fresh[:, :-1] = y[:, :-1] <= most[:, 1:]
    tail = np.minimum.accumulate(np.where(fresh, place, n + pad)[:, ::-1], 1)[:, ::-1].ravel()[: n - w + 1]
    return np.where(most.ravel()[: n - w + 1] <= least, tail, head)


def leftmost_minima(h: np.ndarray, w: int) -> np.ndarray:
    """Sorted positions that are the leftmost minimum of some window of w values: the same for equal windows."""
    at = sliding_argmin(h, w)
    return at[np.concatenate([[True], at[1:] != at[:-1]])] if len(at) else at


# --- keys that may be in a set, and components -------------------------------------------------------

def maybe_in(df: DataFrame, key: str, members: DataFrame, member_key: str, bits: int = 22) -> DataFrame:
    """Rows of `df` whose key may be among the members: a bit map of 2**bits bits, whatever the members' number.

    The map is a table of at most 2**(bits-6) rows, so its broadcast has a fixed bound. Rows that pass by accident
    only cost the exact join that has to follow.
    """
    place = lambda c: F.pmod(F.xxhash64(F.col(c)), F.lit(1 << bits))
    words = members.select(F.col(member_key).alias("_k")).select(place("_k").alias("_p")).select(F.shiftright("_p", 6).alias("_word"), F.expr("shiftleft(1L, cast(_p & 63 as int))").alias("_bit")).groupBy("_word").agg(F.bit_or("_bit").alias("_bits"))
    tagged = df.withColumn("_p", place(key)).withColumn("_word", F.shiftright("_p", 6))
    return tagged.join(F.broadcast(words), "_word").filter(F.expr("(_bits & shiftleft(1L, cast(_p & 63 as int))) != 0")).drop("_p", "_word", "_bits")


def _local_forest(batches):
    """Spanning forest of a partition's links: each node with the least node it reaches here."""
    parent: dict[int, int] = {}

    def find(x):
        root = x
        while (up := parent.get(root, root)) != root:
            root = up
        while (up := parent.get(x, x)) != root and up != x:
            parent[x], x = root, up
        return root

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            a, b = find(a), find(b)
            if a != b:
                if a > b:
                    a, b = b, a
                parent[b] = a
                parent.setdefault(a, a)
    nodes = [x for x in parent if find(x) != x]
    for i in range(0, len(nodes), 50_000):
        part = nodes[i : i + 50_000]
        yield pa.RecordBatch.from_arrays([pa.array(part, pa.int64()), pa.array([find(x) for x in part], pa.int64())], names=["a", "b"])


def components(links: DataFrame, keep: Durable) -> DataFrame:
    """(node, component): the least node reachable over links (a, b), for the nodes above it; others are absent.

    Each partition first shrinks its links to a forest; then nodes point at ever smaller neighbours (alternating
    large and small stars) until nothing changes. Links stay distributed, and each round is a written table. It ends when
    every node has one link and no link leads to a node that has one, however many rounds that takes.
    """
    edges = keep(links.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).filter("a <> b").mapInArrow(_local_forest, "a long, b long").distinct(), "cc0")
    i = 0
    while True:
        owners = edges.groupBy("a").agg(F.count("*").alias("n"))
        if owners.filter("n > 1").isEmpty() and edges.select(F.col("b").alias("a")).join(owners, "a", "left_semi").isEmpty():
            break
        i += 1
        both = edges.select("a", "b").union(edges.select(F.col("b"), F.col("a")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b")
        large = large.distinct()
        down = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(down, "a").select(F.col("b").alias("x"), F.col("a").alias("y"), "m")
        edges = keep(small.select(F.col("x").alias("a"), F.col("m").alias("b")).union(small.select(F.col("y").alias("a"), F.col("m").alias("b"))).filter("a <> b").distinct(), f"cc{i}")
        keep.release(f"cc{i - 1}")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component"))


def without(df: DataFrame, key: str, members: DataFrame, member_key: str, bits: int = 22, whole: bool = False) -> DataFrame:
    """Rows whose key is not among the members. Only rows that the bit map cannot clear are shuffled.

    whole: the map lists all its 2**(bits-6) words, so that the plan stays the same where there are no members.
    """
    place = lambda c: F.pmod(F.xxhash64(F.col(c)), F.lit(1 << bits))
    words = members.select(place(member_key).alias("_p")).select(F.shiftright("_p", 6).alias("_word"), F.expr("shiftleft(1L, cast(_p & 63 as int))").alias("_bit")).groupBy("_word").agg(F.bit_or("_bit").alias("_bits"))
    if whole:
        words = df.sparkSession.range(1 << (bits - 6)).withColumnRenamed("id", "_word").join(F.broadcast(words), "_word", "left")
    tagged = df.withColumn("_p", place(key)).withColumn("_word", F.shiftright("_p", 6)).join(F.broadcast(words), "_word", "inner" if whole else "left")
    tagged = tagged.withColumn("_maybe", F.expr("coalesce((_bits & shiftleft(1L, cast(_p & 63 as int))) != 0, false)")).drop("_p", "_word", "_bits")
    sure = tagged.filter("not _maybe").drop("_maybe")
    rest = tagged.filter("_maybe").drop("_maybe")
    return sure.union(rest.join(members.select(F.col(member_key).alias("_m")).distinct(), rest[key] == F.col("_m"), "left_anti"))


def whole_groups(batches, keys: list[str], most_rows: int = 50_000):
    """Tables of whole key groups from batches sorted by the keys; a group goes on over batches until it ends."""
    held: list[pa.Table] = []
    rows, least = 0, most_rows
    for batch in (x.slice(i, least) for x in batches for i in range(0, x.num_rows, least)):
        held.append(pa.Table.from_batches([batch]))
        rows += batch.num_rows
        if rows < most_rows:
            continue
        table = pa.concat_tables(held).combine_chunks()
        last = np.ones(table.num_rows, bool)
        for k in keys:
            c = table.column(k).to_numpy()
            last &= c == c[-1]
        other = np.flatnonzero(~last)
        cut = int(other[-1]) + 1 if len(other) else 0
        if cut:
            yield table.slice(0, cut).combine_chunks()
        held = [table.slice(cut)]
        rows = table.num_rows - cut
        most_rows = max(least, 2 * rows) if not cut else least
    if rows:
        yield pa.concat_tables(held).combine_chunks()


def spread_starts(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """first[i], first[i] + 1, ... count[i] values of each i, in one array."""
    total = int(count.sum())
    if not total:
        return np.zeros(0, np.int64)
    at = np.cumsum(count) - count
    return np.arange(total) - np.repeat(at - first, count)
