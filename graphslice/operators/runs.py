"""Run-length coding of ordered columns, and rank, select and lookup on the runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .durable import partitions, written

BATCH = 100_000


def rle_encode_window(df: DataFrame, pos: str, sym: str, batch: int | None = None) -> DataFrame:
    """(batch, run_no, start, len, head) of the sequence sym ordered by pos, one run store per `batch` positions.

    Null symbols equal each other. Without batch the whole sequence is one window and so one task: `rle_encode` has no
    such window.
    """
    key = F.lit(0).cast("long") if batch is None else F.floor(F.col(pos) / batch).cast("long")
    x = df.select(key.alias("batch"), F.col(pos).cast("long").alias("pos"), F.col(sym).alias("head"))
    w = Window.partitionBy("batch").orderBy("pos")
    x = x.withColumn("new", (F.row_number().over(w) == 1) | ~F.lag("head").over(w).eqNullSafe(F.col("head")))
    x = x.withColumn("run_no", F.sum(F.col("new").cast("long")).over(w.rowsBetween(Window.unboundedPreceding, 0)) - 1)
    return x.groupBy("batch", "run_no").agg(F.min("pos").alias("start"), F.count("*").alias("len"), F.first("head").alias("head"))


def rle_encode(df: DataFrame, pos: str, sym: str, batch: int | None = None) -> DataFrame:
    """The same for a sequence of any length: by batches, or for one run store by range partitions."""
    return rle_encode_window(df, pos, sym, batch) if batch else rle_encode_parallel(df, pos, sym)


def rle_encode_parallel(df: DataFrame, pos: str, sym: str) -> DataFrame:
    """One run store for the whole sequence: each position is a run of its own, and these are stitched."""
    return stitch(df.select(F.col(pos).cast("long").alias("start"), F.lit(1).cast("long").alias("len"), F.col(sym).alias("head")))


def stitch(parts: DataFrame) -> DataFrame:
    """(batch 0, run_no, start, len, head) of runs (start, len, head) that follow each other: neighbours of one head become one run.

    Range partitions are stitched by themselves; then only each partition's first and last run can join others, so the
    step in a single task sees two rows per partition.
    """
    from .graph import dense_ids

    spark = parts.sparkSession
    ranged = parts.select("start", "len", "head").repartitionByRange(partitions(spark), "start").sortWithinPartitions("start").withColumn("_m", F.monotonically_increasing_id())
    fixed = written(ranged.select("start", "len", "head", F.shiftright("_m", 33).alias("p")), "ranged")
    w = Window.partitionBy("p").orderBy("start")
    new = (F.row_number().over(w) == 1) | ~F.lag("head").over(w).eqNullSafe(F.col("head"))
    local = fixed.withColumn("new", new).withColumn("r", F.sum(F.col("new").cast("long")).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    runs = local.groupBy("p", "r").agg(F.min("start").alias("start"), F.sum("len").alias("len"), F.first("head").alias("head"))
    runs = written(runs.withColumn("last", F.max("r").over(Window.partitionBy("p"))), "runs")
    border = runs.filter("r = 1 or r = last")
    o = Window.orderBy("start")  # two rows per partition
    border = border.withColumn("_new", (F.row_number().over(o) == 1) | ~F.lag("head").over(o).eqNullSafe(F.col("head")) | ((F.lag("p").over(o) == F.col("p"))))
    border = border.withColumn("_g", F.sum(F.col("_new").cast("long")).over(o.rowsBetween(Window.unboundedPreceding, 0)))
    joined = border.groupBy("_g").agg(F.min("start").alias("start"), F.sum("len").alias("len"), F.min_by("head", "start").alias("head")).select("start", "len", "head")
    whole = runs.filter("r > 1 and r < last").select("start", "len", "head").union(joined)
    return dense_ids(whole, ["start"], "run_no").select(F.lit(0).cast("long").alias("batch"), "run_no", "start", "len", "head")


def rle_decode(runs: DataFrame) -> DataFrame:
    """(pos, sym); narrow."""
    return runs.select(F.explode(F.sequence(F.col("start"), F.col("start") + F.col("len") - 1)).alias("pos"), F.col("head").alias("sym"))


def rle_validate(runs: DataFrame, n: int) -> DataFrame:
    """Violations of maximality and coverage, by kind; no rows for sound runs."""
    w = Window.partitionBy("batch").orderBy("run_no")
    x = runs.withColumn("_h", F.lag("head").over(w)).withColumn("_e", F.lag(F.col("start") + F.col("len")).over(w))
    bad = x.filter("_e is not null and _h <=> head").select(F.lit("not maximal").alias("kind")).union(x.filter("_e <> start").select(F.lit("gap").alias("kind")))
    total = runs.agg(F.coalesce(F.sum("len"), F.lit(0)).alias("s")).filter(F.col("s") != n).select(F.lit("coverage").alias("kind"))
    return bad.union(total).groupBy("kind").agg(F.count("*").alias("n"))


def by_batch(runs: DataFrame, batch: int = BATCH) -> DataFrame:
    """Runs cut at multiples of `batch`, with the batch as key: a position's run is then found by an equi-join."""
    b = runs.withColumn("_b", F.explode(F.sequence((F.col("start") / batch).cast("long"), ((F.col("start") + F.col("len") - 1) / batch).cast("long"))))
    lo, hi = F.greatest("start", F.col("_b") * batch), F.least(F.col("start") + F.col("len"), (F.col("_b") + 1) * batch)
    return b.select(F.col("_b").alias("batch"), lo.alias("start"), (hi - lo).alias("len"), "head")


def lookup(runs: DataFrame, positions: DataFrame, pos: str, out: str = "head", batch: int = BATCH, spread: int = 8) -> DataFrame:
    """positions with the head of their run; positions outside all runs go. An as-of join by one sort: run starts and
    positions of a batch of ids stand in one order, and the last start's head is carried on, so the rows are the runs and
    the positions and never their pairs.

    A batch's positions are dealt over `spread` groups, each with the batch's runs, for the batches of hubs.
    """
    r = by_batch(runs, batch).select(F.col("batch").alias("_b"), F.explode(F.sequence(F.lit(0), F.lit(spread - 1))).alias("_g"), F.col("start").alias("_at"), F.lit(0).alias("_kind"), F.struct("head", (F.col("start") + F.col("len")).alias("end")).alias("_run"))
    columns = [c for c in positions.columns if c != out]
    p = positions.select((F.col(pos) / batch).cast("long").alias("_b"), F.pmod(F.xxhash64(*columns), F.lit(spread)).cast("int").alias("_g"), F.col(pos).cast("long").alias("_at"), F.lit(1).alias("_kind"), F.struct(*columns).alias("_row"))
    w = Window.partitionBy("_b", "_g").orderBy("_at", "_kind").rowsBetween(Window.unboundedPreceding, 0)
    both = r.unionByName(p, allowMissingColumns=True).withColumn("_run", F.last("_run", ignorenulls=True).over(w))
    return both.filter("_kind = 1 and _at < _run.end").select(*[F.col(f"_row.{c}").alias(c) for c in columns], F.col("_run.head").alias(out))


def lookup_few(runs: DataFrame, positions: DataFrame, pos: str, out: str = "head", batch: int = BATCH) -> DataFrame:
    """The same as an equi-join on the batch and a test of each of its runs: for few positions in a long run table, since
    a batch with r runs and p positions makes r x p rows before the test."""
    r = by_batch(runs, batch).select(F.col("batch").alias("_b"), F.col("start").alias("_s"), F.col("len").alias("_l"), F.col("head").alias(out))
    p = positions.withColumn("_k", (F.col(pos) / batch).cast("long"))
    return p.join(r, (F.col("_k") == F.col("_b")) & (F.col(pos) >= F.col("_s")) & (F.col(pos) < F.col("_s") + F.col("_l"))).drop("_k", "_b", "_s", "_l")


def rank(runs: DataFrame, positions: DataFrame, pos: str, bit: int = 1) -> DataFrame:
    """(pos, rank): run starts up to and including each position (bit 1), or the other positions (bit 0)."""
    ones = lookup(runs.select("batch", "run_no", "start", "len", (F.col("run_no") + 1).alias("head")), positions.select(pos), pos, "ones")
    return ones.select(pos, (F.col("ones") if bit else F.col(pos) + 1 - F.col("ones")).alias("rank"))


def select(runs: DataFrame, ranks: DataFrame, x: str, bit: int = 1) -> DataFrame:
    """(x, pos): place of the x-th run start (an equi-join on the run number), or of the x-th other position.

    Before the zeros of run number r there are start - r others, so the x-th one lies in the last run with fewer.
    """
    if bit:
        return ranks.select(x).join(runs.select((F.col("run_no") + 1).alias(x), F.col("start").alias("pos")), x)
    zeros = runs.filter("len > 1").select(F.lit(0).cast("long").alias("batch"), F.lit(0).cast("long").alias("run_no"), (F.col("start") - F.col("run_no") + 1).alias("start"), (F.col("len") - 1).alias("len"), F.col("run_no").alias("head"))
    return lookup(zeros, ranks.select(x), x, "_r").select(x, (F.col(x) + F.col("_r")).alias("pos"))


def rank_symbol(df: DataFrame, pos: str, sym: str) -> DataFrame:
    """(pos, sym, rank): occurrences of the symbol up to and including its position."""
    return df.select(F.col(pos).alias("pos"), F.col(sym).alias("sym"), F.count("*").over(Window.partitionBy(sym).orderBy(pos).rowsBetween(Window.unboundedPreceding, 0)).alias("rank"))


def select_symbol(df: DataFrame, pos: str, sym: str, asked: DataFrame) -> DataFrame:
    """asked(sym, x) with the position of the symbol's x-th occurrence."""
    r = rank_symbol(df, pos, sym).select("sym", F.col("rank").alias("x"), "pos")
    return asked.join(r, ["sym", "x"])


def run_stats(runs: DataFrame) -> DataFrame:
    """runs, positions, mean and largest length, and positions per run."""
    return runs.agg(F.count("*").alias("runs"), F.sum("len").alias("positions"), F.max("len").alias("longest"), F.round(F.avg("len"), 6).alias("mean_len"), F.percentile("len", 0.5).alias("median_len"))
