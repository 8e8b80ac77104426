"""Quality and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.score import limit
from .stores import head_bits


def edge_blocks(edges: DataFrame, assign: DataFrame, hint: str | None = None) -> DataFrame:
    """edges with src_block and dst_block; hint: 'broadcast', 'merge' or 'shuffle_hash' for the labels' side."""
    a, b = assign.select(F.col("id").alias("src"), F.col("block").alias("src_block")), assign.select(F.col("id").alias("dst"), F.col("block").alias("dst_block"))
    if hint:
        a, b = a.hint(hint), b.hint(hint)
    return edges.join(a, "src").join(b, "dst")


def edge_cut(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """One row: cut (weight of edges between blocks), cut_edges, edges."""
    x = edge_blocks(edges, assign)
    return x.agg(F.coalesce(F.sum(F.when(F.col("src_block") != F.col("dst_block"), F.col("w"))), F.lit(0.0)).alias("cut"), F.coalesce(F.sum((F.col("src_block") != F.col("dst_block")).cast("long")), F.lit(0)).alias("cut_edges"), F.count("*").alias("edges"))


def relative_cut(edges: DataFrame, assign: DataFrame) -> DataFrame:
    return edge_cut(edges, assign).select((F.col("cut_edges") / F.col("edges")).alias("relative_cut"))


def block_sizes(assign: DataFrame, k: int, weights: DataFrame | None = None) -> DataFrame:
    """(block, size) of all k blocks, empty ones too."""
    x = assign if weights is None else assign.join(weights, "id")
    c = F.count("*").cast("double") if weights is None else F.sum("c")
    s = x.groupBy("block").agg(c.alias("size"))
    return assign.sparkSession.range(k).select(F.col("id").cast("int").alias("block")).join(F.broadcast(s), "block", "left").select("block", F.coalesce("size", F.lit(0.0)).alias("size"))


def balance(assign: DataFrame, k: int, n: float, eps: float = 0.03, weights: DataFrame | None = None) -> DataFrame:
    """One row: largest size, the limit, whether it holds, and the imbalance largest / (n / k) - 1."""
    return block_sizes(assign, k, weights).agg(F.max("size").alias("largest")).select("largest", F.lit(limit(n, k, eps)).cast("long").alias("allowed"), (F.col("largest") <= limit(n, k, eps)).alias("feasible"), F.round(F.col("largest") / (n / k) - 1, 6).alias("imbalance"))


def quotient(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """(a, b, edges) between blocks a <= b."""
    return edge_blocks(edges, assign).groupBy(F.least("src_block", "dst_block").alias("a"), F.greatest("src_block", "dst_block").alias("b")).agg(F.count("*").alias("edges"))


def boundary(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """(block, nodes): nodes with a neighbour in another block."""
    x = edge_blocks(edges, assign).filter("src_block <> dst_block")
    ends = x.select(F.col("src").alias("id"), F.col("src_block").alias("block")).union(x.select("dst", "dst_block"))
    return ends.groupBy("block").agg(F.countDistinct("id").alias("nodes"))


def structure_sizes(runs: DataFrame, n: int, k: int, corr_bits: int | str = "auto") -> DataFrame:
    """Bits of a placement in each form: dense 32-bit, packed, plain bits and heads, run list (and learned, by fit)."""
    b = head_bits(k)
    r = runs.agg(F.count("*").alias("r"))
    return r.select(F.lit(32 * n).cast("long").alias("dense32"), F.lit(n * b).cast("long").alias("packed"), (F.lit(n) + F.col("r") * b).cast("long").alias("plain"), (F.col("r") * (b + 64)).cast("long").alias("runs"))


def queue_profile(edges: DataFrame) -> DataFrame:
    """(id, waiting): messages that are in the queue after each node has been placed and has sent its own."""
    d = edges.select(F.col("src").alias("id"), F.lit(1).alias("x")).union(edges.select("dst", F.lit(-1)))
    d = d.groupBy("id").agg(F.sum("x").alias("x"))
    cell = 4096
    cells = d.groupBy(F.expr(f"id div {cell}").alias("c")).agg(F.sum("x").alias("t"))
    below = cells.withColumn("b", F.coalesce(F.sum("t").over(Window.orderBy("c").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("c", "b")
    inner = d.withColumn("c", F.expr(f"id div {cell}")).withColumn("s", F.sum("x").over(Window.partitionBy("c").orderBy("id").rowsBetween(Window.unboundedPreceding, 0)))
    return inner.join(below, "c").select("id", (F.col("s") + F.col("b")).cast("long").alias("waiting"))


# --- over measurements (algo, graph, k, metric, value) ------------------------------------------------

def geomean(m: DataFrame) -> DataFrame:
    return m.groupBy("algo", "metric").agg(F.round(F.exp(F.avg(F.log("value"))), 6).alias("geomean"))


def _against(m: DataFrame, a: str, b: str) -> DataFrame:
    x, y = m.filter(F.col("algo") == a), m.filter(F.col("algo") == b).select("graph", "k", "metric", F.col("value").alias("other"))
    return x.join(y, ["graph", "k", "metric"])


def relative_value(m: DataFrame, a: str, b: str) -> DataFrame:
    return _against(m, a, b).select("graph", "k", "metric", F.round(F.col("value") / F.col("other"), 6).alias("relative"))


def improvement(m: DataFrame, a: str, b: str) -> DataFrame:
    """(a / b - 1) * 100, negative where a is smaller, and the gain b / a - 1 in percent."""
    return _against(m, a, b).select("graph", "k", "metric", F.round((F.col("value") / F.col("other") - 1) * 100, 6).alias("improvement"), F.round((F.col("other") / F.col("value") - 1) * 100, 6).alias("quality_gain"))


def performance_profile(m: DataFrame, taus: list[float]) -> DataFrame:
    """(algo, metric, tau, share): instances on which an algorithm's value is at most tau times the best. A null value
    (no result) is never within any factor."""
    best = F.min("value").over(Window.partitionBy("graph", "k", "metric"))
    x = m.withColumn("ratio", F.when(best > 0, F.col("value") / best).otherwise(F.when(F.col("value") == 0, 1.0)))
    x = x.withColumn("tau", F.explode(F.array(*[F.lit(float(t)) for t in taus])))
    return x.groupBy("algo", "metric", "tau").agg(F.round(F.avg(F.coalesce((F.col("ratio") <= F.col("tau")).cast("double"), F.lit(0.0))), 6).alias("share"))


def win_rate(m: DataFrame, a: str, b: str) -> DataFrame:
    """(metric, wins, ties) of a over b, as shares of their common instances."""
    return _against(m, a, b).groupBy("metric").agg(F.round(F.avg((F.col("value") < F.col("other")).cast("double")), 6).alias("wins"), F.round(F.avg((F.col("value") == F.col("other")).cast("double")), 6).alias("ties"))


def feasible(m: DataFrame, budget_bits: float) -> DataFrame:
    """(algo, graph, k, feasible): whether the structure that holds a placement (metric 'bits') stays within a memory budget."""
    return m.filter("metric = 'bits'").select("algo", "graph", "k", (F.col("value") <= budget_bits).alias("feasible"))


def run_bits(assign: DataFrame, k: int) -> DataFrame:
    """One row: the bits of a placement's run list, from one equi-join of each id with the one before it."""
    last = assign.select((F.col("id") + 1).alias("id"), F.col("block").alias("before"))
    return assign.join(last, "id").agg(((F.sum((F.col("block") != F.col("before")).cast("long")) + 1) * (head_bits(k) + 64)).cast("double").alias("bits"))
