"""Adjacency text and edge lists, and sinks for placements and runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import Graph, dense_ids, make_graph, simple_graph, symmetric
from ..operators.durable import written


def read_adjacency(spark: SparkSession, path: str) -> Graph:
    """A graph from text: a header `n m [fmt]`, then line i with the 1-based neighbours of node i (an empty line for an
    isolated node; fmt 1 or 11: each neighbour followed by its weight; 10 or 11: the node's weight first; % starts a
    comment). Lines are numbered by file offset, so files may be cut and read in parallel."""
    lines = spark.read.text(path, lineSep="\n").select("value", F.col("_metadata.file_path").alias("f"), F.col("_metadata.file_block_start").alias("o"), F.monotonically_increasing_id().alias("i"))
    lines = written(lines.filter(~F.startswith(F.ltrim("value"), F.lit("%"))), "lines")
    numbered = written(dense_ids(lines, ["f", "o", "i"], "line"), "numbered")
    head = numbered.filter("line = 0").first()["value"].split()
    n, fmt = int(head[0]), head[2] if len(head) > 2 else "0"
    body = numbered.filter((F.col("line") > 0) & (F.col("line") <= n)).select((F.col("line") - 1).alias("id"), F.filter(F.split(F.trim("value"), r"\s+"), lambda x: x != "").alias("t"))
    nodes = None
    if fmt.zfill(3)[1] == "1":
        nodes = written(body.select("id", F.coalesce(F.get("t", 0).cast("double"), F.lit(1.0)).alias("c")), "weights")
        body = body.select("id", F.slice("t", F.lit(2), F.greatest(F.size("t") - 1, F.lit(0))).alias("t"))
    if fmt.zfill(3)[2] == "1":
        e = body.select("id", F.posexplode("t").alias("p", "x"), "t").filter("p % 2 = 0").select(F.col("id").alias("src"), (F.col("x").cast("long") - 1).alias("dst"), F.get("t", F.col("p") + 1).cast("double").alias("w")).filter("src < dst")
        edges = simple_graph(e, "sum")
    else:
        edges = simple_graph(body.select(F.col("id").alias("src"), F.explode("t").alias("x")).select("src", (F.col("x").cast("long") - 1).alias("dst")))
    return make_graph(edges, n, nodes)


def write_adjacency(g: Graph, path: str) -> None:
    """Text files in id order, the first of which begins with the header."""
    near = symmetric(g.edges).groupBy("id").agg(F.array_join(F.transform(F.sort_array(F.collect_list("nbr")), lambda x: (x + 1).cast("string")), " ").alias("value"))
    body = g.ids().join(near, "id", "left").select("id", F.coalesce("value", F.lit("")).alias("value"))
    head = g.spark.createDataFrame([(-1, f"{g.n} {g.m}")], "id long, value string")
    head.union(body).repartitionByRange("id").sortWithinPartitions("id").select("value").write.mode("overwrite").text(path)


def read_edges(spark: SparkSession, path: str, format: str = "csv", **options) -> DataFrame:
    """Raw pairs (src, dst[, w]) of an edge list in csv (sep=...), json, orc or parquet."""
    r = spark.read.options(**options)
    if format == "csv":
        r = r.schema("src long, dst long, w double")
    return r.format(format).load(path)


def write_edges(edges: DataFrame, path: str, format: str = "csv", **options) -> None:
    edges.write.mode("overwrite").options(**options).format(format).save(path)


def write_assignment(assign: DataFrame, path: str, format: str = "parquet", by_block: bool = False) -> None:
    """'text': one block per line in node order; else a table, on request partitioned by block."""
    if format == "text":
        assign.repartitionByRange("id").sortWithinPartitions("id").select(F.col("block").cast("string")).write.mode("overwrite").text(path)
    else:
        w = assign.sortWithinPartitions("block", "id").write.mode("overwrite").format(format)
        (w.partitionBy("block") if by_block else w).save(path)


def write_runs(runs: DataFrame, path: str) -> None:
    """The compressed placement, ordered by start."""
    runs.repartitionByRange("batch", "start").sortWithinPartitions("batch", "start").write.mode("overwrite").parquet(path)
