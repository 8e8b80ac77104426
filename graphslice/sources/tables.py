"""Graphs on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..operators.durable import written
from ..operators.graph import Graph, dense_ids, make_graph, simple_graph


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def size(spark, d, name: str) -> int:
    return read(spark, d, name).count()


def order_part(spark, d):
    n = size(spark, d, "orders")
    return simple_graph(read(spark, d, "lineitem").select(F.col("l_orderkey").alias("src"), (F.col("l_partkey") + n).alias("dst"))), n + size(spark, d, "part")


def order_supp(spark, d):
    n = size(spark, d, "orders")
    return simple_graph(read(spark, d, "lineitem").select(F.col("l_orderkey").alias("src"), (F.col("l_suppkey") + n).alias("dst"))), n + size(spark, d, "supplier")


def part_supp(spark, d):
    n = size(spark, d, "part")
    return simple_graph(read(spark, d, "lineitem").select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + n).alias("dst"))), n + size(spark, d, "supplier")


def _together(spark, d, key: str) -> DataFrame:
    """Pairs of keys that share an order; an order has a handful of lines, so the self-join stays near linear. Lines are dealt by
    order once: repeats go there, and both sides of the join read the same."""
    x = read(spark, d, "lineitem").select("l_orderkey", F.col(key).alias("src")).repartition("l_orderkey").distinct()
    y = x.withColumnRenamed("src", "dst")
    return simple_graph(x.join(y, "l_orderkey").filter("src < dst").select("src", "dst"))


def copurchase(spark, d):
    return _together(spark, d, "l_partkey"), size(spark, d, "part")


def coship(spark, d):
    return _together(spark, d, "l_suppkey"), size(spark, d, "supplier")


def _customer_lines(spark, d) -> DataFrame:
    return read(spark, d, "orders").select("o_orderkey", "o_custkey").join(read(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey", "l_suppkey"), "o_orderkey")


def cust_part(spark, d):
    n = size(spark, d, "customer")
    return simple_graph(_customer_lines(spark, d).select(F.col("o_custkey").alias("src"), (F.col("l_partkey") + n).alias("dst"))), n + size(spark, d, "part")


def cust_order(spark, d):
    n = size(spark, d, "customer")
    return simple_graph(read(spark, d, "orders").select(F.col("o_custkey").alias("src"), (F.col("o_orderkey") + n).alias("dst"))), n + size(spark, d, "orders")


def event_chain(spark, d):
    e = read(spark, d, "events").select("event_id", "user_id", "ts")
    nxt = F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return simple_graph(e.select(F.col("event_id").alias("src"), nxt.alias("dst"))), e.count()


def event_time(spark, d):
    """Ids at most 30 apart and at most ten minutes apart: cells of 3000 ids, and the 30 ids after each, are sorted and compared
    with themselves at growing offsets. An earlier event's own cell has all of its pairs, so repeats go there."""
    import numpy as np
    import pyarrow as pa

    e = read(spark, d, "events").select("event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    cells = F.array_distinct(F.array(F.expr("event_id div 3000"), F.expr("(event_id - 30) div 3000")))
    dealt = e.filter("event_id is not null and us is not null").select("event_id", "us", F.expr("event_id div 3000").alias("own"), F.explode(cells).alias("cell"))

    def pairs(key, t):
        ids, us, own = (t.column(c).to_numpy() for c in ("event_id", "us", "own"))
        order = np.lexsort((us, ids))
        ids, us, own = ids[order], us[order], own[order] == key[0].as_py()
        found, step = [np.zeros((2, 0), np.int64)], 1
        while step < len(ids):
            apart = ids[step:] - ids[:-step]
            if apart.min() > 30:
                break
            near = np.flatnonzero((apart > 0) & (apart <= 30) & (np.abs(us[step:] - us[:-step]) <= 600_000_000) & own[:-step])
            found.append(np.stack([ids[near], ids[near + step]]))
            step += 1
        src, dst = np.concatenate(found, 1)
        if (ids[1:] == ids[:-1]).any():
            src, dst = np.unique(np.stack([src, dst]), axis=1)
        return pa.table({"src": src, "dst": dst})

    return dealt.groupBy("cell").applyInArrow(pairs, "src long, dst long").select("src", "dst", F.lit(1.0).alias("w")), e.count()


def doc_lines(spark, d, least: int = 20, most: int = 50):
    """Documents that share a line of 20 characters or more which 2 to 50 documents have. A document's repeated lines go
    before lines are dealt, which is done once: both sides of the join read the same exchange."""
    docs = read(spark, d, "documents").select("doc_id", "text")
    own = F.array_distinct(F.transform(F.split("text", "\n"), F.trim))
    lines = docs.select("doc_id", F.explode(own).alias("l")).filter(F.length("l") >= least).repartition("l").distinct()
    x = lines.withColumn("n", F.count("*").over(Window.partitionBy("l"))).filter(f"n between 2 and {most}")
    return simple_graph(x.select("l", F.col("doc_id").alias("src")).join(x.select("l", F.col("doc_id").alias("dst")), "l").filter("src < dst").select("src", "dst")), docs.count()


def emb_cos(spark, d, least: float = 0.25, block: int = 500, most: int = 4096):
    """Vectors at a cosine of 0.25 or more: blocks of vectors meet in pairs, each pair by matrix products of a strip.

    Blocks grow with the table from `block` to `most` vectors, so that up to 32 * most vectors each is sent at most 32
    times. A pair of ids meets in one pair of blocks only, so repeats go there. Null vectors link with nothing."""
    import numpy as np
    import pyarrow as pa

    v = read(spark, d, "embeddings").select("vec_id", F.col("embedding").alias("v"))
    n = v.count()
    blocks = max(1, -(-n // min(most, max(block, -(-n // 32)))))
    own = v.filter("vec_id is not null and v is not null").withColumn("b", F.pmod("vec_id", F.lit(blocks)).cast("int")).withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    dealt = own.select(F.least("b", "o").alias("i"), F.greatest("b", "o").alias("j"), "b", "vec_id", "v")

    def pairs(key, t):
        t = t.combine_chunks()
        ids, part, column = t.column("vec_id").to_numpy(), t.column("b").to_numpy(), t.column("v").chunk(0)
        x = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
        x = x.reshape(len(ids), -1)
        if (np.diff(column.offsets.to_numpy()) != x.shape[1]).any():
            raise ValueError("vectors differ in length")
        with np.errstate(all="ignore"):  # a zero vector has no cosine
            x /= np.sqrt((x * x).sum(1))[:, None]
        left = np.flatnonzero(part == key[0].as_py())
        right = np.flatnonzero(part == key[1].as_py())
        columns, found = x[right].T, []
        for i in range(0, len(left), 512):
            r, c = np.nonzero(x[left[i : i + 512]] @ columns >= least)
            a, b = ids[left[i + r]], ids[right[c]]
            ok = a < b if key[0] == key[1] else a != b
            found.append(np.stack([np.minimum(a, b)[ok], np.maximum(a, b)[ok]]))
        src, dst = np.concatenate(found, 1) if found else np.zeros((2, 0), np.int64)
        if len(np.unique(ids)) < len(ids):
            src, dst = np.unique(np.stack([src, dst]), axis=1)
        return pa.table({"src": src, "dst": dst})

    return dealt.groupBy("i", "j").applyInArrow(pairs, "src long, dst long").select("src", "dst", F.lit(1.0).alias("w")), n


def page_anchor(spark, d):
    pages = read(spark, d, "pages").select("page_id", "html")
    n = pages.count()
    links = pages.select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), F.lit(1)))).alias("path"))
    paths = written(dense_ids(links.select("path").distinct(), ["path"], "rank"), "paths")
    return simple_graph(links.join(paths, "path").select(F.col("page_id").alias("src"), (F.col("rank") + n).alias("dst"))), n + paths.count()


def conv(spark, d):
    """Turns of one conversation, all with each other; numbered by conversation and turn."""
    turns = written(dense_ids(read(spark, d, "conversations").select("conv_id", "turn"), ["conv_id", "turn"], "node"), "turns")
    a, b = turns.select("conv_id", F.col("node").alias("src")), turns.select("conv_id", F.col("node").alias("dst"))
    return simple_graph(a.join(b, "conv_id").filter("src < dst").select("src", "dst")), turns.count()


def hierarchy(spark, d):
    c = size(spark, d, "customer")
    e = read(spark, d, "nation").select(F.col("n_regionkey").cast("long").alias("src"), (F.col("n_nationkey") + 5).cast("long").alias("dst"))
    e = e.union(read(spark, d, "customer").select((F.col("c_nationkey") + 5).cast("long"), F.col("c_custkey") + 30))
    e = e.union(read(spark, d, "supplier").select((F.col("s_nationkey") + 5).cast("long"), F.col("s_suppkey") + 30 + c))
    return simple_graph(e), 30 + c + size(spark, d, "supplier")


def cust_supp_weighted(spark, d):
    n = size(spark, d, "customer")
    x = _customer_lines(spark, d).select("o_orderkey", F.col("o_custkey").alias("src"), (F.col("l_suppkey") + n).alias("dst")).distinct()
    return simple_graph(x.select("src", "dst"), "count"), n + size(spark, d, "supplier")


BUILDERS = {f.__name__: f for f in (order_part, order_supp, part_supp, copurchase, coship, cust_part, cust_order, event_chain, event_time, doc_lines, emb_cos, page_anchor, conv, hierarchy, cust_supp_weighted)}

#: those that pair rows with each other have the most edges for a row
PAIRED = ("event_time", "emb_cos", "copurchase", "coship", "doc_lines", "conv")


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    edges, n = BUILDERS[name](spark, sf_dir)
    return make_graph(edges, n)


__all__ = ["BUILDERS", "PAIRED", "graph", "read"]
