"""Simple graphs as DataFrames: cleaning, header, orientation, node streams and stream orders."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashes import hashed
from .durable import partitions, written


@dataclass(frozen=True)
class Graph:
    """edges (src < dst, unique, w), n nodes 0..n-1, m edges, total edge weight, optional node weights (id, c); unit: all edges
    are known to weigh one."""

    edges: DataFrame
    n: int
    m: int
    weight: float
    nodes: DataFrame | None = None
    unit: bool = False

    @property
    def spark(self):
        return self.edges.sparkSession

    def ids(self) -> DataFrame:
        return self.spark.range(self.n).withColumnRenamed("id", "id")


def simple_graph(pairs: DataFrame, weights: str = "unit", mode: str = "drop") -> DataFrame:
    """Undirected simple edges (src, dst, w) of raw pairs (src, dst[, w]): directions, self-loops and parallels go.

    weights: 'unit', 'count' of parallels or 'sum' of w. Null endpoints are dropped, or refused with mode='strict'. One
    shuffle, with partial sums before it.
    """
    if mode == "strict" and not pairs.filter("src is null or dst is null").isEmpty():
        raise ValueError("an edge has a null end")
    w = {"unit": F.lit(1.0), "count": F.count("*").cast("double"), "sum": F.sum("w").cast("double") if "w" in pairs.columns else F.count("*").cast("double")}[weights]
    ends = pairs.filter("src is not null and dst is not null and src <> dst").select(F.least("src", "dst").cast("long").alias("src"), F.greatest("src", "dst").cast("long").alias("dst"), *(["w"] if "w" in pairs.columns else []))
    if weights == "unit":
        return ends.select("src", "dst").distinct().withColumn("w", w)
    return ends.groupBy("src", "dst").agg(w.alias("w"))


def make_graph(edges: DataFrame, n: int, nodes: DataFrame | None = None, keep: bool = True) -> Graph:
    """Fix an edge table (written once) and count it; the driver gets four numbers."""
    edges = written(edges.select("src", "dst", "w"), "edges") if keep else edges
    m, weight, ones = edges.agg(F.count("*"), F.coalesce(F.sum("w"), F.lit(0.0)), F.count_if(F.col("w") == 1)).first()
    return Graph(edges, int(n), int(m), float(weight), nodes, m == ones)


def symmetric(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("id"), F.col("dst").alias("nbr"), "w").union(edges.select(F.col("dst").alias("id"), F.col("src").alias("nbr"), "w"))


def degrees(edges: DataFrame) -> DataFrame:
    return symmetric(edges).groupBy("id").agg(F.count("*").alias("degree"))


def meta(g: Graph) -> DataFrame:
    """One row: n, m, cw, ew, max_degree."""
    top = degrees(g.edges).agg(F.coalesce(F.max("degree"), F.lit(0)).alias("max_degree"))
    cw = g.nodes.agg(F.sum("c").alias("cw")) if g.nodes is not None else g.spark.range(1).select(F.lit(float(g.n)).alias("cw"))
    return top.crossJoin(cw).select(F.lit(g.n).cast("long").alias("n"), F.lit(g.m).cast("long").alias("m"), "cw", F.lit(g.weight).alias("ew"), "max_degree")


def forward_adjacency(edges: DataFrame) -> DataFrame:
    """Each edge once, at its later end: (id, nbr < id, w). Narrow."""
    return edges.select(F.col("dst").alias("id"), F.col("src").alias("nbr"), "w")


def check_topological(oriented: DataFrame) -> bool:
    """Every (src, dst) goes from a lower to a higher id."""
    return oriented.filter("src >= dst").isEmpty()


def subgraph(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """Edges with both ends among nodes(id)."""
    a, b = nodes.select(F.col("id").alias("src")), nodes.select(F.col("id").alias("dst"))
    return edges.join(a, "src", "left_semi").join(b, "dst", "left_semi").select("src", "dst", "w")


def validate(edges: DataFrame, n: int) -> DataFrame:
    """Violations of the edge invariants, by kind; no rows for a sound table."""
    bad = edges.filter("src is null or dst is null or src >= dst or src < 0").select(F.lit("order").alias("kind")).union(edges.filter(F.col("dst") >= n).select(F.lit("range").alias("kind"))).union(edges.groupBy("src", "dst").count().filter("count > 1").select(F.lit("parallel").alias("kind")))
    return bad.groupBy("kind").agg(F.count("*").alias("n"))


def stream_rows(g: Graph, later: bool = False) -> DataFrame:
    """Rows of the node stream: (id, nbr, w) with nbr < id (or the later neighbours), and a row with null nbr per node whose w is
    its node weight, so that isolated nodes stream too."""
    arcs = g.edges.select(F.col("src").alias("id"), F.col("dst").alias("nbr"), "w") if later else forward_adjacency(g.edges)
    own = g.ids().withColumn("c", F.lit(1.0)) if g.nodes is None else g.ids().join(g.nodes, "id", "left").select("id", F.coalesce(F.col("c").cast("double"), F.lit(1.0)).alias("c"))
    return arcs.select("id", "nbr", "w").union(own.select("id", F.lit(None).cast("long").alias("nbr"), F.col("c").alias("w")))


def stream_keys(g: Graph, later: bool = False) -> DataFrame:
    """The node stream as one column, key = id * 2^32 + nbr + 1 (0 for no neighbour), where no row has a weight of its own;
    `stream_rows` elsewhere. Keys sort as (id, nbr) do, nulls first."""
    if not g.unit or g.nodes is not None or g.n >= 1 << 31:
        return stream_rows(g, later)
    a, b = ("src", "dst") if later else ("dst", "src")
    arcs = g.edges.select((F.shiftleft(F.col(a).cast("long"), 32) + F.col(b) + 1).alias("key"))
    return arcs.union(g.ids().select(F.shiftleft("id", 32).alias("key")))


def dense_ids(df: DataFrame, by: list, name: str = "id") -> DataFrame:
    """Adds 0, 1, 2, ... in the order of `by`: range partitions, places inside them, and the partitions' offsets.

    Only one count per partition is added up, so no task or driver sees the whole order.
    """
    spark = df.sparkSession
    ranged = df.repartitionByRange(partitions(spark), *by).sortWithinPartitions(*by).withColumn("_m", F.monotonically_increasing_id())
    fixed = written(ranged.withColumn("_p", F.shiftright("_m", 33)).withColumn("_i", F.col("_m").bitwiseAND((1 << 33) - 1)).drop("_m"), "ranged")
    counts = sorted(fixed.groupBy("_p").agg(F.count("*").alias("c")).collect())
    rows, total = [], 0
    for p, c in counts:
        rows.append((p, total))
        total += c
    offsets = spark.createDataFrame(rows or [(0, 0)], "_p long, _o long")
    return fixed.join(F.broadcast(offsets), "_p").withColumn(name, F.col("_o") + F.col("_i")).drop("_p", "_i", "_o")


def reorder(g: Graph, by: str = "default", seed: int = 1) -> Graph:
    """The graph with its nodes renumbered: 'default', 'random' (hashed), 'degree' (descending) or 'bfs' levels from node 0."""
    if by == "default":
        return g
    ids = g.ids()
    if by == "random":
        keyed = ids.withColumn("k", hashed(F.col("id"), seed))
    elif by == "degree":
        keyed = ids.join(degrees(g.edges), "id", "left").select("id", (-F.coalesce("degree", F.lit(0))).alias("k"))
    elif by == "bfs":
        keyed = written(_levels(g), "levels")
    else:
        raise ValueError(by)
    new = written(dense_ids(keyed, ["k", "id"], "new").select("id", "new"), "order")
    a, b = new.select(F.col("id").alias("src"), F.col("new").alias("a")), new.select(F.col("id").alias("dst"), F.col("new").alias("b"))
    edges = g.edges.join(a, "src").join(b, "dst").select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), "w")
    nodes = None if g.nodes is None else g.nodes.join(new, "id").select(F.col("new").alias("id"), "c")
    return make_graph(edges, g.n, nodes)


def _levels(g: Graph) -> DataFrame:
    """(id, k): breadth-first level from the least node of every part; one join per level."""
    both = written(symmetric(g.edges), "arcs")
    level = written(g.ids().select("id", F.when(F.col("id") == 0, 0).alias("k")), "level")
    step = 0
    while True:
        front = both.join(level.filter(F.col("k") == step).select("id"), "id", "left_semi").select(F.col("nbr").alias("id")).distinct().withColumn("_f", F.lit(True))
        nxt = written(level.join(front, "id", "left").select("id", F.coalesce("k", F.when(F.col("_f"), step + 1)).alias("k")), "level")
        if nxt.filter(F.col("k") == step + 1).isEmpty():
            least = nxt.filter("k is null").agg(F.min("id")).first()[0]
            if least is None:
                return nxt
            nxt = written(nxt.withColumn("k", F.when(F.col("id") == least, step + 2).otherwise(F.col("k"))), "level")
            step += 1
        level, step = nxt, step + 1
