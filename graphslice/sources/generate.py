"""Graph generators by recomputation: every edge follows from hashes of ids, so no part has to ask another for it."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashes import hashed, hashed_numpy
from ..operators.durable import written
from ..operators.graph import dense_ids, simple_graph, symmetric


def gen_grid(spark: SparkSession, rows: int, cols: int, chunks: int = 8) -> tuple[DataFrame, int]:
    """A mesh with row-major ids; two projections of a range, no shuffle."""
    i = spark.range(0, rows * cols, 1, chunks)
    right = i.filter(F.col("id") % cols < cols - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    down = i.filter(F.col("id") < (rows - 1) * cols).select(F.col("id").alias("src"), (F.col("id") + cols).alias("dst"))
    return right.union(down).withColumn("w", F.lit(1.0)), rows * cols


def gen_ba(spark: SparkSession, n: int, d: int, seed: int = 42, chunks: int = 8) -> tuple[DataFrame, int]:
    """Preferential attachment, d edges per node. Endpoint slots 2 e hold edge e's source e div d; slot 2 e + 1 copies a
    uniformly hashed earlier slot, and that one its own, until a source slot is met: the chain is recomputed, two hashes
    long on average, so nothing is shuffled before parallels are removed."""

    def ends(batches):
        for b in batches:
            e = b.column(0).to_numpy()
            slot = 2 * e + 1
            while True:
                odd = np.flatnonzero(slot & 1)
                if not len(odd):
                    break
                s = slot[odd]
                slot[odd] = hashed_numpy(s, seed) % s
            yield pa.RecordBatch.from_arrays([pa.array(e // d), pa.array(slot // 2 // d)], names=["src", "dst"])

    return simple_graph(spark.range(0, n * d, 1, chunks).mapInArrow(ends, "src long, dst long")), n


def gen_rgg(spark: SparkSession, n: int, radius: float, seed: int = 42, chunks: int = 8) -> tuple[DataFrame, int]:
    """Random geometric graph in the unit square; ids follow the cells, row by row, so that near nodes have near ids.

    Cells are at least `radius` wide, and each point meets the points of its own and eight neighbouring cells by an
    equi-join on the cell. The points do not depend on `chunks`.
    """
    side = max(1, math.floor(1 / radius))
    i = F.col("id")
    p = spark.range(0, n, 1, chunks).select((hashed(2 * i, seed) / 2147483647.0).alias("x"), (hashed(2 * i + 1, seed) / 2147483647.0).alias("y"), i.alias("point"))
    p = p.withColumn("cx", F.floor(F.col("x") * side)).withColumn("cy", F.floor(F.col("y") * side))
    p = written(dense_ids(p, ["cy", "cx", "point"], "id"), "points")
    near = p.select(F.col("id").alias("dst"), F.col("x").alias("x2"), F.col("y").alias("y2"), F.explode(F.array(*[F.struct((F.col("cx") + a).alias("cx"), (F.col("cy") + b).alias("cy")) for a in (-1, 0, 1) for b in (-1, 0, 1)])).alias("c")).select("dst", "x2", "y2", "c.cx", "c.cy")
    e = p.select(F.col("id").alias("src"), "x", "y", "cx", "cy").join(near, ["cx", "cy"]).filter("src < dst")
    dx, dy = F.col("x") - F.col("x2"), F.col("y") - F.col("y2")
    return e.filter(dx * dx + dy * dy <= radius * radius).select("src", "dst", F.lit(1.0).alias("w")), n


def gen_rhg(spark: SparkSession, n: int, degree: float, gamma: float = 2.9, seed: int = 42, chunks: int = 8) -> tuple[DataFrame, int]:
    """Random hyperbolic graph: radial bands cut in angular cells; a band's points look into each band's cells within the
    largest angle at which the two bands can still be near, an equi-join on (band, cell). Ids follow the angle."""
    alpha = (gamma - 1) / 2
    xi = alpha / (alpha - 0.5)
    big = 2 * math.log(2 * n * xi * xi / (math.pi * degree))
    bands = max(1, int(big / 2))
    inner = [big / 2 * (1 + b / bands) if b else 0.0 for b in range(bands)] + [big]
    cosh_a = math.cosh(alpha * big) - 1

    def reach(r1: float, r2: float) -> float:
        if r1 + r2 <= big:
            return math.pi
        x = (math.cosh(r1) * math.cosh(r2) - math.cosh(big)) / (math.sinh(r1) * math.sinh(r2))
        return math.acos(max(-1.0, min(1.0, x)))

    width = [max(reach(inner[b], inner[b]) if b else math.pi, 2 * math.pi / max(4, n)) for b in range(bands)]
    cells = [max(1, int(2 * math.pi / w)) for w in width]
    i = F.col("id")
    u, v = (hashed(2 * i, seed) + 0.5) / 2147483647.0, (hashed(2 * i + 1, seed) + 0.5) / 2147483647.0
    y = 1 + u * cosh_a
    p = spark.range(0, n, 1, chunks).select(i.alias("point"), (v * 2 * math.pi).alias("phi"), (F.log(y + F.sqrt(y * y - 1)) / alpha).alias("r"))
    band = F.lit(0)
    for b in range(1, bands):
        band = F.when(F.col("r") >= inner[b], b).otherwise(band)
    p = p.withColumn("band", band)
    count = F.element_at(F.array(*[F.lit(c) for c in cells]), F.col("band") + 1)
    p = p.withColumn("cell", F.floor(F.col("phi") / (2 * math.pi) * count).cast("int"))
    p = written(dense_ids(p, ["phi", "point"], "id"), "points")
    looks = []
    for a in range(bands):
        for b in range(a, bands):
            span = reach(inner[a], inner[b]) if a or b else math.pi
            steps = min(cells[b] // 2, math.ceil(span / (2 * math.pi) * cells[b]) + 1)
            base = F.floor(F.col("phi") / (2 * math.pi) * cells[b])
            around = F.sequence(F.lit(-steps), F.lit(steps)) if 2 * steps + 1 < cells[b] else F.sequence(F.lit(0), F.lit(cells[b] - 1))
            looks.append(p.filter(F.col("band") == a).select("id", "phi", "r", F.lit(a).alias("own"), F.lit(b).alias("band"), F.explode(around).alias("s")).withColumn("cell", F.pmod(base + F.col("s"), F.lit(cells[b])).cast("int")))
    asked = looks[0]
    for x in looks[1:]:
        asked = asked.union(x)
    q = p.select(F.col("id").alias("id2"), F.col("phi").alias("phi2"), F.col("r").alias("r2"), "band", "cell")
    e = asked.join(q, ["band", "cell"]).filter("id <> id2")
    near = F.cosh("r") * F.cosh("r2") - F.sinh("r") * F.sinh("r2") * F.cos(F.col("phi") - F.col("phi2")) <= math.cosh(big)
    return simple_graph(e.filter(near).select(F.col("id").alias("src"), F.col("id2").alias("dst"))), n


def gen_rdg(spark: SparkSession, n: int, seed: int = 42, cells: int = 4, chunks: int = 8) -> tuple[DataFrame, int]:
    """Random Delaunay graph in the unit square: every strip is triangulated with a halo of its neighbours, and keeps the
    triangles whose centre is its own; halos double until all their circles lie inside. Ids follow x, then y."""
    i = F.col("id")
    p = spark.range(0, n, 1, chunks).select(i.alias("point"), (hashed(2 * i, seed) / 2147483647.0).alias("x"), (hashed(2 * i + 1, seed) / 2147483647.0).alias("y"))
    p = written(dense_ids(p, ["x", "y", "point"], "id"), "points")
    own = F.least(F.floor(F.col("x") * cells), F.lit(cells - 1)).cast("int")
    halo = 1
    while True:
        width = halo

        def strip_edges(key, t):
            c = key[0].as_py()
            ids, pts = t.column("id").to_numpy(), np.stack([t.column("x").to_numpy(), t.column("y").to_numpy()], 1)
            lo, hi = (c - width) / cells if c > width else -1e18, (c + width + 1) / cells if c + width + 1 < cells else 1e18
            left, right = c / cells if c else -1e18, (c + 1) / cells if c < cells - 1 else 1e18
            found = set()
            for a, b, d in triangulate(pts):
                (cx, _), r = _circle(pts[a], pts[b], pts[d])
                if left <= cx < right:
                    if cx - r < lo or cx + r > hi:  # a point outside the halo might lie in the circle
                        found.add((-1, -1))
                    for x, y in ((a, b), (b, d), (a, d)):
                        found.add((min(ids[x], ids[y]), max(ids[x], ids[y])))
            e = sorted(found)
            return pa.table({"src": pa.array([x for x, _ in e], pa.int64()), "dst": pa.array([y for _, y in e], pa.int64())})

        strips = F.transform(F.sequence(F.lit(-width), F.lit(width)), lambda k: own + k)
        dealt = p.select("id", "x", "y", F.explode(strips).alias("strip")).filter(f"strip >= 0 and strip < {cells}")
        pairs = written(dealt.groupBy("strip").applyInArrow(strip_edges, "src long, dst long"), "triangles")
        if width >= cells or pairs.filter("src < 0").isEmpty():
            return simple_graph(pairs.filter("src >= 0")), n
        halo *= 2


def _circle(a, b, c):
    d = 2 * (a[0] * (b[1] - c[1]) + b[0] * (c[1] - a[1]) + c[0] * (a[1] - b[1]))
    if not d:
        return (0.0, 0.0), float("inf")
    s, t, u = a @ a, b @ b, c @ c
    x = (s * (b[1] - c[1]) + t * (c[1] - a[1]) + u * (a[1] - b[1])) / d
    y = (s * (c[0] - b[0]) + t * (a[0] - c[0]) + u * (b[0] - a[0])) / d
    return (x, y), math.hypot(a[0] - x, a[1] - y)


def triangulate(pts: np.ndarray) -> list[tuple[int, int, int]]:
    """Delaunay triangles by insertion: the triangles whose circle holds the new point are replaced by a fan."""
    n = len(pts)
    if n < 3:
        return []
    far = np.concatenate([pts, [[-50.0, -50.0], [50.0, -50.0], [0.0, 80.0]]])
    tri = np.array([[n, n + 1, n + 2]])
    mid = np.array([_circle(*far[tri[0]])[0]])
    rad = np.array([_circle(*far[tri[0]])[1] ** 2])
    for p in range(n):
        hit = ((mid - far[p]) ** 2).sum(1) < rad
        bad = tri[hit]
        sides = np.sort(np.concatenate([bad[:, [0, 1]], bad[:, [1, 2]], bad[:, [0, 2]]]), axis=1)
        sides, count = np.unique(sides, axis=0, return_counts=True)
        rim = sides[count == 1]
        fan = np.concatenate([rim, np.full((len(rim), 1), p)], 1)
        circles = [_circle(*far[t]) for t in fan]
        tri = np.concatenate([tri[~hit], fan])
        mid = np.concatenate([mid[~hit], np.array([c[0] for c in circles])])
        rad = np.concatenate([rad[~hit], np.array([c[1] ** 2 for c in circles])])
    return [tuple(int(v) for v in t) for t in tri if (t < n).all()]


def as_adjacency(edges: DataFrame, n: int) -> DataFrame:
    """(id, neighbours array) of all nodes in id order of the partitions; arrays, so for graphs without huge hubs."""
    spark = edges.sparkSession
    near = symmetric(edges).groupBy("id").agg(F.sort_array(F.collect_list("nbr")).alias("nbrs"))
    return spark.range(n).join(near, "id", "left").select("id", F.coalesce("nbrs", F.array().cast("array<long>")).alias("nbrs"))
