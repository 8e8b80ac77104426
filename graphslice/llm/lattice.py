"""Embedding near-duplicates by lattice hashing: random projections decoded to E8 points, neighbouring cells probed."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Durable, components, mix, partitions, whole_groups

U64 = np.uint64


@dataclass(frozen=True)
class Lattice:
    """tables: projections to 8 dimensions; scale: lattice spacing against a unit vector; probes: cells visited per table
    besides the own one; least: cosine; cell: vectors of a cell beyond which it is dealt over pairs of blocks.

    With these values a pair at a cosine of exactly 0.93 in 64 dimensions meets in one table in 97 of 100 cases, so
    three tables miss some 3 of 100,000 such pairs, and fewer the closer they are."""

    tables: int = 3
    scale: float = 0.22
    probes: int = 12
    least: float = 0.93
    cell: int = 2000
    seed: int = 5


def closest_integer_point(x: np.ndarray) -> np.ndarray:
    """Nearest point of D8 (integers with an even sum): round, and if the sum is odd re-round the worst coordinate."""
    r = np.rint(x)
    off = x - r
    odd = np.flatnonzero(r.sum(1).astype(np.int64) & 1)
    if len(odd):
        k = np.abs(off[odd]).argmax(1)
        step = np.where(off[odd, k] >= 0, 1.0, -1.0)
        r[odd, k] += step
    return r


def decode_e8(x: np.ndarray) -> np.ndarray:
    """Nearest E8 point of each row, doubled to be whole numbers: the better of D8 and D8 shifted by one half."""
    a = closest_integer_point(x)
    b = closest_integer_point(x - 0.5) + 0.5
    near = ((x - a) ** 2).sum(1) <= ((x - b) ** 2).sum(1)
    return np.rint(2 * np.where(near[:, None], a, b)).astype(np.int64)


def minimal_vectors() -> np.ndarray:
    """The 240 shortest vectors of E8, doubled: the steps to neighbouring cells."""
    out = []
    for i in range(8):
        for j in range(i + 1, 8):
            for s in (2, -2):
                for t in (2, -2):
                    v = [0] * 8
                    v[i], v[j] = s, t
                    out.append(v)
    for bits in range(256):
        if bin(bits).count("1") % 2 == 0:
            out.append([-1 if bits >> i & 1 else 1 for i in range(8)])
    return np.array(out, np.int64)


STEPS = minimal_vectors()


def projections(dim: int, l: Lattice) -> np.ndarray:
    """tables x dim x 8, with orthonormal columns."""
    rng = np.random.default_rng(l.seed)
    out = np.zeros((l.tables, dim, 8))
    for t in range(l.tables):
        a = rng.standard_normal((max(dim, 8), 8))
        out[t] = np.linalg.qr(a)[0][:dim] if dim >= 8 else a[:dim] / np.sqrt(8)
    return out


def unit_rows(raw: np.ndarray) -> np.ndarray:
    x = raw.astype(np.float64)
    return x / np.sqrt((x * x).sum(1))[:, None]


def _codes(points: np.ndarray) -> np.ndarray:
    h = np.full(points.shape[:-1], 0x243F6A8885A308D3, U64)
    for i in range(8):
        h = mix(h + points[..., i].astype(np.int64).view(U64))
    return h.view(np.int64)


def cells(x: np.ndarray, projection: np.ndarray, l: Lattice) -> tuple[np.ndarray, np.ndarray]:
    """Own cell (rows) and the probed neighbouring cells (rows x probes) of unit rows in one table, as hashes.

    The neighbours are those whose centres are closest to the projected point.
    """
    y = x @ projection / l.scale
    home = decode_e8(y)
    off = 2 * y - home
    # distance to home + step, up to what all steps share: all 240 have the same length
    gain = off @ STEPS.T.astype(np.float64)
    best = np.argpartition(-gain, min(l.probes, 239), axis=1)[:, : l.probes]
    return _codes(home), _codes(home[:, None, :] + STEPS[best])


_ENTRY = pa.schema([("dim", pa.int32()), ("label", pa.int64()), ("tab", pa.int32()), ("cell", pa.int64()), ("home", pa.bool_()), ("id", pa.int64()), ("n", pa.int64()), ("vector", pa.binary())])


def _entries(l: Lattice):
    def run(batches):
        tables: dict[int, np.ndarray] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                piece = batch.slice(at, 1000)
                dims = piece.column("dim").to_numpy()
                for dim in np.unique(dims).tolist():
                    part = piece.filter(pa.array(dims == dim))
                    if dim not in tables:
                        tables = {dim: projections(dim, l)}
                    raw = part.column("vector").to_pylist()
                    x = unit_rows(np.frombuffer(b"".join(raw), np.float32).reshape(len(raw), dim))
                    for t in range(l.tables):
                        own, near = cells(x, tables[dim][t], l)
                        for cell, home in ((own[:, None], True), (near, False)):
                            row = np.repeat(np.arange(len(raw)), cell.shape[1])
                            take = part.take(pa.array(row))
                            yield pa.RecordBatch.from_arrays([take.column("dim"), take.column("label"), pa.array(np.full(len(row), t, np.int32)), pa.array(cell.ravel()), pa.array(np.full(len(row), home)), take.column("id"), take.column("n"), take.column("vector")], schema=_ENTRY)

    return run


def exact_cosine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Cosines of paired rows: double precision, sums in index order."""
    a, b = a.astype(np.float64), b.astype(np.float64)
    dot, na, nb = (np.zeros(len(a)) for _ in range(3))
    for i in range(a.shape[1]):
        dot += a[:, i] * b[:, i]
        na += a[:, i] * a[:, i]
        nb += b[:, i] * b[:, i]
    return dot / (np.sqrt(na) * np.sqrt(nb))


def _links(l: Lattice):
    """Links of whole cells: (id, links counted, a smaller partner or itself), per cell; every pair counts in one place only.

    A pair is found where one vector's home cell is the other's home or probe. It counts in the first table and, there,
    in the least cell in which it is found; both follow from the two vectors alone.
    """
    schema = pa.schema([("id", pa.int64()), ("links", pa.int64()), ("partner", pa.int64())])

    def found(tables, x, y):
        """First table in which unit rows x and y meet, and the cell hash there."""
        table, cell = np.full(len(x), -1), np.zeros(len(x), np.int64)
        for t in range(l.tables):
            todo = np.flatnonzero(table < 0)
            if not len(todo):
                break
            hx, nx = cells(x[todo], tables[t], l)
            hy, ny = cells(y[todo], tables[t], l)
            big = np.iinfo(np.int64).max
            in_y = np.where((hx == hy) | (nx == hy[:, None]).any(1), hy, big)  # met at y's home
            in_x = np.where((ny == hx[:, None]).any(1), hx, big)
            at = np.minimum(in_y, in_x)
            hit = at < big
            table[todo[hit]], cell[todo[hit]] = t, at[hit]
        return table, cell

    def run(batches):
        dim, tables = 0, None
        for table in (part for whole in whole_groups(batches, ["dim", "label", "tab", "cell", "b1", "b2"], 20_000) for part in _by_dim(whole)):
            if table.column("dim")[0].as_py() != dim:
                dim = table.column("dim")[0].as_py()
                tables = projections(dim, l)
            label, tab, cell, b1, b2, ids, n, block = (table.column(c).to_numpy() for c in ("label", "tab", "cell", "b1", "b2", "id", "n", "block"))
            home = table.column("home").to_numpy()
            raw = np.frombuffer(b"".join(table.column("vector").to_pylist()), np.float32).reshape(len(ids), dim)
            x = unit_rows(raw)
            cut = np.concatenate([[True], (label[1:] != label[:-1]) | (tab[1:] != tab[:-1]) | (cell[1:] != cell[:-1]) | (b1[1:] != b1[:-1]) | (b2[1:] != b2[:-1]), [True]])
            edge = np.flatnonzero(cut)
            left, right = [], []
            for s, e in zip(edge[:-1].tolist(), edge[1:].tolist()):
                if e - s < 2 or not home[s:e].any():
                    continue
                at_home = s + np.flatnonzero(home[s:e])
                for i in range(s, e, 1000):
                    rows = np.arange(i, min(e, i + 1000))
                    close = x[rows] @ x[at_home].T >= l.least - 1e-9
                    r, c = np.nonzero(close)
                    r, c = rows[r], at_home[c]
                    # pairs of two homes once; blocks other than the group's own pair belong to another group
                    ok = (ids[r] != ids[c]) & (~home[r] | (ids[r] < ids[c]))
                    if b1[s] != b2[s]:
                        ok &= block[r] != block[c]
                    left.append(r[ok])
                    right.append(c[ok])
            if not sum(map(len, left)):
                continue
            r, c = np.concatenate(left), np.concatenate(right)
            kept_r, kept_c = [], []
            for i in range(0, len(r), 50_000):
                a, b = r[i : i + 50_000], c[i : i + 50_000]
                ok = exact_cosine(raw[a], raw[b]) >= l.least
                a, b = a[ok], b[ok]
                t, where = found(tables, x[a], x[b])
                ok = (t == tab[a]) & (where == cell[a])
                kept_r.append(a[ok])
                kept_c.append(b[ok])
            r, c = np.concatenate(kept_r), np.concatenate(kept_c)
            if not len(r):
                continue
            me, other, weight = np.concatenate([ids[r], ids[c]]), np.concatenate([ids[c], ids[r]]), np.concatenate([n[c], n[r]])
            # per cell and vector: links counted, and the least partner in each of its local components
            who, place = np.unique(me, return_inverse=True)
            total = np.bincount(place, weight).astype(np.int64)
            least = np.full(len(who), np.iinfo(np.int64).max)
            np.minimum.at(least, place, other)
            yield pa.RecordBatch.from_arrays([pa.array(who), pa.array(total), pa.array(least)], schema=schema)
            forest = _forest(ids[r], ids[c])
            if len(forest):
                yield pa.RecordBatch.from_arrays([pa.array(forest[:, 0]), pa.array(np.zeros(len(forest), np.int64)), pa.array(forest[:, 1])], schema=schema)

    return run


def _by_dim(table: pa.Table):
    """Parts of a table sorted by dim, one for each."""
    dims = table.column("dim").to_numpy()
    edge = np.flatnonzero(np.concatenate([[True], dims[1:] != dims[:-1], [True]]))
    for s, e in zip(edge[:-1].tolist(), edge[1:].tolist()):
        yield table.slice(s, e - s).combine_chunks()


def _forest(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Links that join what earlier ones have not: at most one less than the vectors."""
    parent: dict[int, int] = {}
    out = []
    for x, y in zip(a.tolist(), b.tolist()):
        rx, ry = x, y
        while parent.get(rx, rx) != rx:
            rx = parent[rx]
        while parent.get(ry, ry) != ry:
            ry = parent[ry]
        if rx != ry:
            parent[max(rx, ry)] = min(rx, ry)
            out.append((x, y))
        for z, root in ((x, min(rx, ry)), (y, min(rx, ry))):
            if z != root:
                parent[z] = root
    return np.array(out, np.int64).reshape(-1, 2)


def near_vectors(vectors: DataFrame, l: Lattice = Lattice()) -> DataFrame:
    """vec_id, n_links, component_id, kept of every vector; links join equal non-null labels at a cosine of `least` or more.

    Equal vectors of a label are one class, whose members all link. Classes are hashed to E8 cells in several tables,
    meet at their own and at probed neighbouring cells, and are confirmed by the exact cosine in double precision; what
    leaves a cell are counts and a spanning forest, never all pairs. Cells of more than `cell` entries are dealt over
    pairs of blocks. Null or zero vectors, vectors with null or non-finite components and null labels link with nothing;
    vectors of different lengths do not link with each other. Rows that repeat a vec_id count as one vector each.
    """
    spark, n = vectors.sparkSession, partitions(vectors.sparkSession)
    keep = Durable(spark)
    schema = pa.schema([("vec_id", pa.int64()), ("label", pa.int64()), ("dim", pa.int32()), ("vector", pa.binary())])

    def clean(batches):
        for batch in batches:
            out = []
            for v in batch.column(2).to_pylist():
                ok = v is not None and len(v) > 0 and None not in v
                a = np.asarray(v, np.float32) if ok else None
                ok = ok and bool(np.isfinite(a).all() and a.any())
                out.append(a.tobytes() if ok else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([len(b) // 4 if b else None for b in out], pa.int32()), pa.array(out, pa.binary())], schema=schema)

    plain = keep(vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), F.col("embedding").cast("array<float>").alias("v")).mapInArrow(clean, "vec_id long, label long, dim int, vector binary"), "plain")
    usable = plain.filter("label is not null and vector is not null")
    classes = keep(usable.groupBy("label", "dim", "vector").agg(F.min("vec_id").alias("id"), F.count("*").alias("n")), "classes")
    entries = classes.select("dim", "label", "id", "n", "vector").mapInArrow(_entries(l), "dim int, label long, tab int, cell long, home boolean, id long, n long, vector binary")
    at = ["dim", "label", "tab", "cell"]
    hot = keep(entries.groupBy(*at).agg(F.count("*").alias("m")).filter(F.col("m") > l.cell).select(*at, F.ceil(F.col("m") / l.cell).cast("int").alias("blocks")), "hot")
    side = F.broadcast(hot) if hot.count() <= 100_000 else hot
    dealt = entries.join(side, at, "left").withColumn("blocks", F.coalesce("blocks", F.lit(1))).withColumn("block", F.pmod(F.xxhash64("id", "tab"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("_w", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("b1", F.least("block", "_w").cast("int")).withColumn("b2", F.greatest("block", "_w").cast("int"))
    order = [*at, "b1", "b2"]
    links = dealt.select(*order, "home", "id", "n", "vector", "block").repartition(n, *order).sortWithinPartitions(*order).mapInArrow(_links(l), "id long, links long, partner long")
    links = keep(links, "links")
    counts = links.groupBy("id").agg(F.sum("links").alias("links"))
    comps = components(links.select(F.col("id").alias("a"), F.col("partner").alias("b")), keep)
    known = classes.join(counts, "id", "left").join(comps, classes["id"] == comps["node"], "left").select("label", "dim", "vector", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", classes["id"]).alias("component_id"))
    out = plain.join(known, ["label", "dim", "vector"], "left")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id")).withColumn("kept", F.col("vec_id") == F.col("component_id"))
