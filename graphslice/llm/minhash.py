"""MinHash near-duplicates by an LSH forest: sorted signature orders whose long common prefixes give the candidates."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BYTE_CODES, LOWER, Durable, components, maybe_in, mix, partitions, settle, string_slices, whole_groups, word_hashes, word_spans

U64 = np.uint64


@dataclass(frozen=True)
class Forest:
    """trees: sorted orders of the signatures, each of `deep` values. shallow: the shortest common prefix that makes two
    texts neighbours. A region (the texts of a prefix) with more than `region` texts is cut by the next value, down to
    `deep`; regions that are larger even there are dealt over pairs of blocks. words: shingle length; share: least Jaccard in %.

    A pair at Jaccard 0.8 has a common prefix of 3 in one of 20 orders but for 6e-7 of all pairs, of 4 but for 3e-5, of 5
    but for 4e-4, of 6 but for 2e-3; pairs that are closer are missed far less. The estimate that spares full comparisons lets
    such a pair pass but for 1e-6."""

    trees: int = 20
    shallow: int = 3
    deep: int = 6
    region: int = 2000
    words: int = 5
    share: int = 80


QUERY = Forest(words=2)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct 64-bit shingle hashes of each row, sorted, and the rows' offsets in them. A-Z count as a-z.

    A row with fewer words than a shingle has its whole sequence as the only one; a row without words has none.
    """
    starts, ends, before = word_spans(data, offsets)
    n = len(offsets) - 1
    count = np.diff(before)
    h = word_hashes(data, starts, ends, BYTE_CODES[LOWER])
    size = np.where(count >= words, count - words + 1, (count > 0).astype(np.int64))
    row = np.repeat(np.arange(n), size)
    inner = np.arange(len(row)) - np.repeat(np.concatenate([[0], np.cumsum(size)[:-1]]), size)
    first = before[:-1][row] + inner
    length = np.minimum(count, words)[row]
    out = length.astype(U64) * U64(0x9E3779B97F4A7C15)
    for i in range(words):
        m = length > i
        if m.all():
            out = mix(out + h[first + i])
        elif m.any():
            out[m] = mix(out[m] + h[first[m] + i])
    order = np.lexsort((out, row))
    out, row = out[order], row[order]
    new = np.ones(len(out), bool)
    new[1:] = (out[1:] != out[:-1]) | (row[1:] != row[:-1])
    out, row = out[new], row[new]
    return out, np.searchsorted(row, np.arange(n + 1))


def signatures(sets: np.ndarray, cut: np.ndarray, n: int) -> np.ndarray:
    """rows x n minima of n hash functions over each row's set (rows with an empty set: all ones)."""
    rows = len(cut) - 1
    out = np.full((rows, n), 0xFFFFFFFF, np.uint32)
    filled = np.flatnonzero(np.diff(cut))
    if not len(filled):
        return out
    seeds = mix(np.arange(1, n + 1, dtype=U64) * U64(0xC2B2AE3D27D4EB4F))
    at = cut[:-1][filled]
    for j in range(n):
        x = sets ^ seeds[j]
        x *= U64(0xFF51AFD7ED558CCD)
        x ^= x >> U64(32)
        x *= U64(0xC4CEB9FE1A85EC53)
        out[filled, j] = (np.minimum.reduceat(x, at) >> U64(32)).astype(np.uint32)
    return out


_CODED = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("h1", pa.int64()), ("h2", pa.int64()), ("keys", pa.list_(pa.int64())), ("sig", pa.binary())])


def coded_documents(docs: DataFrame, f: Forest) -> DataFrame:
    """doc_id, n_shingles, two 64-bit digests of the set, the orders' shallow prefixes and a byte of each signature value.

    Texts are read once and not shuffled.
    """
    values = f.trees * f.deep

    def run(batches):
        for batch in batches:
            for a, b, data, offsets in string_slices(batch.column(1)):
                sets, cut = shingle_sets(data, offsets, f.words)
                sig = signatures(sets, cut, values)
                digest = []
                for salt in (0x5851F42D4C957F2D, 0x14057B7EF767814F):
                    total = np.zeros(len(sets) + 1, U64)
                    np.cumsum(mix(sets + U64(salt)), out=total[1:])
                    digest.append(mix(total[cut[1:]] - total[cut[:-1]]).view(np.int64))
                keys = np.empty((b - a, f.trees), U64)
                for t in range(f.trees):
                    key = np.full(b - a, t + 1, U64)
                    for d in range(f.shallow):
                        key = mix(key + sig[:, t * f.deep + d].astype(U64))
                    keys[:, t] = key
                lists = pa.ListArray.from_arrays(pa.array(np.arange(b - a + 1, dtype=np.int32) * f.trees), pa.array(keys.ravel().view(np.int64)))
                raw = sig.astype(np.uint8).tobytes()
                bytes_ = pa.array([raw[i * values : (i + 1) * values] for i in range(b - a)], pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(np.diff(cut).astype(np.int64)), pa.array(digest[0]), pa.array(digest[1]), lists, bytes_], schema=_CODED)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, n_shingles long, h1 long, h2 long, keys array<long>, sig binary")


def _least_equal(f: Forest) -> int:
    """Equal signature values that a pair at the least Jaccard has, five deviations below what is expected."""
    values, p = f.trees * f.deep, f.share / 100
    return int(np.floor(values * p - 5 * np.sqrt(values * p * (1 - p))))


def _equal_values(sig: np.ndarray, rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
    x, y = sig[:, rows], sig[:, cols]
    same = np.zeros((len(rows), len(cols)), np.uint8)
    for a, b in zip(x, y):
        same += a[:, None] == b[None]
    return same


def _close_sizes(sizes: np.ndarray, rows: np.ndarray, cols: np.ndarray, f: Forest) -> np.ndarray:
    return 100 * np.minimum(sizes[rows][:, None], sizes[cols][None]) >= f.share * np.maximum(sizes[rows][:, None], sizes[cols][None])


_PAIR = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("near", pa.int32())])


def _neighbours(f: Forest):
    """Candidates (a < b, near) from partitions sorted by region, block and path, the order of a tree's signatures.

    For each text, from the longest common prefix to the region's own: the least id among the texts of that prefix that
    looks similar (enough equal signature values, sizes that allow the least Jaccard). So a region of n texts gives less
    than n pairs, each with its number of equal values and the length of its common prefix.
    """
    least, step, levels = _least_equal(f), 256, f.deep - f.shallow

    def pairs(ids, sizes, path, sig):
        partner, near = np.full(len(ids), -1), np.zeros(len(ids), np.int64)
        for level in range(levels, -1, -1):
            group = path >> np.int64(8 * (levels - level))
            order = np.lexsort((ids, group))
            edge = np.flatnonzero(np.concatenate([[True], group[order][1:] != group[order][:-1], [True]]))
            for s, e in zip(edge[:-1].tolist(), edge[1:].tolist()):
                own = order[s:e]
                todo = np.flatnonzero(partner[own] < 0)
                if len(own) < 2 or not len(todo):
                    continue
                for i in range(0, len(todo), step):
                    at = todo[i : i + step]
                    for j in range(0, int(at[-1]), step):
                        at = at[partner[own[at]] < 0]
                        cols = np.arange(j, min(j + step, len(own)))
                        at = at[at > j]
                        if not len(at):
                            break
                        same = _equal_values(sig, own[at], own[cols])
                        ok = (same >= least) & _close_sizes(sizes, own[at], own[cols], f) & (at[:, None] > cols[None]) & (ids[own[at]][:, None] > ids[own[cols]][None])
                        r = np.flatnonzero(ok.any(1))
                        c = ok[r].argmax(1)
                        partner[own[at[r]]] = own[cols[c]]
                        near[own[at[r]]] = same[r, c].astype(np.int64) * 16 + f.shallow + level
        r = np.flatnonzero(partner >= 0)
        return ids[partner[r]], ids[r], near[r]

    def run(batches):
        for table in whole_groups(batches, ["region", "block"], 4000):
            region, block, ids, sizes, path = (table.column(n).to_numpy() for n in ("region", "block", "id", "size", "path"))
            sig = np.frombuffer(b"".join(table.column("sig").to_pylist()), np.uint8).reshape(len(ids), -1).T
            edge = np.flatnonzero(np.concatenate([[True], (region[1:] != region[:-1]) | (block[1:] != block[:-1]), [True]]))
            found = [pairs(ids[s:e], sizes[s:e], path[s:e], np.ascontiguousarray(sig[:, s:e])) for s, e in zip(edge[:-1].tolist(), edge[1:].tolist()) if e - s > 1]
            if found:
                x, y, near = (np.concatenate(c) for c in zip(*found))
                yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(y), pa.array(near.astype(np.int32))], schema=_PAIR)

    return run


def _bridges(f: Forest):
    """Pairs of components (a, b) that have similar-looking texts in a region: a spanning forest per region."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])
    least, step = _least_equal(f), 256

    def pairs(sizes, comps, sig):
        order = np.argsort(comps, kind="stable")
        sizes, comps, sig = sizes[order], comps[order], np.ascontiguousarray(sig[:, order])
        n = len(comps)
        for i in range(0, n, step):
            rows = np.arange(i, min(i + step, n))
            for j in range(0, i + 1, step):
                cols = np.arange(j, min(j + step, n))
                if comps[cols[0]] == comps[rows[-1]]:  # sorted by component: all the same between them
                    continue
                r, c = np.nonzero((comps[rows][:, None] > comps[cols][None]) & _close_sizes(sizes, rows, cols, f))
                if not len(r):
                    continue
                r, c = np.nonzero((_equal_values(sig, rows, cols) >= least) & (comps[rows][:, None] > comps[cols][None]) & _close_sizes(sizes, rows, cols, f))
                if len(r):
                    yield np.unique(np.stack([comps[cols[c]], comps[rows[r]]]), axis=1)

    def run(batches):
        for table in whole_groups(batches, ["region", "block"], 4000):
            region, block, sizes, comps = (table.column(n).to_numpy() for n in ("region", "block", "size", "comp"))
            sig = np.frombuffer(b"".join(table.column("sig").to_pylist()), np.uint8).reshape(len(comps), -1).T
            edge = np.flatnonzero(np.concatenate([[True], (region[1:] != region[:-1]) | (block[1:] != block[:-1]), [True]]))
            found = [x for s, e in zip(edge[:-1].tolist(), edge[1:].tolist()) if e - s > 1 and (comps[s:e] != comps[s]).any() for x in pairs(sizes[s:e], comps[s:e], sig[:, s:e])]
            if found:
                a, b = np.concatenate(found, 1).tolist()
                a, b = _forest(a, b)
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], schema=schema)

    return run


def _forest(a: list, b: list) -> tuple[np.ndarray, np.ndarray]:
    """The links that join what earlier links have not."""
    parent: dict = {}

    def find(x):
        while parent.get(x, x) != x:
            parent[x] = x = parent.get(parent[x], parent[x])
        return x

    out = []
    for x, y in zip(a, b):
        p, q = find(x), find(y)
        if p != q:
            parent[max(p, q)] = min(p, q)
            out.append((x, y))
    return np.array([x for x, _ in out], np.int64), np.array([y for _, y in out], np.int64)


def _family_links(f: Forest):
    """Pairs of components that a link joins within families of texts that look similar, from rows sorted by family and
    pair of blocks.

    Every pair of different components that looks similar is confirmed on the full sets unless its ends are joined by
    then, so no link between components is missed; what is returned is a forest.
    """
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])
    least, step = _least_equal(f), 256

    def run(batches):
        for table in whole_groups(batches, ["family", "b1", "b2"], 1000):
            family, b1, b2, block, comps = (table.column(c).to_numpy() for c in ("family", "b1", "b2", "block", "comp"))
            edge = np.flatnonzero(np.concatenate([[True], (family[1:] != family[:-1]) | (b1[1:] != b1[:-1]) | (b2[1:] != b2[:-1]), [True]]))
            for s, e in zip(edge[:-1].tolist(), edge[1:].tolist()):
                if e - s < 2 or (comps[s:e] == comps[s]).all():
                    continue
                sets = []
                for _, _, data, offsets in string_slices(table.column("text").slice(s, e - s)):
                    flat, cut = shingle_sets(data, offsets, f.words)
                    sets += [flat[cut[i] : cut[i + 1]].copy() for i in range(len(offsets) - 1)]
                sig = np.ascontiguousarray(np.frombuffer(b"".join(table.column("sig").slice(s, e - s).to_pylist()), np.uint8).reshape(e - s, -1).T)
                size, comp, part = np.array([len(x) for x in sets]), comps[s:e], block[s:e]
                parent: dict = {}

                def find(x):
                    while parent.get(x, x) != x:
                        parent[x] = x = parent.get(parent[x], parent[x])
                    return x

                out = []
                order = np.argsort(comp, kind="stable")
                for i in range(0, e - s, step):
                    rows = order[i : i + step]
                    for j in range(0, i + 1, step):
                        cols = order[j : j + step]
                        if comp[cols[0]] == comp[rows[-1]]:
                            continue
                        same = _equal_values(sig, rows, cols)
                        ok = (same >= least) & _close_sizes(size, rows, cols, f) & (comp[rows][:, None] > comp[cols][None])
                        if b1[s] != b2[s]:
                            ok &= part[rows][:, None] != part[cols][None]
                        r, c = np.nonzero(ok)
                        for k in np.argsort(-same[r, c].astype(np.int16), kind="stable").tolist():
                            x, y = rows[r[k]], cols[c[k]]
                            px, py = find(comp[x]), find(comp[y])
                            if px == py:
                                continue
                            both = np.intersect1d(sets[x], sets[y], assume_unique=True).size
                            if 100 * both >= f.share * (size[x] + size[y] - both):
                                parent[max(px, py)] = min(px, py)
                                out.append((comp[y], comp[x]))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array([int(x) for x, _ in out]), pa.array([int(y) for _, y in out])], schema=schema)

    return run


def _verified(f: Forest):
    """Links (a, b) on the full shingle sets, from texts sorted by a, the text of a itself (b null) coming first."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches):
        leader, own = None, None
        for batch in batches:
            ids_a, ids_b = batch.column("a").to_pylist(), batch.column("b").to_pylist()
            links: list[tuple[int, int]] = []
            for first, end, data, offsets in string_slices(batch.column("text")):
                sets, cut = shingle_sets(data, offsets, f.words)
                for i in range(first, end):
                    mine = sets[cut[i - first] : cut[i - first + 1]]
                    if ids_b[i] is None:
                        leader, own = ids_a[i], mine.copy()
                    elif ids_a[i] == leader and len(own):
                        both = np.intersect1d(mine, own, assume_unique=True).size
                        if 100 * both >= f.share * (len(mine) + len(own) - both):
                            links.append((leader, ids_b[i]))
            if links:
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*links)], schema=schema)

    return run


def _confirm(pairs: DataFrame, docs: DataFrame, f: Forest, keep: Durable) -> DataFrame:
    """The pairs (a, b) that are links. Each b's text goes to its a, and a's text goes there once (once per block of b's)."""
    blocks = pairs.groupBy("a").agg(F.ceil(F.count("*") / f.region).cast("int").alias("blocks"))
    members = pairs.join(blocks, "a").select(F.col("b").alias("id"), "a", "b", F.pmod(F.xxhash64("b"), F.col("blocks")).cast("int").alias("block"))
    leaders = blocks.select(F.col("a").alias("id"), "a", F.lit(None).cast("long").alias("b"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"))
    wanted = keep(members.unionByName(leaders), "wanted")
    rows = maybe_in(_plain(docs), "doc_id", wanted, "id").join(wanted, F.col("doc_id") == F.col("id")).select("a", "block", "b", "text")
    rows = rows.repartition(partitions(docs.sparkSession), "a", "block").sortWithinPartitions("a", "block", F.col("b").asc_nulls_first())
    return keep(rows.mapInArrow(_verified(f), "a long, b long"), "links")


def _plain(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def signature_orders(classes: DataFrame, f: Forest, keep: Durable) -> DataFrame:
    """(region, blocks, id, size, path, sig): each class in the regions of its trees that it shares with others.

    A region is a common prefix of `shallow` values, or where more than `region` texts share it, the shortest longer
    prefix that fewer share. path: the values after `shallow`, by which a region's texts are sorted.
    """
    tail = f.deep - f.shallow
    path = F.conv(F.hex(F.expr(f"substring(sig, tree * {f.deep} + {f.shallow + 1}, {tail})")), 16, 10).cast("long")
    keyed = classes.select(F.posexplode("keys").alias("tree", "key"), F.col("rep").alias("id"), F.col("n_shingles").alias("size"), "sig")
    shared = keep(keyed.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1"), "shared")
    views = keep(maybe_in(keyed, "key", shared, "key", 22).join(shared, "key").withColumn("path", path if tail else F.lit(0).cast("long")).drop("tree"), "views")
    calm = views.filter(F.col("n") <= f.region).select(F.col("key").alias("region"), F.lit(1).alias("blocks"), "id", "size", "path", "sig")
    crowded = views.filter(F.col("n") > f.region)
    deeper = crowded.select("key", "id", "path", F.explode(F.sequence(F.lit(0), F.lit(tail))).alias("d")).withColumn("region", F.xxhash64("key", "d", F.expr(f"shiftright(path, cast(8 * ({tail} - d) as int))")))
    counts = deeper.groupBy("region").agg(F.count("*").alias("m"))
    placed = deeper.join(counts, "region").filter((F.col("m") <= f.region) | (F.col("d") == tail)).groupBy("key", "id").agg(F.min(F.struct("d", "region", "m")).alias("x"))
    placed = placed.select(F.col("key").alias("_k"), F.col("id").alias("_i"), "x.region", F.ceil(F.col("x.m") / f.region).cast("int").alias("blocks"))
    cut = crowded.join(placed, (F.col("key") == F.col("_k")) & (F.col("id") == F.col("_i"))).select("region", "blocks", "id", "size", "path", "sig")
    return keep(calm.union(cut), "orders")


def near_duplicates(docs: DataFrame, f: Forest = Forest()) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every document.

    Texts with equal shingle sets (by two 64-bit digests of 64-bit shingle hashes) are one class. Each tree of the forest is
    an order of the classes' signatures, cut at common prefixes whose length adapts to how many share them; of its
    neighbours by longest common prefix in all trees, a class gets the one that looks most similar, and that pair is confirmed
    on the full sets. Components so linked that still look similar to others in a region form families, in which every
    similar-looking pair between components is confirmed, so no link is lost to the choice of neighbours. Null, empty and
    wordless texts have an empty set and stay alone; rows with a repeated doc_id count as one document in links and are
    all returned; of equal texts the least doc_id is kept.
    """
    keep = Durable(docs.sparkSession)
    n = partitions(docs.sparkSession)
    coded = keep(coded_documents(docs, f), "coded")
    classes = coded.filter("n_shingles > 0").groupBy("h1", "h2", "n_shingles").agg(F.min("doc_id").alias("rep"), F.min_by(F.struct("keys", "sig"), "doc_id").alias("x"))
    classes = keep(classes.select("h1", "h2", "n_shingles", "rep", "x.keys", "x.sig"), "classes")
    orders = signature_orders(classes, f, keep)
    keep.release("shared", "views")
    settle(docs.sparkSession)
    block = F.when(F.col("blocks") > 1, F.pmod(F.xxhash64("id", "region"), F.col("blocks"))).otherwise(0).cast("int")
    first = orders.select("region", block.alias("block"), "path", "id", "size", "sig").repartition(n, "region", "block").sortWithinPartitions("region", "block", "path", "id")
    near = first.mapInArrow(_neighbours(f), "a long, b long, near int").groupBy("b").agg(F.max_by("a", F.struct("near", -F.col("a"))).alias("a"))
    links = _confirm(keep(near.select("a", "b"), "near"), docs, f, keep)
    comps = keep(components(links, keep), "comps1")
    named = orders.join(comps, orders["id"] == comps["node"], "left").withColumn("comp", F.coalesce("component", "id")).drop("node", "component")
    named = keep(named, "named")
    apart = named.groupBy("region").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("lo <> hi").select("region")
    open_ = named.join(apart, "region", "left_semi").withColumn("own", block)
    # regions over several blocks: a text meets every block, each pair of blocks being one group
    open_ = open_.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("block", F.least("own", "with") * F.col("blocks") + F.greatest("own", "with"))
    second = open_.select("region", "block", "size", "comp", "sig").repartition(n, "region", "block").sortWithinPartitions("region", "block")
    bridges = keep(second.mapInArrow(_bridges(f), "a long, b long").distinct(), "bridges")
    keep.release("orders", "named", "near", "wanted")
    settle(docs.sparkSession)
    final = comps
    if not bridges.isEmpty():
        # families: components that bridges bring together; their texts meet once, or once per block for large families
        family = keep(components(bridges, keep), "family")
        whole = keep(family.select(F.col("node").alias("comp"), F.col("component").alias("family")).union(family.select(F.col("component").alias("comp"), F.col("component").alias("family")).distinct()), "families")
        members = whole.join(comps, F.col("comp") == F.col("component")).select(F.col("node").alias("id"), "comp", "family").union(whole.select(F.col("comp").alias("id"), "comp", "family"))
        size = members.groupBy("family").agg(F.ceil(F.count("*") / f.region).cast("int").alias("blocks"))
        who = members.join(size, "family").join(classes.select(F.col("rep").alias("id"), "sig"), "id").withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
        who = keep(who, "members")
        texts = maybe_in(_plain(docs), "doc_id", who, "id").join(who, F.col("doc_id") == F.col("id")).dropDuplicates(["doc_id"])
        dealt = texts.withColumn("_w", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        dealt = dealt.withColumn("b1", F.least("block", "_w").cast("int")).withColumn("b2", F.greatest("block", "_w").cast("int")).select("family", "b1", "b2", "block", "comp", "sig", "text")
        joined = keep(dealt.repartition(n, "family", "b1", "b2").sortWithinPartitions("family", "b1", "b2").mapInArrow(_family_links(f), "a long, b long"), "joined")
        top = keep(components(joined, keep), "top").select(F.col("node").alias("_n"), F.col("component").alias("_c"))
        final = comps.join(top, F.col("component") == F.col("_n"), "left").select("node", F.coalesce("_c", "component").alias("component")).union(top.select("_n", "_c"))
    rep = classes.select("h1", "h2", "n_shingles", "rep").join(final, F.col("rep") == F.col("node"), "left").select("h1", "h2", "n_shingles", F.coalesce("component", "rep").alias("component_id"))
    joined = coded.select("doc_id", "h1", "h2", "n_shingles").join(rep, ["h1", "h2", "n_shingles"], "left")
    return joined.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id")).withColumn("kept", F.col("doc_id") == F.col("component_id"))


def keep_representatives(docs: DataFrame, f: Forest = Forest()) -> DataFrame:
    """One document (the least doc_id) of each group of near-duplicates, all columns kept."""
    lost = near_duplicates(docs, f).filter("not kept").select(F.col("doc_id").alias("_lost")).distinct()
    return docs.join(lost, docs["doc_id"] == lost["_lost"], "left_anti")
