"""Byte-level substring dedup by a hash-compared suffix sort over content-chosen places."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import BYTE_CODES, BYTE_CODES_2, Durable, leftmost_minima, maybe_in, mix, partitions, powers, prefix_hash, span_hash, string_slices, whole_groups, without

U64 = np.uint64


@dataclass(frozen=True)
class Suffixes:
    """window: bytes that have to recur; gram: bytes at an anchor by which windows meet; crowd: occurrences of an anchor
    (repeats inside a document count) beyond which its windows are compared by aggregation instead of in one task."""

    window: int = 400
    gram: int = 200
    crowd: int = 8_000

    @property
    def reach(self) -> int:
        return self.window - self.gram


def _anchors(data: np.ndarray, p: Suffixes) -> tuple[np.ndarray, np.ndarray]:
    """Places whose gram is the leftmost least of some window, and the grams' hashes: equal windows choose equally."""
    if len(data) < p.window:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    prefix = prefix_hash(BYTE_CODES[data])
    at = np.arange(len(data) - p.gram + 1)
    h = mix(span_hash(prefix, at, at + p.gram))
    at = leftmost_minima((h >> U64(1)).view(np.int64), p.reach + 1)
    return at, h[at].view(np.int64)


# --- the suffix sort --------------------------------------------------------------------------------

class HashedText:
    """Prefix polynomial hashes of joined strings; common extensions by binary search on them.

    Powers are counted from each string's own start, so their tables are as long as the longest string only.
    """

    def __init__(self, data: np.ndarray, offset: np.ndarray):
        size = np.diff(offset)
        self.data, n = data, len(data)
        power, self.inverse = powers(int(size.max()) + 1 if len(size) else 1)
        self.local = np.zeros(n + 1, np.int32)
        self.local[:n] = np.arange(n, dtype=np.int32) - np.repeat(offset[:-1], size).astype(np.int32)
        self.prefix = np.zeros(n + 1, U64)
        for at in range(0, n, 1 << 19):
            end = min(n, at + (1 << 19))
            x = BYTE_CODES[data[at:end]]
            x *= power[self.local[at:end]]
            np.cumsum(x, out=x)
            self.prefix[at + 1 : end + 1] = x + self.prefix[at]

    def span(self, i: np.ndarray, end: np.ndarray) -> np.ndarray:
        return (self.prefix[end] - self.prefix[i]) * self.inverse[self.local[i]]

    def common(self, i: np.ndarray, j: np.ndarray, most: np.ndarray) -> np.ndarray:
        """Length of the longest common prefix of the suffixes at i and j, at most `most`."""
        low, high = np.zeros(len(i), np.int64), most.astype(np.int64).copy()
        ii, ij = self.inverse[self.local[i]], self.inverse[self.local[j]]
        pi, pj = self.prefix[i], self.prefix[j]
        while (open_ := low < high).any():
            mid = (low + high + 1) >> 1
            same = (self.prefix[i + mid] - pi) * ii == (self.prefix[j + mid] - pj) * ij
            low = np.where(open_ & same, mid, low)
            high = np.where(open_ & ~same, mid - 1, high)
        return low


def suffix_sort(text: HashedText, group: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of the suffixes [start, end) within their groups (the groups are in order), and each one's common prefix
    with the one before it in its group (-1 for a group's first).

    A bottom-up mergesort in which all runs of a level merge at once: a suffix finds its place in the other run by
    binary search, and each comparison finds the common prefix by binary search on the hashes and looks at one byte.
    """
    n = len(start)
    order = np.arange(n)
    first = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]])) if n else np.zeros(0, np.int64)
    size = np.diff(np.append(first, n))
    base, length = np.repeat(first, size), np.repeat(size, size)
    inner = np.arange(n) - base
    longest = int(size.max()) if n else 0

    def less(a, b, equal):
        """suffix a < suffix b (or <= if `equal`)"""
        most = np.minimum(end[a] - start[a], end[b] - start[b])
        lcp = text.common(start[a], start[b], most)
        out = np.where(equal, end[a] - start[a] <= end[b] - start[b], end[a] - start[a] < end[b] - start[b])
        differ = lcp < most
        out[differ] = text.data[start[a[differ]] + lcp[differ]] < text.data[start[b[differ]] + lcp[differ]]
        return out

    run = 1
    while run < longest:
        left = inner // run % 2 == 0
        other = inner // (2 * run) * (2 * run) + np.where(left, run, 0)  # where the run to merge with begins
        room = np.clip(length - other, 0, run)
        act = np.flatnonzero((room > 0) & (length > run))
        low, high = np.zeros(len(act), np.int64), room[act].copy()
        me, at, is_left = order[act], base[act] + other[act], left[act]
        while (open_ := np.flatnonzero(low < high)).size:
            mid = (low[open_] + high[open_]) >> 1
            before = less(order[at[open_] + mid], me[open_], ~is_left[open_])  # a left suffix goes before its equals
            low[open_[before]] = mid[before] + 1
            high[open_[~before]] = mid[~before]
        place = base + inner
        place[act] = base[act] + inner[act] // (2 * run) * (2 * run) + inner[act] % run + low
        new = np.empty(n, np.int64)
        new[place] = order
        order = new
        run *= 2
    lcp = np.full(n, -1, np.int64)
    if n > 1:
        k = np.flatnonzero(group[order[1:]] == group[order[:-1]]) + 1
        a, b = order[k], order[k - 1]
        lcp[k] = text.common(start[a], start[b], np.minimum(end[a] - start[a], end[b] - start[b]))
    return order, lcp


def covered_spans(group: np.ndarray, left: np.ndarray, context: list[bytes], p: Suffixes) -> tuple[np.ndarray, np.ndarray]:
    """For each context (the bytes around an anchor, which begins at `left`), the bytes from .. to that lie in a window
    over the anchor whose string is also in another context of the group; from = to for none. Groups are in order.

    Windows are `window` bytes and hold the anchor's gram, so what they cover together is one interval: it is fixed by
    the earliest and the latest recurring window.
    """
    n, w, r = len(group), p.window, p.reach
    low, high = np.zeros(n, np.int64), np.zeros(n, np.int64)
    size = np.array([len(c) for c in context], np.int64)
    offset = np.concatenate([[0], np.cumsum(size)])
    data = np.frombuffer(b"".join(context), np.uint8)
    text = HashedText(data, offset)
    edge = np.concatenate([[0], np.flatnonzero(group[1:] != group[:-1]) + 1, [n]])

    # equal contexts first: their common bytes are covered wherever a window fits
    whole = text.span(offset[:-1], offset[1:])
    key = mix(whole + left.astype(U64) * U64(0x9E3779B97F4A7C15) + size.astype(U64))
    order = np.lexsort((key, group))
    new = np.concatenate([[True], (key[order][1:] != key[order][:-1]) | (group[order][1:] != group[order][:-1])])
    head = order[np.flatnonzero(new)[np.cumsum(new) - 1]]
    for i, h in zip(order.tolist(), head.tolist()):
        if i != h and context[i] != context[h]:  # two contexts with one hash: compare plainly
            return _plain_spans(edge, left, context, p)
    count = np.diff(np.append(np.flatnonzero(new), n))[np.cumsum(new) - 1]
    many = np.zeros(n, bool)
    many[order] = count > 1
    high[many & (size >= w)] = size[many & (size >= w)]
    one = np.zeros(n, bool)
    one[order[new]] = True  # one context of each kind takes part from here
    loose = one & ~many & (size >= w)
    busy = np.zeros(n, bool)
    at = np.repeat(np.arange(len(edge) - 1), np.diff(edge))
    kinds, wants = np.bincount(at, one), np.bincount(at, loose)
    busy = one & ((kinds > 1) & (wants > 0))[at]
    rows = np.flatnonzero(busy)
    if not len(rows):
        return low, high

    # suffixes at the leftmost and at the rightmost window that can be in the context
    def recurs(begin, fits):
        s = rows[fits]
        out = np.zeros(n, bool)
        if len(s) < 2:
            return out
        order, lcp = suffix_sort(text, at[s], offset[s] + begin[s], offset[s + 1])
        k = np.flatnonzero(lcp >= w)
        a, b = s[order[k]], s[order[k - 1]]
        for x, y in zip(a.tolist(), b.tolist()):
            if context[x][begin[x] : begin[x] + w] != context[y][begin[y] : begin[y] + w]:
                raise _Collision
        out[a] = out[b] = True
        return out

    try:
        # anchors are aligned, so windows compare only at the same distance from them
        right = recurs(left, size[rows] - left[rows] >= w)
        full = recurs(left - r, (left[rows] == r) & (size[rows] >= w))
    except _Collision:
        return _plain_spans(edge, left, context, p)
    done = loose & right & full
    high[done] = size[done]
    need = loose & ~done
    rows = np.flatnonzero(busy & (np.bincount(at, need) > 0)[at])
    if not len(rows):
        return low, high
    # the rest, distance by distance: window hashes are equal next to each other in hash order
    least, most = np.full(n, 1 << 30), np.full(n, -1)
    witness = np.zeros((2, n), np.int64)
    salt = mix(at[rows].astype(U64) + U64(1))
    begin, close = left[rows] - r, size[rows]
    for s in range(r + 1):
        b = begin + s
        ok = np.flatnonzero((b >= 0) & (b + w <= close))
        if len(ok) < 2:
            continue
        x = offset[rows[ok]] + b[ok]
        h = mix(text.span(x, x + w) ^ salt[ok])
        order = np.argsort(h)
        same = np.flatnonzero(h[order][1:] == h[order][:-1])
        if not len(same):
            continue
        for me, partner in ((order[same], order[same + 1]), (order[same + 1], order[same])):
            me, partner = rows[ok[me]], rows[ok[partner]]
            fresh = least[me] > s
            least[me[fresh]], witness[0, me[fresh]] = s, partner[fresh]
            most[me], witness[1, me] = s, partner
    for i in np.flatnonzero(need & (most >= 0)).tolist():
        for s, k in ((least[i], 0), (most[i], 1)):
            j = witness[k, i]
            x, y = left[i] - r + s, left[j] - r + s
            if group[i] != group[j] or context[i][x : x + w] != context[j][y : y + w]:
                return _plain_spans(edge, left, context, p)
        low[i], high[i] = left[i] - r + least[i], left[i] - r + most[i] + w
    return low, high


class _Collision(Exception):
    pass


def _plain_spans(edge, left, context, p: Suffixes):
    """The same by comparing bytes, for the rare batch in which two strings share a hash."""
    low, high = np.zeros(len(context), np.int64), np.zeros(len(context), np.int64)
    for a, b in zip(edge[:-1].tolist(), edge[1:].tolist()):
        for s in range(p.reach + 1):
            at: dict[bytes, list[int]] = {}
            for i in range(a, b):
                x = int(left[i]) - p.reach + s
                if x >= 0 and x + p.window <= len(context[i]):
                    at.setdefault(context[i][x : x + p.window], []).append(i)
            for found in at.values():
                for i in found if len(found) > 1 else ():
                    x = int(left[i]) - p.reach + s
                    low[i], high[i] = (min(low[i], x), x + p.window) if high[i] else (x, x + p.window)
    return low, high


# --- the distributed part ---------------------------------------------------------------------------

_CODED = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("sha256", pa.string()), ("keys", pa.list_(pa.int64())), ("times", pa.list_(pa.int64()))])


def coded_documents(docs: DataFrame, p: Suffixes) -> DataFrame:
    """doc_id, n_bytes, digest of the bytes, the keys of the document's anchors and how often each is there."""

    def run(batches):
        for batch in batches:
            for a, b, data, offsets in string_slices(batch.column(1)):
                sizes, digests, keys, times = np.diff(offsets), [], [], []
                for i in range(b - a):
                    part = data[offsets[i] : offsets[i + 1]]
                    digests.append(hashlib.sha256(part).hexdigest())
                    k, t = np.unique(_anchors(part, p)[1], return_counts=True)
                    keys.append(k)
                    times.append(t)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(sizes), pa.array(digests), pa.array(keys, pa.list_(pa.int64())), pa.array(times, pa.list_(pa.int64()))], schema=_CODED)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, n_bytes long, sha256 string, keys array<long>, times array<long>")


_CONTEXT = pa.schema([("key", pa.int64()), ("doc_id", pa.int64()), ("begin", pa.int64()), ("left", pa.int32()), ("context", pa.binary())])


def _contexts(p: Suffixes):
    """(doc_id, text, wanted keys) to the bytes around each wanted anchor."""

    def run(batches):
        for batch in batches:
            ids, texts, wanted = batch.column("doc_id"), batch.column("text"), batch.column("wanted")
            out: list[list] = [[], [], [], [], []]
            for i in range(batch.num_rows):
                raw = (texts[i].as_py() or "").encode()
                at, key = _anchors(np.frombuffer(raw, np.uint8), p)
                keep = np.isin(key, np.asarray(wanted[i].values))
                doc_id = ids[i].as_py()
                for a, k in zip(at[keep].tolist(), key[keep].tolist()):
                    begin = max(0, a - p.reach)
                    for c, x in zip(out, (k, doc_id, begin, a - begin, raw[begin : a + p.window])):
                        c.append(x)
                    if len(out[0]) >= 2000:
                        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, _CONTEXT)], schema=_CONTEXT)
                        out = [[], [], [], [], []]
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, _CONTEXT)], schema=_CONTEXT)

    return run


_SPAN = pa.schema([("doc_id", pa.int64()), ("from", pa.int64()), ("to", pa.int64())])


def _grouped_spans(p: Suffixes):
    def run(batches):
        for table in whole_groups(batches, ["key"], 1500):
            key, doc, begin, left = (table.column(c).to_numpy() for c in ("key", "doc_id", "begin", "left"))
            # rows that repeat a doc_id are one place: that of the anchor, since contexts at the head of a text all begin at 0
            place = begin + left
            order = np.lexsort((place, doc, key))
            k, d, b = key[order], doc[order], place[order]
            new = np.concatenate([[True], (k[1:] != k[:-1]) | (d[1:] != d[:-1]) | (b[1:] != b[:-1])])
            rows = order[new]
            context = table.column("context").take(pa.array(rows)).to_pylist()
            low, high = covered_spans(key[rows], left[rows].astype(np.int64), context, p)
            hit = high > low
            yield pa.RecordBatch.from_arrays([pa.array(doc[rows][hit]), pa.array(begin[rows][hit] + low[hit]), pa.array(begin[rows][hit] + high[hit])], schema=_SPAN)

    return run


def _hot_windows(p: Suffixes):
    """Windows over the anchors that are too common for one task, by two hashes, each place of a document once. Windows that
    recur inside the document are settled here: they leave as whole runs (n null), and one row with their number stands
    for them among the documents. (doc_id, from, to, h1, h2, n)"""
    schema = pa.schema([("doc_id", pa.int64()), ("from", pa.int64()), ("to", pa.int64()), ("h1", pa.int64()), ("h2", pa.int64()), ("n", pa.int64())])

    def run(batches):
        for batch in batches:
            ids, texts, wanted = batch.column("doc_id"), batch.column("text"), batch.column("hot")
            for i in range(batch.num_rows):
                data = np.frombuffer((texts[i].as_py() or "").encode(), np.uint8)
                at, key = _anchors(data, p)
                at = at[np.isin(key, np.asarray(wanted[i].values))]
                depth = np.zeros(len(data) + 2, np.int32)  # windows that hold the gram of a wanted anchor
                np.add.at(depth, np.maximum(at - p.reach, 0), 1)
                np.add.at(depth, np.minimum(at + 1, len(data)), -1)
                start = np.flatnonzero(np.cumsum(depth)[: max(0, len(data) - p.window + 1)] > 0)
                if not len(start):
                    continue
                h1, h2 = (mix(span_hash(prefix_hash(codes[data]), start, start + p.window)).view(np.int64) for codes in (BYTE_CODES, BYTE_CODES_2))
                order = np.lexsort((start, h2, h1))
                first = np.flatnonzero(np.concatenate([[True], (h1[order][1:] != h1[order][:-1]) | (h2[order][1:] != h2[order][:-1])]))
                count = np.diff(np.append(first, len(start)))
                doc_id, again = ids[i].as_py(), np.sort(start[order[np.repeat(count, count) > 1]])
                if len(again):
                    edge = np.flatnonzero(np.concatenate([[True], again[1:] > again[:-1] + p.window, [True]]))
                    lo, hi = again[edge[:-1]], again[edge[1:] - 1] + p.window
                    none = pa.nulls(len(lo), pa.int64())
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(lo), doc_id)), pa.array(lo), pa.array(hi), none, none, none], schema=schema)
                rows = order[first]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(rows), doc_id)), pa.array(start[rows]), pa.array(start[rows] + p.window), pa.array(h1[rows]), pa.array(h2[rows]), pa.array(count)], schema=schema)

    return run


def _cut(p: Suffixes, with_text: bool):
    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                part, rows = batch.slice(at, 200), []
                texts, lists = part.column("text"), part.column("spans")
                for i, doc_id in enumerate(part.column("doc_id").to_pylist()):
                    raw = np.frombuffer((texts[i].as_py() or "").encode(), np.uint8)
                    spans = lists[i].values
                    depth = np.zeros(len(raw) + 1, np.int32)
                    np.add.at(depth, spans.field("from").to_numpy(), 1)
                    np.add.at(depth, spans.field("to").to_numpy(), -1)
                    gone = np.cumsum(depth[:-1]) > 0
                    n_spans = int(np.count_nonzero(gone[1:] & ~gone[:-1]) + (len(gone) > 0 and gone[0]))
                    kept = raw[~gone].tobytes()
                    rows.append((doc_id, int(gone.sum()), n_spans, kept.decode(errors="ignore") if with_text else hashlib.sha256(kept).hexdigest()))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.string()))], names=["doc_id", "n_removed", "n_spans", "kept"])

    return run


def _spans(docs: DataFrame, p: Suffixes, keep: Durable, with_text: bool) -> tuple[DataFrame, DataFrame, DataFrame]:
    spark, n = docs.sparkSession, partitions(docs.sparkSession)
    coded = keep(coded_documents(docs, p), "coded")
    copied = coded.filter(F.col("n_bytes") >= p.window).groupBy("sha256").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).filter("first <> last")
    copies = keep(coded.select("doc_id", "sha256").join(copied, "sha256").select("doc_id", (F.col("doc_id") != F.col("first")).alias("later")).distinct(), "copies")
    later = copies.filter("later").select("doc_id")
    single = without(coded.select("doc_id", "keys", "times"), "doc_id", later, "doc_id").select("doc_id", F.explode(F.arrays_zip("keys", "times")).alias("k")).select("doc_id", F.col("k.keys").alias("key"), F.col("k.times").alias("times"))
    recurring = keep(single.groupBy("key").agg(F.sum("times").alias("n")).filter("n > 1"), "recurring")
    wanted = maybe_in(single.drop("times"), "key", recurring, "key", 22).join(recurring, "key")
    wanted = wanted.groupBy("doc_id").agg(F.collect_set(F.when(F.col("n") <= p.crowd, F.col("key"))).alias("wanted"), F.collect_set(F.when(F.col("n") > p.crowd, F.col("key"))).alias("hot"))
    wanted = keep(wanted, "wanted")
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    texts = maybe_in(plain, "doc_id", wanted, "doc_id").join(wanted, "doc_id")
    contexts = texts.filter("size(wanted) > 0").mapInArrow(_contexts(p), "key long, doc_id long, begin long, left int, context binary")
    spans = contexts.repartition(n, "key").sortWithinPartitions("key").mapInArrow(_grouped_spans(p), "doc_id long, from long, to long")
    if not recurring.filter(F.col("n") > p.crowd).isEmpty():
        hot = wanted.filter("size(hot) > 0").drop("wanted")
        found = keep(maybe_in(plain, "doc_id", hot, "doc_id").join(hot, "doc_id").mapInArrow(_hot_windows(p), "doc_id long, from long, to long, h1 long, h2 long, n long").distinct(), "hot")
        rows = found.filter("n is not null")
        shared = rows.groupBy("h1", "h2").agg(F.sum("n").alias("m")).filter("m > 1").select("h1", "h2")
        shared = rows.join(shared, ["h1", "h2"], "left_semi")
        # windows that follow each other become one span before they are gathered by document
        of_doc = Window.partitionBy("doc_id").orderBy("from")
        shared = shared.withColumn("_new", F.coalesce((F.col("from") > F.lag("to").over(of_doc)).cast("int"), F.lit(1))).withColumn("_run", F.sum("_new").over(of_doc.rowsBetween(Window.unboundedPreceding, 0)))
        spans = spans.union(found.filter("n is null").select("doc_id", "from", "to")).union(shared.groupBy("doc_id", "_run").agg(F.min("from").alias("from"), F.max("to").alias("to")).select("doc_id", "from", "to"))
    spans = keep(spans, "spans").groupBy("doc_id").agg(F.collect_set(F.struct("from", "to")).alias("spans"))
    spans = keep(without(spans, "doc_id", copies, "doc_id"), "by_doc")
    cut = maybe_in(plain, "doc_id", spans, "doc_id").join(spans, "doc_id").mapInArrow(_cut(p, with_text), "doc_id long, n_removed long, n_spans long, kept string").dropDuplicates(["doc_id"])
    return coded, copies, cut


def repeated_bytes(docs: DataFrame, p: Suffixes = Suffixes()) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256: each byte under a string of `window` bytes that also starts elsewhere goes.

    Anchors chosen from the content alone are in every window, alike in equal windows. The bytes around the anchors that
    recur meet by anchor and are suffix-sorted there by hash comparisons; equal strings are confirmed byte by byte.
    Texts that are equal as a whole are removed as a whole. Null, empty and short texts lose nothing; rows that repeat
    a doc_id count as one document.
    """
    coded, copies, cut = _spans(docs, p, Durable(docs.sparkSession), False)
    cut = cut.select(F.col("doc_id").alias("_c"), F.col("n_removed").alias("_r"), F.col("n_spans").alias("_s"), F.col("kept").alias("_k"))
    gone = copies.select(F.col("doc_id").alias("_g"))
    out = coded.select("doc_id", "n_bytes", "sha256").join(cut, F.col("doc_id") == F.col("_c"), "left").join(gone, F.col("doc_id") == F.col("_g"), "left")
    copy = F.col("_g").isNotNull()
    return out.select("doc_id", "n_bytes", F.when(copy, F.col("n_bytes")).otherwise(F.coalesce("_r", F.lit(0))).cast("long").alias("n_removed"), F.when(copy, 1).otherwise(F.coalesce("_s", F.lit(0))).cast("long").alias("n_spans"), F.when(copy, F.lit(hashlib.sha256(b"").hexdigest())).otherwise(F.coalesce("_k", "sha256")).alias("kept_sha256"))


def without_repeated_bytes(docs: DataFrame, p: Suffixes = Suffixes()) -> DataFrame:
    """The documents with the bytes that are left (a character cut in two goes too); other columns as they were."""
    _, copies, cut = _spans(docs, p, Durable(docs.sparkSession), True)
    cut = cut.select(F.col("doc_id").alias("_c"), F.col("kept").alias("_k"))
    gone = copies.select(F.col("doc_id").alias("_g"))
    out = docs.join(cut, docs["doc_id"] == F.col("_c"), "left").join(gone, docs["doc_id"] == F.col("_g"), "left")
    text = F.when(F.col("_g").isNotNull(), F.lit("")).otherwise(F.coalesce("_k", docs["text"])).alias("text")
    return out.select(*[text if c == "text" else docs[c] for c in docs.columns])
