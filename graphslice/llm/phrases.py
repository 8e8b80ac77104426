"""Substring dedup by repeated phrases: recurring word windows, located by Aho-Corasick automata."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import BYTE_CODES, Durable, leftmost_minima, maybe_in, mix, partitions, prefix_hash, sliding_argmin, span_hash, spread_starts, string_slices, whole_groups, without, word_hashes, word_spans

U64 = np.uint64


@dataclass(frozen=True)
class Phrases:
    """window: words that have to recur; phrase: words of the phrases by which windows are found; crowd: located occurrences of
    a phrase (after those that repeat inside a document) beyond which its windows are dealt by their own hash instead of by the phrase."""

    window: int = 20
    phrase: int = 6
    crowd: int = 4_096


def phrase_keys(h: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each k consecutive words (k <= 6): their 16-bit codes packed into two longs, and an order hash.

    The key spells the phrase in codes, so it is also the pattern that the automaton looks for.
    """
    n = len(h) - k + 1
    if n <= 0:
        z = np.zeros(0, np.int64)
        return z, z, z.view(U64)
    code = h & U64(0xFFFF)
    hi, lo = np.zeros(n, U64), np.zeros(n, U64)
    for i in range(k):
        part = code[i : i + n]
        if i < 3:
            hi |= part << U64(16 * i)
        else:
            lo |= part << U64(16 * (i - 3))
    return hi.view(np.int64), lo.view(np.int64), mix(mix(hi) + lo) >> U64(1)


def _anchors(h: np.ndarray, p: Phrases) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Positions of the phrases that are the leftmost least of some window, and their keys."""
    hi, lo, order = phrase_keys(h, p.phrase)
    at = leftmost_minima(order.view(np.int64), p.window - p.phrase + 1)
    return at, hi[at], lo[at]


_CODED = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("kept_sha256", pa.string()), ("hi", pa.list_(pa.int64())), ("lo", pa.list_(pa.int64()))])


def coded_documents(docs: DataFrame, p: Phrases) -> DataFrame:
    """doc_id, n_words, digest of the joined words, and the keys of the document's phrases, each at most twice."""

    def run(batches):
        for batch in batches:
            for a, b, data, offsets in string_slices(batch.column(1)):
                starts, ends, before = word_spans(data, offsets)
                h = word_hashes(data, starts, ends)
                raw = data.tobytes()
                cols: list[list] = [[], [], [], []]
                for i in range(b - a):
                    s, e = before[i], before[i + 1]
                    joined = b" ".join(raw[offsets[i] : offsets[i + 1]].split())
                    digest = hashlib.sha256(joined)
                    _, hi, lo = _anchors(h[s:e], p) if e - s >= p.window else (None, h[:0].view(np.int64), h[:0].view(np.int64))
                    order = np.lexsort((lo, hi))
                    hi, lo = hi[order], lo[order]
                    third = np.zeros(len(hi), bool)  # two listings are enough to show that a phrase recurs
                    third[2:] = (hi[2:] == hi[:-2]) & (lo[2:] == lo[:-2])
                    for c, x in zip(cols, (e - s, digest.hexdigest(), hi[~third], lo[~third])):
                        c.append(x)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), *(pa.array(c, f.type) for c, f in zip(cols, list(_CODED)[1:]))], schema=_CODED)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, n_words long, kept_sha256 string, hi array<long>, lo array<long>")


_WINDOWS = pa.schema([("hi", pa.int64()), ("lo", pa.int64()), ("doc_id", pa.int64()), ("start", pa.int32()), ("hashes", pa.list_(pa.int64())), ("count", pa.int32())])


def _located(p: Phrases):
    """Shards come as their recurring phrases, then their documents. Each shard's automaton runs over its documents; the
    phrases it locates that are the leftmost least of some window give a row with the hashes of those windows. Windows that
    recur inside a document are settled here and leave as runs (hi null) with their number."""
    import ahocorasick

    def found(doc_id, h, machine, out):
        """Adds to `out` the phrases' keys, document, first window and number of windows, the hashes, and the inner repeats."""
        ends = np.fromiter((e for e, _ in machine.iter(spelled(h))), np.int64)
        hits = (ends[ends % 2 == 1] + 1) // 2 - p.phrase
        if not len(hits):
            return
        hi, lo, order = phrase_keys(h, p.phrase)
        w = p.window - p.phrase + 1
        order = order.view(np.int64)
        recurring = np.zeros(len(order), bool)
        recurring[hits] = True
        # each window belongs to the phrase that is its leftmost least
        owner = sliding_argmin(order, w)
        windows = np.flatnonzero(recurring[owner])
        if not len(windows):
            return
        owner = owner[windows]
        prefix = prefix_hash(h)
        digest = mix(span_hash(prefix, windows, windows + p.window)).view(np.int64)
        # what recurs inside the document is later than its first place there, whatever other documents hold
        fresh = np.zeros(len(digest), bool)
        fresh[np.unique(digest, return_index=True)[1]] = True
        if not fresh.all():
            again = windows[~fresh]
            edge = np.flatnonzero(np.concatenate([[True], again[1:] != again[:-1] + 1, [True]]))
            out["inner"].append((np.full(len(edge) - 1, doc_id), again[edge[:-1]], np.diff(edge)))
            windows, owner, digest = windows[fresh], owner[fresh], digest[fresh]
        edge = np.flatnonzero(np.concatenate([[True], (owner[1:] != owner[:-1]) | (windows[1:] != windows[:-1] + 1), [True]]))
        first = edge[:-1]
        out["rows"].append((hi[owner[first]], lo[owner[first]], np.full(len(first), doc_id), windows[first], np.diff(edge)))
        out["hashes"].append(digest)

    def spelled(h):
        """The words' 16-bit codes as two letters each: a node of the automaton has few letters to look through."""
        return (h & U64(0xFFFF)).astype("<u2").tobytes().decode("latin-1")

    def run(batches):
        shard, machine, ready = None, None, False
        out = {"inner": [], "rows": [], "hashes": []}
        for batch in batches:
            shards, texts, ids = batch.column("shard").to_numpy(), batch.column("text"), batch.column("doc_id")
            plain = ids.is_null().to_numpy(zero_copy_only=False)
            edge = np.flatnonzero(np.concatenate([[True], (shards[1:] != shards[:-1]) | (plain[1:] != plain[:-1]), [True]]))
            for s, e in zip(edge[:-1].tolist(), edge[1:].tolist()):
                if shards[s] != shard:
                    shard, machine, ready = shards[s], ahocorasick.Automaton(ahocorasick.STORE_INTS), False
                if plain[s]:
                    keys = np.stack([batch.column(c).slice(s, e - s).to_numpy().astype("<i8") for c in ("hi", "lo")], 1)
                    raw = np.ascontiguousarray(keys.view(np.uint8).reshape(e - s, 2, 8)[:, :, :6]).tobytes().decode("latin-1")
                    for i in range(0, len(raw), 12):
                        machine.add_word(raw[i : i + 2 * p.phrase], 1)
                    continue
                if not len(machine):
                    continue
                if not ready:
                    ready = True
                    machine.make_automaton()
                names = ids.slice(s, e - s).to_pylist()
                for a, b, data, offsets in string_slices(texts.slice(s, e - s)):
                    starts, ends, before = word_spans(data, offsets)
                    h = word_hashes(data, starts, ends)
                    for i in range(b - a):
                        if before[i + 1] - before[i] >= p.window:
                            found(names[a + i], h[before[i] : before[i + 1]], machine, out)
                    if len(out["rows"]) > 500:
                        yield _rows(out)
                        out = {"inner": [], "rows": [], "hashes": []}
        if out["hashes"]:
            yield _rows(out)

    def _rows(out):
        hi, lo, doc, start, count = (np.concatenate(c) for c in zip(*out["rows"]))
        inner = [np.concatenate(c) for c in zip(*out["inner"])] if out["inner"] else [np.zeros(0, np.int64)] * 3
        n, m = len(hi), len(inner[0])
        none = np.arange(n + m) >= n  # rows of inner repeats have no phrase
        pad = np.zeros(m, np.int64)
        lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(np.concatenate([count, pad]))]).astype(np.int32)), pa.array(np.concatenate(out["hashes"])))
        columns = [pa.array(np.concatenate([hi, pad]), mask=none), pa.array(np.concatenate([lo, pad]), mask=none), pa.array(np.concatenate([doc, inner[0]]))]
        columns += [pa.array(np.concatenate([start, inner[1]]).astype(np.int32)), lists, pa.array(np.concatenate([np.zeros(n, np.int64), inner[2]]).astype(np.int32), mask=~none)]
        return pa.RecordBatch.from_arrays(columns, schema=_WINDOWS)

    return run


def _later(batches):
    """Runs of windows (doc_id, start, count) whose hash also starts earlier, from rows sorted by phrase."""
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int32()), ("count", pa.int32())])
    for table in whole_groups(batches, ["hi", "lo"]):
        hi, lo, doc, start = (table.column(n).to_numpy() for n in ("hi", "lo", "doc_id", "start"))
        lists = table.column("hashes").combine_chunks()
        lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
        count = np.diff(lists.offsets.to_numpy()).astype(np.int64)
        flat = lists.flatten().to_numpy()
        row = np.repeat(np.arange(len(hi)), count)
        at = spread_starts(start.astype(np.int64), count)
        group = np.cumsum(np.concatenate([[True], (hi[1:] != hi[:-1]) | (lo[1:] != lo[:-1])]))[row]
        d = doc[row]
        order = np.lexsort((at, d, flat, group))
        g, f = group[order], flat[order]
        d, at = d[order], at[order]
        new = np.concatenate([[True], (g[1:] != g[:-1]) | (f[1:] != f[:-1])])
        head = np.flatnonzero(new)[np.cumsum(new) - 1]
        again = (d != d[head]) | (at != at[head])
        d, at = d[again], at[again]
        if not len(d):
            continue
        order = np.lexsort((at, d))
        d, at = d[order], at[order]
        edge = np.flatnonzero(np.concatenate([[True], (d[1:] != d[:-1]) | (at[1:] != at[:-1] + 1), [True]]))
        first, last = edge[:-1], edge[1:] - 1
        yield pa.RecordBatch.from_arrays([pa.array(d[first]), pa.array(at[first].astype(np.int32)), pa.array((at[last] - at[first] + 1).astype(np.int32))], schema=schema)


_RESULT = "doc_id long, n_words long, n_removed long, kept_sha256 string"


def _trimmed(p: Phrases, with_text: bool):
    """Words outside the runs of later windows: (doc_id, text, runs) to counts and digest (or the text that is left)."""

    def run(batches):
        for batch in batches:
            ids, rows = batch.column("doc_id").to_pylist(), []
            texts, runs = batch.column("text"), batch.column("runs").to_pylist()
            for i, doc_id in enumerate(ids):
                words = (texts[i].as_py() or "").encode().split()
                gone = np.zeros(len(words) + 1, np.int32)
                for r in runs[i]:
                    gone[r["start"]] += 1
                    gone[r["start"] + r["count"] + p.window - 1] -= 1
                keep = np.cumsum(gone)[:-1] == 0
                left = b" ".join([w for w, k in zip(words, keep.tolist()) if k])
                rows.append((doc_id, len(words), int(len(words) - keep.sum()), left.decode() if with_text else hashlib.sha256(left).hexdigest()))
            if rows:
                a, b, c, d = zip(*rows)
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(c, pa.int64()), pa.array(d, pa.string())], names=["doc_id", "n_words", "n_removed", "kept_sha256"])

    return run


def later_windows(docs: DataFrame, p: Phrases, keep: Durable) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The coded documents, the ids of later copies (equal words as an earlier document), and the runs of windows that
    start earlier elsewhere as (doc_id, runs array<struct<start,count>>) for all but those copies."""
    spark = docs.sparkSession
    coded = keep(coded_documents(docs, p), "coded")
    first = coded.filter(F.col("n_words") >= p.window).groupBy("kept_sha256").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).filter("first <> last")
    copies = keep(coded.select("doc_id", "kept_sha256").join(first, "kept_sha256").filter("doc_id <> first").select("doc_id").distinct(), "copies")
    single = without(coded.select("doc_id", "hi", "lo"), "doc_id", copies, "doc_id")
    spelled = single.select("doc_id", F.explode(F.arrays_zip("hi", "lo")).alias("k")).select("doc_id", "k.hi", "k.lo")
    counted = spelled.groupBy("hi", "lo").agg(F.count("*").alias("n"))
    recurring = keep(counted.filter("n > 1"), "recurring")
    found = maybe_in(spelled.withColumn("_key", F.xxhash64("hi", "lo")), "_key", recurring.select(F.xxhash64("hi", "lo").alias("_key")), "_key", 24).drop("_key")
    shards = 4 * partitions(spark)
    own = keep(found.join(recurring.drop("n"), ["hi", "lo"]), "found")
    shard = F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(shards)).cast("int")
    phrases = own.select(shard.alias("shard"), "hi", "lo").distinct().select("shard", F.lit(None).cast("long").alias("doc_id"), "hi", "lo", F.lit(None).cast("string").alias("text"))
    members = keep(own.select("doc_id").distinct(), "members")
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    texts = maybe_in(plain, "doc_id", members, "doc_id")
    texts = without(texts, "doc_id", copies, "doc_id")
    texts = texts.select(shard.alias("shard"), "doc_id", F.lit(None).cast("long").alias("hi"), F.lit(None).cast("long").alias("lo"), "text")
    dealt = phrases.union(texts).repartition(shards, "shard").sortWithinPartitions("shard", F.col("doc_id").asc_nulls_first())
    located = keep(dealt.mapInArrow(_located(p), "hi long, lo long, doc_id long, start int, hashes array<long>, count int"), "windows")
    windows = located.filter("hi is not null").drop("count")
    counts = windows.groupBy("hi", "lo").agg(F.count("*").alias("n"))
    hot = keep(counts.filter(F.col("n") > p.crowd).select("hi", "lo", F.xxhash64("hi", "lo").alias("_key")), "hot")
    calm = without(windows.withColumn("_key", F.xxhash64("hi", "lo")), "_key", hot, "_key", 16, whole=True).drop("_key")
    n = partitions(spark)
    runs = calm.repartition(n, "hi", "lo").sortWithinPartitions("hi", "lo").mapInArrow(_later, "doc_id long, start int, count int")
    # hot phrases: rows with equal windows all are later but for the first of them, so only first rows are taken apart by window
    crowded = keep(maybe_in(windows.withColumn("_key", F.xxhash64("hi", "lo")), "_key", hot, "_key", 16).join(hot.select("hi", "lo"), ["hi", "lo"]).select("hi", "lo", "doc_id", "start", "hashes"), "crowded")
    firsts = keep(crowded.groupBy("hi", "lo", "hashes").agg(F.min(F.struct("doc_id", "start")).alias("e")).select("hi", "lo", "e.doc_id", "e.start", "hashes"), "firsts")
    whole = crowded.join(firsts, ["doc_id", "start", "hi", "lo", "hashes"], "left_anti").select("doc_id", "start", F.size("hashes").alias("count"))
    apart = firsts.select("hi", "lo", "doc_id", "start", F.posexplode("hashes").alias("i", "h")).select("hi", "lo", "h", "doc_id", (F.col("start") + F.col("i")).alias("start"))
    earliest = apart.groupBy("hi", "lo", "h").agg(F.min(F.struct("doc_id", "start")).alias("e"))
    later = apart.join(earliest, ["hi", "lo", "h"]).filter("struct(doc_id, start) <> e")
    of_doc = Window.partitionBy("doc_id").orderBy("start")
    later = later.withColumn("_new", F.coalesce((F.col("start") > F.lag("start").over(of_doc) + 1).cast("int"), F.lit(1))).withColumn("_run", F.sum("_new").over(of_doc.rowsBetween(Window.unboundedPreceding, 0)))
    more = later.groupBy("doc_id", "_run").agg(F.min("start").cast("int").alias("start"), (F.max("start") - F.min("start") + 1).cast("int").alias("count")).drop("_run")
    grouped = runs.union(more).union(whole).union(located.filter("hi is null").select("doc_id", "start", "count")).groupBy("doc_id").agg(F.collect_list(F.struct("start", "count")).alias("runs"))
    return coded, copies, keep(grouped, "runs")


def trimmed_texts(docs: DataFrame, p: Phrases, keep: Durable, with_text: bool) -> tuple[DataFrame, DataFrame, DataFrame]:
    coded, copies, runs = later_windows(docs, p, keep)
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    cut = maybe_in(plain, "doc_id", runs, "doc_id").join(runs, "doc_id").mapInArrow(_trimmed(p, with_text), _RESULT).dropDuplicates(["doc_id"])
    return coded, copies, cut


def repeated_words(docs: DataFrame, p: Phrases = Phrases()) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256: words covered by a window of `window` words that also starts earlier go.

    Phrases of a few words, chosen from the content alone, recur wherever a window recurs. Recurring phrases are dealt
    with their documents to shards; an Aho-Corasick automaton per shard locates them; the windows at the located
    phrases are compared within their phrase, whose six words they share, by a 64-bit hash of all their words. A document whose words all equal an earlier document's is cut without
    that. Null, empty and short texts have no windows and lose nothing; rows that repeat a doc_id count as one document.
    """
    keep = Durable(docs.sparkSession)
    coded, copies, cut = trimmed_texts(docs, p, keep, False)
    cut = cut.select(F.col("doc_id").alias("_c"), F.col("n_removed").alias("_r"), F.col("kept_sha256").alias("_k"))
    gone = copies.select(F.col("doc_id").alias("_g"))
    out = coded.select("doc_id", "n_words", "kept_sha256").join(cut, F.col("doc_id") == F.col("_c"), "left").join(gone, F.col("doc_id") == F.col("_g"), "left")
    removed = F.when(F.col("_g").isNotNull(), F.col("n_words")).otherwise(F.coalesce("_r", F.lit(0)))
    digest = F.when(F.col("_g").isNotNull(), F.lit(hashlib.sha256(b"").hexdigest())).otherwise(F.coalesce("_k", "kept_sha256"))
    return out.select("doc_id", "n_words", removed.cast("long").alias("n_removed"), digest.alias("kept_sha256"))


def without_repeats(docs: DataFrame, p: Phrases = Phrases()) -> DataFrame:
    """The documents with the words that are left, joined by spaces where words were removed; other columns as they were."""
    keep = Durable(docs.sparkSession)
    _, copies, cut = trimmed_texts(docs, p, keep, True)
    cut = cut.select(F.col("doc_id").alias("_c"), F.col("kept_sha256").alias("_left"))
    gone = copies.select(F.col("doc_id").alias("_g"))
    out = docs.join(cut, docs["doc_id"] == F.col("_c"), "left").join(gone, docs["doc_id"] == F.col("_g"), "left")
    text = F.when(F.col("_g").isNotNull(), F.lit("")).otherwise(F.coalesce("_left", docs["text"])).alias("text")
    return out.select(*[text if c == "text" else docs[c] for c in docs.columns])
