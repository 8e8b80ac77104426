"""Packing token streams into windows by minimum bin slack over the multiset of remaining lengths."""

from __future__ import annotations

import json
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import Durable, partitions

WINDOW = 1024
# fixed value: how the byte-level vocabulary splits text before merging
SPLIT_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
_encoders: dict = {}


def plain_byte_level(spec: dict) -> bool:
    """Whether the file splits and merges as the fast way does: byte letters, the usual split pattern, nothing normalised, no
    prefix space, and no merge option that changes ids."""
    split, model = spec.get("pre_tokenizer") or {}, spec["model"]
    options = [model.get(o) for o in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges")]
    return not spec.get("normalizer") and split.get("type") == "ByteLevel" and not split.get("add_prefix_space") and split.get("use_regex", True) and not any(options)


def encoder(path: str):
    """A function text -> uint32 ids of the byte-level vocabulary file at `path`.

    A file that `plain_byte_level` accepts is run by tiktoken, which gives the same ids as the file's own library
    (tested on whole tables) some seven times faster; any other file is run by its own library, tokenizers.
    """
    if path not in _encoders:
        spec = json.load(open(path, encoding="utf-8"))
        if spec["model"]["type"] == "BPE" and plain_byte_level(spec):
            import tiktoken

            shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
            letter = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in shown)}
            special = {t["content"] for t in spec.get("added_tokens", ())}
            ranks = {bytes(letter[c] for c in k): v for k, v in spec["model"]["vocab"].items() if k not in special}
            own = tiktoken.Encoding("own", pat_str=SPLIT_PATTERN, mergeable_ranks=ranks, special_tokens={})
            _encoders[path] = lambda text: np.asarray(own.encode_ordinary(text), np.uint32)
        else:
            from tokenizers import Tokenizer

            own = Tokenizer.from_file(path)
            own.encode_special_tokens = True
            _encoders[path] = lambda text: np.asarray(own.encode(text, add_special_tokens=False).ids, np.uint32)
    return _encoders[path]


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


_PIECE = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("ids", pa.list_(pa.int64()))])


def cut_pieces(docs: DataFrame, vocabulary: str, window: int = WINDOW, with_ids: bool = False) -> DataFrame:
    """Documents cut into whole windows and a remainder: doc_id, start, length, ids_crc32, doc_tokens (and the ids).

    A null or empty text is the single id 0; every document ends with id 0. Repeated rows are cut again.
    """
    schema = pa.schema(list(_PIECE)[: 6 if with_ids else 5])

    def run(batches):
        encode = encoder(vocabulary)
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                out: list[list] = [[] for _ in schema]
                for doc_id, text in zip(batch.column(0).slice(at, 500).to_pylist(), batch.column(1).slice(at, 500).to_pylist()):
                    ids = np.append(encode(text or ""), np.uint32(0)).astype("<u4")
                    raw = ids.tobytes()
                    for s in range(0, len(ids), window):
                        piece = raw[4 * s : 4 * (s + window)]
                        for column, x in zip(out, (doc_id, s, len(piece) // 4, zlib.crc32(piece), len(ids), ids[s : s + window].astype(np.int64) if with_ids else None)):
                            column.append(x)
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, schema)], schema=schema)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long" + ", ids array<long>" * with_ids)


def fullest(counts: dict[int, int], room: int) -> dict[int, int]:
    """A multiset of the lengths (each at most as often as it is there) whose sum is closest to `room` from below.

    Subset sums are the bits of one integer; a length's count is split into 1, 2, 4, ... copies, each one shift. The
    reachable sets after each step are kept, and the way back from the best sum gives the counts.
    """
    mask = (1 << room + 1) - 1
    reach, steps = 1, []
    for length in sorted(counts, reverse=True):
        left, chunk = min(counts[length], room // length), 1
        while left > 0:
            take = min(chunk, left)
            steps.append((length, take, reach))
            reach |= reach << take * length & mask
            left -= take
            chunk *= 2
        if reach >> room & 1:
            break
    total, used = reach.bit_length() - 1, {}
    for length, take, before in reversed(steps):
        if not before >> total & 1:
            used[length] = used.get(length, 0) + take
            total -= take * length
    return used


def bin_patterns(histogram: dict[int, int], window: int = WINDOW) -> list[tuple[dict[int, int], int]]:
    """(counts by length, how many windows are filled so) that use up the histogram.

    Each window takes the longest length left and the fullest filling of the rest; the same filling is repeated as
    often as the counts allow, so the number of patterns depends on the lengths and not on the documents.
    """
    left, out = {n: c for n, c in histogram.items() if c > 0}, []
    while left:
        longest = max(left)
        rest = dict(left)
        rest[longest] -= 1
        used = fullest({n: c for n, c in rest.items() if c > 0 and n <= window - longest}, window - longest) if longest < window else {}
        used[longest] = used.get(longest, 0) + 1
        times = min(left[n] // c for n, c in used.items())
        out.append((dict(sorted(used.items(), reverse=True)), times))
        for n, c in used.items():
            left[n] -= c * times
            if not left[n]:
                del left[n]
    return out


def place_pieces(pieces: DataFrame, window: int = WINDOW) -> tuple[DataFrame, list]:
    """Adds sequence_id and offset to written pieces; also returns the patterns.

    Pieces of a length are ranked within hashed salts, on top of the salts' counts, so a length that most pieces have
    is not one task. A rank finds its window in the patterns' table, which has at most a few rows per length pair.
    """
    spark = pieces.sparkSession
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `window` rows
    patterns = bin_patterns(histogram, window)
    parts, used, base = {}, dict.fromkeys(histogram, 0), 0
    for counts, times in patterns:
        offset = 0
        for length, c in counts.items():
            parts.setdefault(length, []).append((used[length], base, c, offset))
            used[length] += c * times
            offset += c * length
        base += times
    starts = {n: [x[0] for x in p] for n, p in parts.items()}
    schema = pa.schema([*list(_PIECE)[:5], ("sequence_id", pa.int64()), ("offset", pa.int64())])

    def locate(batches):
        for batch in batches:
            length, rank = batch.column("length").to_numpy(), batch.column("rank").to_numpy()
            sequence, offset = np.empty(len(rank), np.int64), np.empty(len(rank), np.int64)
            for n in np.unique(length):
                m = length == n
                table = np.array(parts[int(n)], np.int64)
                row = table[np.searchsorted(starts[int(n)], rank[m], "right") - 1]
                q = rank[m] - row[:, 0]
                sequence[m] = row[:, 1] + q // row[:, 2]
                offset[m] = row[:, 3] + q % row[:, 2] * n
            yield pa.RecordBatch.from_arrays([*(batch.column(f.name) for f in list(schema)[:5]), pa.array(sequence), pa.array(offset)], schema=schema)

    salts = max(64, 4 * partitions(spark))
    salted = pieces.withColumn("_salt", F.pmod(F.xxhash64("doc_id", "start"), F.lit(salts)))
    counts = salted.groupBy("length", "_salt").agg(F.count("*").alias("_n"))
    below = counts.withColumn("_below", F.coalesce(F.sum("_n").over(Window.partitionBy("length").orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_n")
    inner = F.row_number().over(Window.partitionBy("length", "_salt").orderBy("doc_id", "start", "ids_crc32")) - 1
    ranked = salted.join(below, ["length", "_salt"]).withColumn("rank", (F.col("_below") + inner).cast("long"))
    return ranked.select(*[f.name for f in list(schema)[:5]], "rank").mapInArrow(locate, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"), patterns


def pack_documents(docs: DataFrame, vocabulary: str | None = None, window: int = WINDOW) -> DataFrame:
    """All documents as pieces in sequences of at most `window` tokens: doc_id, start, length, ids_crc32, doc_tokens,
    sequence_id, offset.

    Whole windows stand alone; remainders share windows by minimum bin slack. The pieces are written once to the
    shared folder, so texts are tokenized once and never shuffled. Empty tables give no rows.
    """
    keep = Durable(docs.sparkSession)
    pieces = keep(cut_pieces(docs, vocabulary or default_vocabulary(), window), "pieces")
    return place_pieces(pieces, window)[0]


def pack_tokens(docs: DataFrame, vocabulary: str | None = None, window: int = WINDOW, pad_id: int = 0) -> DataFrame:
    """The packed sequences themselves: sequence_id, ids (array of `window` ids, padded), n_tokens.

    Sequences whose token number is a power of two stay unpadded.
    """
    keep = Durable(docs.sparkSession)
    cut = keep(cut_pieces(docs, vocabulary or default_vocabulary(), window, True), "pieces")
    placed, _ = place_pieces(cut.drop("ids"), window)
    # equal pieces of a repeated doc_id are interchangeable: number them on both sides
    nth = F.row_number().over(Window.partitionBy("doc_id", "start", "ids_crc32").orderBy("length"))
    joined = placed.withColumn("_nth", nth).join(cut.withColumn("_nth", nth).select("doc_id", "start", "ids_crc32", "_nth", "ids"), ["doc_id", "start", "ids_crc32", "_nth"])
    out = joined.groupBy("sequence_id").agg(F.sum("length").alias("n_tokens"), F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("offset", "ids"))), lambda x: x["ids"])).alias("ids"))
    whole = F.when(F.expr("n_tokens & (n_tokens - 1)") == 0, F.col("ids")).otherwise(F.concat("ids", F.array_repeat(F.lit(pad_id).cast("long"), F.lit(window) - F.col("n_tokens").cast("int"))))
    return out.select("sequence_id", "n_tokens", whole.alias("ids"))


def slack(patterns: list, window: int = WINDOW) -> int:
    """Padding tokens of the patterns' windows (0 for a token number that is a power of two)."""
    sums = [(sum(n * c for n, c in counts.items()), times) for counts, times in patterns]
    return sum((window - s) * times for s, times in sums if s & (s - 1))


