"""Toxicity by non-negative positive-unlabelled learning on words and word stems: a numpy classifier from confirmed examples and plain text."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BYTE_CODES, LOWER, mix, settle, string_slices, word_hashes, word_spans

FEATURE_BITS = 22
#: Stems are the first so many characters of a word; a stem counts by the number of distinct words with it that a text has.
STEMS = (4, 6)
LEVELS = (1, 2, 3, 5)
CODES = BYTE_CODES[LOWER]  # A-Z count as a-z
PUNCTUATION = np.zeros(256, bool)
PUNCTUATION[[c for c in range(33, 127) if not chr(c).isalnum()]] = True


@dataclass(frozen=True)
class Settings:
    """Bounds of the fitting sample and of the model. The sample holds the labelled (positive) and unlabelled training
    rows of least hashed id; scoring always reads every document."""

    most_positive: int = 3000
    most_unlabelled: int = 9000
    features: int = 1500
    least_support: int = 3
    least_ratio: float = 15.0
    epochs: int = 400
    rate: float = 0.05
    shrink: float = 1e-3
    beta: float = 0.0
    threshold: float = 0.7


def _stem_features(data: np.ndarray, row: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> list[np.ndarray]:
    """Hashes of (row, stem, level) from each row's distinct words: the level is reached by that many words with the stem."""
    letters = np.flatnonzero((data & 0xC0) != 0x80)
    place = np.searchsorted(letters, starts)
    letters = np.append(letters, np.full(max(STEMS), len(data)))
    out = []
    for n in STEMS:
        close = letters[place + n]
        long = close <= ends
        h = word_hashes(data, starts[long], close[long], CODES)
        r = row[long]
        order = np.lexsort((h, r))
        h, r = h[order], r[order]
        first = np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (r[1:] != r[:-1]))) if len(h) else np.zeros(0, np.int64)
        count = np.diff(np.append(first, len(h)))
        for level in LEVELS:
            at = first[count >= level]
            out.append(_keys(r[at], mix(h[at] ^ np.uint64(n << 8 | level))))
    return out


def _keys(row: np.ndarray, h: np.ndarray) -> np.ndarray:
    return row.astype(np.int64) << FEATURE_BITS | (h >> np.uint64(64 - FEATURE_BITS)).astype(np.int64)


def row_features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (row, feature) pairs, sorted by row: hashed lower-cased words without punctuation at their ends, and
    their stems with the levels that they reach."""
    starts, ends, before = word_spans(data, offsets)
    if not len(starts):
        z = np.zeros(0, np.int64)
        return z, z
    for _ in range(3):
        m = PUNCTUATION[data[starts]] & (ends - starts > 1)
        starts = starts + m
        m = PUNCTUATION[data[ends - 1]] & (ends - starts > 1)
        ends = ends - m
    h = word_hashes(data, starts, ends, CODES)
    row = np.searchsorted(offsets, starts, "right") - 1
    _, at = np.unique(mix(h ^ mix(row.astype(np.uint64) + np.uint64(1))), return_index=True)
    key = np.unique(np.concatenate([_keys(row[at], h[at]), *_stem_features(data, row[at], starts[at], ends[at])]))
    return key >> FEATURE_BITS, key & ((1 << FEATURE_BITS) - 1)


def document_features(docs: DataFrame, carry: str) -> DataFrame:
    """(carried long column, features array<int>) per row."""
    schema = pa.schema([(carry, pa.int64()), ("features", pa.list_(pa.int32()))])

    def run(batches):
        for batch in batches:
            for a, b, data, offsets in string_slices(batch.column(1)):
                row, feature = row_features(data, offsets)
                cut = np.searchsorted(row, np.arange(b - a + 1)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.ListArray.from_arrays(pa.array(cut), pa.array(feature.astype(np.int32)))], schema=schema)

    return docs.select(F.col(carry).cast("long").alias(carry), F.col("text").cast("string").alias("text")).mapInArrow(run, f"{carry} long, features array<int>")


@dataclass
class Model:
    features: np.ndarray
    weights: np.ndarray
    bias: float
    prior: float
    losses: list


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


def fit_nnpu(positive: list[np.ndarray], unlabelled: list[np.ndarray], prior: float, s: Settings = Settings()) -> Model:
    """Minimise prior * R+(positive) + max(beta, R-(unlabelled) - prior * R-(positive)) with the logistic loss.

    When the corrected negative risk falls below -beta, the step goes up its gradient instead (the non-negative
    correction). Features are the words and stem levels whose document share is most enriched among the positives. Deterministic.
    """
    size = 1 << FEATURE_BITS
    dp, du = np.zeros(size, np.int32), np.zeros(size, np.int32)
    for counts, rows in ((dp, positive), (du, unlabelled)):
        for r in rows:
            counts[r] += 1
    n_p, n_u = max(1, len(positive)), max(1, len(unlabelled))
    able = np.flatnonzero(dp >= s.least_support)
    a, b = (dp[able] + 0.5) / (n_p + 1), (du[able] + 0.5) / (n_u + 1)
    able = able[a > 3 * b]
    dp, du = dp[able].astype(np.float64), du[able].astype(np.float64)
    # a feature counts if its share among the positives is far above that of plain text: likelihood ratio of one rate against two
    rate = (dp + du) / (n_p + n_u)
    with np.errstate(divide="ignore", invalid="ignore"):
        term = lambda k, n, q: np.where(k > 0, k * np.log(k / np.maximum(n * q, 1e-300)), 0) + np.where(n - k > 0, (n - k) * np.log((n - k) / np.maximum(n * (1 - q), 1e-300)), 0)
        score = np.nan_to_num(2 * (term(dp, n_p, rate) + term(du, n_u, rate)))
    kept = np.flatnonzero(score > s.least_ratio)
    chosen = np.sort(able[kept[np.argsort(-score[kept], kind="stable")][: s.features]])
    place = np.full(size, -1, np.int32)
    place[chosen] = np.arange(len(chosen))

    def entries(rows):
        """The ones of the documents' feature matrix, as rows and columns."""
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        for i, x in enumerate(rows):
            c = place[x]
            c = c[c >= 0]
            out.append((np.full(len(c), i), c))
        return tuple(np.concatenate(x) for x in zip(*out))

    (rp, cp_), (ru, cu_) = entries(positive), entries(unlabelled)
    del place
    of = lambda r, c, w, n: np.bincount(r, w[c], n)
    back = lambda r, c, g, n: np.bincount(c, g[r], n)
    w, bias = np.zeros(len(chosen)), float(np.log(max(prior, 1e-4) / max(1 - prior, 1e-4)))
    m, v, t, losses = np.zeros(len(chosen) + 1), np.zeros(len(chosen) + 1), 0, []
    for _ in range(s.epochs if len(chosen) and len(positive) else 0):
        fp, fu = of(rp, cp_, w, len(positive)) + bias, of(ru, cu_, w, len(unlabelled)) + bias
        gp_plus, gp_minus, gu_minus = -_sigmoid(-fp), _sigmoid(fp), _sigmoid(fu)
        plus = np.logaddexp(0, -fp).mean()
        corrected = np.logaddexp(0, fu).mean() - prior * np.logaddexp(0, fp).mean()
        losses.append(prior * plus + max(corrected, 0.0))
        if corrected >= -s.beta:
            cp, cu = (prior * gp_plus - prior * gp_minus) / n_p, gu_minus / n_u
        else:
            cp, cu = prior * gp_minus / n_p, -gu_minus / n_u
        g = np.append(back(rp, cp_, cp, len(w)) + back(ru, cu_, cu, len(w)) + s.shrink * w * prior, cp.sum() + cu.sum())
        t += 1
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        step = s.rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        w, bias = w - step[:-1], bias - step[-1]
    return Model(chosen, w, bias, prior, losses)


FOLD = "pmod(crc32(cast(cast(doc_id as string) as binary)), 3)"


def train(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> Model:
    """Fit on the training fold. The prior is the toxic share of its labelled rows; unlabelled text is any document of it.

    No labelled positives give a model that scores everything at the prior's floor.
    """
    marked = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).filter("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic")).filter(f"{FOLD} <> 1")
    n, toxic = marked.agg(F.count("*"), F.sum("toxic")).first()
    prior = min(0.9, max(0.005, (toxic or 0) / n)) if n else 0.05
    order = F.xxhash64("doc_id", F.lit(11))
    positive = marked.filter("toxic = 1").withColumn("_o", order).orderBy("_o").limit(s.most_positive).select(F.col("doc_id").alias("_id"), F.lit(1).alias("_role"))
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id")).filter("doc_id is not null").filter(f"{FOLD} <> 1").withColumn("_o", order).orderBy("_o").limit(s.most_unlabelled).select(F.col("doc_id").alias("_id"), F.lit(0).alias("_role"))
    ids = positive.union(plain).groupBy("_id").agg(F.sum(F.when(F.col("_role") == 1, 1)).alias("_p"), F.sum(F.when(F.col("_role") == 0, 1)).alias("_u"))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(ids), F.col("doc_id") == F.col("_id"))  # at most most_positive + most_unlabelled ids
    coded = rows.select((F.col("_p").isNotNull().cast("long") + 2 * F.col("_u").isNotNull().cast("long")).alias("role"), "text", "doc_id")
    got = document_features(coded, "role").toArrow()
    roles, lists = got.column("role").to_pylist(), got.column("features").combine_chunks()
    flat, cut = lists.flatten().to_numpy(), lists.offsets.to_numpy() - (lists.offsets[0].as_py() if len(lists) else 0)
    each = [flat[cut[i] : cut[i + 1]] for i in range(len(roles))]
    # partitions end in any order: fix the rows' order so that reruns agree
    order = sorted(range(len(roles)), key=lambda i: (len(each[i]), each[i].tobytes(), roles[i]))
    model = fit_nnpu([each[i] for i in order if roles[i] & 1], [each[i] for i in order if roles[i] & 2], prior, s)
    del got, lists, flat, each
    settle(docs.sparkSession)  # the sample's memory goes back before the scoring pass
    return model


def score_documents(docs: DataFrame, model: Model, s: Settings = Settings(), carry: str = "doc_id") -> DataFrame:
    """(carried column, score) of every whole text in one narrow pass; null and empty texts get the model's bias alone."""
    bias = model.bias
    schema = pa.schema([(carry, pa.int64()), ("score", pa.float64())])
    packed = (model.features.astype(np.int32), model.weights.astype(np.float64))

    def run(batches):
        weights = np.zeros(1 << FEATURE_BITS)
        weights[packed[0]] = packed[1]
        known = np.zeros(1 << FEATURE_BITS, bool)
        known[packed[0]] = True
        for batch in batches:
            for a, b, data, offsets in string_slices(batch.column(1)):
                total = np.full(b - a, bias)
                row, feature = row_features(data, offsets)
                hit = known[feature]
                np.add.at(total, row[hit], weights[feature[hit]])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(_sigmoid(total))], schema=schema)

    return docs.select(F.col(carry).cast("long").alias(carry), F.col("text").cast("string").alias("text")).mapInArrow(run, f"{carry} long, score double")


def toxic_scores(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> DataFrame:
    """doc_id, held_out, score, predicted of every document. Null ids are scored but never train; repeated rows stay."""
    model = train(docs, labels, s)
    scored = score_documents(docs, model, s)
    return scored.select("doc_id", F.expr(f"coalesce({FOLD} = 1, false)").alias("held_out"), "score", (F.col("score") >= s.threshold).cast("int").alias("predicted"))


def keep_civil(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> DataFrame:
    """Documents that the classifier does not reject, all columns kept. Texts are not shuffled: each row is judged where it is read."""
    model = train(docs, labels, s)
    packed = (model.features.astype(np.int32), model.weights.astype(np.float64), model.bias)
    at = docs.columns.index("text")
    cut = float(np.log(s.threshold / (1 - s.threshold)))

    def run(batches):
        weights = np.zeros(1 << FEATURE_BITS)
        weights[packed[0]] = packed[1]
        for batch in batches:
            total = np.full(batch.num_rows, packed[2])
            for a, b, data, offsets in string_slices(batch.column(at)):
                row, feature = row_features(data, offsets)
                np.add.at(total, row + a, weights[feature])
            yield batch.filter(pa.array(total < cut))

    return docs.mapInArrow(run, docs.schema)
