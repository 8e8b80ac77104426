"""The corpus pipeline on a small folder of tables: each stage against a plain version on what the stage before kept."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

pytest.importorskip("graphslice.llm")
corpus_pipeline = pytest.importorskip("corpus_pipeline")
from graphslice.llm import packing, surrogates, toxicity  # noqa: E402
from test_operators import near_groups  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, cell long, block int, region long"


def rows_of(seed=3):
    rng = random.Random(seed)
    w = lambda n, p="w": " ".join(f"{p}{rng.randrange(900)}" for _ in range(n))
    base = w(120)
    texts = [None, "", " \t\n", "one", base, base, base + " tail", "x " * 4000, w(3000), "write to ab.cd@mail.org or +1 (017) 555-7713 " + w(30), "ab.cd@mail.org " + w(12)]
    texts += [w(40) for _ in range(40)] + [w(20) + " " + w(8, "vile") for _ in range(20)]
    rows = [(i, t, "en", ["a", "b", None][i % 3], None if t is None else len(t), "k", 1, 2, 3) for i, t in enumerate(texts)]
    return rows + rows[4:6]  # repeated rows


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = f"file://{tmp_path_factory.mktemp('tables')}"
    rows = rows_of()
    spark.createDataFrame(rows, SCHEMA).repartition(3).write.parquet(f"{path}/documents.parquet")
    marks = [(i, 1, int("vile" in (t or ""))) for i, t, *_ in rows[:71]]
    spark.createDataFrame(marks, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    spark.createDataFrame([], SCHEMA).write.parquet(f"{path}/none.parquet")
    return path


def plain(df):
    return sorted((tuple(r) for r in df.collect()), key=repr)


def words(t):
    return len((t or "").encode().split())


def test_stages_against_plain_versions(spark, folder):
    docs, columns = spark.read.parquet(f"{folder}/documents.parquet"), SCHEMA.count(",") + 1
    stages = dict(corpus_pipeline.STAGES)
    kept = stages["toxicity"](spark, docs, folder)
    model = toxicity.train(docs, spark.read.parquet(f"{folder}/labels.parquet"))
    weight = dict(zip(model.features.tolist(), model.weights.tolist()))

    def score(t):
        raw = np.frombuffer((t or "").encode(), np.uint8)
        _, features = toxicity.row_features(raw, np.array([0, len(raw)]))
        return 1 / (1 + np.exp(-model.bias - sum(weight.get(f, 0.0) for f in features.tolist())))

    want = sorted((tuple(r) for r in docs.collect() if score(r["text"]) < 0.7), key=repr)
    assert plain(kept) == want and 40 <= len(want) < docs.count() and sum("vile" in (r[1] or "") for r in want) < 20
    scored = {r["doc_id"]: r["score"] for r in toxicity.toxic_scores(docs, spark.read.parquet(f"{folder}/labels.parquet")).collect()}
    assert all(abs(scored[r["doc_id"]] - score(r["text"])) < 1e-9 for r in docs.collect())

    kept = spark.createDataFrame(want, SCHEMA)
    alone = stages["near-duplicates"](spark, kept, folder)
    groups = near_groups([(r[0], r[1]) for r in want], 5, 80)
    want = sorted((r for r in want if groups[r[0]][2]), key=repr)
    assert plain(alone) == want and len(alone.columns) == columns

    alone = spark.createDataFrame(want, SCHEMA)
    clean = stages["pii"](spark, alone, folder)
    got = plain(clean)
    assert clean.columns == alone.columns and len(got) == len(want)
    before, after = {r[0]: r for r in want}, {r[0]: r for r in got}
    assert all(after[i][2:4] == r[2:4] and after[i][5:] == r[5:] for i, r in before.items())
    assert all((after[i][1] == r[1]) == ("@" not in (r[1] or "")) for i, r in before.items())
    mail = after[9][1].split()[2]
    assert "@" in mail and "ab.cd@mail.org" not in after[9][1] and after[10][1].startswith(mail + " ") and after[9][4] == len(after[9][1])

    clean = spark.createDataFrame(got, SCHEMA)
    mixed = stages["mixing"](spark, clean, folder)
    out = plain(mixed)
    assert set(out) <= set(got) and mixed.columns == clean.columns
    size, taken = {}, {}
    for r in got:
        size[r[3]] = size.get(r[3], 0) + words(r[1])
    for r in out:
        assert words(r[1])
        taken[r[3]] = taken.get(r[3], 0) + words(r[1])
    longest = max(words(r[1]) for r in got)
    assert all(taken[s] <= 2 * n + longest for s, n in size.items()) and abs(sum(taken.values()) - 1.5 * sum(size.values())) < 3 * longest + 4 * len(size)

    pieces = stages["packing"](spark, spark.createDataFrame(out, SCHEMA), folder).collect()
    encode, ids = packing.encoder(packing.default_vocabulary()), {}
    for r in out:
        ids.setdefault(r[0], []).append(len(encode(r[1] or "")) + 1)
    for i, lengths in ids.items():
        assert sum(p["length"] for p in pieces if p["doc_id"] == i) == sum(lengths)
    sequences = {}
    for p in pieces:
        sequences.setdefault(p["sequence_id"], []).append((p["offset"], p["length"]))
    for s in sequences.values():
        end = 0
        for a, n in sorted(s):
            assert a == end
            end += n
        assert end <= 1024


def test_whole_pipeline(spark, folder):
    a, b = (plain(corpus_pipeline.run(spark, folder).select("doc_id", "start", "length", "ids_crc32")) for _ in range(2))
    assert a == b and len(a) > 40


def test_empty_documents(spark, folder):
    none = spark.read.parquet(f"{folder}/none.parquet")
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, none, folder).count() == 0, name


def test_session_key(spark):
    d = spark.createDataFrame([(1, "ab.cd@mail.org")], "doc_id long, text string")
    images = {surrogates.replace_entities(d, k).first()["text"] for k in ("a", "b", "c")}
    assert len(images) == 3


def test_encoder_equals_the_files_library_on_a_whole_table(spark, sf):
    from tokenizers import Tokenizer

    path = packing.default_vocabulary()
    own, encode = Tokenizer.from_file(path), packing.encoder(path)
    texts = [r[0] or "" for r in spark.read.parquet(f"{sf}/documents.parquet").select("text").collect()]
    texts += ["x" * 100_000, "é中" * 20_000, " " * 30_000]
    for t, e in zip(texts, own.encode_batch(texts, add_special_tokens=False)):
        assert encode(t).tolist() == e.ids


def test_vectors_of_many_lengths(spark):
    from graphslice.llm import lattice

    rng = np.random.default_rng(0)
    rows = []
    for n in range(1, 1200):
        v = (1 + rng.random(n)).tolist()
        rows += [(2 * n, v, 0), (2 * n + 1, [*v[:-1], v[-1] * 1.0001], 0)]
    got = lattice.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")).filter("n_links = 1 and component_id = vec_id - vec_id % 2")
    assert got.count() == len(rows)
