"""Training-data operators on small inputs: plain versions, round trips, and the cases that break naive code."""

import hashlib
import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

brute = pytest.importorskip("brute")
pytest.importorskip("graphslice.llm")
from graphslice.llm import common, lattice, media, minhash, mixing, packing, phrases, suffixes, surrogates, toxicity, urls  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, cell long, block int"  # last ones: clashing names


def docs_of(spark, texts, sources=None):
    rows = [(i, t, None, (sources or ["s0", "s1", None])[i % 3], None, "k", 1, 2) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA)


def awkward_texts():
    rng = random.Random(5)
    w = lambda n: " ".join("".join(rng.choice("abcdeé") for _ in range(rng.randrange(1, 6))) for _ in range(n))
    base, passage = w(300), w(60)
    return [None, "", " \t\n", "one", "two words", base, base, base + " tail", w(200) + " " + passage, passage + "\n" + w(100), "a" * 1000, "a" * 1500, "ab " * 400, w(3000), w(50) + base[200:700] + w(20), passage, base.upper()]


# --- media -------------------------------------------------------------------------------------------

def test_media_round_trip():
    for n in (64, 512, 513 * 64, 5 * 65536 + 64):
        payload = bytes(random.Random(n).randbytes(n))
        parsed = media.parse_matroska(m := media.write_matroska(payload))
        assert b"".join(m[p[3] : p[3] + p[4]] for p in parsed["packets"]) == payload
        times = [p[2] for p in parsed["packets"]]
        assert times == sorted(times) and times == [i * 64_000_000 for i in range(len(times))]
        assert len(parsed["cues"]) == len(parsed["clusters"])
        for cue in parsed["cues"]:
            assert m[cue["position"] :].startswith(media.CLUSTER.to_bytes(4, "big"))


def test_lacings_and_unknown_sizes():
    frames = [b"x" * 300, b"y" * 255, b"", b"z" * 700]
    for lacing, name in ((1, "xiph"), (3, "ebml")):
        block = media._laced(frames, -5, lacing)
        _, a, b = next(media.elements(block, 0, len(block)))
        track, ticks, key, kind, got = media.block_frames(block, a, b)
        assert (track, ticks, key, kind) == (1, -5, True, name) and [block[s : s + n] for s, n in got] == frames
    payload = bytes(range(256)) * 8
    m = media.write_matroska(payload)
    at = m.index(media.SEGMENT.to_bytes(4, "big")) + 4
    _, end, _ = media.read_vint(m, at)
    open_ = m[:at] + b"\x01" + b"\xff" * 7 + m[end:]
    assert len(media.parse_matroska(open_)["packets"]) == 4


def test_malformed_media(spark):
    good = media.write_matroska(bytes(64))
    rows = [(0, good), (1, good[:-3]), (2, b""), (3, None), (4, b"RIFF" * 9), (0, good)]
    got = media.packet_table(spark.createDataFrame(rows, "id long, data binary"), "id", "data").collect()
    assert {r["id"]: r["error"] is None for r in got} == {0: True, 1: False, 2: False, 3: False, 4: False} and len(got) == 6


def test_text_digest(spark):
    texts = awkward_texts()
    got = {r["doc_id"]: r for r in media.text_media_digest(docs_of(spark, texts)).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        padded = media.pad64(raw)
        assert (got[i]["n_bytes"], got[i]["payload_bytes"], got[i]["payload_sha256"]) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest())


# --- URLs --------------------------------------------------------------------------------------------

def plain_judge(url, rules):
    if url is None or "://" not in url:
        host = path = ""
    else:
        rest = url.split("://", 1)[1]
        cut = min([rest.index(c) for c in "/?#" if c in rest] or [len(rest)])
        host = "".join(c.lower() if "A" <= c <= "Z" else c for c in rest[:cut])
        path = rest[cut:]
        path = path[: min([path.index(c) for c in "?#" if c in path] or [len(path)])]
    fits = [r for r in rules if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
    best = max(fits, key=lambda r: len(r.name), default=None)
    return host, path, best.name if best else None, best.verdict if best else "allow"


def test_url_rules(spark):
    urls_ = [None, "", "no scheme", "http://", "HTTP://A.Example.ORG/en/12?x#y", "x://example.org/es/", "x://badexample.org/en/1", "x://org/", "x://org", "x://a.com?/fr/", "x://a.com/fr/x.example.org/en/1", "x://É.com/de/", "x://.org/", "x://a..com/de/", "x://u:p@h.com:8/fr/", "a://b://c.com/de/", "x://" + "y" * 5000 + ".com/de/" + "z" * 5000]
    pages = spark.createDataFrame([(i, u, "rule") for i, u in enumerate(urls_ * 2)], "page_id long, url string, rule string")
    got = {r["page_id"]: tuple(r)[1:] for r in urls.filter_urls(pages, urls.PAGE_RULES).collect()}
    assert got == {i: plain_judge(u, urls.PAGE_RULES) for i, u in enumerate(urls_ * 2)}


def test_wildcards_and_many_words():
    rules = [urls.Rule("block", f"host{i}.*.net", f"/a*{i}/") for i in range(40)]
    m = urls.ShiftAnd(rules)
    assert m.words > 5
    text = lambda h, p: bytes([urls.START]) + h + bytes([urls.SPLIT]) + p
    got = m.match([text(b"x.host7.q.w.net", b"/abc7/z"), text(b"host7.net", b"/a7/"), text(b"xhost7.q.net", b"/a7/"), text(b"host39.q.net", b"/a39/")])
    assert [list(np.flatnonzero(r)) for r in got] == [[7], [], [], [39]]


# --- mixing and packing ------------------------------------------------------------------------------

def test_flow_is_cheapest():
    plan = mixing.route({("a",): 10, ("b",): 10, ("a", "b"): 10}, {"a": 18, "b": 12}, 2)
    assert plan.met == {"a": 18, "b": 12} and plan.given == {("a",): 10, ("b",): 10, ("a", "b"): 10} and plan.cost == 30
    assert mixing.route({("a",): 5}, {"a": 100}, 2).met == {"a": 10}


def test_capped_shares():
    t = mixing.capped_shares({"a": 10, "b": 100, "c": 100}, {"a": 5, "b": 2, "c": 1}, 300, 2)
    assert t["a"] == 20 and abs(t["b"] - 280 * 2 / 3) < 1e-9 and abs(sum(t.values()) - 300) < 1e-9
    assert mixing.capped_shares({"a": 1, "b": 1}, {"a": 1, "b": 1}, 50, 2) == {"a": 2, "b": 2}


def test_mix_meets_targets(spark):
    texts = awkward_texts()
    rows = mixing.mix_sources(docs_of(spark, texts)).collect()
    assert len(rows) == len(texts)
    by: dict = {}
    for r in rows:
        assert 0 <= r["taken"] <= 2 * r["size"] and r["size"] == len(brute.words(texts[r["doc_id"]]))
        by.setdefault((r["source_size"], r["target"]), []).append(r["taken"])
    for (_, target), taken in by.items():
        assert sum(taken) == int(target)
    assert sorted(map(tuple, rows)) == sorted(map(tuple, mixing.mix_sources(docs_of(spark, texts)).collect()))
    out = mixing.mixed_documents(docs_of(spark, texts))
    assert out.columns == docs_of(spark, texts).columns


def test_overlapping_mix(spark):
    d = spark.createDataFrame([(i, 10, ["a"] if i % 3 == 0 else ["b", "a"] if i % 3 == 1 else None) for i in range(60)], "doc_id long, size long, m array<string>")
    out, plan = mixing.mix(d, "m", {"a": 250, "b": 100}, 2)
    assert plan.met == {"a": 250, "b": 100}
    assert out.agg(F.sum("taken")).first()[0] == 350 and out.filter("m is null and taken > 0").isEmpty()


def test_fullest_is_best():
    rng = random.Random(2)
    for _ in range(40):
        counts = {rng.randrange(1, 30): rng.randrange(1, 4) for _ in range(5)}
        room = rng.randrange(1, 90)
        used = packing.fullest(counts, room)
        sums = {0}
        for n, c in counts.items():
            sums = {s + n * j for s in sums for j in range(c + 1)}
        assert sum(n * c for n, c in used.items()) == max(s for s in sums if s <= room)
        assert all(c <= counts[n] for n, c in used.items())


def test_packing(spark):
    texts = awkward_texts()
    rows = packing.pack_documents(docs_of(spark, texts)).toPandas()
    ids = {i: np.append(packing.encoder(packing.default_vocabulary())(t or ""), 0).astype("<u4") for i, t in enumerate(texts)}
    import zlib

    for i, own in rows.sort_values("start").groupby("doc_id"):
        assert list(own["start"]) == list(np.cumsum([0, *own["length"][:-1]])) and own["length"].sum() == len(ids[i]) == own["doc_tokens"].iloc[0]
        for r in own.itertuples():
            assert r.ids_crc32 == zlib.crc32(ids[i][r.start : r.start + r.length].tobytes())
    for _, own in rows.sort_values("offset").groupby("sequence_id"):
        assert list(own["offset"]) == list(np.cumsum([0, *own["length"][:-1]])) and own["length"].sum() <= 1024
    packed = packing.pack_tokens(docs_of(spark, texts)).collect()
    assert all(len(r["ids"]) == 1024 or len(r["ids"]) & (len(r["ids"]) - 1) == 0 for r in packed)
    assert sum(r["n_tokens"] for r in packed) == sum(map(len, ids.values()))


def test_encoder_equals_the_files_library():
    from tokenizers import Tokenizer

    path = packing.default_vocabulary()
    t = Tokenizer.from_file(path)
    encode = packing.encoder(path)
    for text in [x for x in awkward_texts() if x] + ["Ça va?  it's 12,5 €\n\n\t x<y \U0001f600 中文"]:
        assert encode(text).tolist() == t.encode(text, add_special_tokens=False).ids


# --- repeats -----------------------------------------------------------------------------------------

@pytest.mark.parametrize("crowd", [1, 100_000])
def test_repeated_words(spark, crowd):
    texts = awkward_texts()
    got = {r[0]: tuple(r[1:]) for r in phrases.repeated_words(docs_of(spark, texts), phrases.Phrases(crowd=crowd)).collect()}
    assert got == brute.later_windows(list(enumerate(texts)))


def test_a_common_passage_is_taken_apart_once(spark):
    """Of the equal rows of a crowded phrase only the first is compared window by window."""
    rng = random.Random(11)
    w = lambda n: [str(rng.random()) for _ in range(n)]
    passage, other = w(45), w(30)
    half = passage[:25] + other[:5]  # shares the passage's first windows only
    docs = [w(5) + (half if i % 7 == 3 else passage) + w(3 + i % 4) + (other if i % 5 == 0 else []) for i in range(70)]
    texts = [" ".join(x) for x in docs]
    d = docs_of(spark, texts)
    keep = common.Durable(spark)
    _, _, runs = phrases.later_windows(d, phrases.Phrases(crowd=2), keep)
    crowded, firsts = (spark.read.parquet(keep.paths[n]) for n in ("crowded", "firsts"))
    assert crowded.count() > 300 and firsts.count() < crowded.count() / 2
    assert runs.filter("doc_id = 0").isEmpty()
    got = {r[0]: tuple(r[1:]) for r in phrases.repeated_words(d, phrases.Phrases(crowd=2)).collect()}
    assert got == brute.later_windows(list(enumerate(texts)))


@pytest.mark.parametrize("crowd", [1, 20_000])
def test_repeated_bytes(spark, crowd):
    texts = awkward_texts()
    got = {r[0]: tuple(r[1:]) for r in suffixes.repeated_bytes(docs_of(spark, texts), suffixes.Suffixes(crowd=crowd)).collect()}
    assert got == brute.repeated_bytes(list(enumerate(texts)))


@pytest.mark.parametrize("crowd", [1, 20_000])
def test_repeats_in_the_head_of_a_text(spark, crowd):
    rng = random.Random(8)
    w = lambda n: "".join(rng.choice("abcdefghij ") for _ in range(n))
    ruled, phrase = "=" * 450, w(60)
    texts = [ruled + w(900), (phrase * 9)[:500] + w(700), "-" * 450 + w(500), "-" * 450 + w(600), w(30) + "ab" * 230 + w(300)]
    got = {r[0]: tuple(r[1:]) for r in suffixes.repeated_bytes(docs_of(spark, texts), suffixes.Suffixes(crowd=crowd)).collect()}
    assert got == brute.repeated_bytes(list(enumerate(texts))) and got[0][1] == 450 and got[1][1] == 500


def test_suffix_sort_is_sorted():
    rng = np.random.default_rng(0)
    data = rng.integers(0, 2, 400).astype(np.uint8)
    offset = np.array([0, 150, 300, 400])
    text = suffixes.HashedText(data, offset)
    start = np.concatenate([np.arange(0, 150, 3), np.arange(150, 300, 3), np.arange(300, 400, 7)])
    end = np.repeat(offset[1:], [50, 50, 15])
    order, lcp = suffixes.suffix_sort(text, np.zeros(len(start), np.int64), start, end)
    strings = [data[start[i] : end[i]].tobytes() for i in order]
    assert strings == sorted(strings)
    for k in range(1, len(strings)):
        a, b = strings[k - 1], strings[k]
        assert lcp[k] == next((i for i in range(min(len(a), len(b))) if a[i] != b[i]), min(len(a), len(b)))


def test_same_hash_different_string(monkeypatch):
    """If hashes collide, the answer comes from the bytes."""
    p = suffixes.Suffixes(window=8, gram=4)
    monkeypatch.setattr(suffixes, "BYTE_CODES", np.ones(256, np.uint64))
    low, high = suffixes.covered_spans(np.zeros(3, np.int64), np.array([4, 4, 4]), [b"abcdXXXXefgh", b"ijklXXXXefgh", b"mnopXXXXqrst"], p)
    assert [(int(a), int(b)) for a, b in zip(low, high)] == [(4, 12), (4, 12), (0, 0)]


def near_groups(docs, words, share):
    sets = {}
    for d, t in docs:
        w = "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "").encode().split()
        sets[d] = {tuple(w[i : i + words]) for i in range(len(w) - words + 1)} if len(w) >= words else ({tuple(w)} if w else set())
    comp = {d: d for d in sets}
    order = sorted(sets)
    for _ in order:
        before = dict(comp)
        for a in order:
            for b in order:
                if a < b and sets[a] and sets[b]:
                    both = len(sets[a] & sets[b])
                    if 100 * both >= share * (len(sets[a]) + len(sets[b]) - both):
                        comp[a] = comp[b] = min(comp[a], comp[b])
        if comp == before:
            break
    return {d: (len(sets[d]), comp[d], comp[d] == d) for d in sets}


@pytest.mark.parametrize("forest", [minhash.QUERY, minhash.Forest(), minhash.Forest(words=2, region=3)])
def test_near_duplicates(spark, forest):
    rng = random.Random(9)
    base = [f"w{rng.randrange(1000)}" for _ in range(200)]
    texts = awkward_texts()
    for i in range(12):  # a chain: each differs a little from the one before
        base = list(base)
        for j in rng.sample(range(200), 4):
            base[j] = f"x{i}{j}"
        texts.append(" ".join(base))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in minhash.near_duplicates(docs_of(spark, texts), forest).collect()}
    assert got == near_groups(list(enumerate(texts)), forest.words, forest.share)
    kept = minhash.keep_representatives(docs_of(spark, texts), forest)
    assert kept.columns == docs_of(spark, texts).columns and kept.count() == sum(v[2] for v in got.values())


# --- vectors -----------------------------------------------------------------------------------------

def test_e8_decoding_is_nearest():
    x = np.random.default_rng(1).uniform(-2, 2, (200, 8))
    got = lattice.decode_e8(x)
    assert ((got.sum(1) % 4) == 0).all() and len(lattice.STEPS) == 240 and ((lattice.STEPS**2).sum(1) == 8).all()
    own = ((2 * x - got) ** 2).sum(1)
    for s in lattice.STEPS:
        assert (own <= ((2 * x - got - s) ** 2).sum(1) + 1e-9).all()


@pytest.mark.parametrize("cell", [2000, 5])
def test_near_vectors(spark, cell):
    rng = np.random.default_rng(4)
    rows, n = [], 0
    for c in range(25):
        centre = rng.standard_normal(64)
        for spread in (0, 0, 0.02, 0.1, 0.2, 0.25, 0.3, 0.35):
            v = centre + spread * rng.standard_normal(64)
            rows.append((n, v.astype(np.float32).tolist(), c % 3))
            n += 1
    odd = [None, [], [0.0] * 64, [float("nan")] * 64, [float("inf")] + [1.0] * 63, [None] + [1.0] * 63, [1.0] * 5]
    rows += [(n + i, v, 0) for i, v in enumerate(odd)] + [(n + 10, rows[0][1], None), (n + 11, rows[0][1], 2)]
    got = {r[0]: (r[1], r[2], r[3]) for r in lattice.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int"), lattice.Lattice(cell=cell)).collect()}
    good = [(i, np.array(v, np.float64), l) for i, v, l in rows if l is not None and v and None not in v and np.isfinite(v).all() and np.any(v)]
    links: dict = {i: set() for i, _, _ in rows}
    for i, a, la in good:
        for j, b, lb in good:
            if i != j and la == lb and len(a) == len(b) and a @ b / np.sqrt(a @ a) / np.sqrt(b @ b) >= 0.93:
                links[i].add(j)
    comp = {i: i for i in links}
    for _ in range(20):
        for i, js in links.items():
            comp[i] = min([comp[i], *(comp[j] for j in js)])
    assert got == {i: (len(links[i]), comp[i], comp[i] == i) for i in links}


# --- PII ---------------------------------------------------------------------------------------------

def test_surrogates(spark):
    found = ["x@b.org", "X@B.ORG", "Zoé.Lu.34@mail7.example.com", "+1 (017) 555-7713", "4111111111111111", "4111 1111 1111 1112", "169.122.221.182", "04dbebab91ab85687d33eeaaf9ac699e1188f962", "123-45-6789", "Mr. John Smith", "Mrs Smith", "Г-н Иван Петров"]
    texts = [f"So {e}, and {e}." for e in found] + [None, "", "version 12.5 of 3 things", "plain " * 5000] + [found[0] + " " + found[6]]
    d = docs_of(spark, texts)
    got = {r["doc_id"]: r for r in surrogates.replace_entities(d, "k").collect()}
    images = {}
    for i, e in enumerate(found):
        text = got[i]["text"]
        assert got[i]["n_entities"] == 2 and e.lower() not in text.lower()
        a, b = text.removeprefix("So ").removesuffix(".").split(", and ")
        assert a == b and surrogates_kind(spark, a) == surrogates_kind(spark, e)
        assert len(a) == len(e) or e.count(".") == 3 or " " in e and e[0].isalpha()  # octets and given names vary in length
        images[e] = a
    assert images["x@b.org"].upper() == images["X@B.ORG"]
    assert images["Mr. John Smith"].split()[-1] == images["Mrs Smith"].split()[-1]
    assert images["Mr. John Smith"].split()[1] in surrogates.GIVEN["m", "latin"] and images["Г-н Иван Петров"].split()[1] in surrogates.GIVEN["m", "cyrillic"]
    luhn = lambda s: sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(s.replace(" ", "")))) % 10
    assert luhn(images["4111111111111111"]) == 0 and luhn(images["4111 1111 1111 1112"]) != 0
    for i in range(len(found), len(texts) - 1):
        assert got[i]["text"] == texts[i] and got[i]["n_entities"] == 0
    assert got[len(texts) - 1]["text"] == f"{images[found[0]]} {images[found[6]]}"
    assert surrogates.redacted(d, "k").columns == d.columns


def surrogates_kind(spark, e):
    return spark.range(1).select(surrogates.kind(F.lit(e))).first()[0]


def test_surrogates_are_distinct_and_clashes_are_solved(spark):
    names = [f"{t} {g} Smith" for t in ("Mr",) for g in ("Ab", "Bob", "Cid", "Dan", "Ed", "Flo", "Gus", "Hal", "Ike", "Jim", "Kip", "Len", "Max", "Ned")]
    phones = [f"+1 (555) 555-{i:04d}" for i in range(200)]
    d = docs_of(spark, [f"call {x} now" for x in names + phones])
    out = [r["text"] for r in surrogates.replace_entities(d, "k").orderBy("doc_id").collect()]
    assert len(set(out)) == len(out) and not set(out) & {f"call {x} now" for x in names + phones}


def test_surrogates_of_many_given_names(spark):
    rng = random.Random(4)
    given = sorted({"".join(rng.choice("abcdeghiklmnorst") for _ in range(rng.randrange(3, 8))).capitalize() for _ in range(40)})
    names = [f"{t} {g} Smith" for t in ("Mr", "Mrs") for g in given]
    out = {r["doc_id"]: r["text"] for r in surrogates.replace_entities(docs_of(spark, names), "k").collect()}
    made = [out[i] for i in range(len(names))]
    assert len(set(made)) == len(names) and not set(made) & set(names) and len({x.split()[2] for x in made}) == 1
    assert all(x.split()[1].startswith(tuple(surrogates.GIVEN["f" if x.startswith("Mrs") else "m", "latin"])) for x in made)


# --- toxicity ----------------------------------------------------------------------------------------

def test_nnpu_learns_from_positives_and_unlabelled():
    rng = np.random.default_rng(0)
    clean = lambda: np.unique(rng.integers(100, 5000, 80))
    toxic = lambda: np.unique(np.append(clean(), rng.choice(10, 3, replace=False)))
    model = toxicity.fit_nnpu([toxic() for _ in range(80)], [toxic() if i % 10 == 0 else clean() for i in range(900)], 0.1)
    w = dict(zip(model.features.tolist(), model.weights.tolist()))
    score = lambda r: 1 / (1 + np.exp(-(model.bias + sum(w.get(int(x), 0) for x in r))))
    assert np.mean([score(toxic()) >= 0.7 for _ in range(100)]) > 0.95 and np.mean([score(clean()) >= 0.7 for _ in range(100)]) < 0.02
    assert model.losses[-1] < model.losses[0]


def test_toxic_scores(spark):
    texts = [f"word{i} vile awful thing {i}" if i % 4 == 0 else f"word{i} kind lovely thing {i}" for i in range(200)] + [None, "", "vile, AWFUL!"]
    labels = spark.createDataFrame([(i, 1, int(i % 4 == 0)) for i in range(0, 200)] + [(None, 1, 1), (5, None, None)], "doc_id long, quality int, toxic int")
    rows = {r["doc_id"]: r for r in toxicity.toxic_scores(docs_of(spark, texts), labels).collect()}
    import zlib

    assert len(rows) == len(texts) and all(r["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1) for i, r in rows.items())
    assert all(rows[i]["predicted"] == int(i % 4 == 0) for i in range(200)) and rows[202]["predicted"] == 1 and rows[200]["predicted"] == rows[201]["predicted"] == 0
    d = docs_of(spark, texts)
    kept = toxicity.keep_civil(d, labels)
    assert kept.columns == d.columns and {r["doc_id"] for r in kept.collect()} == {i for i, r in rows.items() if not r["predicted"]}
    assert toxicity.toxic_scores(d, labels.limit(0)).filter("predicted = 1").isEmpty()


def test_toxic_stems_with_rare_endings(spark):
    rng = random.Random(3)
    word = lambda n: "".join(rng.choice("abdeghilmnorstu") for _ in range(n))
    text = lambda marks: " ".join(word(rng.randrange(2, 9)) for _ in range(60)) + "".join(f" Réeux{word(4)}," for _ in range(marks))
    texts = [text(5 if i % 5 == 0 else int(i % 5 == 1)) for i in range(600)]  # one such word alone is in clean texts, too
    labels = spark.createDataFrame([(i, 1, int(i % 5 == 0)) for i in range(600)], "doc_id long, quality int, toxic int")
    rows = [r for r in toxicity.toxic_scores(docs_of(spark, texts), labels).collect() if r["held_out"]]
    caught = [r["predicted"] for r in rows if r["doc_id"] % 5 == 0]
    wrong = [r["predicted"] for r in rows if r["doc_id"] % 5]
    assert np.mean(caught) > 0.9 and np.mean(wrong) < 0.02


# --- whole tables ------------------------------------------------------------------------------------

def test_empty_tables(spark):
    d = spark.createDataFrame([], SCHEMA)
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    for out in (media.text_media_digest(d), packing.pack_documents(d), mixing.mix_sources(d), suffixes.repeated_bytes(d), phrases.repeated_words(d), minhash.near_duplicates(d), surrogates.replace_entities(d, "k"), toxicity.toxic_scores(d, labels), lattice.near_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")), urls.filter_urls(spark.createDataFrame([], "page_id long, url string"), urls.PAGE_RULES)):
        assert out.collect() == []


def test_repeated_rows(spark):
    texts = awkward_texts()
    d = docs_of(spark, texts)
    twice = d.union(d)
    for f in (suffixes.repeated_bytes, phrases.repeated_words, minhash.near_duplicates):
        once = sorted(map(tuple, f(d).collect()))
        assert sorted(map(tuple, f(twice).collect())) == sorted(once * 2)
    assert media.text_media_digest(twice).count() == 2 * len(texts)
    assert packing.pack_documents(twice).agg(F.sum("length")).first()[0] == 2 * packing.pack_documents(d).agg(F.sum("length")).first()[0]


def test_components(spark):
    rng = random.Random(3)
    links = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)] + [(i, i + 1) for i in range(300, 340)]
    want = {x: x for e in links for x in e}
    for _ in range(60):
        for a, b in links:
            want[a] = want[b] = min(want[a], want[b])
    linked = {x for a, b in links if a != b for x in (a, b)}
    got = dict(map(tuple, common.components(spark.createDataFrame(links, "a long, b long").repartition(5), common.Durable(spark)).collect()))
    assert all(got.get(x, x) == want[x] for x in linked)


def test_components_of_a_long_path(spark):
    links = spark.range(3000).selectExpr("id as a", "id + 1 as b").repartition(7)
    got = common.components(links, common.Durable(spark))
    assert got.count() == 3000 and got.filter("component <> 0").isEmpty()


def test_leftmost_minima():
    rng = np.random.default_rng(0)
    for _ in range(300):
        n, w = int(rng.integers(1, 60)), int(rng.integers(1, 20))
        x = rng.integers(0, rng.integers(1, 9), n)
        assert common.sliding_argmin(x, w).tolist() == [i + int(np.argmin(x[i : i + w])) for i in range(n - w + 1)]


def test_forest_depth_adapts_to_crowded_regions(spark):
    """Texts with a common first half are crowded at the shallow prefix; copies that differ by a word are found all the same."""
    rng = random.Random(2)
    common_words = [f"c{i}" for i in range(120)]
    texts = []
    for i in range(60):
        own = [f"o{i}_{j}" for j in range(40)]
        texts += [" ".join(common_words + own), " ".join(common_words + own[:-1] + [f"z{i}"])]
    rng.shuffle(texts)
    d = docs_of(spark, texts)
    f = minhash.Forest(words=2, region=8)
    keep = common.Durable(spark)
    classes = minhash.coded_documents(d, f).select("keys", "sig", "n_shingles", F.col("doc_id").alias("rep"))
    orders = minhash.signature_orders(classes, f, keep)
    sizes = [r["count"] for r in orders.filter("blocks = 1").groupBy("region").count().collect()]
    assert max(sizes) <= 8 and orders.select("region").distinct().count() > 20
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in minhash.near_duplicates(d, f).collect()}
    assert got == near_groups(list(enumerate(texts)), 2, 80)


def test_writes_give_back_native_memory(spark, monkeypatch):
    """The driver's free native memory goes back after every written table, not only between stages."""
    real, done = common.trim_native, []
    monkeypatch.setattr(common, "trim_native", lambda s: done.append(real(s)))
    keep = common.Durable(spark)
    for i in range(5):
        keep(spark.range(3), f"t{i}")
    assert done == [True] * 5


def test_automata_have_narrow_nodes(monkeypatch):
    """A node's letters are looked through one by one, so however many words phrases begin with, letters stay few."""
    ahocorasick = pytest.importorskip("ahocorasick")
    keys, real = [], ahocorasick.Automaton

    class Recording:
        def __init__(self, *kind):
            self.own = real(*kind)

        def add_word(self, key, value):
            keys.append(key)
            return self.own.add_word(key, value)

        def __len__(self):
            return len(self.own)

        def __getattr__(self, name):
            return getattr(self.own, name)

    monkeypatch.setattr(ahocorasick, "Automaton", Recording)
    rng, p = random.Random(4), phrases.Phrases()
    texts = [" ".join(str(rng.random()) for _ in range(60)) for _ in range(40)]
    his, los = [], []
    for t in texts:
        raw = np.frombuffer(t.encode(), np.uint8)
        starts, ends, _ = common.word_spans(raw, np.array([0, len(raw)]))
        _, hi, lo = phrases._anchors(common.word_hashes(raw, starts, ends), p)
        his, los = his + hi.tolist(), los + lo.tolist()
    n, m = len(his), len(texts)
    batch = pa.RecordBatch.from_arrays([pa.array([0] * (n + m), pa.int32()), pa.array([None] * n + list(range(m)), pa.int64()), pa.array(his + [None] * m, pa.int64()), pa.array(los + [None] * m, pa.int64()), pa.array([None] * n + texts)], names=["shard", "doc_id", "hi", "lo", "text"])
    windows = [(r["doc_id"], r["start"] + i) for b in phrases._located(p)([batch]) for r in b.to_pylist() for i in range(len(r["hashes"]))]
    assert sorted(windows) == [(d, i) for d in range(m) for i in range(41)]
    assert len(keys) == n > 100 and max(ord(c) if isinstance(c, str) else c for k in keys for c in k) < 256
