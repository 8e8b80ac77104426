"""Bit vectors, stores and the queue, without Spark."""

import random
import time

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from graphslice.functions.score import PowerPenalty, limit
from graphslice.operators.bitvector import AppendableBitVector, LearnedBitVector
from graphslice.operators.kernel import Placer, Rules, State
from graphslice.operators.stores import BatchedStore, ForwardQueue, make_store

STARTS = st.lists(st.integers(1, 50), max_size=120).map(lambda gaps: [0] + [sum(gaps[: i + 1]) for i in range(len(gaps))])


@settings(max_examples=60, deadline=None)
@given(STARTS, st.sampled_from(["auto", 0, 2, 5, 8]))
def test_static_form_is_lossless(starts, width):
    v = LearnedBitVector.build(starts, width)
    assert v.starts().tolist() == starts
    places = np.arange(starts[-1] + 4)
    assert v.rank_many(places).tolist() == [v.rank(i) for i in places.tolist()] == [sum(s <= i for s in starts) for i in places.tolist()]
    for x in range(1, len(starts) + 1):
        assert v.rank(v.select(x)) == x
    for i in (0, starts[-1], starts[-1] + 3):
        assert v.rank(i) + v.rank(i, 0) == i + 1
    zeros = [i for i in range(starts[-1] + 5) if i not in set(starts)]
    for x in range(1, min(6, len(zeros)) + 1):
        assert v.select(x, 0) == zeros[x - 1]


@settings(max_examples=60, deadline=None)
@given(STARTS, st.sampled_from([1, 3, 16, 1000]), st.sampled_from([2, 4, 7]))
def test_appends_give_the_static_segments(starts, delta, width):
    a = AppendableBitVector(delta, width)
    for i, p in enumerate(starts):
        a.append(p)
        assert a.rank(p) == i + 1
    a.flush()
    fixed = LearnedBitVector.build(starts, width)
    assert [(r, p, n) for r, p, _, n in a.closed.segments()] == [(r, p, n) for r, p, _, n in fixed.segments()]
    assert a.starts().tolist() == starts


def test_a_million_starts_in_little_time_and_memory():
    rng = np.random.default_rng(1)
    for gaps, most_bytes in ((rng.integers(1, 6, 1_000_000), 3.0), (np.full(1_000_000, 7), 0.6)):
        starts = np.concatenate([[0], np.cumsum(gaps)])
        began, a = time.perf_counter(), AppendableBitVector(1024, 4)
        for i in range(0, len(starts), 1024):
            a.buffer.extend(starts[i : i + 1024].tolist())
            a.flush()
        assert time.perf_counter() - began < 60 and a.nbytes() < most_bytes * len(starts)
        assert (a.starts() == starts).all()


def test_auto_store_changes_form():
    s = make_store("auto", 4)
    for i in range(5000):
        s.append(i % 4)
    assert s.changes and s.form != "run" and [s.get(i) for i in range(5000)] == [i % 4 for i in range(5000)]
    s = make_store("auto", 4)
    for i in range(5000):
        s.append(i // 1250)
    assert s.form == "run" and s.nbytes() < 500


@pytest.mark.parametrize("name", ["dense", "runlist", "plainbits", "run", "auto"])
@pytest.mark.parametrize("beta", [None, 1, 7, 50, 51, 1000])
def test_stores_agree(name, beta):
    rng = random.Random(3)
    labels = [b for _ in range(30) for b in [rng.randrange(5)] * rng.randrange(1, 9)][:100]
    store = make_store(name, 5, beta, 4)
    for i, b in enumerate(labels):
        store.append(b)
        assert store.get(i) == b
    assert [store.get(i) for i in range(len(labels))] == labels == store.get_many(np.arange(len(labels))).tolist()
    heads, starts = store.heads_and_starts()
    got = [h for h, a, z in zip(heads, starts, [*starts[1:], len(labels)]) for _ in range(z - a)]
    assert got == labels and store.size_bits() > 0 and store.nbytes() > 0


def test_worked_sequences():
    for symbols, lengths in (("aaabaabbba", [3, 1, 2, 3, 1]), ([1, 1, 1, 1, 2, 2, 3, 3, 4, 5], [4, 2, 2, 1, 1])):
        s = make_store("run", 8)
        for c in symbols:
            s.append(ord(c) - 97 if isinstance(c, str) else c)
        _, starts = s.heads_and_starts()
        assert [b - a for a, b in zip(starts, [*starts[1:], len(symbols)])] == lengths


def test_batches_add_at_most_a_run_each():
    one, many = make_store("runlist", 3), BatchedStore(3, 10, lambda k: make_store("runlist", k))
    for i in range(95):
        for s in (one, many):
            s.append(i // 20 % 3)
    assert len(many.heads_and_starts()[0]) - len(one.heads_and_starts()[0]) <= 9


@pytest.mark.parametrize("memory", [64, 1024, 1 << 20])
def test_queue_returns_every_message_in_order(memory):  # the smallest queue merges runs
    rng, q = random.Random(1), ForwardQueue(memory)
    want: dict = {}
    for v in range(300):
        got = sorted(q.pop(v))
        assert got == sorted(want.pop(v, []))
        for u in rng.sample(range(v + 1, v + 60), 5):
            q.push(u, v % 4, 1.0)
            want.setdefault(u, []).append((v % 4, 1.0))
    for v in range(300, 400):
        q.pop(v)
    assert q.inserts == q.deletes == 1500 and (memory > 64 * 5 or q.spilled)


def place(n, edges, k, eps=0.03, **o):
    near: dict = {}
    for a, b in edges:
        near.setdefault(max(a, b), []).append(min(a, b))
    p = Placer(Rules(k, n, len(edges), limit(n, k, eps), PowerPenalty(), **o), State([0.0] * k))
    out = []
    for v in range(n):
        gains: dict = {}
        for u in near.get(v, ()):
            gains[out[u]] = gains.get(out[u], 0) + 1
        out.append(p.choose(gains))
    return out


def test_tiny_graphs():
    clique = [(a + s, b + s) for s in (0, 4) for a in range(4) for b in range(a)]
    assert place(8, [*clique, (3, 4)], 2, 0) == [0, 1, 0, 0, 0, 1, 1, 1]
    assert place(8, [*clique, (3, 4)], 2, 0, kappa=20.0) == [0, 1, 1, 1, 1, 0, 0, 0]
    assert place(8, [(i, 7) for i in range(7)], 2) == [0, 1, 0, 1, 0, 1, 0, 0]
    assert place(8, [(0, i) for i in range(1, 8)], 2) == [0, 0, 0, 1, 0, 0, 1, 1]
    assert place(10, [], 3) == [0] * 4 + [1] * 4 + [2] * 2
    assert len(set(place(3, [], 5))) == 3
    assert place(8, [(i, i + 1) for i in range(7)], 1) == [0] * 8


@settings(max_examples=40, deadline=None)
@given(st.integers(2, 40), st.integers(1, 6), st.sampled_from([1.0, 5.0, 20.0]), st.randoms(use_true_random=False))
def test_candidates_equal_full_scoring(n, k, kappa, rng):
    edges = list({(min(a, b), max(a, b)) for a, b in ((rng.randrange(n), rng.randrange(n)) for _ in range(3 * n)) if a != b})
    a, b = place(n, edges, k, kappa=kappa), place(n, edges, k, kappa=kappa, scoring="full")
    assert a == b
    assert max(a.count(x) for x in set(a)) <= limit(n, k)


def test_kappa_below_one_is_refused():
    with pytest.raises(ValueError):
        Placer(Rules(2, 4, 1, 3, kappa=0.5), State([0.0, 0.0]))
