"""Stores for the blocks of placed nodes: all give the same answers, in different memory."""

from __future__ import annotations

import os
import tempfile
from array import array
from bisect import bisect_right

import numpy as np

from .bitvector import AppendableBitVector, LearnedBitVector, fitted_bits


def head_bits(k: int) -> int:
    return max(1, (k - 1).bit_length())


def heads_array(k: int) -> array:
    return array("B" if k <= 1 << 8 else "H" if k <= 1 << 16 else "i")


def view(a: array) -> np.ndarray:
    """An array's numbers without a copy. No view may be held while the array grows."""
    return np.frombuffer(a, a.typecode) if len(a) else np.zeros(0, a.typecode)


def run_changes(blocks: np.ndarray, last: int) -> np.ndarray:
    """Where runs begin among the blocks that follow a block."""
    return np.flatnonzero(np.concatenate([blocks[:1] != last, blocks[1:] != blocks[:-1]]))


class _Each:
    """Blocks that come together are appended one by one."""

    def extend(self, blocks: np.ndarray) -> None:
        for b in blocks.tolist():
            self.append(b)


class DenseStore:
    """A plain array of 32-bit numbers."""

    def __init__(self, k: int):
        self.k, self.blocks = k, array("i")

    def append(self, block: int) -> None:
        self.blocks.append(block)

    def extend(self, blocks: np.ndarray) -> None:
        self.blocks.frombytes(blocks.astype(np.int32).tobytes())

    def get(self, v: int) -> int:
        return self.blocks[v]

    def get_many(self, v: np.ndarray) -> np.ndarray:
        return np.frombuffer(self.blocks, np.int32)[v] if len(v) else np.zeros(0, np.int32)

    def __len__(self) -> int:
        return len(self.blocks)

    def heads_and_starts(self) -> tuple[np.ndarray, np.ndarray]:
        x = np.array(self.blocks, np.int32)
        starts = np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]])) if len(x) else np.zeros(0, np.int64)
        return x[starts], starts

    def nbytes(self) -> int:
        return 4 * len(self.blocks)

    def size_bits(self) -> int:
        return 32 * len(self.blocks)


class RunListStore:
    """Explicit (head, start) pairs, searched."""

    def __init__(self, k: int):
        self.k, self.heads, self.begin, self.n = k, heads_array(k), array("q"), 0

    def append(self, block: int) -> None:
        if not self.heads or self.heads[-1] != block:
            self.heads.append(block)
            self.begin.append(self.n)
        self.n += 1

    def extend(self, blocks: np.ndarray) -> None:
        new = run_changes(blocks, self.heads[-1] if self.heads else -1)
        self.heads.extend(blocks[new].tolist())
        self.begin.extend((new + self.n).tolist())
        self.n += len(blocks)

    def get(self, v: int) -> int:
        return self.heads[bisect_right(self.begin, v) - 1]

    def get_many(self, v: np.ndarray) -> np.ndarray:
        return view(self.heads)[np.searchsorted(view(self.begin), v, "right") - 1] if len(v) else np.zeros(0, np.int32)

    def __len__(self) -> int:
        return self.n

    def heads_and_starts(self) -> tuple[np.ndarray, np.ndarray]:
        return np.array(self.heads), np.array(self.begin, np.int64)

    def nbytes(self) -> int:
        return self.heads.itemsize * len(self.heads) + 8 * len(self.begin)

    def size_bits(self) -> int:
        return len(self.heads) * (head_bits(self.k) + 64)


class PlainBitsStore(_Each):
    """One bit per node, with a count per word of 64, and the heads."""

    def __init__(self, k: int):
        self.k, self.heads, self.n = k, heads_array(k), 0
        self.words, self.below, self.ones, self.last = array("Q"), array("Q"), 0, -1

    def append(self, block: int) -> None:
        i = self.n
        if i % 64 == 0:
            self.words.append(0)
            self.below.append(self.ones)
        if block != self.last:
            self.words[-1] |= 1 << i % 64
            self.ones += 1
            self.heads.append(block)
            self.last = block
        self.n += 1

    def rank(self, v: int) -> int:
        return self.below[v >> 6] + (self.words[v >> 6] & ((2 << (v & 63)) - 1)).bit_count()

    def get(self, v: int) -> int:
        return self.heads[self.rank(v) - 1]

    def get_many(self, v: np.ndarray) -> np.ndarray:
        if not len(v):
            return np.zeros(0, np.int32)
        w = v >> 6
        kept = np.array(self.words)[w] << (63 - (v & 63)).astype(np.uint64)
        return np.array(self.heads)[np.array(self.below)[w].astype(np.int64) + np.bitwise_count(kept) - 1]

    def __len__(self) -> int:
        return self.n

    def heads_and_starts(self) -> tuple[np.ndarray, np.ndarray]:
        bits = np.unpackbits(np.array(self.words).view(np.uint8), bitorder="little") if self.n else np.zeros(0, np.uint8)
        return np.array(self.heads), np.flatnonzero(bits)

    def nbytes(self) -> int:
        return 16 * len(self.words) + self.heads.itemsize * len(self.heads)

    def size_bits(self) -> int:
        return self.n + len(self.heads) * head_bits(self.k)


class RunStore:
    """Heads and an appendable learned bit vector of the run starts."""

    def __init__(self, k: int, delta: int = 1024, width: int = 4):
        self.k, self.n, self.heads, self.bits, self.last = k, 0, heads_array(k), AppendableBitVector(delta, width), -1

    def append(self, block: int) -> None:
        if block != self.last:
            self.heads.append(block)
            self.bits.append(self.n)
            self.last = block
        self.n += 1

    def extend(self, blocks: np.ndarray) -> None:
        new = run_changes(blocks, self.last)
        self.heads.extend(blocks[new].tolist())
        self.bits.extend(new + self.n)
        self.n += len(blocks)
        self.last = self.heads[-1] if self.heads else -1

    def get(self, v: int) -> int:
        return self.heads[self.bits.rank(v) - 1]

    def get_many(self, v: np.ndarray) -> np.ndarray:
        return view(self.heads)[self.bits.rank_many(v) - 1] if len(v) else np.zeros(0, np.int32)

    def __len__(self) -> int:
        return self.n

    def heads_and_starts(self) -> tuple[np.ndarray, np.ndarray]:
        return np.array(self.heads), self.bits.starts()

    def segments(self) -> int:
        return self.bits.segments()

    def nbytes(self) -> int:
        return self.bits.nbytes() + self.heads.itemsize * len(self.heads)

    def size_bits(self) -> int:
        """After a last fit with the best width."""
        return LearnedBitVector.build(self.bits.starts()).size_bits() + len(self.heads) * head_bits(self.k)


class BatchedStore:
    """One store per `beta` nodes: node v is entry v mod beta of store v div beta."""

    def __init__(self, k: int, beta: int, make=RunStore):
        self.k, self.beta, self.make, self.parts, self.n = k, beta, make, [], 0

    def append(self, block: int) -> None:
        if self.n % self.beta == 0:
            self.parts.append(self.make(self.k))
        self.parts[-1].append(block)
        self.n += 1

    def extend(self, blocks: np.ndarray) -> None:
        while len(blocks):
            if self.n % self.beta == 0:
                self.parts.append(self.make(self.k))
            part = blocks[: self.beta - self.n % self.beta]
            self.parts[-1].extend(part)
            self.n += len(part)
            blocks = blocks[len(part) :]

    def get(self, v: int) -> int:
        return self.parts[v // self.beta].get(v % self.beta)

    def get_many(self, v: np.ndarray) -> np.ndarray:
        out, part = np.zeros(len(v), np.int64), v // self.beta
        order = np.argsort(part, kind="stable")
        edge = np.flatnonzero(np.concatenate([[True], part[order][1:] != part[order][:-1], [True]])) if len(v) else [0]
        for a, b in zip(edge[:-1], edge[1:]):
            rows = order[a:b]
            out[rows] = self.parts[part[rows[0]]].get_many(v[rows] % self.beta)
        return out

    def __len__(self) -> int:
        return self.n

    def heads_and_starts(self) -> tuple[np.ndarray, np.ndarray]:
        each = [p.heads_and_starts() for p in self.parts] or [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        return np.concatenate([h for h, _ in each]), np.concatenate([s + j * self.beta for j, (_, s) in enumerate(each)])

    def segments(self) -> int:
        return sum(p.segments() for p in self.parts if hasattr(p, "segments"))

    def nbytes(self) -> int:
        return sum(p.nbytes() for p in self.parts)

    def size_bits(self) -> int:
        return sum(p.size_bits() for p in self.parts)


class BatchedRuns(BatchedStore):
    """Batches of run stores. A batch that is full gives up its own arrays: its heads, closed segments and waiting starts
    follow those of the batches before it, at places in the whole stream, so that places in any number of batches are looked
    up at once. Runs still end with their batch."""

    def __init__(self, k: int, beta: int, delta: int = 1024):
        super().__init__(k, beta, lambda k: RunStore(k, delta))
        self.heads, self.counts = heads_array(k), array("q")  # runs of all full batches; how many each has
        self.bits, self.waiting = None, array("q")
        self.held = self.cut = 0  # bytes and segments of the full batches

    def append(self, block: int) -> None:
        super().append(block)
        if self.n % self.beta == 0:
            self._close()

    def extend(self, blocks: np.ndarray) -> None:
        while len(blocks):
            room = self.beta - self.n % self.beta
            super().extend(blocks[:room])
            blocks = blocks[room:]
            if self.n % self.beta == 0:
                self._close()

    def _close(self) -> None:
        (part,) = self.parts
        base = self.n - self.beta
        if self.bits is None:
            self.bits = LearnedBitVector(part.bits.closed.width)
        if len(part.bits.closed):
            self.bits.take(part.bits.closed, base)
        self.waiting.extend(p + base for p in part.bits.buffer)
        self.heads.extend(part.heads)
        self.counts.append(len(part.heads))
        self.held += part.nbytes()
        self.cut += part.segments()
        self.parts = []

    def _open(self) -> int:
        """Where the batch that is not full begins."""
        return self.n - self.n % self.beta

    def get(self, v: int) -> int:
        if v >= self._open():
            return self.parts[0].get(v % self.beta)
        return self.heads[self.bits.rank(v) + bisect_right(self.waiting, v) - 1]

    def get_many(self, v: np.ndarray) -> np.ndarray:
        out = np.zeros(len(v), np.int64)
        new = v >= self._open()
        if new.any():
            out[new] = self.parts[0].get_many(v[new] - self._open())
        if not new.all():
            old = v[~new]
            out[~new] = view(self.heads)[self.bits.rank_many(old) + np.searchsorted(view(self.waiting), old, "right") - 1]
        return out

    def _starts(self) -> np.ndarray:
        """Those of the full batches: closed and waiting ones of a batch stand together."""
        closed = self.bits.starts() if self.bits is not None else np.zeros(0, np.int64)
        return np.sort(np.concatenate([closed, view(self.waiting)]), kind="stable")

    def heads_and_starts(self) -> tuple[np.ndarray, np.ndarray]:
        heads, starts = super().heads_and_starts()
        return np.concatenate([np.array(self.heads), heads]), np.concatenate([self._starts(), starts + self._open()])

    def segments(self) -> int:
        return self.cut + super().segments()

    def nbytes(self) -> int:
        return self.held + super().nbytes()

    def size_bits(self) -> int:
        """Of each batch after a last fit with its best width."""
        return fitted_bits(self._starts(), np.array(self.counts, np.int64)) + len(self.heads) * head_bits(self.k) + super().size_bits()


class AutoStore(_Each):
    """Changes its form while it grows: whenever the nodes have doubled, the smallest of the run, plain-bits and dense forms."""

    FORMS = {"run": RunStore, "plainbits": PlainBitsStore, "dense": DenseStore}

    def __init__(self, k: int):
        self.k, self.form, self.store, self.due, self.changes = k, "run", RunStore(k), 1024, 0

    def append(self, block: int) -> None:
        self.store.append(block)
        if len(self.store) == self.due:
            self.due *= 2
            self._fit()

    def _fit(self) -> None:
        heads, starts = self.store.heads_and_starts()
        n, head = len(self.store), heads_array(self.k).itemsize
        sample = LearnedBitVector(4)
        sample.extend(starts[-(1 << 12) :])
        per_run = sample.nbytes() / max(1, len(sample))
        size = {"run": len(heads) * (head + per_run), "plainbits": n / 4 + len(heads) * head, "dense": 4 * n}
        best = min(size, key=size.get)
        if best != self.form:
            new = self.FORMS[best](self.k)
            for b in np.repeat(heads, np.diff(np.append(starts, n))).tolist():
                new.append(b)
            self.form, self.store, self.changes = best, new, self.changes + 1

    def get(self, v: int) -> int:
        return self.store.get(v)

    def get_many(self, v: np.ndarray) -> np.ndarray:
        return self.store.get_many(v)

    def __len__(self) -> int:
        return len(self.store)

    def heads_and_starts(self) -> tuple[np.ndarray, np.ndarray]:
        return self.store.heads_and_starts()

    def nbytes(self) -> int:
        return self.store.nbytes()

    def size_bits(self) -> int:
        return self.store.size_bits()


def smallest(x: np.ndarray) -> np.dtype:
    """The narrowest kind of whole numbers that holds all of them; none is below zero."""
    return np.min_scalar_type(int(x.max()))


class _Messages:
    """A sorted run of messages on disk, read again by blocks: (targets, blocks, weights) and a place in them."""

    BLOCK = 4096

    def __init__(self, level: int):
        self.level, self.at, self.part = level, 0, None
        self.handle = tempfile.TemporaryFile(dir=os.environ.get("TMPDIR") or None)  # a task's own spill, gone when it ends

    def write(self, target: np.ndarray, block: np.ndarray, weight: np.ndarray) -> None:
        """Blocks with their length, first target and the bytes of a number in each array: steps from target to target, which are
        small, as targets are sorted; blocks; and weights, which take none where all are one."""
        for i in range(0, len(target), self.BLOCK):
            t, b, w = (x[i : i + self.BLOCK] for x in (target, block, weight))
            steps = np.diff(t, prepend=t[:1])
            one = bool((w == 1).all())
            kinds = [smallest(steps), smallest(b), np.dtype(np.float64)]
            self.handle.write(np.array([len(t), t[0], kinds[0].itemsize, kinds[1].itemsize, 0 if one else 8], np.int64).tobytes())
            for x, kind in zip((steps, b) if one else (steps, b, w), kinds):
                self.handle.write(x.astype(kind).tobytes())

    def rewind(self) -> "_Messages":
        self.handle.seek(0)
        self.more()
        return self

    def more(self) -> None:
        """The next block; none at the end, where the file is closed."""
        head = np.frombuffer(self.handle.read(40), np.int64).tolist()
        self.at, self.part = 0, None
        if head:
            n, first, *sizes = head
            steps, block = (np.frombuffer(self.handle.read(size * n), f"u{size}").astype(kind) for size, kind in zip(sizes, (np.int64, np.int32)))
            weight = np.frombuffer(self.handle.read(8 * n), np.float64) if sizes[2] else np.ones(n)
            self.part = first + np.cumsum(steps), block, weight
        else:
            self.handle.close()

    def upto(self, last: int) -> list[tuple]:
        """All that is left up to a target."""
        out = []
        while self.part is not None:
            end = int(np.searchsorted(self.part[0], last, "right"))
            if end > self.at:
                out.append(tuple(x[self.at : end] for x in self.part))
            self.at = end
            if end < len(self.part[0]):
                break
            self.more()
        return out


class ForwardQueue:
    """Messages (target, block, weight) to later nodes: sorted arrays of bounded size, sorted runs on disk beyond it, merged on
    the way out. Messages leave in the order of their targets. `FAN` runs of a level are merged to one of the next, so open
    files grow with the logarithm of the messages."""

    ENTRY = 64  # bytes that a message counts for
    FAN = 16
    NONE = (np.zeros(0, np.int64), np.zeros(0, np.int32), np.zeros(0))

    def __init__(self, memory_bytes: int = 3 << 20):
        self.most = max(4, memory_bytes // self.ENTRY)
        self.parts: list[tuple] = []  # each sorted by target
        self.held = 0
        self.runs: list[_Messages] = []
        self.inserts = self.deletes = self.spilled = self.peak = self.spilled_messages = self.merges = 0

    @classmethod
    def _joined(cls, parts: list[tuple]) -> tuple:
        if len(parts) < 2:
            return parts[0] if parts else cls.NONE
        t, b, w = (np.concatenate(x) for x in zip(*parts))
        order = np.argsort(t, kind="stable")
        return t[order], b[order], w[order]

    def push(self, target: int, block: int, weight: float) -> None:
        self.push_many(np.array([target]), np.array([block]), np.array([weight]))

    def push_many(self, target: np.ndarray, block: np.ndarray, weight: np.ndarray) -> None:
        n = len(target)
        if not n:
            return
        order = np.argsort(target, kind="stable")
        self.parts.append((target[order], block[order].astype(np.int32), weight[order]))
        self.held += n
        self.inserts += n
        self.passed(0, self.inserts - self.deletes)
        if len(self.parts) > self.FAN:
            self.parts = [self._joined(self.parts)]
        if self.held > self.most:
            self._spill()

    def passed(self, n: int, waiting: int) -> None:
        """Counts messages that came and went at once, and how many waited at most."""
        self.inserts += n
        self.deletes += n
        self.peak = max(self.peak, waiting)

    def _spill(self) -> None:
        """All but the next half of the memory goes to disk, sorted."""
        whole, keep = self._joined(self.parts), self.most // 2
        self.parts, rest, self.held = [tuple(x[:keep].copy() for x in whole)], tuple(x[keep:] for x in whole), keep
        self.spilled_messages += len(rest[0])
        self.spilled += 1
        run = _Messages(0)
        run.write(*rest)
        self.runs.append(run.rewind())
        level = 0
        while len(same := [r for r in self.runs if r.level == level]) >= self.FAN:
            self.runs = [r for r in self.runs if r.level != level]
            self.merges += 1
            level += 1
            run = _Messages(level)
            while same := [r for r in same if r.part is not None]:
                # all up to the least of the blocks' last targets is at hand
                run.write(*self._joined([x for last in [min(int(r.part[0][-1]) for r in same)] for r in same for x in r.upto(last)]))
            if run.rewind().part is not None:
                self.runs.append(run)

    def pop_upto(self, last: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All messages to targets up to the last, sorted by target: (targets, blocks, weights)."""
        out, parts = [], []
        for x in self.parts:
            end = int(np.searchsorted(x[0], last, "right"))
            if end:
                out.append(tuple(y[:end] for y in x))
                self.held -= end
            if end < len(x[0]):
                parts.append(tuple(y[end:] for y in x) if end else x)
        self.parts = parts
        for r in self.runs:
            out += r.upto(last)
        self.runs = [r for r in self.runs if r.part is not None]
        got = self._joined(out)
        self.deletes += len(got[0])
        return got

    def pop(self, target: int) -> list[tuple[int, float]]:
        """All messages to the target, the next one that has any."""
        return list(zip(*(x.tolist() for x in self.pop_upto(target)[1:])))


def make_store(name: str, k: int, beta: int | None = None, delta: int = 1024):
    inner = {"dense": DenseStore, "runlist": RunListStore, "plainbits": PlainBitsStore, "run": lambda k: RunStore(k, delta), "learned": lambda k: RunStore(k, delta), "auto": AutoStore}[name]
    if beta and name in ("run", "learned"):
        return BatchedRuns(k, beta, delta)
    return inner(k) if not beta else BatchedStore(k, beta, inner)
