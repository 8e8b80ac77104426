"""A bit vector kept as straight lines with small corrections in packed arrays, and its appendable form."""

from __future__ import annotations

from array import array
from bisect import bisect_right

import numpy as np

FRACTION = 20  # slopes are multiples of 2**-20, so lines are whole-number arithmetic and need no rounding margin
SEGMENT_BITS = 3 * 64  # first rank, first position, slope
STEEPEST = 1 << 62


class PackedInts:
    """Whole numbers of `width` bits each, one after the other in a byte array."""

    def __init__(self, width: int):
        self.width, self.n, self.bytes = width, 0, bytearray()
        self.least = -(1 << width - 1) if width else 0
        self.most = (1 << width - 1) - 1 if width else 0

    def extend(self, values: np.ndarray) -> None:
        if self.width:
            for at in range(0, len(values), 1 << 16):
                part = (values[at : at + (1 << 16)] - self.least).astype(np.uint8)
                bits = (part[:, None] >> np.arange(self.width, dtype=np.uint8) & 1).ravel()
                if used := self.n * self.width % 8:
                    bits = np.concatenate([np.unpackbits(np.array([self.bytes.pop()], np.uint8), bitorder="little")[:used], bits])
                self.bytes += np.packbits(bits, bitorder="little").tobytes()
                self.n += len(part)
        else:
            self.n += len(values)

    def truncate(self, n: int) -> None:
        self.n = n
        del self.bytes[(n * self.width + 7) // 8 :]

    def __getitem__(self, i: int) -> int:
        if not self.width:
            return 0
        bit = i * self.width
        at = bit >> 3
        return (int.from_bytes(self.bytes[at : at + 2], "little") >> (bit & 7) & (1 << self.width) - 1) + self.least

    def many(self, i: np.ndarray) -> np.ndarray:
        if not self.width or not len(i):
            return np.zeros(len(i), np.int64)
        raw, bit = np.frombuffer(self.bytes, np.uint8), i * self.width
        at = bit >> 3
        both = raw[at].astype(np.int64) | raw[np.minimum(at + 1, len(raw) - 1)].astype(np.int64) << 8
        return (both >> (bit & 7) & (1 << self.width) - 1) + self.least


def widen(points: np.ndarray, first: int, offset: int, low: int, high: int, least: int, most: int) -> tuple[int, int, int]:
    """How many of the points, which are entries offset, offset + 1, ... of a segment that begins at `first`, its cone of
    slopes still takes, and the cone after them.

    A slope s (a multiple of 2**-FRACTION) serves entry i at distance x if x - floor(s * i) lies between least and most,
    which is one interval of whole numbers for s; the cone is what is left of all of them, so no point is looked at again.
    """
    at, step = 0, 32
    while at < len(points):
        x = points[at : at + step] - first
        i = np.arange(offset + at, offset + at + len(x))
        a = np.maximum.accumulate(np.maximum(-((most - x << FRACTION) // i), low))
        b = np.minimum.accumulate(np.minimum(-((least - 1 - x << FRACTION) // i) - 1, high))
        crossed = int((a <= b).argmin()) if a[-1] > b[-1] else len(x)
        if crossed < len(x):
            return (at + crossed, int(a[crossed - 1]), int(b[crossed - 1])) if crossed else (at, low, high)
        low, high, at, step = int(a[-1]), int(b[-1]), at + len(x), min(2 * step, 1 << 16)
    return at, low, high


class LearnedBitVector:
    """The sorted positions of the 1-bits: per segment its first rank, first position and slope, and for each position a
    correction of `width` bits. Segments are cut greedily from the left, so later positions never change a closed one."""

    WIDTHS = (0, 2, 3, 4, 5, 6, 7, 8)

    def __init__(self, width: int):
        self.width, self.corrections = width, PackedInts(width)
        self.ranks, self.firsts, self.slopes = array("q"), array("q"), array("q")
        self.low, self.high, self.refits = 0, STEEPEST, 0  # the last segment's cone

    @classmethod
    def build(cls, starts, corr_bits: int | str = "auto") -> LearnedBitVector:
        """'auto': the width that is smallest on the first 2**15 positions."""
        points = np.asarray(starts, np.int64)

        def fit(width: int, some: np.ndarray) -> LearnedBitVector:
            v = LearnedBitVector(width)
            v.extend(some)
            return v

        if corr_bits == "auto":
            sample = points[: 1 << 15]
            best = min((fit(w, sample) for w in cls.WIDTHS), key=lambda v: v.size_bits())
            corr_bits = best.width
            if len(sample) == len(points):
                return best
        return fit(int(corr_bits), points)

    def extend(self, points: np.ndarray) -> None:
        """Larger positions go on from the last segment, whose cone is still known."""
        c = self.corrections
        at = 0
        if self.ranks and len(points):
            first, rank = self.firsts[-1], self.ranks[-1]
            held = c.n - rank
            at, self.low, self.high = widen(points, first, held, self.low, self.high, c.least, c.most)
            if at:
                slope = self.slopes[-1]
                if held == 1 or not self.low <= slope <= self.high:
                    # the line turns: the segment is opened and written again; each turn at least halves the cone
                    old = self._decoded(rank, c.n)
                    c.truncate(rank)
                    slope = self.slopes[-1] = (self.low + self.high) // 2
                    self.refits += 1
                    c.extend(old - first - (slope * np.arange(held) >> FRACTION))
                c.extend(points[:at] - first - (slope * np.arange(held, held + at) >> FRACTION))
        while at < len(points):
            first = int(points[at])
            took, self.low, self.high = widen(points[at + 1 :], first, 1, 0, STEEPEST, c.least, c.most)
            slope = (self.low + self.high) // 2 if took else 0
            self.ranks.append(c.n)
            self.firsts.append(first)
            self.slopes.append(slope)
            c.extend(points[at : at + took + 1] - first - (slope * np.arange(took + 1) >> FRACTION))
            at += took + 1

    def take(self, other: LearnedBitVector, offset: int) -> None:
        """The closed segments of another one of the same width follow, its positions moved by `offset`, beyond all here. What
        was taken is not extended any more."""
        if other.width != self.width:
            raise ValueError("widths differ")
        base = len(self)
        self.ranks.extend(r + base for r in other.ranks)
        self.firsts.extend(f + offset for f in other.firsts)
        self.slopes.extend(other.slopes)
        self.corrections.extend(other.corrections.many(np.arange(len(other))))

    def _decoded(self, a: int, b: int) -> np.ndarray:
        """Positions of the ranks a .. b - 1, all of them in one segment that begins at rank a."""
        k = bisect_right(self.ranks, a) - 1
        return self.firsts[k] + (self.slopes[k] * np.arange(b - a) >> FRACTION) + self.corrections.many(np.arange(a, b))

    def __len__(self) -> int:
        return self.corrections.n

    def _size(self, k: int) -> int:
        return (self.ranks[k + 1] if k + 1 < len(self.ranks) else self.corrections.n) - self.ranks[k]

    def rank(self, i: int, bit: int = 1) -> int:
        """1-bits (or 0-bits) up to and including i: the segment by binary search, then the few places where the line
        and its corrections leave it open."""
        k = bisect_right(self.firsts, i) - 1
        if k < 0:
            return 0 if bit else i + 1
        size, first, slope, base = self._size(k), self.firsts[k], self.slopes[k], self.ranks[k]
        x, c = i - first, self.corrections
        low, high = 1, size
        if slope:
            if x >= c.most:
                low = max(1, min(size, ((x - c.most) << FRACTION) // slope + 1))
            high = max(low, min(size, -(-((x - c.least + 1) << FRACTION) // slope)))
        while low < high:
            mid = (low + high) // 2
            if (slope * mid >> FRACTION) + c[base + mid] <= x:
                low = mid + 1
            else:
                high = mid
        return base + low if bit else i + 1 - base - low

    def rank_many(self, i: np.ndarray) -> np.ndarray:
        """rank of many places at once."""
        if not self.ranks or not len(i):
            return np.zeros(len(i), np.int64)
        firsts, ranks, slopes = (np.frombuffer(a, np.int64) for a in (self.firsts, self.ranks, self.slopes))  # views, not copies
        k = np.searchsorted(firsts, i, "right") - 1
        before = k < 0
        k = np.maximum(k, 0)
        slope, base, c = slopes[k], ranks[k], self.corrections
        size = np.where(k + 1 < len(ranks), ranks[np.minimum(k + 1, len(ranks) - 1)], len(self)) - base
        x = np.clip(i - firsts[k], 0, 1 << 42)
        flat = np.maximum(slope, 1)
        low = np.where((slope > 0) & (x >= c.most), np.clip(((x - c.most) << FRACTION) // flat + 1, 1, size), 1)
        high = np.where(slope > 0, np.maximum(low, np.minimum(size, -(-((x - c.least + 1) << FRACTION) // flat))), size)
        while (open_ := np.flatnonzero(low < high)).size:
            mid = (low[open_] + high[open_]) // 2
            below = (slope[open_] * mid >> FRACTION) + c.many(base[open_] + mid) <= x[open_]
            low[open_] = np.where(below, mid + 1, low[open_])
            high[open_] = np.where(below, high[open_], mid)
        return np.where(before, 0, base + low)

    def at(self, rank: int) -> int:
        k = bisect_right(self.ranks, rank) - 1
        return self.firsts[k] + (self.slopes[k] * (rank - self.ranks[k]) >> FRACTION) + self.corrections[rank]

    def select(self, x: int, bit: int = 1) -> int:
        """Place of the x-th 1-bit (x >= 1), or of the x-th 0-bit."""
        if bit:
            return self.at(x - 1)
        low, high = x - 1, x - 1 + len(self)
        while low < high:
            mid = (low + high) // 2
            if self.rank(mid, 0) >= x:
                high = mid
            else:
                low = mid + 1
        return low

    def starts(self) -> np.ndarray:
        if not self.ranks:
            return np.zeros(0, np.int64)
        ranks = np.array(self.ranks)
        size = np.diff(np.append(ranks, self.corrections.n))
        k, i = np.repeat(np.arange(len(ranks)), size), np.arange(self.corrections.n)
        return np.array(self.firsts)[k] + (np.array(self.slopes)[k] * (i - ranks[k]) >> FRACTION) + self.corrections.many(i)

    def segments(self) -> list[tuple[int, int, float, int]]:
        """(first rank, first position, slope, positions) of each."""
        return [(r, f, s / (1 << FRACTION), self._size(k)) for k, (r, f, s) in enumerate(zip(self.ranks, self.firsts, self.slopes))]

    def nbytes(self) -> int:
        return SEGMENT_BITS // 8 * len(self.ranks) + len(self.corrections.bytes)

    def size_bits(self) -> int:
        return SEGMENT_BITS * len(self.ranks) + 8 + self.width * self.corrections.n


def fitted_bits(points: np.ndarray, counts: np.ndarray, most: int = 256, group: int = 1 << 16) -> int:
    """The sum of LearnedBitVector.build(...).size_bits() over lists of positions that follow each other, `counts` long each.
    Lists of up to `most` positions are cut in segments side by side, one position of each list at a time, with the cones
    of `widen`; longer ones one after the other."""
    ends = np.cumsum(counts)
    begins, total = ends - counts, 0
    for a, b in zip(begins[counts > most].tolist(), ends[counts > most].tolist()):
        total += LearnedBitVector.build(points[a:b]).size_bits()
    short = np.flatnonzero(counts <= most)
    short = short[np.argsort(-counts[short], kind="stable")]  # those that go on stand first
    for part in (short[i : i + group] for i in range(0, len(short), group)):
        size, begin = counts[part], begins[part]
        going = [int(np.searchsorted(-size, -i, "left")) for i in range(int(size[0]) + 1)]  # lists of more than i positions
        best = np.full(len(part), np.iinfo(np.int64).max)
        for width in LearnedBitVector.WIDTHS:
            c = PackedInts(width)
            cut = (size > 0).astype(np.int64)
            first, place = points[np.minimum(begin, len(points) - 1)], np.zeros(len(part), np.int64)
            low, high = np.zeros(len(part), np.int64), np.full(len(part), STEEPEST)
            for i in range(1, int(size[0])):
                m = going[i]
                at, place[:m] = points[begin[:m] + i], place[:m] + 1
                x, n = at - first[:m], place[:m]
                a = np.maximum(-((c.most - x << FRACTION) // n), low[:m])
                b = np.minimum(-((c.least - 1 - x << FRACTION) // n) - 1, high[:m])
                new = a > b
                cut[:m] += new
                low[:m], high[:m] = np.where(new, 0, a), np.where(new, STEEPEST, b)
                first[:m], place[:m] = np.where(new, at, first[:m]), np.where(new, 0, n)
            best = np.minimum(best, SEGMENT_BITS * cut + 8 + width * size)
        total += int(best.sum())
    return total


class AppendableBitVector:
    """Appends go to a buffer of `delta` positions; when it is full, the last segment is opened and goes on from it."""

    def __init__(self, delta: int = 1024, width: int = 4):
        self.delta, self.closed, self.buffer = delta, LearnedBitVector(width), array("q")

    def append(self, position: int) -> None:
        self.buffer.append(position)
        if len(self.buffer) >= self.delta:
            self.flush()

    def extend(self, positions: np.ndarray) -> None:
        while len(positions):
            room = max(1, self.delta - len(self.buffer))
            self.buffer.frombytes(positions[:room].astype(np.int64).tobytes())
            positions = positions[room:]
            if len(self.buffer) >= self.delta:
                self.flush()

    def flush(self) -> None:
        self.closed.extend(np.array(self.buffer, np.int64))
        self.buffer = array("q")

    def __len__(self) -> int:
        return len(self.closed) + len(self.buffer)

    def rank(self, i: int) -> int:
        if self.buffer and i >= self.buffer[0]:
            return len(self.closed) + bisect_right(self.buffer, i)
        return self.closed.rank(i)

    def rank_many(self, i: np.ndarray) -> np.ndarray:
        out = self.closed.rank_many(i)
        if self.buffer:
            waiting = np.frombuffer(self.buffer, np.int64)
            new = i >= waiting[0]
            out[new] = len(self.closed) + np.searchsorted(waiting, i[new], "right")
        return out

    def starts(self) -> np.ndarray:
        return np.concatenate([self.closed.starts(), np.array(self.buffer, np.int64)])

    def segments(self) -> int:
        return len(self.closed.ranks) + bool(self.buffer)

    def nbytes(self) -> int:
        return self.closed.nbytes() + 8 * len(self.buffer)

    def size_bits(self) -> int:
        return self.closed.size_bits() + 64 * len(self.buffer)


def learn_segments(runs, corr_bits: int | str = "auto"):
    """(batch, seg_no, first_rank, first_pos, slope, corr_bits, points, bits) of a run table, a batch at a time."""
    import pandas as pd

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        v = LearnedBitVector.build(np.sort(pdf["start"].to_numpy()), corr_bits)
        rank, pos, slope, points = zip(*v.segments())
        return pd.DataFrame({"batch": int(pdf["batch"].iloc[0]), "seg_no": range(len(rank)), "first_rank": rank, "first_pos": pos, "slope": slope, "corr_bits": v.width, "points": points, "bits": [SEGMENT_BITS + v.width * p for p in points]})

    return runs.select("batch", "start").groupBy("batch").applyInPandas(fit, "batch long, seg_no int, first_rank long, first_pos long, slope double, corr_bits int, points int, bits long")
