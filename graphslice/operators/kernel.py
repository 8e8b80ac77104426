"""The ordered part of one-pass placement: nodes in id order, each placed once and for all."""

from __future__ import annotations

import heapq
import json
import resource
import time
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from ..functions.score import LinearPenalty, PowerPenalty
from .stores import ForwardQueue, make_store

OUT = pa.schema([("kind", pa.string()), ("shard", pa.int32()), ("batch", pa.int64()), ("run_no", pa.int64()), ("start", pa.int64()), ("len", pa.int64()), ("head", pa.int32()), ("stats", pa.string())])
OUT_DDL = "kind string, shard int, batch long, run_no long, start long, len long, head int, stats string"


@dataclass(frozen=True)
class Rules:
    """What places a node: the objective over (n, m, k), the block limit (None: penalty only), stickiness and scoring."""

    k: int
    n: float
    m: float
    cap: float | None
    objective: PowerPenalty | LinearPenalty = PowerPenalty()
    kappa: float = 1.0
    scoring: str = "candidates"
    scale: float = 1.0  # a shard's block sizes stand for this many times as much


@dataclass
class State:
    """Sizes, the previous block and counters; all that goes from one chunk to the next besides the runs."""

    sizes: list[float]
    previous: int = -1
    placed: int = 0
    lookups: int = 0
    overfull: int = 0
    cut: float = 0.0
    unit: bool = True
    queue: dict = field(default_factory=dict)


class Placer:
    """Chooses blocks. Scores only the blocks of placed neighbours, the least loaded one and the previous one: any other
    block has no gain and no smaller penalty, so it cannot win (kappa >= 1)."""

    def __init__(self, rules: Rules, state: State):
        if rules.kappa < 1:
            raise ValueError("kappa is at least 1")
        self.r, self.s = rules, state
        self.score = rules.objective.scorer(rules.n, rules.m, rules.k)
        self.by_load = rules.objective.ties_by_load
        self.many = rules.objective.many(rules.n, rules.m, rules.k) if rules.scoring == "candidates" and rules.n * rules.scale < 1 << 40 else None
        self.loads = [(x, b) for b, x in enumerate(state.sizes)]
        heapq.heapify(self.loads)

    def least_loaded(self) -> int:
        """One entry per block, set right when it comes to the top: sizes only grow, so an old entry is a lower bound."""
        sizes, loads = self.s.sizes, self.loads
        while sizes[loads[0][1]] != loads[0][0]:
            heapq.heapreplace(loads, (sizes[loads[0][1]], loads[0][1]))
        return loads[0][1]

    def choose(self, gains: dict[int, float], c: float = 1.0) -> int:
        r, sizes, previous = self.r, self.s.sizes, self.s.previous
        free = self.least_loaded()
        cap = r.cap
        if cap is not None and sizes[free] + c > cap:
            self.s.overfull += 1
            best = free
        else:
            if r.scoring == "full":
                candidates = range(r.k)
            else:
                candidates = {free, *gains}
                if previous >= 0:
                    candidates.add(previous)
            best, top = -1, None
            kappa, scale, score = r.kappa, r.scale, self.score
            for b in candidates:
                size = sizes[b]
                if cap is not None and size + c > cap:
                    continue
                x = score(gains.get(b, 0), size * scale)
                if b == previous and kappa != 1:
                    x = x * kappa if x > 0 else x / kappa if x < 0 else x
                key = (x, -size, -b) if self.by_load else (x, -b)
                if top is None or key > top:
                    best, top = b, key
        sizes[best] += c
        self.s.previous = best
        self.s.placed += 1
        if gains:
            self.s.cut += sum(gains.values()) - gains.get(best, 0)
        return best

    def level(self, most: int) -> np.ndarray:
        """What `choose` gives for up to `most` nodes of weight one without gains, where there is no stickiness: each goes to
        the least loaded block, the lowest of equal ones. It ends before a node that finds all blocks full. Whole sizes."""
        r, k = self.r, self.r.k
        sizes = np.array(self.s.sizes)
        order = np.sort(sizes)
        below = np.cumsum(order)
        j = int(np.searchsorted(np.arange(1, k) * order[1:] - below[:-1], most)) + 1  # the blocks that rise
        room = np.maximum(0, -(-(most + below[j - 1]) // j) - sizes).astype(np.int64)
        block = np.repeat(np.arange(k), room)
        at = sizes[block] + np.arange(len(block)) - np.repeat(np.cumsum(room) - room, room)
        first = np.lexsort((block, at))[:most]
        block, at = block[first], at[first]
        if r.cap is not None:
            block = block[: int(np.searchsorted(at + 1, r.cap, "right"))]
        if len(block):
            self.s.sizes[:] = (sizes + np.bincount(block, minlength=k)).tolist()
            self.s.previous = int(block[-1])
            self.s.placed += len(block)
        return block

    def stay(self, most: int, node: np.ndarray, block: np.ndarray, gain: np.ndarray) -> int:
        """How many of the next `most` nodes of weight one `choose` puts in the previous block, one after the other; they are
        placed. Gains come as (node, block, gain), in pieces, those from the nodes themselves as if all of them stayed: up to
        the first that leaves, they did. Whole sizes and gains, so that no order of sums matters."""
        r, s, k = self.r, self.s, self.r.k
        p, sizes = s.previous, np.array(s.sizes)
        if r.cap is not None:
            most = min(most, int(r.cap - sizes[p]))
        if most <= 0:
            return 0
        inside = node < most
        node, block, gain = node[inside], block[inside], gain[inside]
        mine = block == p
        size = sizes[p] + np.arange(most)
        own = self.many(np.bincount(node[mine], gain[mine], most), size * r.scale)
        if r.kappa != 1:
            own = np.where(own > 0, own * r.kappa, np.where(own < 0, own / r.kappa, own))
        stays = np.ones(most, bool)
        if k > 1:
            load, free = min((x, b) for b, x in enumerate(s.sizes) if b != p)
            x = self.many(0.0, np.float64(load * r.scale))
            # it is a candidate without gain only where it is the least loaded
            stays = (own > x) | (own == x) & (p < free) | (load > size) | (load == size) & (p < free)
        node, block, gain = node[~mine], block[~mine], gain[~mine]
        if len(node):
            key, place = np.unique(node * k + block, return_inverse=True)
            gain, node, block = np.bincount(place, gain, len(key)), key // k, key % k
            x, mine = self.many(gain, sizes[block] * r.scale), own[node]
            lost = ~((mine > x) | (mine == x) & (p < block))
            if r.cap is not None:
                lost &= sizes[block] + 1 <= r.cap
            stays[node[lost]] = False
        count = most if stays.all() else int(stays.argmin())
        s.sizes[p] += count
        s.placed += count
        s.cut += float(gain[node < count].sum())
        return count


class _Shard:
    """The nodes of one shard as they come: the store, and the node whose rows may go on in the next batch."""

    def __init__(self, rules: Rules, store: str, beta: int | None, delta: int, memory_bytes: int, shard: int, first: int, begin: State | None):
        self.k, self.shard, self.first, self.beta = rules.k, shard, first, beta
        self.state = State(list(begin.sizes), begin.previous) if begin is not None else State([0.0] * rules.k)
        self.placer = Placer(rules, self.state)
        self.store = None if store == "forward" else make_store(store, rules.k, beta, delta)
        self.queue = ForwardQueue(memory_bytes) if store == "forward" else None
        self.runs = make_store("runlist", rules.k) if store == "forward" else self.store
        self.held: int | None = None  # the node that is not placed yet
        self.gains: dict[int, float] = {}
        self.weight = 1.0
        self.recent: list[int] = []  # blocks of the nodes placed since the batch began
        self.same, self.need = 0, self.TRY  # nodes in a row in one block, and how many of them make it worth to look ahead

    TRY = 16

    def place_held(self) -> None:
        if self.held is None:
            return
        if self.queue is None:
            block = self.placer.choose(self.gains, self.weight)
            self.runs.append(block)
            self.recent.append(block)
        self.held, self.gains, self.weight = None, {}, 1.0

    def feed(self, ids: np.ndarray, nbr: np.ndarray, w: np.ndarray, block: np.ndarray) -> None:
        """Rows sorted by id, with -1 for no neighbour and for no block. A row with nbr gives a neighbour; one with block a
        gain that is already known; one with neither the node's weight.

        Neighbours that were placed before this batch are looked up together and their weights summed by node and block;
        those that are placed within it are read from the list of recent blocks. A hub's rows are folded as they come.

        Nodes are scored one by one only where blocks change: where weights are whole, stretches of nodes that stay in one
        block, and of nodes without gains, are placed at once (Placer.stay, Placer.level), with the same blocks.
        """
        if (ids[1:] < ids[:-1]).any() or self.held is not None and ids[0] < self.held:
            raise ValueError(f"nodes out of order near {ids[0]}")
        if self.state.unit and not (w[nbr >= 0] == 1).all():
            self.state.unit = False
        if self.queue is not None:
            return self.forward(ids, nbr, w)
        if self.held is not None and self.held != ids[0]:
            self.place_held()
        self.recent = []
        base = self.first + self.state.placed
        cut = np.concatenate([[0], np.flatnonzero(ids[1:] != ids[:-1]) + 1])
        group = np.repeat(np.arange(len(cut)), np.diff(np.append(cut, len(ids))))
        known = block >= 0
        far = ~known & (nbr >= 0) & (nbr < base)
        blocks = block.copy()
        if far.any():
            blocks[far] = self.store.get_many(nbr[far] - self.first)
        summed = np.flatnonzero(known | far)
        key, place = np.unique(group[summed] * self.k + blocks[summed], return_inverse=True)
        sums = np.bincount(place, w[summed], len(key)).tolist() if len(key) else []
        at = np.searchsorted(key, np.arange(len(cut) + 1) * self.k).tolist()
        sum_at, sum_node, sum_block, sum_gain = at, key // self.k, key % self.k, np.array(sums, float)
        key = sum_block.tolist()
        near = np.flatnonzero(~known & ~far & (nbr >= 0))
        near_at = np.searchsorted(group[near], np.arange(len(cut) + 1)).tolist()
        near_nbr, near_w = nbr[near].tolist(), w[near].tolist()
        own = np.flatnonzero((nbr < 0) & ~known)
        weights = dict(zip(group[own].tolist(), w[own].tolist()))
        self.state.lookups += len(near) + int(far.sum())
        recent, choose, state = self.recent, self.placer.choose, self.state
        last = len(cut) - 1
        whole = self.placer.many is not None and bool((w[own] == 1).all() and (w > 0).all() and (w == np.rint(w)).all()) and all(x.is_integer() for x in state.sizes)
        level = whole and self.placer.r.kappa == 1
        if whole:
            busy = np.union1d(sum_node, group[near]).tolist() if level else []  # nodes with gains
            near_node, near_place, near_gain = group[near], nbr[near] - base, w[near]
            blocks, told = np.zeros(len(cut), np.int64), 0  # recent blocks as an array, up to `told`
            ahead, fill = 4 * self.TRY, 0
        nodes, g = ids[cut].tolist(), 0
        while g <= last:
            v = nodes[g]
            if whole and g < last and self.held is None:
                if level:
                    while fill < len(busy) and busy[fill] < g:
                        fill += 1
                    bare = min(last, busy[fill] if fill < len(busy) else last) - g
                    if bare >= self.TRY:
                        got = self.placer.level(bare)
                        if len(got):
                            recent += got.tolist()
                            g, self.same = g + len(got), 0
                            continue
                if self.same >= self.need:
                    most = min(ahead, last - g)
                    blocks[told:g], told = recent[told:g], g
                    a, z, c, e = sum_at[g], sum_at[g + most], near_at[g], near_at[g + most]
                    place = near_place[c:e]
                    block_of = np.where(place < g, blocks[place], state.previous)
                    node = np.concatenate([sum_node[a:z], near_node[c:e]]) - g
                    stayed = self.placer.stay(most, node, np.concatenate([sum_block[a:z], block_of]), np.concatenate([sum_gain[a:z], near_gain[c:e]]))
                    recent += [state.previous] * stayed
                    g += stayed
                    if stayed == most:
                        ahead *= 4
                        continue
                    # a short stretch costs more than it saves
                    self.same, self.need = 0, self.TRY if stayed >= 2 * self.TRY else min(2 * self.need, 1 << 12)
                    ahead = max(4 * self.TRY, 2 * stayed)
                    v = nodes[g]
            gains = self.gains if self.held == v else {}
            for i in range(at[g], at[g + 1]):
                gains[key[i]] = gains.get(key[i], 0) + sums[i]
            for i in range(near_at[g], near_at[g + 1]):
                b = recent[near_nbr[i] - base]
                gains[b] = gains.get(b, 0) + near_w[i]
            c = weights.get(g, self.weight if self.held == v else 1.0)
            if g < last:
                self.held = None
                before = state.previous
                b = choose(gains, c)
                self.same = self.same + 1 if b == before else 0
                recent.append(b)
                self.gains, self.weight = {}, 1.0
            else:
                self.held, self.gains, self.weight = v, gains, c
            g += 1
        if recent:
            self.runs.extend(np.array(recent, np.int64))

    def forward(self, ids: np.ndarray, nbr: np.ndarray, w: np.ndarray) -> None:
        """The same with messages instead of a store. A node is placed at its first row, which holds its weight, so that a
        hub's messages leave as they come. What the batch's nodes are told by earlier batches leaves the queue at once and is
        summed by node and block; messages between nodes of the batch are read from the list of recent blocks."""
        queue, k = self.queue, self.k
        cut = np.concatenate([[0], np.flatnonzero(ids[1:] != ids[:-1]) + 1])
        nodes = ids[cut]
        first, end, count = int(nodes[0]), int(nodes[-1]), len(nodes)
        if end - first != count - 1:
            raise ValueError(f"nodes are missing near {first}")
        again = self.held == first  # placed with the batch before
        recent = self.recent = [self.state.previous] if again else []
        waiting = queue.inserts - queue.deletes
        target, block, weight = queue.pop_upto(end)
        key, place = np.unique((target - first) * k + block, return_inverse=True)
        sums = np.bincount(place, weight, len(key)).tolist() if len(key) else []
        at = np.searchsorted(key, np.arange(count + 1) * k).tolist()
        key = (key % k).tolist()
        later = nbr > ids
        inside = np.flatnonzero(later & (nbr <= end))
        inside = inside[np.argsort(nbr[inside], kind="stable")]
        near_at = np.searchsorted(nbr[inside], np.arange(first, end + 2)).tolist()
        near, near_w = (ids[inside] - first).tolist(), w[inside].tolist()
        sent, got = np.bincount(ids[later] - first, minlength=count), np.bincount(np.concatenate([target, nbr[inside]]) - first, minlength=count)
        queue.passed(len(inside), waiting + int((np.cumsum(sent) - np.cumsum(got)).max()))
        own = np.flatnonzero(nbr < 0)
        weights = dict(zip((ids[own] - first).tolist(), w[own].tolist()))
        choose, append = self.placer.choose, self.runs.append
        for g in range(int(again), count):
            gains: dict[int, float] = {}
            for i in range(at[g], at[g + 1]):
                gains[key[i]] = gains.get(key[i], 0) + sums[i]
            for i in range(near_at[g], near_at[g + 1]):
                b = recent[near[i]]
                gains[b] = gains.get(b, 0) + near_w[i]
            b = choose(gains, weights.get(g, 1.0))
            append(b)
            recent.append(b)
        out = np.flatnonzero(later & (nbr > end))
        queue.push_many(nbr[out], np.array(recent, np.int64)[ids[out] - first], w[out])
        self.held = end

    def finish(self, began: float):
        self.place_held()
        state, queue = self.state, self.queue
        heads, starts = self.runs.heads_and_starts()
        lens = np.diff(np.append(starts, state.placed))
        stats = {"seconds": time.perf_counter() - began, "peak_rss_kb": resource.getrusage(resource.RUSAGE_SELF).ru_maxrss, "runs": len(heads), "lookups": state.lookups, "appends": state.placed, "overfull": state.overfull, "cut": state.cut, "unit": state.unit, "sizes": state.sizes, "previous": state.previous}
        if queue is None:
            stats |= {"size_bits": int(self.store.size_bits()), "nbytes": int(self.store.nbytes()), "segments": self.store.segments() if hasattr(self.store, "segments") else 0}
        else:
            stats |= {"size_bits": queue.peak * ForwardQueue.ENTRY * 8, "nbytes": min(queue.peak, queue.most) * ForwardQueue.ENTRY, "segments": 0}
            stats |= {"queue_inserts": queue.inserts, "queue_deletes": queue.deletes, "queue_peak": queue.peak, "spilled_runs": queue.spilled, "spilled_messages": queue.spilled_messages, "merges": queue.merges}
        for i in range(0, len(heads), 50_000):
            part = slice(i, i + 50_000)
            start = starts[part] + self.first
            m = len(start)
            yield pa.RecordBatch.from_arrays([pa.array(["run"] * m), pa.array(np.full(m, self.shard, np.int32)), pa.array(start // self.beta if self.beta else np.zeros(m, np.int64)), pa.array(np.arange(i, i + m)), pa.array(start), pa.array(lens[part]), pa.array(heads[part].astype(np.int32)), pa.nulls(m, pa.string())], schema=OUT)
        yield pa.RecordBatch.from_arrays([pa.array(["stats"]), pa.array([self.shard], pa.int32()), *(pa.nulls(1, t) for t in (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32())), pa.array([json.dumps(stats)])], schema=OUT)


def place(batches, rules: Rules, store: str, beta: int | None, delta: int, memory_bytes: int, begin: State | None = None, offset: int = 0):
    """Arrow batches of runs, then one row of statistics per shard, from rows (shard, id, nbr, w, block) sorted by shard, id.

    Neighbours below `offset`, or of other shards, have to come as gains. With store='forward' there is no store:
    later neighbours get messages, and earlier ones are read from the queue; the row of a node's weight comes first.
    The statistics hold the weight of the cut edges that the shard has seen, and whether all weights were one.
    """
    own, began = None, time.perf_counter()
    for batch in batches:
        if not batch.num_rows:
            continue
        shards, ids = batch.column("shard").to_numpy(), batch.column("id").to_numpy()
        w = batch.column("w").to_numpy()
        nbr, block = (pc.fill_null(batch.column(n), -1).to_numpy() for n in ("nbr", "block"))
        edge = np.flatnonzero(np.concatenate([[True], shards[1:] != shards[:-1], [True]]))
        for a, b in zip(edge[:-1].tolist(), edge[1:].tolist()):
            s = int(shards[a])
            if own is None or own.shard != s:
                if own is not None:
                    yield from own.finish(began)
                own = _Shard(rules, store, beta, delta, memory_bytes, s, int(ids[a]) if s > 0 and begin is None and offset == 0 else offset, begin)
            own.feed(ids[a:b], nbr[a:b], w[a:b], block[a:b].astype(np.int64))
    if own is not None:
        yield from own.finish(began)


class _Stores:
    """Stores that get the same labels and lookups. Labels are handed on before a lookup; each store's own seconds are kept."""

    def __init__(self, stores: list):
        self.stores, self.own, self.waiting = stores, [0.0] * len(stores), []
        self.append = self.waiting.append

    def hand_on(self) -> None:
        labels = np.array(self.waiting, np.int64)
        for i, s in enumerate(self.stores):
            began = time.perf_counter()
            s.extend(labels)
            self.own[i] += time.perf_counter() - began
        self.waiting.clear()

    def extend(self, blocks: np.ndarray) -> None:
        self.waiting += blocks.tolist()

    def get_many(self, v: np.ndarray) -> np.ndarray:
        self.hand_on()
        first = None
        for i, s in enumerate(self.stores):
            began = time.perf_counter()
            x = s.get_many(v)
            self.own[i] += time.perf_counter() - began
            if first is None:
                first = x
            elif not np.array_equal(first, x):
                raise ValueError("stores disagree on a label")
        return first


class _Side(_Shard):
    """One placement whose labels go to several stores (store, beta, delta); a node's choice does not depend on them."""

    def __init__(self, rules: Rules, kinds: list[tuple]):
        super().__init__(rules, "runlist", None, 1024, 0, 0, 0, None)
        self.kinds = kinds
        self.store = self.runs = self.all = _Stores([make_store(n, rules.k, beta, delta) for n, beta, delta in kinds])

    def finish(self, began: float):
        self.place_held()
        self.all.hand_on()
        shared = time.perf_counter() - began - sum(self.all.own)
        for i, (store, (_, beta, _)) in enumerate(zip(self.all.stores, self.kinds)):
            self.shard, self.beta, self.store, self.runs = i, beta, store, store
            # a store's run ends with its own seconds after the shared ones
            yield from super().finish(time.perf_counter() - shared - self.all.own[i])


def place_side(batches, rules: Rules, kinds: list[tuple]):
    """Arrow batches of runs and a row of statistics for each store, numbered as shards, from rows as for `place` of one shard.
    `seconds` are those that all stores share (reading, scoring) and the store's own (appends, lookups)."""
    side, began = _Side(rules, kinds), time.perf_counter()
    for batch in batches:
        if batch.num_rows:
            ids, nbr, w, block = (pc.fill_null(batch.column(c), -1).to_numpy() for c in ("id", "nbr", "w", "block"))
            side.feed(ids, nbr, w, block.astype(np.int64))
    yield from side.finish(began)


def _narrow(x: np.ndarray) -> bytes:
    return (x.astype(np.int32) if x.min() >= -(1 << 31) and x.max() < 1 << 31 else x).tobytes()


def packed(batches, most: int = 1 << 14):
    """Sorted rows (id, nbr, w), or keys of both (stream_keys), as few rows of bytes (id, nbr of the first row; rows; ids, nbrs,
    ws): a task that has to read a whole stream in order then sorts and moves pieces of `most` rows. Numbers take four bytes
    where they fit (ids: from the first one), weights none where all are one."""
    part, held = [], 0

    def piece():
        t = pa.Table.from_batches(part)
        if "key" in t.column_names:
            key = t.column("key").to_numpy()
            ids, nbr, w = key >> 32, (key & 0xFFFFFFFF) - 1, np.ones(1)
        else:
            ids, w = t.column("id").to_numpy(), t.column("w").to_numpy()
            nbr = pc.fill_null(t.column("nbr"), -1).to_numpy()
        edge = np.append(np.arange(0, len(ids), most), len(ids)).tolist()
        rows = [(ids[a:b], nbr[a:b], w[a:b]) for a, b in zip(edge[:-1], edge[1:])]
        one = [b"" if (c == 1).all() else c.tobytes() for _, _, c in rows]
        return pa.RecordBatch.from_arrays([pa.array([int(x[0]) for x, _, _ in rows], pa.int64()), pa.array([int(y[0]) for _, y, _ in rows], pa.int64()), pa.array([len(x) for x, _, _ in rows], pa.int32()), pa.array([_narrow(x - x[0]) for x, _, _ in rows]), pa.array([_narrow(y) for _, y, _ in rows]), pa.array(one, pa.binary())], names=["id", "nbr", "rows", "ids", "nbrs", "ws"])

    for batch in batches:
        part.append(batch)
        held += batch.num_rows
        if held >= most:
            yield piece()
            part, held = [], 0
    if held:
        yield piece()


PACKED_DDL = "id long, nbr long, rows int, ids binary, nbrs binary, ws binary"


def unpacked(batches):
    """The stream's rows again, a batch per piece."""
    for batch in batches:
        for first, rows, ids, nbrs, ws in zip(*(batch.column(c) for c in ("id", "rows", "ids", "nbrs", "ws"))):
            i, n = (np.frombuffer(x.as_buffer(), np.int32 if len(x.as_buffer()) == 4 * rows.as_py() else np.int64).astype(np.int64) for x in (ids, nbrs))
            i += first.as_py()
            w = np.frombuffer(ws.as_buffer(), np.float64) if len(ws.as_buffer()) else np.ones(len(i))
            yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(i), np.int32)), pa.array(i), pa.array(n), pa.array(w), pa.array(np.full(len(i), -1, np.int32))], names=["shard", "id", "nbr", "w", "block"])


class _Frozen(_Shard):
    """Buffers of nodes, each scored as a whole against the state before it. Gains from earlier buffers are summed in a table of
    the buffer's nodes and the blocks as the rows come; edges inside a buffer count for nothing."""

    def __init__(self, rules: Rules, buffer: int, n: int):
        super().__init__(rules, "runlist", None, 1024, 0, 0, 0, None)
        self.rules, self.buffer, self.n, self.number = rules, buffer, n, 0
        self.begin()

    def begin(self) -> None:
        lo = self.number * self.buffer
        self.lo, self.hi = lo, min(self.n, lo + self.buffer)
        self.table = np.zeros(max(0, self.hi - lo) * self.k)

    def feed(self, ids: np.ndarray, nbr: np.ndarray, w: np.ndarray, block: np.ndarray) -> None:
        if (ids[1:] < ids[:-1]).any() or len(ids) and ids[0] < self.lo:
            raise ValueError(f"nodes out of order near {ids[0]}")
        while len(ids):
            m = int(np.searchsorted(ids, self.hi))
            far = np.flatnonzero((nbr[:m] >= 0) & (nbr[:m] < self.lo))
            if len(far):
                at = (ids[far] - self.lo) * self.k + self.store.get_many(nbr[far])
                self.table += np.bincount(at, w[far], len(self.table))
            self.state.lookups += len(far)
            if m < len(ids):
                self.place_buffer()
            ids, nbr, w = ids[m:], nbr[m:], w[m:]

    def place_buffer(self) -> None:
        r, sizes, count = self.rules, self.state.sizes, self.hi - self.lo
        order = sorted(range(self.k), key=lambda b: (sizes[b], b)) if r.objective.ties_by_load else list(range(self.k))
        order = [b for b in order if r.cap is None or sizes[b] + 1 <= r.cap]  # the first of equal scores wins
        gains, values = self.table.reshape(count, self.k), np.empty((count, len(order)))
        for i, b in enumerate(order):
            x = self.placer.score(gains[:, b], sizes[b])
            if b == self.state.previous and r.kappa != 1:
                x = np.where(x > 0, x * r.kappa, np.where(x < 0, x / r.kappa, x))
            values[:, i] = x
        best = np.array(order)[values.argmax(1)]
        # more nodes than a block has room for: the rest, by id, fill the least loaded blocks
        rest = []
        for b in range(self.k):
            own = np.flatnonzero(best == b)
            room = len(own) if r.cap is None else max(0, int(r.cap - sizes[b]))
            rest += own[room:].tolist()
            sizes[b] += min(len(own), room)
        for v in sorted(rest):
            b = min(range(self.k), key=lambda b: (sizes[b], b))
            sizes[b] += 1
            best[v] = b
        for b in best.tolist():
            self.runs.append(b)
        self.state.placed += count
        self.state.previous = int(best[-1])
        self.number += 1
        self.begin()

    def place_held(self) -> None:
        if self.lo < self.hi:
            self.place_buffer()


def place_frozen(batches, rules: Rules, buffer: int, n: int):
    """Arrow batches of runs and a row of statistics from rows as for `place`: nodes in buffers, as joins and an argmax per
    buffer would place them (plans.execute.buffered), in one task."""
    shard, began = _Frozen(rules, buffer, n), time.perf_counter()
    for batch in batches:
        if batch.num_rows:
            shard.feed(*(pc.fill_null(batch.column(c), -1).to_numpy() for c in ("id", "nbr", "w", "block")))
    yield from shard.finish(began)


__all__ = ["OUT", "OUT_DDL", "PACKED_DDL", "Placer", "Rules", "State", "packed", "place", "place_frozen", "place_side", "unpacked"]
