"""Mixing overlapping sources to target weights by a min-cost flow over membership patterns."""

from __future__ import annotations

import heapq
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

WORD = r"[^\x20\x09-\x0D]+"
BUCKETS = 4096


class MinCostFlow:
    """Successive shortest paths with potentials; integer capacities and costs."""

    def __init__(self, n: int):
        self.arcs: list[list[int]] = [[] for _ in range(n)]
        self.to: list[int] = []
        self.room: list[int] = []
        self.cost: list[int] = []

    def add(self, a: int, b: int, room: int, cost: int) -> int:
        for x, y, r, c in ((a, b, room, cost), (b, a, 0, -cost)):
            self.arcs[x].append(len(self.to))
            self.to.append(y)
            self.room.append(r)
            self.cost.append(c)
        return len(self.to) - 2

    def run(self, s: int, t: int, most: int) -> tuple[int, int]:
        n, sent, paid = len(self.arcs), 0, 0
        height = [0] * n
        while sent < most:
            far, via = [None] * n, [-1] * n
            far[s], heap = 0, [(0, s)]
            while heap:
                d, x = heapq.heappop(heap)
                if d > far[x]:
                    continue
                for e in self.arcs[x]:
                    if self.room[e] and (far[y := self.to[e]] is None or d + self.cost[e] + height[x] - height[y] < far[y]):
                        far[y] = d + self.cost[e] + height[x] - height[y]
                        via[y] = e
                        heapq.heappush(heap, (far[y], y))
            if far[t] is None:
                break
            height = [h + (f if f is not None else 0) for h, f in zip(height, far)]
            push, x = most - sent, t
            while x != s:
                push, x = min(push, self.room[via[x]]), self.to[via[x] ^ 1]
            x = t
            while x != s:
                self.room[via[x]] -= push
                self.room[via[x] ^ 1] += push
                paid += push * self.cost[via[x]]
                x = self.to[via[x] ^ 1]
            sent += push
        return sent, paid


def capped_shares(sizes: dict, weights: dict, total: float, most: float) -> dict:
    """Targets in proportion to the weights, stopped at `most` times a source's size; what is over goes to the others by
    weight, until none is above. Everything is at its stop if the total does not fit."""
    target, open_, left = {}, sorted(sizes, key=lambda s: (s is None, s)), total
    while open_:
        whole = sum(weights[s] for s in open_)
        share = {s: weights[s] * (left / whole) for s in open_}
        over = [s for s in open_ if share[s] > most * sizes[s]]
        if not over:
            return target | share
        for s in over:
            target[s] = most * sizes[s]
            left -= target[s]
        open_ = [s for s in open_ if s not in over]
    return target


@dataclass
class Plan:
    """Tokens that each membership pattern gives to each quota, and how full the quotas are."""

    flow: dict  # (pattern, source) -> tokens
    given: dict  # pattern -> tokens
    met: dict  # source -> tokens
    cost: int


def route(capacity: dict, quotas: dict, epochs: int) -> Plan:
    """Flow from patterns (tuples of sources; capacity: tokens of one epoch) to the sources' quotas.

    The e-th use of a pattern's tokens costs 2 e - 1 a token, so the whole cost grows with the square of the
    repetitions: fresh tokens go before repeated ones, and repetition spreads evenly.
    """
    patterns, sources = list(capacity), list(quotas)
    net = MinCostFlow(2 + len(patterns) + len(sources))
    column = {s: 2 + len(patterns) + j for j, s in enumerate(sources)}
    arcs = {}
    for i, p in enumerate(patterns):
        for e in range(1, epochs + 1):
            net.add(0, 2 + i, capacity[p], 2 * e - 1)
        for s in dict.fromkeys(p):
            if s in column:
                arcs[p, s] = net.add(2 + i, column[s], capacity[p] * epochs, 0)
    for s in sources:
        net.add(column[s], 1, int(quotas[s]), 0)
    _, cost = net.run(0, 1, sum(int(q) for q in quotas.values()))
    flow = {k: net.room[e ^ 1] for k, e in arcs.items()}
    given, met = dict.fromkeys(patterns, 0), dict.fromkeys(sources, 0)
    for (p, s), x in flow.items():
        given[p] += x
        met[s] += x
    return Plan(flow, given, met, cost)


def select_seeded(docs: DataFrame, given: DataFrame, pattern: list[str], seed: int = 0) -> DataFrame:
    """Adds `taken` to (doc_id, size, pattern columns): every document as often as its pattern's tokens are used up
    wholly, and in a seeded order one more time until the rest is reached; the last one gives only what is missing.

    given: pattern columns, cap (tokens of an epoch), give (tokens to take). The order comes from a digest of seed and doc_id. Its running
    sum is taken within 4096 digest ranges of each pattern, on top of the ranges' own totals, so no task gets a whole
    pattern.
    """
    same = lambda a, b: [a[c].eqNullSafe(b[c]) for c in pattern]
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.col("doc_id").cast("string")))
    keyed = docs.withColumn("_h", digest).withColumn("_b", F.conv(F.substring("_h", 1, 3), 16, 10).cast("int"))
    ranges = keyed.groupBy(*pattern, "_b").agg(F.sum("size").alias("_in"))
    below = ranges.withColumn("_below", F.sum("_in").over(Window.partitionBy(*pattern).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1))).drop("_in")
    g = given.alias("g")
    below = below.alias("b")
    plan = below.join(F.broadcast(g), same(below, g)).select(*[F.col(f"b.{c}").alias(f"p_{c}") for c in pattern], F.col("b._b").alias("p_b"), F.coalesce("b._below", F.lit(0)).alias("_below"), F.col("g.cap").alias("_cap"), F.col("g.give").alias("_give"))
    joined = keyed.join(plan, [keyed[c].eqNullSafe(plan[f"p_{c}"]) for c in pattern] + [keyed["_b"] == plan["p_b"]], "left")
    run = Window.partitionBy(*pattern, "_b").orderBy("_h", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    at = F.coalesce("_below", F.lit(0)) + F.coalesce(F.sum("size").over(run), F.lit(0))
    full = F.when(F.col("_cap") > 0, F.expr("_give div greatest(_cap, 1L)")).otherwise(F.lit(0))
    rest = F.col("_give") - full * F.col("_cap")
    taken = full * F.col("size") + F.greatest(F.lit(0), F.least(F.col("size"), rest - F.col("_at")))
    return joined.withColumn("_at", at).withColumn("taken", F.coalesce(taken, F.lit(0)).cast("long")).drop("_h", "_b", "_below", "_cap", "_give", "_at", "p_b", *[f"p_{c}" for c in pattern])


def word_count(text: str = "text"):
    return F.coalesce(F.size(F.regexp_extract_all(F.col(text), F.lit(WORD), F.lit(0))), F.lit(0)).cast("long")


def mix(docs: DataFrame, memberships: str, quotas: dict, epochs: int = 2, seed: int = 0, most_patterns: int = 100_000) -> tuple[DataFrame, Plan]:
    """Documents (doc_id, size, an array column of sources) with `taken`, and the flow behind it.

    Raises if there are more than `most_patterns` membership patterns: they are the flow's nodes and sit on the driver.
    Null memberships count as none; a document with none of the quotas' sources is not taken.
    """
    spark = docs.sparkSession
    named = docs.withColumn("_pattern", F.to_json(F.array_sort(F.array_distinct(F.coalesce(F.col(memberships), F.array().cast("array<string>"))))))
    rows = named.groupBy("_pattern").agg(F.sum("size").alias("n"), F.first(F.array_sort(F.array_distinct(F.col(memberships)))).alias("m")).limit(most_patterns + 1).collect()
    if len(rows) > most_patterns:
        raise ValueError(f"more than {most_patterns} membership patterns")
    names = {tuple(r["m"] or ()): r["_pattern"] for r in rows}
    capacity = {tuple(r["m"] or ()): int(r["n"] or 0) for r in rows}
    plan = route(capacity, quotas, epochs)
    given = spark.createDataFrame([(names[p], capacity[p], plan.given[p]) for p in capacity] or [("", 0, 0)], "_pattern string, cap long, give long")
    return select_seeded(named, given, ["_pattern"], seed).drop("_pattern"), plan


WEIGHTS = (5, 2, 1)


def mix_sources(docs: DataFrame, share: float = 1.5, epochs: int = 2, seed: int = 7, most_sources: int = 100_000) -> DataFrame:
    """doc_id, size, source_size, target, taken of every document; each document belongs to its one source.

    Size: words of the text (null: 0). Sources in code-point order, null last, weigh 5, 2, 1 and so on again. Empty
    tables give no rows; repeated rows each count; other columns are not carried.
    """
    spark = docs.sparkSession
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), word_count().alias("size"))
    rows = base.groupBy("source").agg(F.sum("size").alias("n")).limit(most_sources + 1).collect()
    if len(rows) > most_sources:
        raise ValueError(f"more than {most_sources} sources")
    sizes = {r["source"]: int(r["n"]) for r in rows}
    order = sorted(sizes, key=lambda s: (s is None, s.encode("utf-32-be") if s is not None else b""))
    weights = {s: WEIGHTS[i % len(WEIGHTS)] for i, s in enumerate(order)}
    # a null source is a source of its own; flow nodes are positions in the order
    place = {s: i for i, s in enumerate(order)}
    by_place = capped_shares({i: sizes[s] for s, i in place.items()}, {i: weights[s] for s, i in place.items()}, share * sum(sizes.values()), epochs)
    plan = route({(i,): sizes[s] for s, i in place.items()}, {i: int(by_place[i]) for i in by_place}, epochs)
    given = spark.createDataFrame([(s, sizes[s], plan.given[(place[s],)], float(by_place[place[s]])) for s in order] or [(None, 0, 0, 0.0)], "source string, cap long, give long, target double")
    picked = select_seeded(base, given.drop("target"), ["source"], seed)
    info = given.select(F.col("source").alias("_s"), F.col("cap").alias("source_size"), "target")
    return picked.join(F.broadcast(info), picked["source"].eqNullSafe(info["_s"])).select("doc_id", "size", "source_size", "target", "taken")


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The mix as documents: each row as often as it is taken (a part counts as a whole), all columns kept."""
    picks = mix_sources(docs, **options).filter("taken > 0").select(F.col("doc_id").alias("_d"), F.expr("cast((taken + size - 1) div size as int)").alias("_times"))
    times = picks.groupBy("_d").agg(F.max("_times").alias("_times"))
    return docs.join(times, docs["doc_id"] == times["_d"]).withColumn("_one", F.explode(F.sequence(F.lit(1), F.col("_times")))).select(*docs.columns)
