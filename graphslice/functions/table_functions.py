"""SQL table functions over graphs and runs. Each partition of the given table is one stream; `register` names them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..operators.bitvector import LearnedBitVector
from ..operators.kernel import Placer, Rules, State
from ..operators.stores import RunListStore
from .score import limit


class PartitionGraph:
    """partition_graph(TABLE(id, nbrs) ordered by id from 0, k, n, m, kappa): (id, block), exact for one partition."""

    def __init__(self):
        self.placer = None

    def eval(self, node, k: int, n: int, m: float, kappa: float):
        if self.placer is None:
            self.store = RunListStore(k)
            self.placer = Placer(Rules(k, n, m, limit(n, k), kappa=kappa), State([0.0] * k))
        if node["id"] != self.store.n:
            raise ValueError(f"node {node['id']} where {self.store.n} was due")
        gains: dict[int, float] = {}
        for u in node["nbrs"] or ():
            if u < node["id"]:
                b = self.store.get(u)
                gains[b] = gains.get(b, 0) + 1
        block = self.placer.choose(gains)
        self.store.append(block)
        yield node["id"], block


class DecodeRuns:
    """decode_runs(TABLE(start, len, head)): (pos, head)."""

    def eval(self, run):
        for pos in range(run["start"], run["start"] + run["len"]):
            yield pos, str(run["head"])


class LearnSegments:
    """learn_segments(TABLE(batch, start) partitioned by batch): (batch, first_rank, first_pos, slope, points)."""

    def __init__(self):
        self.batch, self.starts = None, []

    def eval(self, run):
        self.batch = run["batch"]
        self.starts.append(run["start"])

    def terminate(self):
        if self.starts:
            v = LearnedBitVector.build(np.sort(np.array(self.starts, np.int64)))
            for rank, pos, slope, points in v.segments():
                yield self.batch, int(rank), int(pos), float(slope), int(points)


def register(spark: SparkSession) -> None:
    for name, cls, out in (
        ("partition_graph", PartitionGraph, "id: bigint, block: int"),
        ("decode_runs", DecodeRuns, "pos: bigint, sym: string"),
        ("learn_segments", LearnSegments, "batch: bigint, first_rank: bigint, first_pos: bigint, slope: double, points: int"),
    ):
        spark.udtf.register(name, udtf(cls, returnType=out))
