"""Competitors on graphs that do not fit a task.

Recursive bisection halves a graph by the distributed driver until a half fits a task,
whose kernel makes the rest. Plain propagation runs as supersteps; its clusters are
packed by counts of equal sizes, so the driver sees a row per size and bin, not per
cluster.
"""

from __future__ import annotations

from dataclasses import replace
from math import ceil, log2

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutfold.functions.caps import block_cap
from cutfold.functions.hashing import part_of
from cutfold.functions.storage import saved, scope
from cutfold.kernels.multilevel import recursive_bisection
from cutfold.operators import lpa, metrics
from cutfold.operators.graph import WeightedGraph, to_local
from cutfold.plans import presets
from cutfold.plans.partition import PartitionResult, partition

#: Clusters of one size are ranked bin by bin, so that no task ranks all of them.
BINS = 64
_HALVES = replace(presets.get("mi-eco"), name="recursive-bisect", coarsener="matching", tries=3)


def _result(g: WeightedGraph, part: DataFrame, k: int, eps: float) -> PartitionResult:
    cap = block_cap(g.sizes()["total"], k, eps)
    return PartitionResult(part, cap, [{"cycle": 1, "level": 1, "phase": "final", "cut": int(metrics.cut(g, part).first()["cut"])}])


def _bisected_in_a_task(g: WeightedGraph, k: int, eps: float, seed: int, limit: int) -> DataFrame:
    spark = g.nodes.sparkSession
    local, ids = to_local(g, limit)
    shared = spark.sparkContext.broadcast(local)

    def run(batches):
        for batch in batches:
            for s in batch.column(0).to_pylist():
                part = recursive_bisection(shared.value, k, eps, "matching", 3, s)
                yield pa.RecordBatch.from_pydict({"part": pa.array([part.tolist()], pa.list_(pa.int32()))})

    jobs = spark.createDataFrame(spark.sparkContext.parallelize([(seed,)], 1), "seed long")
    part = np.array(jobs.mapInArrow(run, "part array<int>").first().part, np.int32)
    return spark.createDataFrame(pa.table({"id": pa.array(ids, pa.int64()), "block": pa.array(part, pa.int32())}))


def _side(g: WeightedGraph, part: DataFrame, block: int) -> WeightedGraph:
    nodes = g.nodes.join(part.where(F.col("block") == block), "id", "left_semi")
    ids = nodes.select("id")
    edges = g.edges.join(ids.withColumnRenamed("id", "u"), "u", "left_semi").join(ids.withColumnRenamed("id", "v"), "v", "left_semi")
    return WeightedGraph(nodes, edges).saved()


def recursive_bisect(g: WeightedGraph, k: int, eps: float, seed: int, limit: int, stop_at: int | None = None) -> PartitionResult:
    """k blocks by halving; each split gets an even share of the slack, as in the kernel.
    An odd number of blocks above ``limit`` arcs is made in one pass, as the driver knows
    equal shares only."""
    step = (1 + eps) ** (1 / max(1, ceil(log2(max(k, 1))))) - 1
    with scope() as tables:
        done, todo = [], [(g, k, 0)]
        while todo:
            cur, kk, first = todo.pop()
            here = seed * 7919 + first * 64 + kk
            slack = (1 + step) ** ceil(log2(kk)) - 1
            if kk == 1:
                part = cur.nodes.select("id", F.lit(0).alias("block"))
            elif 2 * cur.edges.count() <= limit:
                part = _bisected_in_a_task(cur, kk, slack, here, limit)
            elif kk % 2:
                part = partition(cur, kk, _HALVES, slack, here, limit, stop_at).part
            else:
                halves = partition(cur, 2, _HALVES, step, here, limit, stop_at).part
                if kk > 2:
                    todo += [(_side(cur, halves, side), kk // 2, first + side * kk // 2) for side in (0, 1)]
                    continue
                part = halves
            done.append(saved(part.select("id", (F.col("block") + first).cast("int").alias("block")), "part"))
        whole = done[0]
        for part in done[1:]:
            whole = whole.union(part)
        return _result(g, tables.keep(saved(whole, "part")), k, eps)


def packed(counts: dict[int, int], k: int) -> dict[int, np.ndarray]:
    """How many clusters of each size go into each block, if they come largest first and
    each goes into the lightest block."""
    load, to = np.zeros(k, np.int64), {}
    for size in sorted(counts, reverse=True):
        if size <= 0:
            to[size] = np.array([counts[size]] + [0] * (k - 1), np.int64)
            continue
        # Block b takes its j-th cluster at load[b] + j * size; the least of these are taken.
        taken = lambda level: np.maximum(0, -((load - level) // size))  # noqa: B023, E731
        low, high = int(load.min()), int(load.max()) + size * (counts[size] // k + 1)
        while low < high:
            mid = (low + high + 1) // 2
            low, high = (mid, high) if int(taken(mid).sum()) <= counts[size] else (low, mid - 1)
        n = taken(low)
        at_level = np.flatnonzero(load + n * size == low)[: counts[size] - int(n.sum())]
        n[at_level] += 1
        load += n * size
        to[size] = n
    return to


def plain_lp(g: WeightedGraph, k: int, eps: float, seed: int) -> PartitionResult:
    """Propagation without a size bound, clusters packed largest first."""
    spark = g.nodes.sparkSession
    with scope() as tables:
        labels = saved(lpa.propagate(g, None, seed=seed).select("id", "cluster", "c"), "labels")
        sizes = saved(labels.groupBy("cluster").agg(F.sum("c").alias("size")).withColumn("bin", part_of(F.col("cluster"), 7, BINS)), "sizes")
        bins = sizes.groupBy("size", "bin").agg(F.count(F.lit(1)).alias("n")).orderBy("size", "bin").toArrow().to_pylist()
        counts: dict[int, int] = {}
        starts = []
        for b in bins:
            starts.append((b["size"], b["bin"], counts.get(b["size"], 0)))
            counts[b["size"]] = counts.get(b["size"], 0) + b["n"]
        ranges = []
        for size, n in packed(counts, k).items():
            ends = np.cumsum(n)
            ranges += [(size, int(e - m), int(e), b) for b, (m, e) in enumerate(zip(n, ends)) if m]
        begin = spark.createDataFrame(starts, "size long, bin long, begin long")
        rank = F.row_number().over(Window.partitionBy("size", "bin").orderBy("cluster")) - 1
        placed = sizes.select("cluster", "size", F.col("bin").cast("long").alias("bin"), rank.alias("r")).join(begin, ["size", "bin"])
        spans = spark.createDataFrame(ranges, "size long, lo long, hi long, block int")
        at = F.col("begin") + F.col("r")
        blocks = placed.join(spans, "size").where((at >= F.col("lo")) & (at < F.col("hi"))).select("cluster", "block")
        return _result(g, tables.keep(saved(labels.join(blocks, "cluster").select("id", "block"), "part")), k, eps)
