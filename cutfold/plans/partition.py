"""The multilevel driver: distributed levels while the graph is large, one task's
kernel from where it fits.

A level above ``local_arcs`` is clustered, contracted and refined by DataFrame
operators with every result saved on shared storage; coarsening goes on until the
graph fits, also below the node count at which a small graph would stop, so what is
brought to the driver never exceeds ``local_arcs``. From there the rest of the
hierarchy runs inside tasks, several seeds in parallel, and the best is projected
back up. So driver round trips are spent only on levels where data is big.

Where a value per node fits a task (:data:`vectors.NODES`), the distributed levels of
the presets with propagation or matching and the ``lp`` search are worked on by
:mod:`vectors`, which makes the same choices without a shuffle per wave.

Cycles are counted here. The kernel makes one pass per cycle and knows how many
levels lie above it, so slack is that of the whole hierarchy and of its first cycle.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.functions.caps import block_cap, cluster_cap, ensemble_size, level_cap
from cutfold.functions.storage import saved, scope
from cutfold.kernels import multilevel
from cutfold.kernels.csr import Csr, block_weights, cut
from cutfold.operators import ensemble, matching, metrics, refine, vectors
from cutfold.operators.contract import contract, inherit, project
from cutfold.operators.graph import WeightedGraph, to_local
from cutfold.operators.lpa import propagate, sizes_of
from cutfold.plans import presets
from cutfold.plans.presets import Preset

#: Arcs that one task's kernel takes; some 100 bytes each while it works.
LOCAL_ARCS = 8_000_000


@dataclass
class PartitionResult:
    """``part(id, block)`` and what happened on the way."""

    part: DataFrame
    cap: int
    history: list = field(default_factory=list)


def _solve(g: Csr, k: int, preset: Preset, eps: float, cap: int, stop_at: int | None, start, cycle: int, above: int):
    def run(batches):
        for batch in batches:
            for seed in batch.column(0).to_pylist():
                history: list = []
                part = multilevel.partition(g.value, k, preset, eps, seed, stop_at, start, cap, history, cycle, above)
                levels = next((h["levels"] for h in reversed(history) if h["phase"] == "final"), 1)
                most = level_cap(above + 1, above + levels, int(g.value.c.sum()), k, eps, preset.delta, cycle) if preset.slack else cap
                over = max(0, int(block_weights(g.value, part, k).max()) - max(cap, most)) if len(part) else 0
                first = next((h["cut"] for h in history if h["phase"] == "initial"), 0)
                yield pa.RecordBatch.from_pydict({"seed": [seed], "over": [over], "cut": [cut(g.value, part)], "first": [first], "levels": [levels], "part": pa.array([part.tolist()], pa.list_(pa.int32()))})

    return run


def solve_local(spark, g: Csr | Broadcast, k: int, preset: Preset, eps: float, cap: int, seeds: list[int], stop_at=None, start=None, cycle: int = 1, above: int = 0) -> tuple[np.ndarray, dict]:
    """The best of several seeds, one task each, by (overload, cut, seed)."""
    shared = g if isinstance(g, Broadcast) else spark.sparkContext.broadcast(g)
    jobs = spark.createDataFrame(spark.sparkContext.parallelize([(s,) for s in seeds], len(seeds)), "seed long")
    out = jobs.mapInArrow(_solve(shared, k, preset, eps, cap, stop_at, start, cycle, above), "seed long, over long, cut long, first long, levels long, part array<int>")
    best = out.orderBy("over", "cut", "seed").first()
    return np.array(best.part, np.int64), {"cut": best.cut, "initial_cut": best.first, "over": best.over, "levels": best.levels}


def _paired(g: WeightedGraph, labels: DataFrame, bound: int, within) -> DataFrame:
    """Clusters that are still single nodes, two by two under a common heaviest
    neighbour: what propagation cannot do once a hub's cluster is full."""
    alone = sizes_of(labels.withColumn("c", F.lit(1))).where("size = 1").select(F.col("cluster").alias("id"))
    free = g.nodes.where(F.col("c") * 2 <= bound).join(alone, "id", "left_semi").select("id")
    arcs = g.arcs()
    if within is not None:
        side = within.select(F.col("id").alias("x"), "block")
        # A hub may be anywhere; only nodes of one block are paired.
        free = free.join(side.withColumnRenamed("x", "id"), "id")
    pairs = matching.two_hop_pairs(arcs, free)
    to = pairs.select(F.col("v").alias("id"), F.col("u").alias("_to"))
    return labels.join(to, "id", "left").select("id", F.coalesce("_to", "cluster").alias("cluster"), "c")


def _labels(g: WeightedGraph, bound: int, preset: Preset, k: int, seed: int, level: int, cycle: int, within) -> DataFrame:
    if preset.coarsener in ("matching", "two_hop"):
        found = matching.heavy_edge_matching(g, bound, seed=seed + level, within=within)
        return _paired(g, found, bound, within) if preset.coarsener == "two_hop" else found
    how = {"rounds": preset.rounds, "stop": preset.stop, "order": preset.order, "level": level, "cycle": cycle, "within": within, "active": preset.active}
    if preset.ensemble:
        runs = ensemble.base(g, bound, ensemble_size(k), seed, **how)
        return ensemble.overlay_tuple(runs).join(g.nodes, "id")
    return propagate(g, bound, seed=seed, **how)


def _coarser(g: WeightedGraph, s: dict, cap: int, preset: Preset, k: int, seed: int, level: int, cycle: int, within) -> tuple[WeightedGraph, DataFrame, dict]:
    """The next level. Where the cluster bound stalls coarsening, single nodes are paired
    over a common neighbour; where that stalls too, the bound is doubled."""
    f = preset.f
    while True:
        bound = cluster_cap(cap, s["heaviest"], f)
        labels = _labels(g, bound, preset, k, seed, level, cycle, within)
        for pair in (False, True):
            if pair:
                labels = _paired(g, saved(labels, "labels"), bound, within)
            coarse, to = contract(g, labels)
            coarse, to = coarse.saved(), saved(to, "projection")
            now = coarse.sizes()
            if now["n"] <= 0.95 * s["n"]:
                return coarse, to, now
        if f <= 1:
            raise ValueError(f"{s['n']} nodes and {s['m']} edges cannot be coarsened further; raise local_arcs")
        f = max(1, f // 2)


def _coarser_vectors(g: vectors.VectorGraph, cap: int, preset: Preset, seed: int, level: int, cycle: int, within):
    """As :func:`_coarser`; None where a level has hubs that are too large."""
    f, s = preset.f, g.size()
    while True:
        bound = cluster_cap(cap, s["heaviest"], f)
        if preset.coarsener in ("matching", "two_hop"):
            labels = vectors.heavy_edge_matching(g, bound, seed=seed + level, within=within)
            if preset.coarsener == "two_hop":
                labels = vectors.paired(g, labels, bound, within)
        else:
            labels = vectors.propagate(g, bound, preset.rounds, preset.stop, preset.order, seed, level, cycle, within, preset.active)
        for pair in (False, True):
            if pair:
                labels = vectors.paired(g, labels, bound, within)
            if vectors.clusters(labels) <= 0.95 * s["n"]:
                return vectors.contract(g, labels)
        if f <= 1:
            raise ValueError(f"{s['n']} nodes and {s['m']} edges cannot be coarsened further; raise local_arcs")
        f = max(1, f // 2)


def _partition_vectors(g: WeightedGraph, size: dict, k: int, preset: Preset, eps: float, seed: int, local_arcs: int, stop_at: int | None, tries: int, cap: int) -> PartitionResult | None:
    """The cycles of :func:`partition` on arrays of nodes; None where they do not fit."""
    finest = vectors.load(g, size)
    if finest is None:
        return None
    spark, once, history, best = g.nodes.sparkSession, replace(preset, cycles=1), [], None
    quality = lambda g, part, cap: vectors.quality(g, part, k, cap)
    try:
        for cycle in range(1, preset.cycles + 1):
            levels, maps, start = [finest], [], best
            while 2 * levels[-1].m > local_arcs:
                coarse, to = _coarser_vectors(levels[-1], cap, preset, seed, len(levels), cycle, start)
                if coarse is None:
                    return None
                history.append({"cycle": cycle, "level": len(levels) + 1, "phase": "contract", "nodes": coarse.n, "edges": coarse.m})
                maps.append(to)
                if start is not None:
                    down = np.zeros(coarse.n, np.int64)
                    down[to] = start
                    start = down
                levels.append(coarse)
            above, local = len(levels) - 1, vectors.local(levels[-1])
            kernel, shared = {"nodes": local.n, "edges": local.arcs // 2}, spark.sparkContext.broadcast(local)
            del local
            part, told = solve_local(spark, shared, k, once, eps, cap, [seed * 100 + cycle * 10 + i for i in range(tries)], stop_at, start, cycle, above)
            shared.destroy()
            history.append({"cycle": cycle, "level": len(levels), "phase": "kernel"} | kernel | told)
            depth, known = above + told["levels"], told["cut"]
            heaviest_block = int(np.bincount(part, levels[-1].c, minlength=k).max())
            for level in range(above, 0, -1):
                here = max(cap, level_cap(level, depth, size["total"], k, eps, preset.delta, cycle)) if preset.slack else cap
                levels.pop().drop()
                fine, part = levels[-1], part[maps.pop()]
                trial = vectors.lp_refine(fine, part, k, here, seed=seed, level=level, cycle=cycle)
                # A partition has the same cut on the finer level, and the same weights.
                over, cut_now = quality(fine, trial, here)
                if (over, cut_now) <= (max(0, heaviest_block - here), known):
                    part, known = trial, cut_now
                heaviest_block = int(np.bincount(part, fine.c, minlength=k).max())
            over, cut_now = max(0, heaviest_block - cap), known
            if over:
                with scope():
                    forced = refine.force_balance(g, vectors.frame(finest, part), k, cap)
                    part = forced.orderBy("id").toArrow().column("block").to_numpy().astype(np.int64)
                over, cut_now = quality(finest, part, cap)
            if best is None or (over, cut_now) <= score:
                best, score = part, (over, cut_now)
            history.append({"cycle": cycle, "level": 1, "phase": "final", "nodes": size["n"], "edges": size["m"], "depth": depth, "cut": score[1]})
        return PartitionResult(vectors.frame(finest, best), cap, history)
    finally:
        finest.drop()


def partition(g: WeightedGraph, k: int, preset: Preset | str = "ci-fast", eps: float = 0.03, seed: int = 0, local_arcs: int = LOCAL_ARCS, stop_at: int | None = None, tries: int = 4) -> PartitionResult:
    """``k`` blocks of ``g`` by a preset."""
    preset = presets.get(preset) if isinstance(preset, str) else preset
    spark = g.nodes.sparkSession
    once = replace(preset, cycles=1)
    with scope() as tables:
        if not all(hasattr(x, "_scratch_path") for x in (g.nodes, g.edges)):
            g = g.saved()
        size = g.sizes()
        cap = block_cap(size["total"], k, eps)
        history: list = []
        if k <= 1 or size["n"] == 0:
            return PartitionResult(tables.keep(saved(g.nodes.select("id", F.lit(0).alias("block")), "part")), cap, history)
        if 2 * size["m"] > local_arcs and preset.search == "lp" and not preset.ensemble and preset.order in ("degree", "random"):
            if (found := _partition_vectors(g, size, k, preset, eps, seed, local_arcs, stop_at, tries, cap)) is not None:
                tables.keep(found.part)
                return found
        best = shared = None
        for cycle in range(1, preset.cycles + 1):
            with scope() as inner:
                levels, maps, parts, s = [g], [], [best], size
                while 2 * s["m"] > local_arcs:
                    coarse, to, s = _coarser(levels[-1], s, cap, preset, k, seed, len(levels), cycle, parts[-1])
                    history.append({"cycle": cycle, "level": len(levels) + 1, "phase": "contract", "nodes": s["n"], "edges": s["m"]})
                    maps.append(to)
                    parts.append(saved(inherit(parts[-1], to), "inherited") if parts[-1] is not None else None)
                    levels.append(coarse)
                above = len(levels) - 1
                if above or shared is None:
                    # A graph that fits a task is brought to the driver and sent out once.
                    local, ids = to_local(levels[-1], local_arcs)
                    kernel = {"nodes": local.n, "edges": local.arcs // 2}
                    shared = spark.sparkContext.broadcast(local)
                    del local
                start = None
                if parts[-1] is not None:
                    start = parts[-1].orderBy("id").toArrow().column("block").to_numpy().astype(np.int64)
                found, told = solve_local(spark, shared, k, once, eps, cap, [seed * 100 + cycle * 10 + i for i in range(tries)], stop_at, start, cycle, above)
                history.append({"cycle": cycle, "level": len(levels), "phase": "kernel"} | kernel | told)
                depth = above + told["levels"]
                table = pa.table({"id": pa.array(ids, pa.int64()), "block": pa.array(found, pa.int32())})
                part = saved(spark.createDataFrame(table), "part")
                for level in range(above, 0, -1):
                    here = max(cap, level_cap(level, depth, size["total"], k, eps, preset.delta, cycle)) if preset.slack else cap
                    fine, part = levels[level - 1], saved(project(part, maps[level - 1]), "part")
                    if preset.search == "lp":
                        trial = refine.lp_refine(fine, part, k, here, seed=seed, level=level, cycle=cycle)
                    else:
                        trial = refine.boundary_refine(fine, part, k, here, seed=seed, level=level, cycle=cycle)
                    part = refine.keep_better(fine, part, trial, here)
                    if level == 1 and refine.quality(g, part, cap)[0]:
                        part = saved(refine.force_balance(g, part, k, cap), "part")
                inner.keep(best if best is not None and refine.keep_better(g, best, part, cap) is best else part)
                best = next(iter(inner.kept.values()))
            done = metrics.cut(g, best).first()["cut"]
            history.append({"cycle": cycle, "level": 1, "phase": "final", "nodes": size["n"], "edges": size["m"], "depth": depth, "cut": int(done)})
        return PartitionResult(tables.keep(best), cap, history)
