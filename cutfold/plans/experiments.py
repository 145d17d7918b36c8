"""The comparison workloads: every preset and baseline on every graph, k and seed.

A graph that fits a task is collected once and broadcast; each run is a task, so a
table of a thousand runs is one job. Larger graphs are partitioned one run after the
other by the distributed driver.
"""

from __future__ import annotations

import time

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutfold.functions.caps import block_cap, cluster_cap, stop_nodes
from cutfold.functions.storage import drop_saved, saved, scope
from cutfold.kernels import baselines, multilevel
from cutfold.kernels.csr import block_weights, cut
from cutfold.operators import lpa, matching, metrics, vectors
from cutfold.operators.contract import contract
from cutfold.operators.graph import WeightedGraph, to_local
from cutfold.plans import presets, rivals
from cutfold.plans.partition import LOCAL_ARCS
from cutfold.plans.partition import partition as distributed
from cutfold.sources import builders

RUNS = "instance string, preset string, k int, seed long, cut long, initial_cut long, seconds double, max_block long, cap long, feasible boolean, levels int, coarse_nodes long"
PROFILE = "instance string, coarsener string, level int, nodes long, edges long, edge_weight long, edges_per_node double"
KS = (2, 4, 8, 16, 32, 64)


def _run(name: str, g, k: int, eps: float, seed: int, stop_at):
    history: list = []
    began = time.perf_counter()
    if name in baselines.BASELINES:
        part = baselines.BASELINES[name](g, k, eps, seed)
    elif name.startswith("best-of-"):
        count, _, preset = name.removeprefix("best-of-").partition(":")
        part = baselines.best_of(g, k, presets.get(preset), eps, seed, int(count))
    else:
        part = multilevel.partition(g, k, presets.get(name), eps, seed, stop_at, history=history)
    return part, history, time.perf_counter() - began


def _run_distributed(g: WeightedGraph, instance: str, name: str, k: int, eps: float, seed: int, stop_at, limit: int) -> tuple:
    """A row of ``RUNS`` for a graph that does not fit a task."""
    count, preset = 1, name
    if name.startswith("best-of-"):
        count, preset = (f(x) for f, x in zip((int, str), name.removeprefix("best-of-").split(":")))
    preset = baselines.MULTILEVEL.get(preset) or preset
    if preset in baselines.BASELINES and preset not in ("recursive-bisect", "plain-lp"):
        raise ValueError(f"{name} runs in one task only, and {instance} has more than {limit} arcs")
    began = time.perf_counter()
    best = None
    for i in range(count):
        with scope():
            if preset == "recursive-bisect":
                found = rivals.recursive_bisect(g, k, eps, seed, limit, stop_at)
            elif preset == "plain-lp":
                found = rivals.plain_lp(g, k, eps, seed)
            else:
                found = distributed(g, k, preset, eps, seed * count + i, limit, stop_at)
            top = metrics.block_weights(g, found.part).agg(F.max("weight").alias("w")).first().w or 0
            log = found.history
        final = log[-1]["cut"] if log else 0
        first = next((h for h in log if h["phase"] == "kernel"), {"initial_cut": final, "level": 1, "levels": 1, "nodes": 0})
        row = (instance, name, k, seed, final, first["initial_cut"], 0.0, top, found.cap, top <= found.cap, first["level"] - 1 + first["levels"], first["nodes"])
        if best is None or (max(0, top - found.cap), final) < (max(0, best[7] - best[8]), best[4]):
            best = row
    return (*best[:6], time.perf_counter() - began, *best[7:])


def runs(spark: SparkSession, sf_dir: str, instances: list[str], names: list[str], ks=KS, seeds: int = 3, eps: float = 0.03, stop_at: int | None = None, limit: int = LOCAL_ARCS) -> DataFrame:
    """One row per instance, name, k and seed (schema ``RUNS``), saved."""
    out = None
    for instance in instances:
        whole = builders.GRAPHS[instance](spark, sf_dir).saved()
        jobs = [(name, k, seed) for name in names for k in ks for seed in range(seeds)]
        if 2 * whole.edges.count() > limit:
            rows = [_run_distributed(whole, instance, name, k, eps, seed, stop_at, limit) for name, k, seed in jobs]
            one = spark.createDataFrame(rows, RUNS)
            out = one if out is None else out.union(one)
            drop_saved(whole.nodes, whole.edges)
            continue
        g, _ = to_local(whole, limit)
        drop_saved(whole.nodes, whole.edges)
        shared = spark.sparkContext.broadcast(g)

        def solve(batches, shared=shared, instance=instance):
            g = shared.value
            for batch in batches:
                for name, k, seed in zip(*(c.to_pylist() for c in batch.columns)):
                    cap = block_cap(int(g.c.sum()), k, eps)
                    part, history, took = _run(name, g, k, eps, seed, stop_at)
                    top = int(block_weights(g, part, k).max()) if g.n else 0
                    final = cut(g, part)
                    first = next((h for h in history if h["phase"] == "initial"), {"cut": final, "level": 1, "nodes": g.n})
                    yield pa.RecordBatch.from_pylist(
                        [{"instance": instance, "preset": name, "k": k, "seed": seed, "cut": final, "initial_cut": first["cut"], "seconds": took, "max_block": top, "cap": cap, "feasible": top <= cap, "levels": first["level"], "coarse_nodes": first["nodes"]}],
                        pa.schema([("instance", pa.string()), ("preset", pa.string()), ("k", pa.int32()), ("seed", pa.int64()), ("cut", pa.int64()), ("initial_cut", pa.int64()), ("seconds", pa.float64()), ("max_block", pa.int64()), ("cap", pa.int64()), ("feasible", pa.bool_()), ("levels", pa.int32()), ("coarse_nodes", pa.int64())]),
                    )

        # Runs differ in length, so each is a task of its own.
        frame = spark.createDataFrame(spark.sparkContext.parallelize(jobs, len(jobs)), "name string, k int, seed long")
        one = frame.mapInArrow(solve, RUNS)
        out = one if out is None else out.union(one)
    return saved(out, "runs")


def summary(table: DataFrame) -> DataFrame:
    """The comparison table: geometric means of average and best cut, mean seconds,
    share of infeasible runs and the worst overload in per cent."""
    score = metrics.geometric_mean(table, ["preset"])
    other = table.groupBy("preset").agg(F.avg("seconds").alias("seconds"), F.count_if(~F.col("feasible")).alias("infeasible"), F.count(F.lit(1)).alias("runs"), F.max(F.round(100.0 * F.col("max_block") / F.col("cap") - 100, 3)).alias("worst_over_pct"))
    return score.join(other, "preset")


def ratio(table: DataFrame, a: str, b: str) -> DataFrame:
    """How ``b`` compares with ``a``: cut of b over a minus 1, and time ratio."""
    s = summary(table)
    x, y = s.where(F.col("preset") == a), s.where(F.col("preset") == b)
    x = x.select(F.col("avg_cut").alias("a_cut"), F.col("seconds").alias("a_s"))
    y = y.select(F.col("avg_cut").alias("b_cut"), F.col("seconds").alias("b_s"))
    return x.join(y, F.lit(True)).select(F.lit(a).alias("a"), F.lit(b).alias("b"), (F.col("b_cut") / F.col("a_cut") - 1).alias("cut_change"), (F.col("b_s") / F.col("a_s")).alias("time_ratio"))


#: Workload name -> (presets and baselines, k values, rows that are compared).
WORKLOADS = {
    "main_table": (presets.COMPARED + list(baselines.BASELINES), KS),
    "matching_vs_clustering": (["matching-eco", "mi-eco-rand"], KS),
    "node_order": (["mi-eco-rand", "mi-eco", "mi-fast-rand", "mi-fast"], KS),
    "cycles_and_slack": (["mi-eco", "mi-eco+v", "mi-eco+v+b", "mi-fast", "mi-fast+v", "mi-fast+v+b"], KS),
    "ensembles": (["mi-eco+v+b", "mi-eco+v+b+e", "mi-fast+v+b", "mi-fast+v+b+e"], KS),
    "active_nodes": (["mi-eco+v+b+e", "mi-eco+v+b+e+a", "mi-fast+v+b+e", "mi-fast+v+b+e+a"], KS),
    "initial_partitioner": (["mi-fast", "ci-fast", "mi-strong", "ci-strong"], KS),
    "equal_time": (["best-of-10:ci-eco+v+b", "net-kway"], KS),
    "huge": (presets.HUGE + ["two-hop-kway", "recursive-bisect"], (16,)),
    "balance": (["recursive-bisect", "net-kway", "two-hop-kway", "plain-lp"], KS),
}
INSTANCES = ["page_links", "doc_line_hubs", "geo_tree", "supply", "knn", "basket", "order_part", "communities", "hub_communities", "mesh"]


def workload(spark: SparkSession, sf_dir: str, name: str, instances=None, ks=None, seeds: int = 3, **how) -> DataFrame:
    """The runs of a named workload."""
    names, own = WORKLOADS[name]
    return runs(spark, sf_dir, instances or INSTANCES, names, ks or own, seeds, **how)


def coarsening_profile(spark: SparkSession, sf_dir: str, instance: str, k: int = 16, names=("ci-fast", "matching-eco"), seed: int = 0, limit: int = LOCAL_ARCS) -> DataFrame:
    """Nodes, edges, edge weight and edges per node of each level of the hierarchies
    by clustering and by matching; each hierarchy is a task from where it fits one."""
    hows = ("cluster", "matching")
    with scope() as tables:
        whole = builders.GRAPHS[instance](spark, sf_dir).saved()
        full = whole.sizes()
        if 2 * full["m"] <= limit:
            out = _levels_in_tasks(to_local(whole, limit)[0], spark, full, instance, hows, k, seed, 1)
        else:
            # Arrays of nodes where they fit; each coarsener falls back alone.
            finest = vectors.load(whole, full)
            parts = [finest and _levels_vectors(finest, full, instance, how, k, seed, limit) for how in hows]
            parts = [x or _levels(spark, whole, full, instance, how, k, seed, limit) for x, how in zip(parts, hows)]
            out = parts[0].union(parts[1])
        return tables.keep(saved(out, "profile"))


def _levels(spark: SparkSession, cur: WeightedGraph, full: dict, instance: str, how: str, k: int, seed: int, limit: int) -> DataFrame:
    cap, low = block_cap(full["total"], k, 0.03), stop_nodes(full["n"], k)
    above, now = [], full
    while 2 * now["m"] > limit:
        weight = cur.edges.agg(F.sum("w").alias("w")).first().w
        above.append((instance, how, len(above) + 1, now["n"], now["m"], weight, now["m"] / max(1, now["n"])))
        if now["n"] < low:
            return spark.createDataFrame(above, PROFILE)
        bound, s = cluster_cap(cap, now["heaviest"]), seed + len(above)
        labels = lpa.propagate(cur, bound, seed=s) if how == "cluster" else matching.heavy_edge_matching(cur, bound, seed=s)
        coarse = contract(cur, saved(labels, "labels"))[0].saved()
        size = coarse.sizes()
        if size["n"] > 0.95 * now["n"]:
            return spark.createDataFrame(above, PROFILE)
        cur, now = coarse, size
    local = _levels_in_tasks(to_local(cur, limit)[0], spark, full, instance, (how,), k, seed, len(above) + 1)
    return spark.createDataFrame(above, PROFILE).union(local) if above else local


def _levels_vectors(cur: vectors.VectorGraph, full: dict, instance: str, how: str, k: int, seed: int, limit: int) -> DataFrame | None:
    """As :func:`_levels` on arrays of nodes; None where a level has too large hubs."""
    spark, first = cur.spark, cur
    cap, low = block_cap(full["total"], k, 0.03), stop_nodes(full["n"], k)
    above, now = [], full
    while 2 * now["m"] > limit:
        weight = vectors.edge_weight(cur)
        above.append((instance, how, len(above) + 1, now["n"], now["m"], weight, now["m"] / max(1, now["n"])))
        if now["n"] < low:
            return spark.createDataFrame(above, PROFILE)
        bound, s = cluster_cap(cap, now["heaviest"]), seed + len(above)
        labels = vectors.propagate(cur, bound, seed=s) if how == "cluster" else vectors.heavy_edge_matching(cur, bound, seed=s)
        if vectors.clusters(labels) > 0.95 * now["n"]:
            return spark.createDataFrame(above, PROFILE)
        coarse = vectors.contract(cur, labels)[0]
        if cur is not first:
            cur.drop()
        if coarse is None:
            return None
        cur, now = coarse, coarse.size()
    local = _levels_in_tasks(vectors.local(cur), spark, full, instance, (how,), k, seed, len(above) + 1)
    return spark.createDataFrame(above, PROFILE).union(local) if above else local


def _levels_in_tasks(g, spark: SparkSession, full: dict, instance: str, hows: tuple, k: int, seed: int, first: int) -> DataFrame:
    """The levels from ``g``, which was brought to the driver once, a task per coarsener."""
    cap, low = block_cap(full["total"], k, 0.03), stop_nodes(full["n"], k)
    shared = spark.sparkContext.broadcast(g)
    del g

    def levels(batches):
        for batch in batches:
            for how in batch.column(0).to_pylist():
                rows, cur, level = [], shared.value, first
                while True:
                    weight = int(cur.w.sum()) // 2
                    rows.append({"instance": instance, "coarsener": how, "level": level, "nodes": cur.n, "edges": cur.arcs // 2, "edge_weight": weight, "edges_per_node": cur.arcs / 2 / max(1, cur.n)})
                    if cur.n < low:
                        break
                    labels = multilevel.coarsen_once(cur, cluster_cap(cap, int(cur.c.max())), how, seed + level)
                    coarse, _ = multilevel.contract(cur, labels)
                    if coarse.n > 0.95 * cur.n:
                        break
                    cur, level = coarse, level + 1
                yield pa.RecordBatch.from_pylist(rows, pa.schema([("instance", pa.string()), ("coarsener", pa.string()), ("level", pa.int32()), ("nodes", pa.int64()), ("edges", pa.int64()), ("edge_weight", pa.int64()), ("edges_per_node", pa.float64())]))

    jobs = spark.createDataFrame(spark.sparkContext.parallelize([(how,) for how in hows], len(hows)), "how string")
    return jobs.mapInArrow(levels, PROFILE)


