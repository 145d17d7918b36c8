"""Distributed local search on k blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutfold.functions import hashing
from cutfold.functions.storage import saved, scope
from cutfold.operators.graph import WeightedGraph
from cutfold.operators.lpa import RANKED, commit, connections, moved_neighbours, prefix, renewed, sizes_of, superstep, sweep


def _labels_of(g: WeightedGraph, part: DataFrame) -> DataFrame:
    return g.nodes.join(part, "id").select("id", F.col("block").cast("long").alias("cluster"), "c")


def _blocks_of(labels: DataFrame) -> DataFrame:
    return labels.select("id", F.col("cluster").cast("int").alias("block"))


def lp_refine(g: WeightedGraph, part: DataFrame, k: int, cap: int, rounds: int = 10, seed: int = 0, level: int = 1, cycle: int = 1, waves: int = 2, mode: str | None = None, log: list | None = None) -> DataFrame:
    """Label propagation under the block cap: ``part(id, block)`` in and out. Only
    neighbours of nodes moved in the last round are active, and the nodes of
    overloaded blocks, which must leave as far as the excess asks."""
    with scope() as tables:
        arcs = g.arcs()
        labels = saved(_labels_of(g, part).withColumn("start", F.col("cluster")), "labels")
        n, live = labels.count(), None
        if not n:
            return tables.keep(saved(_blocks_of(labels), "refined"))
        mode = mode or ("exact" if n <= RANKED else "histogram")

        def active(who, sizes):
            if live is None:
                return who
            heavy = sizes.where(F.col("size") > cap).select("cluster")
            return who.join(live, "id", "left_semi").union(who.join(heavy, "cluster", "left_semi").select(*who.columns)).distinct()

        for r in range(rounds):
            s = hashing.salt(seed, cycle, level, 500 + r)
            slices = [hashing.part_of(F.col("id"), s, waves) == wave for wave in range(waves)]
            labels, moved = sweep(arcs, labels, slices, cap, s, mode, True, active)
            if log is not None:
                log.append({"round": r, "moved": moved})
            if not moved:
                break
            live = saved(moved_neighbours(arcs, labels), "active")
            labels = renewed(labels)
        return tables.keep(saved(_blocks_of(labels), "refined"))


def boundary_refine(g: WeightedGraph, part: DataFrame, k: int, cap: int, passes: int = 3, seed: int = 0, level: int = 1, cycle: int = 1, waves: int = 4) -> DataFrame:
    """The economical search at scale. A pass visits the boundary nodes in waves; each
    moves to the neighbouring block of largest gain that has room, moves of gain zero
    by a draw included. The state after every wave is scored (overload, then cut), and
    a pass returns to its best one; the search ends when a pass does not improve."""
    with scope() as tables:
        best = saved(_labels_of(g, part), "labels")
        score = quality(g, _blocks_of(best), cap)
        arcs, mode = g.arcs(), "exact" if best.count() <= RANKED else "histogram"
        for p in range(passes):
            labels, better = best, False
            for wave in range(waves):
                s = hashing.salt(seed, cycle, level, 700 + p * waves + wave)
                a, b = (labels.select(F.col("id").alias(end), F.col("cluster").alias(x)) for end, x in (("src", "a"), ("dst", "b")))
                border = arcs.join(a, "src").join(b, "dst").where("a <> b").select(F.col("src").alias("id")).distinct()
                who = border.where(hashing.part_of(F.col("id"), s, waves) == wave)
                moves = saved(superstep(arcs, labels, who, cap, s, mode, over=True, excess=True), "moves")
                labels = saved(commit(labels, moves), "labels")
                now = quality(g, _blocks_of(labels), cap)
                if now < score:
                    best, score, better = labels, now, True
            if not better:
                break
        return tables.keep(saved(_blocks_of(best), "refined"))


def quality(g: WeightedGraph, part: DataFrame, cap: int) -> tuple[int, int]:
    """``(overload, cut)``; smaller is better."""
    from cutfold.operators import metrics

    top = metrics.block_weights(g, part).agg(F.max("weight")).first()[0] or 0
    return max(0, int(top) - cap), int(metrics.cut(g, part).first()["cut"])


def keep_better(g: WeightedGraph, a: DataFrame, b: DataFrame, cap: int) -> DataFrame:
    """b if it is not worse than a."""
    return b if quality(g, b, cap) <= quality(g, a, cap) else a


def force_balance(g: WeightedGraph, part: DataFrame, k: int, cap: int) -> DataFrame:
    """Last resort where no neighbouring block has room: blocks over the cap hand their
    nodes of least loss to the blocks with room, lightest first. The nodes that leave
    and the rooms are laid out on one line of weight and matched by position; a node
    that would straddle two rooms stays."""
    labels = g.nodes.join(part, "id").select("id", F.col("block").cast("long").alias("cluster"), "c")
    known = sizes_of(labels)
    blocks = part.sparkSession.range(k).select(F.col("id").alias("cluster")).join(known, "cluster", "left").select("cluster", F.coalesce("size", F.lit(0)).alias("size"))
    heavy = blocks.where(F.col("size") > cap).select("cluster", (F.col("size") - cap).alias("shed"))
    mine = connections(g.arcs(), labels).withColumnRenamed("cluster", "at")
    own = labels.join(heavy, "cluster").where("c > 0")
    tie = own.join(mine.withColumnRenamed("src", "id"), "id", "left")
    here = F.coalesce(F.max(F.when(F.col("at") == F.col("cluster"), F.col("strength"))), F.lit(0))
    away = F.coalesce(F.max(F.when(F.col("at") != F.col("cluster"), F.col("strength"))), F.lit(0))
    loss = tie.groupBy("id", "cluster", "c", "shed").agg((here - away).alias("loss"))
    first = prefix(loss.withColumn("tie", hashing.mix(F.col("id"), 1)), "cluster", "loss", "shed", before=True)
    # What leaves a block is at most its excess and one node; only that is laid out.
    leave = saved(first, "leaving").withColumn("gone", F.coalesce(F.sum("c").over(Window.partitionBy("cluster").orderBy("loss", "id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    # One row per block from here on.
    before = leave.groupBy("cluster").agg(F.sum("c").alias("all"))
    before = before.select("cluster", F.coalesce(F.sum("all").over(Window.orderBy("cluster").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("shift"))
    room = blocks.where(F.col("size") < cap).select(F.col("cluster").alias("to"), (F.lit(cap) - F.col("size")).alias("room"))
    upto = F.sum("room").over(Window.orderBy(F.col("room").desc(), "to"))
    room = room.select("to", (upto - F.col("room")).alias("lo"), upto.alias("hi"))
    placed = leave.join(before, "cluster").select("id", (F.col("shift") + F.col("gone")).alias("a"), (F.col("shift") + F.col("gone") + F.col("c")).alias("z"))
    moves = placed.join(F.broadcast(room), F.expr("a >= lo and z <= hi")).select("id", F.col("to").alias("target"))
    return commit(labels, moves).select("id", F.col("cluster").cast("int").alias("block"))
