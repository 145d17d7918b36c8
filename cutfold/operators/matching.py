"""Distributed matchings."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutfold.functions import hashing
from cutfold.functions.storage import saved
from cutfold.operators.graph import WeightedGraph


#: Free nodes of a hub that are ranked together.
BIN = 10_000


def mutual_round(arcs: DataFrame, salt: int) -> DataFrame:
    """Pairs ``(u, v)`` in which each is the other's heaviest neighbour; ties by a hash
    that both ends compute alike."""
    rank = F.struct("w", hashing.tie(F.least("src", "dst"), F.greatest("src", "dst"), salt).alias("t"), (-F.col("dst")).alias("d"))
    pick = arcs.groupBy("src").agg(F.max(rank).alias("r")).select("src", (-F.col("r.d")).alias("dst"))
    back = pick.select(F.col("src").alias("dst"), F.col("dst").alias("src"))
    return pick.join(back, ["src", "dst"]).where("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"))


def heavy_edge_matching(g: WeightedGraph, cap: int, rounds: int = 5, seed: int = 0, within: DataFrame | None = None) -> DataFrame:
    """Labels ``(id, cluster, c)`` of a matching by repeated mutual best choice under
    the weight bound; cut edges of ``within`` are not matched."""
    c = g.nodes.select("id", "c")
    arcs = g.arcs().join(c.select(F.col("id").alias("src"), F.col("c").alias("a")), "src").join(c.select(F.col("id").alias("dst"), F.col("c").alias("b")), "dst").where(F.col("a") + F.col("b") <= cap)
    if within is not None:
        arcs = arcs.join(within.select(F.col("id").alias("src"), F.col("block").alias("x")), "src").join(within.select(F.col("id").alias("dst"), F.col("block").alias("y")), "dst").where("x = y")
    arcs = saved(arcs.select("src", "dst", "w"), "match-arcs")
    found = None
    for r in range(rounds):
        pairs = saved(mutual_round(arcs, hashing.salt(seed, 0, 0, r)), "match")
        if pairs.isEmpty():
            break
        found = pairs if found is None else found.union(pairs)
        used = pairs.select(F.explode(F.array("u", "v")).alias("x"))
        arcs = saved(arcs.join(used.withColumnRenamed("x", "src"), "src", "left_anti").join(used.withColumnRenamed("x", "dst"), "dst", "left_anti"), "match-arcs")
    if found is None:
        return g.nodes.select("id", F.col("id").alias("cluster"), "c")
    return g.nodes.join(found.select(F.col("v").alias("id"), "u"), "id", "left").select("id", F.coalesce("u", "id").alias("cluster"), "c")


def two_hop_pairs(arcs: DataFrame, free: DataFrame) -> DataFrame:
    """Pairs ``(u, v)`` of free nodes whose heaviest neighbour is the same hub: the
    free nodes of a hub are paired in id order, in bins of about ``BIN`` by a hash where a
    hub has more. With ``free(id, block)`` only nodes of one block are paired."""
    side = ["block"] if "block" in free.columns else []
    mine = arcs.join(free.select(F.col("id").alias("src")), "src", "left_semi")
    hub = mine.groupBy("src").agg(F.max(F.struct("w", (-F.col("dst")).alias("d"))).alias("r")).select(F.col("src").alias("id"), (-F.col("r.d")).alias("hub"))
    if side:
        hub = hub.join(free.select("id", "block"), "id")
    # Hubs may have any number of free nodes: they are dealt by a hash, in bins whose
    # leftovers (one a bin) stay single.
    bins = hub.groupBy("hub", *side).agg(F.ceil(F.count(F.lit(1)) / BIN).alias("bins"))
    hub = hub.join(bins, ["hub", *side]).withColumn("bin", F.pmod(hashing.mix(F.col("id"), 29), F.col("bins")))
    w = Window.partitionBy("hub", *side, "bin").orderBy("id")
    ranked = hub.withColumn("rn", F.row_number().over(w)).withColumn("mate", F.lead("id").over(w))
    return ranked.where("rn % 2 = 1 and mate is not null").select(F.col("id").alias("u"), F.col("mate").alias("v"))
