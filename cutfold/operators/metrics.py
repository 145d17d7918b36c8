"""Cost, balance and structure measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.operators.graph import WeightedGraph


def _ends(g: WeightedGraph, part: DataFrame) -> DataFrame:
    a = part.select(F.col("id").alias("u"), F.col("block").alias("bu"))
    b = part.select(F.col("id").alias("v"), F.col("block").alias("bv"))
    return g.edges.join(a, "u").join(b, "v")


def cut(g: WeightedGraph, part: DataFrame) -> DataFrame:
    """``cut, edges_cut``: weight and number of edges between blocks."""
    return _ends(g, part).where("bu <> bv").agg(F.coalesce(F.sum("w"), F.lit(0)).cast("long").alias("cut"), F.count(F.lit(1)).alias("edges_cut"))


def block_weights(g: WeightedGraph, part: DataFrame) -> DataFrame:
    return g.nodes.join(part, "id").groupBy("block").agg(F.sum("c").alias("weight"), F.count(F.lit(1)).alias("members"))


def imbalance(g: WeightedGraph, part: DataFrame, k: int, cap: int) -> DataFrame:
    """``max_block, imbalance_pct, feasible, overloaded, underloaded`` over k blocks."""
    w = block_weights(g, part)
    mean = F.ceil(F.sum("weight") / k)
    return w.agg(
        F.max("weight").alias("max_block"),
        F.round(100.0 * F.max("weight") / mean - 100, 6).alias("imbalance_pct"),
        F.bool_and(F.col("weight") <= cap).alias("feasible"),
        F.count_if(F.col("weight") > cap).alias("overloaded"),
        (F.count_if(F.col("weight") < cap) + k - F.count(F.lit(1))).alias("underloaded"),
    )


def quotient(g: WeightedGraph, part: DataFrame) -> DataFrame:
    """``bi, bj, w, cnt`` of block pairs that share edges."""
    e = _ends(g, part).where("bu <> bv")
    return e.groupBy(F.least("bu", "bv").alias("bi"), F.greatest("bu", "bv").alias("bj")).agg(F.sum("w").alias("w"), F.count(F.lit(1)).alias("cnt"))


def block_profile(g: WeightedGraph, part: DataFrame) -> DataFrame:
    """Per block ``cut, neighbours``: its cut and how many blocks it touches."""
    q = quotient(g, part)
    both = q.select(F.col("bi").alias("block"), "w").union(q.select(F.col("bj").alias("block"), "w"))
    return both.groupBy("block").agg(F.sum("w").alias("cut"), F.count(F.lit(1)).alias("neighbours"))


def communication_volume(g: WeightedGraph, part: DataFrame) -> DataFrame:
    """Per block the sum over its nodes of the number of other blocks they touch."""
    e = _ends(g, part).where("bu <> bv")
    seen = e.select(F.col("u").alias("id"), F.col("bu").alias("block"), F.col("bv").alias("other")).union(e.select("v", "bv", "bu")).distinct()
    return seen.groupBy("block").agg(F.count(F.lit(1)).alias("volume"))


def boundary(g: WeightedGraph, part: DataFrame) -> DataFrame:
    """Ids of nodes with a neighbour in another block."""
    e = _ends(g, part).where("bu <> bv")
    return e.select(F.explode(F.array("u", "v")).alias("id")).distinct()


def level_row(g: WeightedGraph) -> dict:
    s = g.sizes()
    w = g.edges.agg(F.sum("w")).first()[0]
    return {"nodes": s["n"], "edges": s["m"], "edge_weight": int(w or 0), "edges_per_node": s["m"] / max(s["n"], 1)}


def geometric_mean(runs: DataFrame, by: list[str], value: str = "cut") -> DataFrame:
    """Mean over seeds, then geometric mean over instances and k; zero means are
    counted apart."""
    mean = runs.groupBy(*by, "instance", "k").agg(F.avg(value).alias("mean"), F.min(value).alias("best"))
    return mean.groupBy(*by).agg(F.exp(F.avg(F.when(F.col("mean") > 0, F.ln("mean")))).alias("avg_" + value), F.exp(F.avg(F.when(F.col("best") > 0, F.ln("best")))).alias("best_" + value), F.count_if(F.col("mean") == 0).alias("zeros"))


def check_contraction(fine: WeightedGraph, coarse: WeightedGraph, to: DataFrame, coarse_part: DataFrame) -> bool:
    """Cut and block weights agree between a coarse partition and its projection."""
    from cutfold.operators.contract import project

    part = project(coarse_part, to)
    same_cut = cut(fine, part).first()["cut"] == cut(coarse, coarse_part).first()["cut"]
    a = {r.block: r.weight for r in block_weights(fine, part).collect()}
    b = {r.block: r.weight for r in block_weights(coarse, coarse_part).collect()}
    return same_cut and a == b
