"""Overlay clusterings."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.functions.storage import saved
from cutfold.operators.components import star_components
from cutfold.operators.graph import WeightedGraph
from cutfold.operators.lpa import propagate


def base(g: WeightedGraph, cap: int | None, runs: int, seed: int = 0, **how) -> DataFrame:
    """``(run, id, cluster)`` of several clusterings with different seeds."""
    out = None
    for i in range(runs):
        one = propagate(g, cap, seed=seed * 31 + i, **how).select(F.lit(i).alias("run"), "id", "cluster")
        out = one if out is None else out.union(one)
    return saved(out, "ensemble")


def overlay_tuple(runs: DataFrame) -> DataFrame:
    """``(id, cluster)``: together if together in every run; named by least member."""
    sig = runs.groupBy("id").agg(F.sort_array(F.collect_list(F.struct("run", "cluster"))).alias("sig"))
    name = sig.groupBy("sig").agg(F.min("id").alias("cluster"))
    return sig.join(name, "sig").select("id", "cluster")


def overlay_fold(runs: DataFrame, count: int) -> DataFrame:
    """The same by folding in one clustering after the other."""
    out = runs.where("run = 0").select("id", F.col("cluster").alias("o"))
    for i in range(count):
        both = out.join(runs.where(F.col("run") == i).select("id", "cluster"), "id")
        name = both.groupBy("o", "cluster").agg(F.min("id").alias("name"))
        out = both.join(name, ["o", "cluster"]).select("id", F.col("name").alias("o"))
    return out.select("id", F.col("o").alias("cluster"))


def overlay_components(g: WeightedGraph, runs: DataFrame) -> DataFrame:
    """Components after removing every edge that some clustering cuts."""
    a = runs.select("run", F.col("id").alias("u"), F.col("cluster").alias("a"))
    b = runs.select("run", F.col("id").alias("v"), F.col("cluster").alias("b"))
    gone = g.edges.select("u", "v").join(a, "u").join(b, ["run", "v"]).where("a <> b").select("u", "v").distinct()
    comp = star_components(g.edges.select("u", "v").join(gone, ["u", "v"], "left_anti"))
    return g.nodes.select("id").join(comp, "id", "left").select("id", F.coalesce("component", "id").alias("cluster"))
