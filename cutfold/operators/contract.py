"""Cluster contraction, projection, and the checks that go with them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.operators.graph import WeightedGraph


def contract(g: WeightedGraph, labels: DataFrame) -> tuple[WeightedGraph, DataFrame]:
    """One node per cluster, named by its smallest member; weights between clusters
    are summed, weights inside vanish. Also returns ``fine_to_coarse(id, cid)``."""
    name = labels.groupBy("cluster").agg(F.min("id").alias("cid"))
    to = labels.select("id", "cluster").join(name, "cluster").select("id", "cid")
    nodes = g.nodes.join(to, "id").groupBy(F.col("cid").alias("id")).agg(F.sum("c").alias("c"))
    a, b = to.select(F.col("id").alias("u"), F.col("cid").alias("cu")), to.select(F.col("id").alias("v"), F.col("cid").alias("cv"))
    ends = g.edges.join(a, "u").join(b, "v").where("cu <> cv")
    edges = ends.groupBy(F.least("cu", "cv").alias("u"), F.greatest("cu", "cv").alias("v")).agg(F.sum("w").alias("w"))
    return WeightedGraph(nodes, edges), to


def project(part: DataFrame, to: DataFrame) -> DataFrame:
    """Fine nodes take the block of their coarse node: ``(id, block)``."""
    return to.join(part.select(F.col("id").alias("cid"), "block"), "cid").select("id", "block")


def inherit(part: DataFrame, to: DataFrame) -> DataFrame:
    """Coarse nodes take their members' block, which must be one."""
    blocks = to.join(part, "id").groupBy(F.col("cid").alias("id")).agg(F.min("block").alias("block"), F.max("block").alias("other"))
    return blocks.select("id", F.when(F.col("block") == F.col("other"), F.col("block")).otherwise(F.raise_error(F.lit("a cluster crosses blocks"))).alias("block"))
