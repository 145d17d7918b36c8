"""Weighted undirected graphs as DataFrames.

``edges(u, v, w)`` holds each undirected edge once with u < v; ``nodes(id, c)`` all
nodes, isolated ones too. Ids and weights are BIGINT, so every sum is exact.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.functions.storage import saved
from cutfold.kernels.csr import Csr, from_edges


@dataclass(frozen=True)
class WeightedGraph:
    nodes: DataFrame
    edges: DataFrame
    #: Whether the nodes are the ends of the edges, each of weight 1.
    ends: bool = False

    def arcs(self) -> DataFrame:
        """Both directions of every edge: ``(src, dst, w)``."""
        e = self.edges
        return e.select(F.col("u").alias("src"), F.col("v").alias("dst"), "w").union(e.select(F.col("v").alias("src"), F.col("u").alias("dst"), "w"))

    def saved(self) -> WeightedGraph:
        edges = saved(self.edges, "edges")
        # What the edges took is not done again for their ends.
        return WeightedGraph(saved(_ends(edges) if self.ends else self.nodes, "nodes"), edges)

    def sizes(self) -> dict:
        """``n, m, total, heaviest`` in two aggregates."""
        a = self.nodes.agg(F.count(F.lit(1)).alias("n"), F.sum("c").alias("c"), F.max("c").alias("h")).first()
        return {"n": a.n, "total": int(a.c or 0), "heaviest": int(a.h or 0), "m": self.edges.count()}

    def degrees(self) -> DataFrame:
        """``(id, c, deg, wdeg)`` for all nodes."""
        d = self.arcs().groupBy("src").agg(F.count(F.lit(1)).alias("deg"), F.sum("w").alias("wdeg"))
        out = self.nodes.join(d, self.nodes["id"] == d["src"], "left")
        return out.select("id", "c", F.coalesce("deg", F.lit(0)).alias("deg"), F.coalesce("wdeg", F.lit(0)).alias("wdeg"))


def canonical(pairs: DataFrame) -> DataFrame:
    """``pairs(u, v, w)`` in any order -> unique edges; self-loops and NULL ends go."""
    e = pairs.where("u is not null and v is not null and u <> v")
    e = e.select(F.least("u", "v").cast("long").alias("u"), F.greatest("u", "v").cast("long").alias("v"), F.col("w").cast("long").alias("w"))
    return e.groupBy("u", "v").agg(F.sum("w").alias("w"))


def _ends(edges: DataFrame) -> DataFrame:
    """The ends of the edges as nodes of weight 1."""
    return edges.select(F.explode(F.array("u", "v")).alias("id")).distinct().withColumn("c", F.lit(1).cast("long"))


def from_distinct(pairs: DataFrame) -> WeightedGraph:
    """As :func:`from_pairs` of the distinct ``pairs(u, v)``, all of weight 1, where ``u``
    and ``v`` are of two kinds, so that no pair comes both ways: one shuffle."""
    e = pairs.where("u is not null and v is not null and u <> v")
    edges = e.select(F.least("u", "v").cast("long").alias("u"), F.greatest("u", "v").cast("long").alias("v")).distinct()
    edges = edges.withColumn("w", F.lit(1).cast("long"))
    return WeightedGraph(_ends(edges), edges, True)


def from_pairs(pairs: DataFrame, nodes: DataFrame | None = None) -> WeightedGraph:
    """A graph from raw pairs; without ``nodes`` all ends weigh 1."""
    edges = canonical(pairs)
    if nodes is None:
        return WeightedGraph(_ends(edges), edges, True)
    return WeightedGraph(nodes.select(F.col("id").cast("long").alias("id"), F.col("c").cast("long").alias("c")), edges)


def to_fixed(weight, scale: int):
    """A real weight as a BIGINT with ``scale`` decimals."""
    return F.round(weight.cast(f"decimal(38,{scale})") * F.lit(10**scale)).cast("long")


def validate(g: WeightedGraph) -> None:
    """Raise unless ids are unique and known, u < v, w > 0 and c >= 0."""
    bad = {
        "repeated or NULL node ids": g.nodes.groupBy("id").count().where("count > 1 or id is null"),
        "negative or NULL node weights": g.nodes.where("c is null or c < 0"),
        "edges out of form": g.edges.where("not coalesce(u < v and w > 0, false)"),
        "repeated edges": g.edges.groupBy("u", "v").count().where("count > 1"),
        "unknown ends": g.edges.select(F.explode(F.array("u", "v")).alias("id")).join(g.nodes, "id", "left_anti"),
    }
    for what, rows in bad.items():
        if not rows.isEmpty():
            raise ValueError(what)


def to_local(g: WeightedGraph, arcs_limit: int) -> tuple[Csr, np.ndarray]:
    """The graph in memory and its node ids; refuses graphs above the limit."""
    if 2 * g.edges.limit(arcs_limit // 2 + 1).count() > arcs_limit:
        raise ValueError(f"the graph has more than {arcs_limit} arcs")
    nodes = g.nodes.orderBy("id").toArrow()
    ids, c = nodes.column("id").to_numpy(), nodes.column("c").to_numpy()
    del nodes
    edges = g.edges.toArrow()
    u, v = (np.searchsorted(ids, edges.column(name).to_numpy()) for name in ("u", "v"))
    w = edges.column("w").to_numpy()
    del edges
    # Handed over, not kept: the graph is made of them in place.
    ends = [u, v, w]
    del u, v, w
    return from_edges(ends.pop(0), ends.pop(0), ends.pop(0), c), ids
