"""Connected components by alternating star contractions.

Every round is two min-aggregations and two joins on the surviving edge list; the
rounds end as soon as the edges are stars, without a round that changes nothing.
The minima are saved before they are joined, so both sides of a join are dealt
anew and adaptive execution can split a hub. The number of rounds
grows with the logarithm of the longest shortest path.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.functions.storage import drop_saved, saved


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = saved(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")), "cc-low")
    return both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    low = saved(down.groupBy("u").agg(F.min("v").alias("m")), "cc-low")
    moved = down.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(low.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def _is_stars(edges: DataFrame) -> bool:
    """Whether every ``u`` has one edge and no ``v`` is a ``u`` as well."""
    ends = edges.select(F.col("u").alias("id"), F.lit(1).alias("up"), F.lit(0).alias("down"))
    ends = ends.union(edges.select(F.col("v").alias("id"), F.lit(0), F.lit(1)))
    seen = ends.groupBy("id").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return seen.where((F.col("up") > 1) | ((F.col("up") > 0) & (F.col("down") > 0))).isEmpty()


def _down(edges: DataFrame) -> DataFrame:
    cur = edges.where("u is not null and v is not null and u <> v")
    return saved(cur.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "cc")


def star_labels(edges: DataFrame, rounds: int = 1) -> DataFrame:
    """``(id, component)`` as :func:`star_components`, but stopped after ``rounds``: equal
    labels are connected, while one component may still carry several."""
    cur = _down(edges)
    for _ in range(rounds):
        nxt = saved(_small_star(_large_star(cur)), "cc")
        drop_saved(cur)
        cur = nxt
    both = cur.select(F.col("u").alias("id"), "v").union(cur.select(F.col("v").alias("id"), "v"))
    return both.groupBy("id").agg(F.min("v").alias("component"))


def star_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges(u, v)`` with BIGINT ends -> ``(id, component)`` for every id that
    has an edge; the component is its smallest id. Self-loops, repeated and
    reversed edges are allowed; NULL ends are ignored; no edges give no rows."""
    cur = _down(edges)
    for _ in range(max_rounds):
        if _is_stars(cur):
            break
        nxt = saved(_small_star(_large_star(cur)), "cc")
        drop_saved(cur)
        cur = nxt
    else:
        raise RuntimeError("components did not converge")
    # Converged edges form stars: every u points at its component's smallest id.
    roots = cur.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct()
    return cur.select(F.col("u").alias("id"), F.col("v").alias("component")).union(roots)
