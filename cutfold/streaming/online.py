"""Structured Streaming around the partitioner.

Windowed co-activity, deduplicated edges, stream joins, first placement of unseen
nodes, and refinement that starts only from the neighbourhood of changed edges.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import LongType, StructField, StructType

from cutfold.functions.storage import saved
from cutfold.operators.graph import WeightedGraph
from cutfold.operators.lpa import commit, superstep

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A folder of event files as a stream."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(path)


def windowed_activity(events: DataFrame, kind: str = "tumbling", late: str = "10 minutes") -> DataFrame:
    """Events per type in 15-minute windows, hour windows every 15 minutes, or
    sessions of a user; state is bounded by the watermark."""
    e = events.withWatermark("ts", late)
    if kind == "session":
        out = e.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id")
    elif kind == "sliding":
        out = e.groupBy(F.window("ts", "1 hour", "15 minutes").alias("w"), "event_type")
    else:
        out = e.groupBy(F.window("ts", "15 minutes").alias("w"), "event_type")
    return out.agg(F.count(F.lit(1)).alias("n"))


def distinct_edges(edges: DataFrame, late: str = "1 hour") -> DataFrame:
    """``edges(ts, u, v)`` once each within the watermark."""
    e = edges.withWatermark("ts", late).select("ts", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).where("u <> v")
    return e.dropDuplicatesWithinWatermark(["u", "v"])


def with_blocks(edges: DataFrame, part: DataFrame) -> DataFrame:
    """Stream-static join: the blocks of both ends; unplaced ends are NULL."""
    a = part.select(F.col("id").alias("u"), F.col("block").alias("bu"))
    b = part.select(F.col("id").alias("v"), F.col("block").alias("bv"))
    return edges.join(a, "u", "left").join(b, "v", "left")


def clicks_to_purchases(clicks: DataFrame, purchases: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Stream-stream join: purchases within an hour after a click of the same user."""
    c = clicks.withWatermark("ts", late).select(F.col("user_id").alias("cu"), F.col("ts").alias("cts"), F.col("event_id").alias("click"))
    p = purchases.withWatermark("ts", late).select(F.col("user_id").alias("pu"), F.col("ts").alias("pts"), F.col("event_id").alias("purchase"))
    return c.join(p, F.expr("cu = pu and pts >= cts and pts <= cts + interval 1 hour")).select("click", "purchase")


class RunningWeights(StatefulProcessor):
    """Total weight per edge ``(u, v)`` over all batches."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.total = handle.getValueState("total", StructType([StructField("w", LongType())]))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        w = self.total.get()[0] if self.total.exists() else 0
        w += sum(int(x["w"].sum()) for x in rows)
        self.total.update((w,))
        yield pd.DataFrame({"u": [key[0]], "v": [key[1]], "w": [w]})

    def close(self) -> None:
        pass


def running_weights(edges: DataFrame) -> DataFrame:
    """``edges(u, v, w)`` as a stream -> updated totals."""
    return edges.groupBy("u", "v").transformWithStateInPandas(RunningWeights(), "u long, v long, w long", "Update", "None")


def place_new_nodes(g: WeightedGraph, part: DataFrame, k: int, cap: int, salt: int = 1) -> DataFrame:
    """Unplaced nodes go to the strongest block with room, or else to the lightest,
    in one admission step; the rest keep their block."""
    loose = g.nodes.join(part, "id", "left_anti").select("id")
    known = part.join(g.nodes, "id").select("id", F.col("block").cast("long").alias("cluster"), "c")
    # An unplaced node is a cluster of its own, under a name outside 0..k-1.
    labels = saved(known.union(g.nodes.join(loose, "id").select("id", (-F.col("id") - 1).alias("cluster"), "c")), "labels")
    moves = superstep(g.arcs().join(known.select(F.col("id").alias("dst")), "dst", "left_semi"), labels, loose, cap, salt, "histogram")
    placed = saved(commit(labels, moves), "labels")
    size = {r.cluster: r.s for r in placed.where("cluster >= 0").groupBy("cluster").agg(F.sum("c").alias("s")).collect()}
    light = sorted(range(k), key=lambda b: (size.get(b, 0), b))[0]
    return placed.select("id", F.when(F.col("cluster") >= 0, F.col("cluster")).otherwise(light).cast("int").alias("block"))


def refine_batch(g: WeightedGraph, part: DataFrame, changed: DataFrame, cap: int, rounds: int = 3, seed: int = 0) -> DataFrame:
    """Local search whose first active nodes are the ends of ``changed(u, v)`` edges."""
    arcs = saved(g.arcs(), "arcs")
    labels = saved(g.nodes.join(part, "id").select("id", F.col("block").cast("long").alias("cluster"), "c"), "labels")
    live = changed.select(F.explode(F.array("u", "v")).alias("id")).distinct()
    for r in range(rounds):
        moves = saved(superstep(arcs, labels, live, cap, seed * 7 + r, "histogram", over=True, excess=True), "moves")
        if moves.isEmpty():
            break
        labels = saved(commit(labels, moves), "labels")
        live = saved(arcs.join(moves.select(F.col("id").alias("dst")), "dst", "left_semi").select(F.col("src").alias("id")).distinct(), "active")
    return labels.select("id", F.col("cluster").cast("int").alias("block"))


def follow(edges: DataFrame, path: str, k: int, eps: float = 0.03, checkpoint: str | None = None):
    """Keep a partition of a growing graph: per batch add the edges, place unseen
    nodes, refine around the change, and write version ``batch_id`` below ``path``."""
    from cutfold.functions.caps import block_cap
    from cutfold.operators.graph import from_pairs

    def step(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        fresh = batch.select("u", "v", F.lit(1).alias("w"))
        if batch_id > 0:
            before = spark.read.parquet(f"{path}/edges/{batch_id - 1}")
            part = spark.read.parquet(f"{path}/part/{batch_id - 1}")
        else:
            before, part = fresh.limit(0), spark.createDataFrame([], "id long, block int")
        g = from_pairs(before.union(fresh)).saved()
        cap = block_cap(g.sizes()["total"], k, eps)
        part = refine_batch(g, place_new_nodes(g, part, k, cap), fresh, cap, seed=batch_id)
        g.edges.write.mode("overwrite").parquet(f"{path}/edges/{batch_id}")
        part.write.mode("overwrite").parquet(f"{path}/part/{batch_id}")

    writer = edges.writeStream.foreachBatch(step).trigger(availableNow=True)
    return (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
