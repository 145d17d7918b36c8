"""Size-constrained label propagation in supersteps.

A round is split into waves: slices of the visiting order (by degree, weighted
degree or a hash), each halved by a hash that is drawn anew every round. The
nodes of a wave choose against the same labels; per target the strongest are
admitted while they fit, departures uncounted, so no cluster ever exceeds the cap.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from cutfold.functions import hashing
from cutfold.functions.storage import drop_saved, saved, scope
from cutfold.operators.graph import WeightedGraph


def singletons(g: WeightedGraph) -> DataFrame:
    """``(id, cluster, c)``: every node its own cluster."""
    return g.nodes.select("id", F.col("id").alias("cluster"), "c")


def connections(arcs: DataFrame, labels: DataFrame) -> DataFrame:
    """``(src, cluster, strength)``: edge weight from a node into each cluster."""
    to = labels.select(F.col("id").alias("dst"), "cluster")
    return arcs.join(to, "dst").groupBy("src", "cluster").agg(F.sum("w").alias("strength"))


def sizes_of(labels: DataFrame) -> DataFrame:
    return labels.groupBy("cluster").agg(F.sum("c").alias("size"))


def buckets_by(degrees: DataFrame, key: str, buckets: int) -> DataFrame:
    """``(id, bucket)``: equal slices of the order by ``key``; equal keys share the
    slice of their first. Only the histogram of the key is ordered as a whole."""
    hist = degrees.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
    upto = Window.orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    everyone = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    below = F.coalesce(F.sum("n").over(upto), F.lit(0)) * buckets
    total = F.sum("n").over(everyone)
    hist = hist.select(key, ((below - below % total) / total).cast("int").alias("bucket"))
    return degrees.join(hist, key).select("id", "bucket")


def choose(strengths: DataFrame, labels: DataFrame, cap: int | None, salt: int, sizes: DataFrame | None = None, over: bool = False) -> DataFrame:
    """``(id, c, source, target, strength, loss, tie)`` of nodes that want to leave.

    ``strengths`` are :func:`connections` of the movers. A cluster other than the own
    one must have room; the own one always counts, with strength 0 if no neighbour
    is inside. With ``over``, nodes of clusters above the cap disregard their own."""
    sizes = sizes_of(labels) if sizes is None else sizes
    own = labels.select(F.col("id").alias("src"), F.col("cluster").alias("own"), "c")
    cand = strengths.join(own, "src").join(sizes, "cluster", "left")
    here = F.col("cluster") == F.col("own")
    limit = F.lit(2**62 if cap is None else cap)
    room = F.col("size") + F.col("c") <= limit
    rank = F.struct("strength", hashing.tie(F.col("src"), F.col("cluster"), salt).alias("tie"), (-F.col("cluster")).alias("neg"))
    best = cand.groupBy("src").agg(
        F.first("own").alias("source"),
        F.first("c").alias("c"),
        F.max(F.when(here, F.col("strength"))).alias("inside"),
        F.max(F.when(here, rank)).alias("stay"),
        F.max(F.when(~here & room, rank)).alias("go"),
    )
    best = best.where("go is not null")
    leave = F.col("stay").isNull() | (F.col("go") > F.col("stay"))
    if over:
        heavy = sizes.where(F.col("size") > limit).select(F.col("cluster").alias("source"), F.lit(True).alias("heavy"))
        best = best.join(heavy, "source", "left")
        leave = leave | F.coalesce("heavy", F.lit(False))
    return best.where(leave).select(F.col("src").alias("id"), "c", "source", (-F.col("go.neg")).alias("target"), F.col("go.strength").alias("strength"), (F.coalesce("inside", F.lit(0)) - F.col("go.strength")).alias("loss"), F.col("go.tie").alias("tie"))


_TIE_BINS = 21  # a bin holds 2**21 of the 2**31 tie values
#: Up to so many nodes, proposals are ranked in windows, which admit the same as sums do.
RANKED = 200_000


def _within(rows: DataFrame, group: list[str], step: str, limit: str, before: bool) -> tuple[DataFrame, DataFrame]:
    """Per group sum the weights of each ``step`` in ascending order: the rows of steps
    that fit as a whole, and those of the step in which ``limit`` falls, with what is
    left of it. Only the sums are ordered, and they are few, so they are broadcast."""
    sums = rows.groupBy(*group, step).agg(F.sum("c").alias("want"), F.first(limit).alias("most"))
    upto = Window.partitionBy(*group).orderBy(step).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    sums = sums.withColumn("need", F.sum("want").over(upto)).where(F.col("need") - F.col("want") < F.col("most") if before else F.col("need") - F.col("want") <= F.col("most"))
    sums = sums.select(*group, step, (F.col("need") <= F.col("most")).alias("all"), (F.col("most") - F.col("need") + F.col("want")).alias("left"))
    known = rows.drop(limit).join(sums, [*group, step])
    return known.where("all"), known.where("not all").drop("all").withColumnRenamed("left", limit)


def prefix(rows: DataFrame, group: str, order: str, limit: str, before: bool = False) -> DataFrame:
    """The rows ``(id, c, tie, ...)`` of each group that come first by (``order``
    ascending, tie descending, id) while their running weight stays within ``limit``; or
    with ``before`` while the weight before them is below it. Whole values of ``order``,
    then whole bins of ties are taken, and only inside one bin rows are ranked, so a
    group of any size is never sorted in one task."""
    cols = [c for c in rows.columns if c != limit]
    rows = saved(rows, "prefix")
    whole, cut = _within(rows, [group], order, limit, before)
    cut = saved(cut.withColumn("_bin", -F.shiftright(F.col("tie").cast("long"), _TIE_BINS)), "prefix-cut")
    bins, last = _within(cut, [group, order], "_bin", limit, before)
    run = Window.partitionBy(group, order, "_bin").orderBy(F.col("tie").desc(), "id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    last = last.withColumn("_need", F.sum("c").over(run))
    last = last.where(F.col("_need") - F.col("c") < F.col(limit) if before else F.col("_need") <= F.col(limit))
    return whole.select(*cols).union(bins.select(*cols)).union(last.select(*cols))


def admit(proposals: DataFrame, sizes: DataFrame, cap: int | None, mode: str = "exact") -> DataFrame:
    """Per target admit proposals, strongest first, while the running weight of all
    asked so far fits the room left.

    Both modes admit the same. ``exact`` ranks every proposal of a target in one window,
    the form for many small targets; ``histogram`` (see :func:`prefix`) is the form for a
    few huge ones."""
    if cap is None:
        return proposals
    room = sizes.select(F.col("cluster").alias("target"), (F.lit(cap) - F.col("size")).alias("room"))
    asked = proposals.join(room, "target")
    by = [F.col("strength").desc(), F.col("tie").desc(), F.col("id")]
    if mode == "exact":
        run = Window.partitionBy("target").orderBy(*by).rowsBetween(Window.unboundedPreceding, Window.currentRow)
        return asked.withColumn("need", F.sum("c").over(run)).where("need <= room").drop("need", "room")
    asked = asked.withColumn("_weak", -F.col("strength"))
    return prefix(asked, "target", "_weak", "room").select(*proposals.columns)


def advance(labels: DataFrame, moves: DataFrame) -> tuple[DataFrame, int]:
    """Save the labels after the moves, and count the moves on the way: one job. Labels
    are never empty here, so the observation cannot be dropped with an empty plan."""
    seen = Observation()
    both = committed(labels, moves).observe(seen, F.count("_to").alias("moved"))
    return saved(both.drop("_to"), "labels"), int(seen.get["moved"])


def renewed(labels: DataFrame) -> DataFrame:
    """Labels whose ``start`` is where they are now; the saved copy stays known."""
    out = labels.withColumn("start", F.col("cluster"))
    out._scratch_path = getattr(labels, "_scratch_path", None)
    return out


def moved_neighbours(arcs: DataFrame, labels: DataFrame) -> DataFrame:
    """Ids next to a node whose cluster is no longer its ``start``."""
    gone = labels.where("cluster <> start").select(F.col("id").alias("dst"))
    return arcs.join(gone, "dst", "left_semi").select(F.col("src").alias("id")).distinct()


def sweep(arcs: DataFrame, labels: DataFrame, waves: list, cap: int | None, salt: int, mode: str = "exact", over: bool = False, also=None) -> tuple[DataFrame, int]:
    """One round: per condition of ``waves`` a superstep of the labels that it selects, in
    one job that writes the labels after it. ``also(who, sizes)`` narrows who may move."""
    total = 0
    for wave in waves:
        who = labels.where(wave)
        if also is not None:
            who = also(who, sizes_of(labels))
        nxt, n = advance(labels, superstep(arcs, labels, who.select("id"), cap, salt, mode, over, over))
        drop_saved(labels)
        labels, total = nxt, total + n
    return labels, total


def committed(labels: DataFrame, moves: DataFrame) -> DataFrame:
    """Labels after the admitted moves, and ``_to``, where a node went or NULL."""
    to = moves.select("id", F.col("target").alias("_to"))
    rest = [c for c in labels.columns if c not in ("id", "cluster")]
    return labels.join(to, "id", "left").select("id", F.coalesce("_to", "cluster").alias("cluster"), *rest, "_to")


def commit(labels: DataFrame, moves: DataFrame) -> DataFrame:
    """Labels after the admitted moves."""
    return committed(labels, moves).drop("_to")


def superstep(arcs: DataFrame, labels: DataFrame, movers: DataFrame | None, cap: int | None, salt: int, mode: str = "exact", over: bool = False, excess: bool = False) -> DataFrame:
    """The admitted moves of one wave. ``movers(id)`` restricts who may move."""
    sizes = sizes_of(labels)
    mine = arcs if movers is None else arcs.join(movers.select(F.col("id").alias("src")), "src", "left_semi")
    wants = choose(connections(mine, labels), labels, cap, salt, sizes, over)
    if mode == "histogram":
        wants = saved(wants, "wants")
    if over and excess and cap is not None:
        # Only as much leaves an overloaded block against its interest as it must shed.
        heavy = sizes.where(F.col("size") > cap).select(F.col("cluster").alias("source"), (F.col("size") - cap).alias("shed"))
        asked = wants.join(heavy, "source", "left")
        if mode == "exact":
            order = Window.partitionBy("source").orderBy("loss", F.col("tie").desc(), "id").rowsBetween(Window.unboundedPreceding, -1)
            gone = F.coalesce(F.sum("c").over(order), F.lit(0))
            wants = asked.withColumn("gone", gone).where("shed is null or loss < 0 or gone < shed").select(*wants.columns)
        else:
            forced = prefix(asked.where("shed is not null"), "source", "loss", "shed", before=True)
            wants = asked.where("shed is null or loss < 0").select(*wants.columns).union(forced.where("loss >= 0").select(*wants.columns))
    return admit(wants, sizes, cap, mode)


def propagate(g: WeightedGraph, cap: int | None, rounds: int = 10, stop: float = 0.05, order: str = "degree", seed: int = 0, level: int = 1, cycle: int = 1, within: DataFrame | None = None, active: bool = False, buckets: int = 2, sub: int = 2, log: list | None = None) -> DataFrame:
    """Cluster ``g``: labels ``(id, cluster, c)``. ``within(id, block)`` forbids clusters
    across blocks; ``active`` lets only neighbours of moved nodes move again. ``log``
    gets a row per round: nodes, moved, and with ``active`` the active nodes and arcs."""
    with scope() as tables:
        arcs = g.arcs()
        if within is not None:
            side = within.select("id", "block")
            arcs = arcs.join(side.select(F.col("id").alias("src"), F.col("block").alias("a")), "src").join(side.select(F.col("id").alias("dst"), F.col("block").alias("b")), "dst").where("a = b").select("src", "dst", "w")
            arcs = saved(arcs, "arcs")
        key = {"degree": "deg", "wdegree": "wdeg"}.get(order)
        base = singletons(g)
        if key:
            base = base.join(buckets_by(g.degrees(), key, buckets), "id")
        else:
            base = base.withColumn("bucket", F.lit(0))
            buckets, sub = 1, buckets * sub
        labels = saved(base.withColumn("start", F.col("cluster")), "labels")
        n = labels.count()
        if not n:
            return tables.keep(saved(labels.select("id", "cluster", "c"), "clusters"))
        live: DataFrame | None = None
        for r in range(rounds):
            s = hashing.salt(seed, cycle, level, r)
            waves = [(F.col("bucket") == wave // sub) & (hashing.part_of(F.col("id"), s, sub) == wave % sub) for wave in range(buckets * sub)]
            also = None if live is None else lambda who, _, live=live: who.join(live, "id", "left_semi")
            row = {"round": r, "nodes": n}
            if log is not None and active:
                row["active"] = n if live is None else live.count()
                row["active_arcs"] = (arcs if live is None else arcs.join(live.select(F.col("id").alias("src")), "src", "left_semi")).count()
            labels, moved = sweep(arcs, labels, waves, cap, s, also=also)
            if log is not None:
                log.append(row | {"moved": moved})
            if not moved or moved < stop * n:
                break
            if active:
                live = saved(moved_neighbours(arcs, labels), "active")
            labels = renewed(labels)
        return tables.keep(saved(labels.select("id", "cluster", "c"), "clusters"))
