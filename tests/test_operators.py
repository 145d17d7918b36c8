import math
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from cutfold.functions import caps, hashing
from cutfold.operators import contract as con
from cutfold.operators import ensemble, lpa, matching, metrics, refine
from cutfold.operators.components import star_components
from cutfold.operators.graph import WeightedGraph, from_pairs, to_local, validate
from cutfold.plans import partition as plan
from cutfold.plans import presets
from cutfold.sources import builders


@pytest.fixture(scope="module")
def two(spark):
    return builders.cliques(spark, 2, 4).saved()


@pytest.fixture(scope="module")
def planted(spark):
    return builders.planted(spark, 240, 4, 5, 1).saved()


def part_of(spark, blocks):
    return spark.createDataFrame(list(enumerate(blocks)), "id long, block int")


def test_mix_agrees_with_python(spark):
    ids = [0, 1, 2, 10**12, 2**60 + 7]
    df = spark.createDataFrame([(i,) for i in ids], "id long").select("id", hashing.mix(F.col("id"), 77).alias("m"), F.expr(hashing.mix_sql("id", 77)).alias("s"), hashing.part_of(F.col("id"), 77, 10).alias("p"))
    for r in df.collect():
        assert r.m == r.s == hashing.mix_int(r.id, 77) and r.p == r.m * 10 // hashing.P


def test_salts_are_independent(spark):
    r = spark.range(20000).select(*[hashing.part_of(F.col("id"), s, 2).alias(f"p{s}") for s in (1, 2)]).agg(F.avg((F.col("p1") == F.col("p2")).cast("double")), F.avg("p1")).first()
    assert abs(r[0] - 0.5) < 0.02 and abs(r[1] - 0.5) < 0.02


def test_validate(spark, two):
    validate(two)
    bad = WeightedGraph(two.nodes, two.edges.union(spark.createDataFrame([(5, 5, 1)], two.edges.schema)))
    with pytest.raises(ValueError):
        validate(bad)


def test_worked_example(spark, two):
    part = part_of(spark, [0] * 4 + [1] * 4)
    assert metrics.cut(two, part).first()["cut"] == 1
    assert sorted(r.id for r in metrics.boundary(two, part).collect()) == [3, 4]
    r = metrics.imbalance(two, part, 2, 4).first()
    assert r.feasible and r.max_block == 4 and r.imbalance_pct == 0 and r.overloaded == 0
    coarse, to = con.contract(two, part.select("id", F.col("block").alias("cluster")))
    assert [tuple(x) for x in coarse.edges.collect()] == [(0, 4, 1)]
    assert metrics.check_contraction(two, coarse, to, coarse.nodes.select("id", (F.col("id") > 0).cast("int").alias("block")))
    assert sorted(tuple(x) for x in metrics.communication_volume(two, part).collect()) == [(0, 1), (1, 1)]


def test_overlays(spark, two):
    runs = lambda *cs: spark.createDataFrame([(i, v, c) for i, cl in enumerate(cs) for v, c in enumerate(cl)], "run int, id long, cluster long")
    r = runs([0, 0, 0, 0, 4, 4, 4, 4], [0, 0, 2, 2, 2, 2, 6, 6])
    want = {0: 0, 1: 0, 2: 2, 3: 2, 4: 4, 5: 4, 6: 6, 7: 6}
    assert dict(map(tuple, ensemble.overlay_tuple(r).collect())) == want
    assert dict(map(tuple, ensemble.overlay_fold(r, 2).collect())) == want
    assert dict(map(tuple, ensemble.overlay_components(two, r).collect())) == want
    line = builders.path(spark, 3).saved()
    r = runs([0, 1, 0], [0, 1, 0])
    assert len({x.cluster for x in ensemble.overlay_tuple(r).collect()}) == 2
    assert len({x.cluster for x in ensemble.overlay_components(line, r).collect()}) == 3


def test_admission(spark):
    prop = spark.createDataFrame([(1, 1, 9, 7, 5, 0, 0), (2, 2, 9, 7, 4, 0, 0), (3, 1, 9, 7, 3, 0, 0)], "id long, c long, source long, target long, strength long, loss long, tie long")
    sizes = spark.createDataFrame([(7, 8)], "cluster long, size long")
    assert [r.id for r in lpa.admit(prop, sizes, 10).collect()] == [1]
    hist = [r.id for r in lpa.admit(prop, sizes, 10, "histogram").collect()]
    assert hist == [1]


def test_synchronous_trap(spark):
    edge = builders.path(spark, 2).saved()
    labels = lpa.singletons(edge)
    swapped = lpa.commit(labels, lpa.superstep(edge.arcs(), labels, None, None, 1))
    assert {r.id: r.cluster for r in swapped.collect()} == {0: 1, 1: 0}
    done = lpa.propagate(edge, None, rounds=6, seed=1, order="random", buckets=2, sub=1)
    assert len({r.cluster for r in done.collect()}) == 1


@pytest.mark.parametrize("order", ["degree", "random", "wdegree"])
def test_propagation_bound_and_quality(planted, order):
    log = []
    labels = lpa.propagate(planted, 60, rounds=4, order=order, seed=3, log=log)
    assert lpa.sizes_of(labels).agg(F.max("size")).first()[0] <= 60
    total = planted.edges.agg(F.sum("w")).first()[0]
    assert metrics.cut(planted, labels.select("id", F.col("cluster").alias("block"))).first()["cut"] < 0.75 * total
    assert log[-1]["moved"] <= log[0]["moved"]


def test_unit_bound(planted):
    assert lpa.propagate(planted, 1, rounds=2).where("id <> cluster").count() == 0


def test_active_and_within(planted):
    block = planted.nodes.select("id", (F.col("id") % 2).cast("int").alias("block"))
    labels = lpa.propagate(planted, 40, rounds=3, within=block, active=True)
    mixed = labels.join(block, "id").groupBy("cluster").agg(F.count_distinct("block").alias("n")).where("n > 1")
    assert mixed.count() == 0 and lpa.sizes_of(labels).agg(F.max("size")).first()[0] <= 40


def test_same_result_for_any_partitioning(spark, planted):
    other = WeightedGraph(planted.nodes.repartition(7), planted.edges.repartition(5))
    a = {tuple(r) for r in lpa.propagate(planted, 30, rounds=2, seed=5).collect()}
    assert a == {tuple(r) for r in lpa.propagate(other, 30, rounds=2, seed=5).collect()}


def test_overloaded_start(spark):
    line = builders.path(spark, 4).saved()
    got = refine.lp_refine(line, part_of(spark, [0, 0, 0, 1]), 2, 2, rounds=3, mode="exact")
    assert {r.id: r.block for r in got.collect()} == {0: 0, 1: 0, 2: 1, 3: 1}


def test_forced_balance(spark):
    """Two components: the overloaded block has no neighbouring block to move to."""
    g = builders.cliques(spark, 1, 6)
    nodes = g.nodes.union(spark.createDataFrame([(10, 1), (11, 1)], "id long, c long"))
    g = WeightedGraph(nodes, g.edges).saved()
    start = g.nodes.select("id", (F.col("id") >= 10).cast("int").alias("block"))
    got = refine.force_balance(g, start, 3, 3)
    assert metrics.imbalance(g, got, 3, 3).first().feasible and got.count() == 8


def test_refinement_improves(spark, planted):
    start = planted.nodes.select("id", hashing.part_of(F.col("id"), 3, 4).alias("block"))
    cap = caps.block_cap(240, 4, 0.1)
    got = refine.lp_refine(planted, start, 4, cap, rounds=3)
    assert refine.quality(planted, got, cap) < refine.quality(planted, start, cap)
    assert refine.quality(planted, refine.keep_better(planted, start, got, cap), cap) == refine.quality(planted, got, cap)


def test_matching(spark):
    g = from_pairs(spark.createDataFrame([(0, 1, 1), (1, 2, 5), (2, 3, 1)], "u long, v long, w long")).saved()
    assert [tuple(r) for r in matching.mutual_round(g.arcs(), 1).collect()] == [(1, 2)]
    labels = matching.heavy_edge_matching(g, 2)
    assert {r.id: r.cluster for r in labels.collect()} == {0: 0, 1: 1, 2: 1, 3: 3}
    star = builders.star(spark, 6).saved()
    pairs = matching.two_hop_pairs(star.arcs(), star.nodes.where("id > 1").select("id"))
    assert sorted(tuple(r) for r in pairs.collect()) == [(2, 3), (4, 5)]


def test_components(spark):
    e = spark.createDataFrame([(1, 2), (2, 3), (3, 4), (4, 5), (10, 11), (11, 10), (7, 7), (None, 3)], "u long, v long")
    assert dict(map(tuple, star_components(e).collect())) == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 10: 10, 11: 10}
    assert star_components(e.limit(0)).count() == 0
    long = builders.path(spark, 200).edges
    assert {r.component for r in star_components(long.select("u", "v")).collect()} == {0}


def test_distributed_partition(spark, planted):
    for preset in ("ci-fast", "mi-eco+b"):
        r = plan.partition(planted, 4, replace(presets.get(preset), rounds=2), local_arcs=1900, stop_at=40, tries=2)
        told = metrics.imbalance(planted, r.part, 4, r.cap).first()
        assert told.feasible and r.part.count() == 240
        assert metrics.cut(planted, r.part).first()["cut"] == r.history[-1]["cut"]
        assert any(h["phase"] == "contract" for h in r.history)


def test_small_and_odd_inputs(spark):
    none = WeightedGraph(spark.createDataFrame([], "id long, c long"), spark.createDataFrame([], "u long, v long, w long"))
    assert plan.partition(none, 4).part.count() == 0
    lone = WeightedGraph(spark.createDataFrame([(1, 1), (2, 0)], "id long, c long"), none.edges)
    assert plan.partition(lone, 2).part.count() == 2
    assert {r.block for r in plan.partition(builders.ring(spark, 8), 1).part.collect()} == {0}
    with pytest.raises(ValueError):
        to_local(builders.ring(spark, 50), 20)


def test_geometric_mean(spark):
    runs = spark.createDataFrame([("a", "x", 2, 4.0), ("a", "x", 2, 6.0), ("a", "y", 2, 20.0), ("a", "z", 2, 0.0)], "preset string, instance string, k int, cut double")
    r = metrics.geometric_mean(runs, ["preset"]).first()
    assert r.avg_cut == pytest.approx(math.sqrt(5 * 20)) and r.best_cut == pytest.approx(math.sqrt(80)) and r.zeros == 1
