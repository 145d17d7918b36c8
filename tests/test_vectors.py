"""Supersteps on arrays of nodes make the choices of the DataFrame operators."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from cutfold.functions import hashing
from cutfold.operators import contract, lpa, matching, refine, vectors
from cutfold.operators.graph import WeightedGraph, to_local
from cutfold.plans import experiments
from cutfold.plans import partition as partitioner
from cutfold.sources import builders


@pytest.fixture(scope="module")
def graph(spark):
    rng = np.random.default_rng(3)
    pairs = sorted({(int(min(a, b)), int(max(a, b))) for a, b in rng.integers(0, 60, (260, 2)) if a != b})
    edges = [(7 * a + 2, 7 * b + 2, int(w)) for (a, b), w in zip(pairs, rng.integers(1, 4, len(pairs)))]
    nodes = [(7 * i + 2, int(c)) for i, c in enumerate(rng.integers(1, 4, 62))]
    return WeightedGraph(spark.createDataFrame(nodes, "id long, c long"), spark.createDataFrame(edges, "u long, v long, w long")).saved()


@pytest.fixture(scope="module")
def loaded(graph):
    return vectors.load(graph, graph.sizes())


def _rows(frame, value):
    return [r[0] for r in frame.orderBy("id").select(value).collect()]


def test_mixes_agree(spark):
    x = np.array([0, 1, 2**31 - 2, 2**31 - 1, 2**40 + 7, 2**62, -5], np.int64)
    assert hashing.mix_array(x, 12345).tolist() == [hashing.mix_int(int(v), 12345) for v in x]
    y = np.array([0, 2**31 - 1, 2**32 - 1, 2**62 - 1, (2**31 - 2) ** 2, 2**31 + 2**31 - 1])
    assert hashing._below(y).tolist() == [int(v) % hashing.P for v in y]


@pytest.mark.parametrize("how", [{}, {"order": "random", "active": True}, {"within": True}])
def test_clusters(graph, loaded, how):
    side = how.pop("within", None)
    within = graph.nodes.select("id", (F.col("id") % 2).cast("int").alias("block")) if side else None
    how = {"rounds": 2, "stop": 0.0} | how
    want = lpa.propagate(graph, 9, seed=4, within=within, **how)
    got = vectors.propagate(loaded, 9, seed=4, within=(loaded.ids % 2) if side else None, **how)
    assert loaded.ids[got].tolist() == _rows(want, "cluster")
    coarse, to = contract.contract(graph, want)
    mine, mapped = vectors.contract(loaded, got)
    assert mine.ids[mapped].tolist() == _rows(to, "cid") and mine.c.tolist() == _rows(coarse.nodes, "c")
    g, ids = to_local(coarse, 10_000)
    h = vectors.local(mine)
    assert all(np.array_equal(a, b) for a, b in ((g.ptr, h.ptr), (g.adj, h.adj), (g.w, h.w), (g.c, h.c), (ids, mine.ids)))
    assert mine.size() == coarse.sizes()
    again, _ = vectors.contract(mine, vectors.propagate(mine, 20, 1, seed=4))
    assert again.size() == contract.contract(coarse, lpa.propagate(coarse, 20, 1, seed=4))[0].sizes()


@pytest.mark.parametrize("over", [0, 5])
def test_blocks(graph, loaded, over):
    start = graph.nodes.select("id", hashing.part_of(F.col("id"), 5, 4).alias("block"))
    part = np.array(_rows(start, "block"))
    cap = int(np.bincount(part, loaded.c).max()) + 2 - over
    want = refine.lp_refine(graph, start, 4, cap, seed=2, rounds=1)
    got = vectors.lp_refine(loaded, part, 4, cap, seed=2, rounds=1)
    assert got.tolist() == _rows(want, "block") and got.tolist() != part.tolist()
    assert vectors.quality(loaded, got, 4, cap) == refine.quality(graph, want, cap)
    assert _rows(vectors.frame(loaded, got), "block") == got.tolist()


@pytest.mark.parametrize("side", [False, True])
def test_matching_and_pairs(graph, loaded, side):
    within = graph.nodes.select("id", (F.col("id") % 2).cast("int").alias("block")) if side else None
    mine = loaded.ids % 2 if side else None
    want = matching.heavy_edge_matching(graph, 4, seed=6, within=within, rounds=2)
    got = vectors.heavy_edge_matching(loaded, 4, seed=6, within=mine, rounds=2)
    assert loaded.ids[got].tolist() == _rows(want, "cluster")
    assert loaded.ids[vectors.paired(loaded, got, 4, mine)].tolist() == _rows(partitioner._paired(graph, want, 4, within), "cluster")


def test_hubs_that_are_too_large_take_the_other_form(spark, graph, monkeypatch):
    assert vectors.load(graph, {"n": vectors.NODES + 1, "m": 1}) is None
    # Tasks run the function that is sent to them, with the limit that they know.
    assert list(vectors._merged(9)(iter(()))) == []
    monkeypatch.setattr(vectors, "MOST_ARCS", 3)
    batch = vectors._dealt(np.array([1, 1, 1, 1]), np.array([2, 3, 4, 5]), np.ones(4, np.int64), 1)
    (row,) = vectors._merged(9)(iter([batch]))
    assert row.column(0).to_pylist() == [4] and row.column(1).to_pylist() == [b""]
    monkeypatch.setattr(partitioner.vectors, "load", lambda *a: None)
    found = partitioner.partition(builders.planted(spark, 120, 2, 4, 1), 2, "ci-fast", local_arcs=900, tries=1)
    assert found.part.count() == 120


@pytest.mark.parametrize("name", ["ci-fast+v@huge", "mi-fast+v+b"])
def test_partition_without_a_shuffle_per_wave(spark, monkeypatch, name):
    """Every wave was joins of all arcs."""
    monkeypatch.setattr(partitioner, "_coarser", lambda *a: pytest.fail("joins"))
    g = builders.planted(spark, 120, 2, 4, 1).saved()
    found = partitioner.partition(g, 2, name, local_arcs=900, tries=1)
    assert found.part.count() == 120
    assert refine.quality(g, found.part, found.cap) == (0, found.history[-1]["cut"])
    assert [h["cycle"] for h in found.history if h["phase"] == "kernel"] == [1, 2, 3]


def test_pairs_of_two_kinds_are_shuffled_once(spark, tmp_path):
    rows = [(1, 5), (1, 5), (2, 5), (None, 4), (3, None), (2, 2)]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long").write.parquet(str(tmp_path / "lineitem.parquet"))
    g = builders.order_part(spark, str(tmp_path))
    assert sorted(map(tuple, g.edges.collect())) == [(2, 11, 1), (4, 5, 1), (4, 11, 1)]
    assert sorted(map(tuple, g.saved().nodes.collect())) == [(2, 1), (4, 1), (5, 1), (11, 1)]
    assert g.edges._jdf.queryExecution().toString().split("== Physical Plan")[1].count("Exchange") <= 2


def test_profile_without_joins_has_the_same_levels(spark):
    """Every level of the profile above a task's limit was made by joins of all edges."""
    whole = builders.planted(spark, 120, 2, 4, 1).saved()
    full = whole.sizes()
    want = experiments._levels(spark, whole, full, "x", "matching", 2, 0, 900).collect()
    got = experiments._levels_vectors(vectors.load(whole, full), full, "x", "matching", 2, 0, 900).collect()
    assert len(want) > 1 and sorted(got) == sorted(want)
