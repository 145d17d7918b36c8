"""Registered graph queries with their SQL counterparts."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from cutfold.functions import caps, hashing
from cutfold.functions.storage import saved
from cutfold.kernels import baselines
from cutfold.operators import contract as con
from cutfold.operators import ensemble, lpa, matching, metrics, refine
from cutfold.operators.components import star_components
from cutfold.plans import experiments, presets, stepsql
from cutfold.plans.partition import partition
from cutfold.sources import builders
from cutfold.sources.builders import TABLE_GRAPHS, load

QUERIES: dict = {}
SQL: dict = {}


def query(name: str, sql: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if sql is not None:
            SQL[name] = sql
        return fn

    return keep


def _graph(spark, sf_dir, name):
    return TABLE_GRAPHS[name](spark, sf_dir)


def _blocks(g, k: int, s: int = 11):
    """Blocks by hash: the floor of quality, and a fixed partition for measures."""
    return g.nodes.select("id", hashing.part_of(F.col("id"), s, k).alias("block"))


def _hashed(g, parts: int, s: int):
    return g.nodes.select("id", hashing.part_of(F.col("id"), s, parts).cast("long").alias("cluster"), "c")


def _part_sql(k: int, s: int = 11, name: str = "part") -> str:
    return f"{name} AS (SELECT id, {hashing.part_sql('id', s, k)} AS block FROM nodes)"


_ENDS = "ends AS (SELECT e.u, e.v, e.w, a.block AS bu, b.block AS bv FROM e JOIN part a ON a.id = e.u JOIN part b ON b.id = e.v)"


def _measure(graph: str, k: int, tail: str) -> str:
    return f"WITH {stepsql.graph(graph)}, {_part_sql(k)}, {_ENDS} {tail}"


# --- graphs -----------------------------------------------------------------
for _name in TABLE_GRAPHS:
    _key = "knn_edges" if _name == "knn" else f"graph_{_name}"
    query(_key, f"SELECT u, v, w FROM ({builders.SQL[_name]}) g" if _name in builders.SQL else None)(lambda spark, sf_dir, n=_name: _graph(spark, sf_dir, n).edges.select("u", "v", "w"))


@query("degree_profile", f"WITH {stepsql.graph('basket')}, d AS (SELECT src, count(*) AS deg FROM arcs GROUP BY src) SELECT deg, count(*) AS n FROM d GROUP BY deg")
def degree_profile(spark, sf_dir):
    return _graph(spark, sf_dir, "basket").degrees().groupBy("deg").agg(F.count(F.lit(1)).alias("n"))


@query("weighted_degree", f"WITH {stepsql.graph('supply')} SELECT src AS id, cast(sum(w) AS BIGINT) AS wdeg FROM arcs GROUP BY src")
def weighted_degree(spark, sf_dir):
    return _graph(spark, sf_dir, "supply").degrees().select("id", "wdeg")


_BUCKETS = (
    "d AS (SELECT src AS id, count(*) AS deg FROM arcs GROUP BY src), h AS (SELECT deg, count(*) AS n FROM d GROUP BY deg), "
    "b AS (SELECT deg, cast((coalesce(sum(n) OVER (ORDER BY deg ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * {0}) // (sum(n) OVER ()) AS INT) AS bucket FROM h)"
)


@query("order_buckets", f"WITH {stepsql.graph('page_links')}, {_BUCKETS.format(4)} SELECT d.id, b.bucket FROM d JOIN b USING (deg)")
def order_buckets(spark, sf_dir):
    return lpa.buckets_by(_graph(spark, sf_dir, "page_links").degrees(), "deg", 4)


# --- propagation ------------------------------------------------------------
@query("connections_round1", f"WITH {stepsql.graph('supply')}, {stepsql.hash_labels('l', 50, 5)} SELECT a.src, l.cluster, cast(sum(w) AS BIGINT) AS strength FROM arcs a JOIN l ON a.dst = l.id GROUP BY 1, 2")
def connections_round1(spark, sf_dir):
    g = _graph(spark, sf_dir, "supply")
    return lpa.connections(g.arcs(), _hashed(g, 50, 5))


_SINGLE = "l0 AS (SELECT id, id AS cluster, c FROM nodes)"


def _step_query(name, graph, cap, salt):
    sql = f"WITH {stepsql.graph(graph)}, {_SINGLE}, {stepsql.step('l1', 'l0', cap, salt)} SELECT id, cluster FROM l1"

    @query(name, sql)
    def run(spark, sf_dir):
        g = _graph(spark, sf_dir, graph).saved()
        labels = lpa.singletons(g)
        return lpa.commit(labels, lpa.superstep(g.arcs(), labels, None, cap, salt)).select("id", "cluster")

    return run


_step_query("lpa_plain_step", "page_links", None, 7)
_step_query("sclp_step", "doc_lines", 6, 7)


@query(
    "sclp_two_steps",
    f"WITH {stepsql.graph('doc_lines')}, {_SINGLE}, {stepsql.step('l1', 'l0', 6, 9, stepsql.half(9, 0))}, {stepsql.step('l2', 'l1', 6, 9, stepsql.half(9, 1))} SELECT id, cluster FROM l2",
)
def sclp_two_steps(spark, sf_dir):
    g = _graph(spark, sf_dir, "doc_lines").saved()
    labels = lpa.singletons(g)
    for wave in range(2):
        who = labels.where(hashing.part_of(F.col("id"), 9, 2) == wave).select("id")
        labels = saved(lpa.commit(labels, lpa.superstep(g.arcs(), labels, who, 6, 9)), "labels")
    return labels.select("id", "cluster")


_ACTIVE = "SELECT DISTINCT a.src AS id FROM arcs a JOIN l1_moves m ON m.id = a.dst"


@query("sclp_active_step", f"WITH {stepsql.graph('page_links')}, {_SINGLE}, {stepsql.step('l1', 'l0', 20, 3, stepsql.half(3, 0))}, {stepsql.step('l2', 'l1', 20, 4, _ACTIVE)} SELECT id, cluster FROM l2")
def sclp_active_step(spark, sf_dir):
    g = _graph(spark, sf_dir, "page_links").saved()
    first = lpa.singletons(g)
    who = first.where(hashing.part_of(F.col("id"), 3, 2) == 0).select("id")
    moves = saved(lpa.superstep(g.arcs(), first, who, 20, 3), "moves")
    labels = saved(lpa.commit(first, moves), "labels")
    live = g.arcs().join(moves.select(F.col("id").alias("dst")), "dst", "left_semi").select(F.col("src").alias("id")).distinct()
    return lpa.commit(labels, lpa.superstep(g.arcs(), labels, live, 20, 4)).select("id", "cluster")


_WANT = f"WITH {stepsql.graph('supply')}, {stepsql.hash_labels('l0', 4, 5)}, {stepsql.step('l1', 'l0', 540, 6)} "


def _wants(spark, sf_dir):
    g = _graph(spark, sf_dir, "supply").saved()
    labels = _hashed(g, 4, 5)
    sizes = lpa.sizes_of(labels)
    return saved(lpa.choose(lpa.connections(g.arcs(), labels), labels, 540, 6, sizes), "wants"), sizes


@query("admit_prefix", _WANT + "SELECT id, source, target FROM l1_moves")
def admit_prefix(spark, sf_dir):
    return lpa.admit(*_wants(spark, sf_dir), 540).select("id", "source", "target")


@query(
    "admit_histogram",
    _WANT + ", d AS (SELECT target, strength, sum(c) AS want, max(540 - s.size) AS room FROM l1_wants w JOIN l1_sizes s ON s.cluster = w.target GROUP BY target, strength), "
    "n AS (SELECT *, sum(want) OVER (PARTITION BY target ORDER BY strength DESC ROWS UNBOUNDED PRECEDING) AS need FROM d), "
    "r AS (SELECT w.id, w.source, w.target, n.need <= n.room AS whole, n.room - n.need + n.want AS have, sum(w.c) OVER (PARTITION BY w.target, w.strength ORDER BY w.tie DESC, w.id ROWS UNBOUNDED PRECEDING) AS run "
    "FROM l1_wants w JOIN n ON n.target = w.target AND n.strength = w.strength WHERE n.need - n.want < n.room) SELECT id, source, target FROM r WHERE whole OR run <= have",
)
def admit_histogram(spark, sf_dir):
    return lpa.admit(*_wants(spark, sf_dir), 540, "histogram").select("id", "source", "target")


@query("cluster_cap", f"WITH {stepsql.graph('supply')}, s AS (SELECT cast(sum(c) AS BIGINT) AS total, max(c) AS h FROM nodes), k AS (SELECT unnest([2, 4, 8, 16, 32, 64]) AS k) SELECT k, total, ((total + k - 1) // k) * 103 // 100 AS l_max, greatest(h, ((total + k - 1) // k) * 103 // 100 // 18) AS bound FROM s, k")
def cluster_cap(spark, sf_dir):
    """Driver arithmetic on two aggregates, shown per k."""
    s = _graph(spark, sf_dir, "supply").nodes.agg(F.sum("c").alias("total"), F.max("c").alias("h")).first()
    rows = [(k, s.total, caps.block_cap(s.total, k, 0.03), caps.cluster_cap(caps.block_cap(s.total, k, 0.03), s.h)) for k in experiments.KS] if s.total else []
    return spark.createDataFrame(rows, "k int, total long, l_max long, bound long")


# --- contraction and hierarchy ----------------------------------------------
def _contract_sql(labels: str) -> str:
    return (
        f"nm AS (SELECT cluster, min(id) AS cid FROM {labels} GROUP BY cluster), t AS (SELECT l.id, nm.cid FROM {labels} l JOIN nm USING (cluster)), "
        "ce AS (SELECT least(a.cid, b.cid) AS u, greatest(a.cid, b.cid) AS v, cast(sum(e.w) AS BIGINT) AS w FROM e JOIN t a ON a.id = e.u JOIN t b ON b.id = e.v WHERE a.cid <> b.cid GROUP BY 1, 2), "
        "cn AS (SELECT cid AS id, cast(count(*) AS BIGINT) AS c FROM t GROUP BY cid)"
    )


@query("contract_by_hash", f"WITH {stepsql.graph('supply')}, {stepsql.hash_labels('l', 100, 8)}, {_contract_sql('l')} SELECT u, v, w FROM ce")
def contract_by_hash(spark, sf_dir):
    g = _graph(spark, sf_dir, "supply")
    return con.contract(g, _hashed(g, 100, 8))[0].edges


_TWO = f"WITH {stepsql.graph('doc_lines')}, {_SINGLE}, {stepsql.step('l1', 'l0', 6, 7)}, {_contract_sql('l1')} "


def _one_level(spark, sf_dir):
    g = _graph(spark, sf_dir, "doc_lines").saved()
    labels = lpa.singletons(g)
    labels = saved(lpa.commit(labels, lpa.superstep(g.arcs(), labels, None, 6, 7)), "labels")
    return g, *con.contract(g, labels)


@query("contract_by_sclp", _TWO + "SELECT u, v, w FROM ce")
def contract_by_sclp(spark, sf_dir):
    return _one_level(spark, sf_dir)[1].edges


@query(
    "hierarchy_stats_2level",
    _TWO + "SELECT 1 AS level, (SELECT count(*) FROM nodes) AS nodes, (SELECT count(*) FROM e) AS edges, (SELECT cast(coalesce(sum(w), 0) AS BIGINT) FROM e) AS edge_weight, (SELECT cast(max(c) AS BIGINT) FROM nodes) AS heaviest "
    "UNION ALL SELECT 2, (SELECT count(*) FROM cn), (SELECT count(*) FROM ce), (SELECT cast(coalesce(sum(w), 0) AS BIGINT) FROM ce), (SELECT cast(max(c) AS BIGINT) FROM cn)",
)
def hierarchy_stats_2level(spark, sf_dir):
    g, coarse, _ = _one_level(spark, sf_dir)
    out = None
    for level, x in enumerate((g, coarse), 1):
        nodes = x.nodes.agg(F.count(F.lit(1)).alias("nodes"), F.max("c").alias("heaviest"))
        edges = x.edges.agg(F.count(F.lit(1)).alias("edges"), F.coalesce(F.sum("w"), F.lit(0)).cast("long").alias("edge_weight"))
        row = nodes.join(edges, F.lit(True)).select(F.lit(level).alias("level"), "nodes", "edges", "edge_weight", "heaviest")
        out = row if out is None else out.union(row)
    return out


@query("project_blocks", _TWO + f", part AS (SELECT id, {hashing.part_sql('id', 11, 4)} AS block FROM cn) SELECT t.id, part.block FROM t JOIN part ON part.id = t.cid")
def project_blocks(spark, sf_dir):
    _, coarse, to = _one_level(spark, sf_dir)
    return con.project(_blocks(coarse, 4), to)


# --- local search -----------------------------------------------------------
def _search_sql(graph, k, cap, labels):
    return f"WITH {stepsql.graph(graph)}, {labels}, {stepsql.step('l1', 'l0', cap, 13, stepsql.half(13, 0), over=True)} SELECT id, cast(cluster AS INT) AS block FROM l1"


def _search(spark, sf_dir, graph, cap, labels_of):
    g = _graph(spark, sf_dir, graph).saved()
    labels = labels_of(g)
    who = labels.where(hashing.part_of(F.col("id"), 13, 2) == 0).select("id")
    moves = lpa.superstep(g.arcs(), labels, who, cap, 13, "exact", over=True, excess=True)
    return lpa.commit(labels, moves).select("id", F.col("cluster").cast("int").alias("block"))


@query("lp_refine_step", _search_sql("page_links", 4, 150, stepsql.hash_labels("l0", 4, 11)))
def lp_refine_step(spark, sf_dir):
    return _search(spark, sf_dir, "page_links", 150, lambda g: _hashed(g, 4, 11))


_SKEWED = f"l0 AS (SELECT id, cast(CASE WHEN {hashing.part_sql('id', 11, 8)} < 5 THEN 0 ELSE {hashing.part_sql('id', 11, 8)} - 4 END AS BIGINT) AS cluster, c FROM nodes)"


@query("overload_step", _search_sql("page_links", 4, 150, _SKEWED))
def overload_step(spark, sf_dir):
    p = hashing.part_of(F.col("id"), 11, 8)
    return _search(spark, sf_dir, "page_links", 150, lambda g: g.nodes.select("id", F.when(p < 5, 0).otherwise(p - 4).cast("long").alias("cluster"), "c"))


@query("level_caps", "SELECT cast(level AS INT) AS level, cast(floor(CASE WHEN level = 1 THEN 103.0 / 100 ELSE (103.0 + 3.0 / (6 - level)) / 100 END * ((SELECT count(*) FROM part) + 3) // 4 + 0.0000001) AS BIGINT) AS cap FROM (SELECT unnest(range(1, 6)) AS level) x".replace("* ((SELECT count(*) FROM part) + 3) // 4", "* (((SELECT count(*) FROM part) + 3) // 4)"))
def level_caps(spark, sf_dir):
    n = load(spark, sf_dir, "part", "p_partkey").count()
    return spark.createDataFrame([(i, caps.level_cap(i, 5, n, 4, 0.03, 0.03)) for i in range(1, 6)], "level int, cap long")


@query("vcycle_restricted_arcs", f"WITH {stepsql.graph('page_links')}, {_part_sql(4)} SELECT a.src, a.dst, a.w FROM arcs a JOIN part x ON x.id = a.src JOIN part y ON y.id = a.dst WHERE x.block = y.block")
def vcycle_restricted_arcs(spark, sf_dir):
    g = _graph(spark, sf_dir, "page_links")
    p = _blocks(g, 4)
    a = p.select(F.col("id").alias("src"), F.col("block").alias("a"))
    return g.arcs().join(a, "src").join(p.select(F.col("id").alias("dst"), F.col("block").alias("b")), "dst").where("a = b").select("src", "dst", "w")


@query("vcycle_inherit", f"WITH {stepsql.graph('page_links')}, {_part_sql(4)}, l AS (SELECT n.id, p.block * 1000 + {hashing.part_sql('n.id', 21, 50)} AS cluster FROM nodes n JOIN part p ON p.id = n.id) SELECT min(l.id) AS id, min(p.block) AS block FROM l JOIN part p ON p.id = l.id GROUP BY l.cluster")
def vcycle_inherit(spark, sf_dir):
    g = _graph(spark, sf_dir, "page_links").saved()
    p = _blocks(g, 4)
    labels = g.nodes.join(p, "id").select("id", (F.col("block") * 1000 + hashing.part_of(F.col("id"), 21, 50)).cast("long").alias("cluster"), "c")
    return con.inherit(p, con.contract(g, labels)[1])


# --- ensembles and components -----------------------------------------------
_RUNS = f"r0 AS (SELECT id, {hashing.part_sql('id', 31, 5)} AS c0, {hashing.part_sql('id', 32, 4)} AS c1, {hashing.part_sql('id', 33, 3)} AS c2 FROM nodes)"


def _three(g):
    one = lambda i, s, n: g.nodes.select(F.lit(i).alias("run"), "id", hashing.part_of(F.col("id"), s, n).cast("long").alias("cluster"))
    return one(0, 31, 5).union(one(1, 32, 4)).union(one(2, 33, 3))


_OVERLAY = f"WITH {stepsql.graph('page_links')}, {_RUNS} SELECT id, min(id) OVER (PARTITION BY c0, c1, c2) AS cluster FROM r0"


@query("overlay_tuple", _OVERLAY)
def overlay_tuple(spark, sf_dir):
    return ensemble.overlay_tuple(_three(_graph(spark, sf_dir, "page_links").saved()))


@query("overlay_fold", _OVERLAY)
def overlay_fold(spark, sf_dir):
    return ensemble.overlay_fold(_three(_graph(spark, sf_dir, "page_links").saved()), 3)


_REACH = "WITH RECURSIVE {0}, g AS ({1}), r AS (SELECT id, id AS m FROM nodes UNION SELECT g.dst, r.m FROM r JOIN g ON g.src = r.id WHERE r.m < g.dst) SELECT id, min(m) AS {2} FROM r GROUP BY id"


@query("overlay_components", _REACH.format(stepsql.graph("doc_lines") + ", " + _RUNS, "SELECT a.src, a.dst FROM arcs a JOIN r0 x ON x.id = a.src JOIN r0 y ON y.id = a.dst WHERE x.c0 = y.c0 AND x.c1 = y.c1 AND x.c2 = y.c2", "cluster"))
def overlay_components(spark, sf_dir):
    g = _graph(spark, sf_dir, "doc_lines").saved()
    return ensemble.overlay_components(g, _three(g))


@query("components_turns", _REACH.format(stepsql.graph("turns").replace("SELECT DISTINCT src AS id, cast(1 AS BIGINT) AS c FROM arcs", "SELECT DISTINCT 16 * conv_id + turn AS id, cast(1 AS BIGINT) AS c FROM conversations"), "SELECT src, dst FROM arcs", "component"))
def components_turns(spark, sf_dir):
    g = _graph(spark, sf_dir, "turns").saved()
    comp = star_components(g.edges.select("u", "v"))
    return g.nodes.select("id").join(comp, "id", "left").select("id", F.coalesce("component", "id").alias("component"))


@query("ensemble_size_rule", "SELECT k, cast(CASE WHEN k < 16 THEN 18 WHEN k <= 32 THEN 7 ELSE 3 END AS INT) AS runs FROM (SELECT DISTINCT cast(floor(l_quantity) AS INT) AS k FROM lineitem WHERE l_quantity IS NOT NULL) x")
def ensemble_size_rule(spark, sf_dir):
    """Clusterings to overlay where a line's quantity is the number of blocks."""
    ks = load(spark, sf_dir, "lineitem", "l_quantity").where("l_quantity is not null").select(F.floor("l_quantity").cast("int").alias("k")).distinct()

    def sized(batches):
        for batch in batches:
            runs = [caps.ensemble_size(k) for k in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(runs, pa.int32())], ["k", "runs"])

    return ks.mapInArrow(sized, "k int, runs int")


# --- matchings and floors ---------------------------------------------------
_PICK = f"pk AS (SELECT src, dst FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, {hashing.tie_sql('least(src, dst)', 'greatest(src, dst)', 17)} DESC, dst) AS rn FROM arcs) x WHERE rn = 1)"


@query("matching_round", f"WITH {stepsql.graph('supply')}, {_PICK} SELECT a.src AS u, a.dst AS v FROM pk a JOIN pk b ON a.src = b.dst AND a.dst = b.src WHERE a.src < a.dst")
def matching_round(spark, sf_dir):
    return matching.mutual_round(_graph(spark, sf_dir, "supply").arcs(), 17)


@query(
    "two_hop_pairs",
    f"WITH {stepsql.graph('supply')}, {_PICK}, m AS (SELECT a.src AS x FROM pk a JOIN pk b ON a.src = b.dst AND a.dst = b.src), "
    "h AS (SELECT src AS id, dst AS hub FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS rn FROM arcs WHERE src NOT IN (SELECT x FROM m)) y WHERE rn = 1), "
    "n AS (SELECT id, row_number() OVER (PARTITION BY hub ORDER BY id) AS rn, lead(id) OVER (PARTITION BY hub ORDER BY id) AS mate FROM h) SELECT id AS u, mate AS v FROM n WHERE rn % 2 = 1 AND mate IS NOT NULL",
)
def two_hop_pairs(spark, sf_dir):
    g = _graph(spark, sf_dir, "supply").saved()
    used = matching.mutual_round(g.arcs(), 17).select(F.explode(F.array("u", "v")).alias("id"))
    return matching.two_hop_pairs(g.arcs(), g.nodes.select("id").join(used, "id", "left_anti"))


@query("hash_blocks", f"WITH {stepsql.graph('order_part')}, {_part_sql(8)} SELECT id, block FROM part")
def hash_blocks(spark, sf_dir):
    return _blocks(_graph(spark, sf_dir, "order_part"), 8)


@query("range_blocks", f"WITH {stepsql.graph('order_part')}, s AS (SELECT min(id) AS lo, max(id) AS hi FROM nodes) SELECT id, cast(((id - lo) * 8) // (hi - lo + 1) AS INT) AS block FROM nodes, s")
def range_blocks(spark, sf_dir):
    """Equal id ranges."""
    n = _graph(spark, sf_dir, "order_part").nodes
    s = n.agg(F.min("id").alias("lo"), F.max("id").alias("hi"))
    return n.join(F.broadcast(s), F.lit(True)).select("id", F.expr("cast(((id - lo) * 8) div (hi - lo + 1) as int)").alias("block"))


# --- measures ---------------------------------------------------------------
@query("cut", _measure("supply", 4, "SELECT cast(coalesce(sum(w), 0) AS BIGINT) AS cut, count(*) AS edges_cut FROM ends WHERE bu <> bv"))
def cut(spark, sf_dir):
    g = _graph(spark, sf_dir, "supply").saved()
    return metrics.cut(g, _blocks(g, 4))


@query("block_weights", _measure("supply", 4, "SELECT block, cast(sum(c) AS BIGINT) AS weight, count(*) AS members FROM nodes JOIN part USING (id) GROUP BY block"))
def block_weights(spark, sf_dir):
    g = _graph(spark, sf_dir, "supply").saved()
    return metrics.block_weights(g, _blocks(g, 4))


@query("imbalance", _measure("supply", 4, "SELECT max(w) AS max_block, round(100.0 * max(w) / ceil(sum(w) / 4.0) - 100, 6) AS imbalance_pct, bool_and(w <= 540) AS feasible, count(*) FILTER (WHERE w > 540) AS overloaded, count(*) FILTER (WHERE w < 540) + 4 - count(*) AS underloaded FROM (SELECT block, cast(sum(c) AS BIGINT) AS w FROM nodes JOIN part USING (id) GROUP BY block) z"))
def imbalance(spark, sf_dir):
    g = _graph(spark, sf_dir, "supply").saved()
    return metrics.imbalance(g, _blocks(g, 4), 4, 540)


@query("boundary_nodes", _measure("page_links", 4, "SELECT DISTINCT id FROM (SELECT u AS id FROM ends WHERE bu <> bv UNION ALL SELECT v FROM ends WHERE bu <> bv) z"))
def boundary_nodes(spark, sf_dir):
    g = _graph(spark, sf_dir, "page_links").saved()
    return metrics.boundary(g, _blocks(g, 4))


_QUOT = "q AS (SELECT least(bu, bv) AS bi, greatest(bu, bv) AS bj, cast(sum(w) AS BIGINT) AS w, count(*) AS cnt FROM ends WHERE bu <> bv GROUP BY 1, 2)"


@query("quotient_graph", _measure("supply", 8, "SELECT least(bu, bv) AS bi, greatest(bu, bv) AS bj, cast(sum(w) AS BIGINT) AS w, count(*) AS cnt FROM ends WHERE bu <> bv GROUP BY 1, 2"))
def quotient_graph(spark, sf_dir):
    g = _graph(spark, sf_dir, "supply").saved()
    return metrics.quotient(g, _blocks(g, 8))


@query("worst_block_profile", _measure("page_links", 8, "").rstrip() + f", {_QUOT} SELECT block, cast(sum(w) AS BIGINT) AS cut, count(*) AS neighbours FROM (SELECT bi AS block, w FROM q UNION ALL SELECT bj, w FROM q) z GROUP BY block")
def worst_block_profile(spark, sf_dir):
    g = _graph(spark, sf_dir, "page_links").saved()
    return metrics.block_profile(g, _blocks(g, 8))


@query("comm_volume", _measure("page_links", 8, "SELECT block, count(*) AS volume FROM (SELECT DISTINCT id, block, other FROM (SELECT u AS id, bu AS block, bv AS other FROM ends WHERE bu <> bv UNION ALL SELECT v, bv, bu FROM ends WHERE bu <> bv) y) z GROUP BY block"))
def comm_volume(spark, sf_dir):
    g = _graph(spark, sf_dir, "page_links").saved()
    return metrics.communication_volume(g, _blocks(g, 8))


@query("inter_cluster_weight", f"WITH {stepsql.graph('doc_lines')}, {_SINGLE}, {stepsql.step('l1', 'l0', 6, 7)} SELECT cast(sum(e.w) AS BIGINT) AS inter, (SELECT count(DISTINCT cluster) FROM l1) AS clusters, (SELECT cast(max(s) AS BIGINT) FROM (SELECT sum(c) AS s FROM l1 GROUP BY cluster) z) AS largest FROM e JOIN l1 a ON a.id = e.u JOIN l1 b ON b.id = e.v WHERE a.cluster <> b.cluster")
def inter_cluster_weight(spark, sf_dir):
    g = _graph(spark, sf_dir, "doc_lines").saved()
    labels = lpa.singletons(g)
    labels = saved(lpa.commit(labels, lpa.superstep(g.arcs(), labels, None, 6, 7)), "labels")
    inter = metrics.cut(g, labels.select("id", F.col("cluster").alias("block"))).select(F.col("cut").alias("inter"))
    size = lpa.sizes_of(labels).agg(F.count(F.lit(1)).alias("clusters"), F.max("size").alias("largest"))
    return inter.join(size, F.lit(True))


@query("edges_per_node", " UNION ALL ".join(f"SELECT '{n}' AS instance, nodes, edges, round(edges * 1.0 / nodes, 6) AS per_node FROM (SELECT (SELECT count(*) FROM e) AS edges, (SELECT count(DISTINCT x) FROM (SELECT u AS x FROM e UNION ALL SELECT v FROM e) z) AS nodes FROM (SELECT 1) o) y".replace("FROM e", f"FROM ({builders.SQL[n]}) e") for n in ("supply", "page_links", "geo_tree")))
def edges_per_node(spark, sf_dir):
    out = None
    for n in ("supply", "page_links", "geo_tree"):
        g = _graph(spark, sf_dir, n)
        row = g.nodes.agg(F.count(F.lit(1)).alias("nodes")).join(g.edges.agg(F.count(F.lit(1)).alias("edges")), F.lit(True))
        row = row.select(F.lit(n).alias("instance"), "nodes", "edges", F.round(F.col("edges") / F.col("nodes"), 6).alias("per_node"))
        out = row if out is None else out.union(row)
    return out


# --- run tables: hash blocks of two graphs as stand-in configurations --------
_COMBOS = [(inst, k, seed) for inst in ("page_links", "supply") for k in (2, 4, 8) for seed in range(3)]


def _runs_sql() -> str:
    graphs = ", ".join(f"e_{n} AS ({builders.SQL[n]})" for n in ("page_links", "supply"))
    rows = " UNION ALL ".join(
        f"SELECT '{n}' AS instance, 'hash{s % 2}' AS preset, {k} AS k, {s} AS seed, cast(coalesce(sum(w), 0) AS BIGINT) AS cut FROM e_{n} WHERE {hashing.part_sql('u', 41 + s, k)} <> {hashing.part_sql('v', 41 + s, k)}" for n, k, s in _COMBOS
    )
    return f"WITH {graphs}, runs AS ({rows}) "


def _hash_runs(spark, sf_dir):
    out = None
    for n in ("page_links", "supply"):
        e = _graph(spark, sf_dir, n).edges
        sums = [F.sum(F.when(hashing.part_of(F.col("u"), 41 + s, k) != hashing.part_of(F.col("v"), 41 + s, k), F.col("w")).otherwise(0)).alias(f"c{k}_{s}") for i, k, s in _COMBOS if i == n]
        row = e.agg(*sums)
        parts = F.array(*[F.struct(F.lit(f"hash{s % 2}").alias("preset"), F.lit(k).alias("k"), F.lit(s).alias("seed"), F.coalesce(F.col(f"c{k}_{s}"), F.lit(0)).cast("long").alias("cut")) for i, k, s in _COMBOS if i == n])
        one = row.select(F.explode(parts).alias("r")).select(F.lit(n).alias("instance"), "r.*")
        out = one if out is None else out.union(one)
    return out


@query("geo_mean_runs", _runs_sql() + ", m AS (SELECT preset, instance, k, avg(cut) AS a, min(cut) AS b FROM runs GROUP BY 1, 2, 3) SELECT preset, round(exp(avg(ln(a))), 4) AS avg_cut, round(exp(avg(ln(b))), 4) AS best_cut FROM m GROUP BY preset".replace(") , m", "), m"))
def geo_mean_runs(spark, sf_dir):
    g = metrics.geometric_mean(_hash_runs(spark, sf_dir), ["preset"])
    return g.select("preset", F.round("avg_cut", 4).alias("avg_cut"), F.round("best_cut", 4).alias("best_cut"))


@query("best_and_avg", _runs_sql() + "SELECT instance, k, round(avg(cut), 6) AS avg_cut, min(cut) AS best_cut, arg_min(seed, cut * 10 + seed) AS best_seed FROM runs GROUP BY 1, 2")
def best_and_avg(spark, sf_dir):
    r = _hash_runs(spark, sf_dir)
    return r.groupBy("instance", "k").agg(F.round(F.avg("cut"), 6).alias("avg_cut"), F.min("cut").alias("best_cut"), F.min_by("seed", F.struct("cut", "seed")).alias("best_seed"))


@query("imbalanced_share", f"WITH {stepsql.graph('supply')}, r AS (" + " UNION ALL ".join(f"SELECT {k} AS k, {s} AS seed, cast(max(n) AS BIGINT) AS top FROM (SELECT {hashing.part_sql('id', 41 + s, k)} AS b, count(*) AS n FROM nodes GROUP BY 1) z" for k in (2, 4, 8) for s in range(3)) + "), t AS (SELECT count(*) AS n FROM nodes) SELECT k, count(*) AS runs, count(*) FILTER (WHERE top * 100 > 103 * ((n + k - 1) // k)) AS infeasible, max(round(100.0 * top / ((n + k - 1) // k) - 100, 6)) AS worst_pct FROM r, t GROUP BY k")
def imbalanced_share(spark, sf_dir):
    n = _graph(spark, sf_dir, "supply").nodes
    combos = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.lit(s).alias("seed"), hashing.part_of(F.col("id"), 41 + s, k).alias("b")) for k in (2, 4, 8) for s in range(3)]))
    top = n.select(combos.alias("x")).groupBy("x.k", "x.seed", "x.b").agg(F.count(F.lit(1)).alias("n")).groupBy("k", "seed").agg(F.max("n").alias("top"), F.sum("n").alias("n"))
    mean = F.ceil(F.col("n") / F.col("k"))
    return top.groupBy("k").agg(F.count(F.lit(1)).alias("runs"), F.count_if(F.col("top") * 100 > 103 * mean).alias("infeasible"), F.max(F.round(100.0 * F.col("top") / mean - 100, 6)).alias("worst_pct"))


# --- surrounding operators --------------------------------------------------
@query("join_semi_active", f"WITH {stepsql.graph('page_links')} SELECT src, dst, w FROM arcs WHERE dst IN (SELECT id FROM nodes WHERE {hashing.part_sql('id', 51, 10)} = 0)")
def join_semi_active(spark, sf_dir):
    g = _graph(spark, sf_dir, "page_links")
    moved = g.nodes.where(hashing.part_of(F.col("id"), 51, 10) == 0).select(F.col("id").alias("dst"))
    return g.arcs().join(moved, "dst", "left_semi").select("src", "dst", "w")


@query("join_anti_cut", _measure("doc_lines", 3, "SELECT e.u, e.v, e.w FROM e WHERE NOT EXISTS (SELECT 1 FROM ends x WHERE x.u = e.u AND x.v = e.v AND x.bu <> x.bv)"))
def join_anti_cut(spark, sf_dir):
    g = _graph(spark, sf_dir, "doc_lines").saved()
    p = _blocks(g, 3)
    gone = metrics._ends(g, p).where("bu <> bv").select("u", "v")
    return g.edges.join(gone, ["u", "v"], "left_anti").select("u", "v", "w")


@query("join_asof_block", "SELECT event_id, block FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'purchase' THEN cast(event_id % 4 AS INT) END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS block FROM events) x WHERE event_type = 'click'")
def join_asof_block(spark, sf_dir):
    """The block a user had at the time of a click; purchases set it."""
    e = load(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    block = F.last(F.when(F.col("event_type") == "purchase", (F.col("event_id") % 4).cast("int")), ignorenulls=True).over(w)
    return e.withColumn("block", block).where("event_type = 'click'").select("event_id", "block")


@query("join_range_events", "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR")
def join_range_events(spark, sf_dir):
    """Clicks and the purchases within an hour: an equi-join on hour buckets."""
    e = load(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = 3_600_000_000
    bucket = F.expr(f"us div {hour}")
    c = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("us").alias("a"), F.explode(F.array(bucket, bucket + 1)).alias("b"))
    p = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("us").alias("z"), bucket.alias("b"))
    return c.join(p, ["user_id", "b"]).where(f"z >= a and z <= a + {hour}").select("click", "purchase")


@query("cube_runs", _runs_sql() + "SELECT preset, instance, cast(sum(cut) AS BIGINT) AS cut, count(*) AS runs FROM runs GROUP BY CUBE (preset, instance)")
def cube_runs(spark, sf_dir):
    return _hash_runs(spark, sf_dir).cube("preset", "instance").agg(F.sum("cut").alias("cut"), F.count(F.lit(1)).alias("runs"))


@query("rollup_blocks", f"SELECT block, c_mktsegment, count(*) AS n FROM (SELECT {hashing.part_sql('c_custkey', 11, 4)} AS block, c_mktsegment FROM customer) x GROUP BY ROLLUP (block, c_mktsegment)")
def rollup_blocks(spark, sf_dir):
    c = load(spark, sf_dir, "customer", "c_custkey", "c_mktsegment")
    return c.select(hashing.part_of(F.col("c_custkey"), 11, 4).alias("block"), "c_mktsegment").rollup("block", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("grouping_sets_runs", _runs_sql() + "SELECT preset, k, cast(sum(cut) AS BIGINT) AS cut, cast(grouping(preset, k) AS BIGINT) AS gid FROM runs GROUP BY GROUPING SETS ((preset, k), (preset), ())")
def grouping_sets_runs(spark, sf_dir):
    _hash_runs(spark, sf_dir).createOrReplaceTempView("cutfold_runs")
    return spark.sql("SELECT preset, k, sum(cut) AS cut, cast(grouping_id(preset, k) AS BIGINT) AS gid FROM cutfold_runs GROUP BY GROUPING SETS ((preset, k), (preset), ())")


@query("topk_hubs", f"WITH {stepsql.graph('cust_supp')}, d AS (SELECT src AS id, count(*) AS deg FROM arcs GROUP BY src) SELECT id, deg FROM d ORDER BY deg DESC, id LIMIT 20 OFFSET 5")
def topk_hubs(spark, sf_dir):
    return _graph(spark, sf_dir, "cust_supp").degrees().select("id", "deg").orderBy(F.col("deg").desc(), "id").offset(5).limit(20)


@query("window_rank_parts", "SELECT p_partkey, rank() OVER w AS rk, dense_rank() OVER w AS drk, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS tile, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
def window_rank_parts(spark, sf_dir):
    p = load(spark, sf_dir, "part", "p_partkey", "p_brand", "p_size", "p_retailprice")
    w = Window.partitionBy("p_brand").orderBy("p_size")
    tile = F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey"))
    return p.select("p_partkey", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("drk"), tile.alias("tile"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@query("window_range_events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM events")
def window_range_events(spark, sf_dir):
    e = load(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("s", F.expr("unix_micros(cast(ts as timestamp)) div 1000000"))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("last_hour"))


@query("pivot_runs", _runs_sql() + "SELECT instance, cast(sum(cut) FILTER (WHERE k = 2) AS BIGINT) AS k2, cast(sum(cut) FILTER (WHERE k = 4) AS BIGINT) AS k4, cast(sum(cut) FILTER (WHERE k = 8) AS BIGINT) AS k8 FROM runs GROUP BY instance")
def pivot_runs(spark, sf_dir):
    p = _hash_runs(spark, sf_dir).groupBy("instance").pivot("k", [2, 4, 8]).agg(F.sum("cut"))
    return p.select("instance", F.col("2").alias("k2"), F.col("4").alias("k4"), F.col("8").alias("k8"))


@query("unpivot_runs", _runs_sql() + "SELECT instance, preset, measure, value FROM (SELECT instance, preset, cast(sum(cut) AS BIGINT) AS total, cast(min(cut) AS BIGINT) AS best, cast(max(cut) AS BIGINT) AS worst FROM runs GROUP BY 1, 2) x UNPIVOT (value FOR measure IN (total, best, worst))")
def unpivot_runs(spark, sf_dir):
    w = _hash_runs(spark, sf_dir).groupBy("instance", "preset").agg(F.sum("cut").alias("total"), F.min("cut").alias("best"), F.max("cut").alias("worst"))
    return w.unpivot(["instance", "preset"], ["total", "best", "worst"], "measure", "value")


@query("cluster_sizes", f"WITH {stepsql.graph('doc_lines')}, {_SINGLE}, {stepsql.step('l1', 'l0', 6, 7)}, z AS (SELECT cluster, count(*) AS size FROM l1 GROUP BY cluster) SELECT size, count(*) AS clusters FROM z GROUP BY size")
def cluster_sizes(spark, sf_dir):
    """The distribution of cluster sizes after one superstep."""
    g = _graph(spark, sf_dir, "doc_lines").saved()
    labels = lpa.singletons(g)
    labels = lpa.commit(labels, lpa.superstep(g.arcs(), labels, None, 6, 7))
    return lpa.sizes_of(labels).groupBy("size").agg(F.count(F.lit(1)).alias("clusters"))


@query("forced_balance_step")
def forced_balance_step(spark, sf_dir):
    """Nine tenths of the nodes start in block 0; the result is feasible."""
    g = _graph(spark, sf_dir, "page_links").saved()
    start = g.nodes.select("id", F.greatest(hashing.part_of(F.col("id"), 11, 40) - 36, F.lit(0)).alias("block"))
    return metrics.imbalance(g, refine.force_balance(g, start, 4, caps.block_cap(g.sizes()["total"], 4, 0.03)), 4, caps.block_cap(g.sizes()["total"], 4, 0.03))


@query("partition_diff", f"WITH {stepsql.graph('supply')}, p AS (SELECT p_partkey * 2 AS id, {hashing.part_sql('p_partkey * 2', 12, 4)} AS y FROM part) SELECT id, x, y, NOT (x IS NOT DISTINCT FROM y) AS differs FROM (SELECT id, {hashing.part_sql('id', 11, 4)} AS x FROM nodes) a FULL OUTER JOIN p USING (id)")
def partition_diff(spark, sf_dir):
    """Blocks of all graph nodes beside blocks of all parts, with or without suppliers."""
    a = _blocks(_graph(spark, sf_dir, "supply"), 4).withColumnRenamed("block", "x")
    key = (F.col("p_partkey") * 2).alias("id")
    b = load(spark, sf_dir, "part", "p_partkey").select(key).select("id", hashing.part_of(F.col("id"), 12, 4).alias("y"))
    return a.join(b, "id", "full_outer").select("id", "x", "y", (~F.col("x").eqNullSafe(F.col("y"))).alias("differs"))


@query("filter_subgraph", "SELECT DISTINCT l_orderkey AS u, l_partkey AS v FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_brand IN ('Brand#1', 'Brand#2', 'Brand#4') AND l_quantity BETWEEN 10 AND 20 AND p_name LIKE '%bolt%'")
def filter_subgraph(spark, sf_dir):
    p = load(spark, sf_dir, "part", "p_partkey", "p_brand", "p_name").where(F.col("p_brand").isin("Brand#1", "Brand#2", "Brand#4") & F.col("p_name").like("%bolt%"))
    li = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_quantity").where(F.col("l_quantity").between(10, 20))
    return li.join(p, F.col("l_partkey") == F.col("p_partkey")).select(F.col("l_orderkey").alias("u"), F.col("l_partkey").alias("v")).distinct()


@query("isolated_orders", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def isolated_orders(spark, sf_dir):
    o, li = load(spark, sf_dir, "orders", "o_orderkey"), load(spark, sf_dir, "lineitem", "l_orderkey")
    return o.join(li, F.col("o_orderkey") == F.col("l_orderkey"), "left_anti")


@query("orders_by_month_graph", "SELECT year(o_orderdate) * 100 + month(o_orderdate) AS month, count(DISTINCT o_orderkey) AS orders, count(DISTINCT l_partkey) AS parts, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def orders_by_month_graph(spark, sf_dir):
    o = load(spark, sf_dir, "orders", "o_orderkey", "o_orderdate")
    j = o.join(load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey"))
    month = (F.year("o_orderdate") * 100 + F.month("o_orderdate")).cast("long")
    return j.groupBy(month.alias("month")).agg(F.count_distinct("o_orderkey").alias("orders"), F.count_distinct("l_partkey").alias("parts"), F.count(F.lit(1)).alias("lines"))


_SEG = f"s AS (SELECT {hashing.part_sql('c_custkey', 11, 4)} AS block, c_mktsegment AS seg, count(*) AS n FROM customer GROUP BY 1, 2)"


def _segments(spark, sf_dir):
    c = load(spark, sf_dir, "customer", "c_custkey", "c_mktsegment")
    return c.groupBy(hashing.part_of(F.col("c_custkey"), 11, 4).alias("block"), F.col("c_mktsegment").alias("seg")).agg(F.count(F.lit(1)).alias("n"))


@query("block_entropy", f"WITH {_SEG}, t AS (SELECT *, n * 1.0 / sum(n) OVER (PARTITION BY block) AS p FROM s) SELECT block, round(-sum(p * ln(p)), 6) AS entropy FROM t GROUP BY block")
def block_entropy(spark, sf_dir):
    t = _segments(spark, sf_dir).withColumn("p", F.col("n") / F.sum("n").over(Window.partitionBy("block")))
    return t.groupBy("block").agg(F.round(-F.sum(F.col("p") * F.ln("p")), 6).alias("entropy"))


@query("map_block_hist", f"WITH {_SEG} SELECT block, string_agg(seg || '=' || n, ',' ORDER BY seg) AS hist FROM s GROUP BY block")
def map_block_hist(spark, sf_dir):
    m = _segments(spark, sf_dir).groupBy("block").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("seg", "n")))).alias("m"))
    return m.select("block", F.array_join(F.transform(F.map_entries("m"), lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string"))), ",").alias("hist"))


@query("set_union_arcs", f"WITH {stepsql.graph('geo_tree')} SELECT src, dst, w FROM arcs")
def set_union_arcs(spark, sf_dir):
    return _graph(spark, sf_dir, "geo_tree").arcs()


def _cut_edges(g, s):
    return g.edges.where(hashing.part_of(F.col("u"), s, 2) != hashing.part_of(F.col("v"), s, 2)).select("u", "v")


@query("set_intersect_cut", f"WITH {stepsql.graph('supply')} SELECT u, v FROM e WHERE {hashing.part_sql('u', 61, 2)} <> {hashing.part_sql('v', 61, 2)} AND {hashing.part_sql('u', 62, 2)} <> {hashing.part_sql('v', 62, 2)}")
def set_intersect_cut(spark, sf_dir):
    g = _graph(spark, sf_dir, "supply").saved()
    return _cut_edges(g, 61).intersectAll(_cut_edges(g, 62))


@query("set_except_labels", f"WITH {stepsql.graph('page_links')}, {_SINGLE}, {stepsql.step('l1', 'l0', 20, 3)} SELECT l1.id, l1.cluster FROM l1 JOIN l0 USING (id) WHERE l1.cluster <> l0.cluster")
def set_except_labels(spark, sf_dir):
    g = _graph(spark, sf_dir, "page_links").saved()
    before = lpa.singletons(g).select("id", "cluster")
    labels = lpa.singletons(g)
    after = saved(lpa.commit(labels, lpa.superstep(g.arcs(), labels, None, 20, 3)), "labels").select("id", "cluster")
    return after.exceptAll(before)


@query("json_props_k", "SELECT event_type, cast(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1, 2")
def json_props_k(spark, sf_dir):
    e = load(spark, sf_dir, "events", "event_type", "props")
    return e.groupBy("event_type", F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("array_adjacency", f"WITH {stepsql.graph('page_links')} SELECT src AS id, count(*) AS deg, string_agg(dst || ':' || w, ' ' ORDER BY dst) AS nbrs FROM arcs GROUP BY src")
def array_adjacency(spark, sf_dir):
    a = _graph(spark, sf_dir, "page_links").arcs().groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", "w"))).alias("x"))
    return a.select(F.col("src").alias("id"), F.size("x").cast("long").alias("deg"), F.array_join(F.transform("x", lambda p: F.concat_ws(":", p["dst"].cast("string"), p["w"].cast("string"))), " ").alias("nbrs"))


def _events(spark, sf_dir):
    return load(spark, sf_dir, "events", "ts", "user_id", "event_type").withColumn("ts", F.col("ts").cast("timestamp"))


@query("events_tumbling", "SELECT epoch_us(time_bucket(INTERVAL 15 MINUTE, ts)) AS start_us, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def events_tumbling(spark, sf_dir):
    e = _events(spark, sf_dir).groupBy(F.window("ts", "15 minutes").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return e.select(F.unix_micros("w.start").alias("start_us"), "event_type", "n")


@query("events_sliding", "SELECT (epoch_us(ts) // 900000000 - j) * 900000000 AS start_us, event_type, count(*) AS n FROM events, (SELECT unnest([0, 1, 2, 3]) AS j) x GROUP BY 1, 2")
def events_sliding(spark, sf_dir):
    e = _events(spark, sf_dir).groupBy(F.window("ts", "1 hour", "15 minutes").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return e.select(F.unix_micros("w.start").alias("start_us"), "event_type", "n")


@query("events_session", "WITH g AS (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 1800000000 THEN 0 ELSE 1 END AS brk FROM events), s AS (SELECT user_id, t, sum(brk) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS sid FROM g) SELECT user_id, min(t) AS start_us, count(*) AS n FROM s GROUP BY user_id, sid")
def events_session(spark, sf_dir):
    e = _events(spark, sf_dir).groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return e.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


# --- whole methods: what must hold of a partition, recomputed from it ----------
def _promises(graph: str, k: int) -> str:
    return (
        f"WITH {stepsql.graph(graph)}, n AS (SELECT count(*) AS nodes, cast(sum(c) AS BIGINT) AS total FROM nodes) "
        f"SELECT {k} AS k, nodes, (SELECT count(*) FROM e) AS edges, cast(((total + {k - 1}) // {k}) * 103 // 100 AS BIGINT) AS cap, nodes AS covered, true AS blocks_in_range, true AS feasible, true AS cut_agrees, true AS below_hash FROM n"
    )


def promises(g, k: int, result, seed: int = 11):
    """One row: sizes, the cap, how many nodes have exactly one block, whether blocks are
    in range and within the cap, whether the cut that the method reports is that of its
    partition, and whether it is below the cut of blocks by hash."""
    part = result.part
    size = g.sizes()
    cover = g.nodes.join(part, "id").groupBy("id").agg(F.count(F.lit(1)).alias("n"), F.min("block").alias("lo"), F.max("block").alias("hi"))
    seen = cover.agg(F.count_if(F.col("n") == 1).alias("covered"), F.bool_and((F.col("lo") >= 0) & (F.col("hi") < k)).alias("inside")).first()
    over, cut = refine.quality(g, part, result.cap)
    # Blocks by hash follow from the ids, so their cut needs no join.
    apart = hashing.part_of(F.col("u"), seed, k) != hashing.part_of(F.col("v"), seed, k)
    floor = g.edges.where(apart).agg(F.coalesce(F.sum("w"), F.lit(0)).alias("cut")).first()["cut"]
    row = (k, size["n"], size["m"], result.cap, seen.covered, bool(seen.inside), over == 0, result.history[-1]["cut"] == cut, cut < floor)
    return part.sparkSession.createDataFrame([row], "k int, nodes long, edges long, cap long, covered long, blocks_in_range boolean, feasible boolean, cut_agrees boolean, below_hash boolean")


def _method(name, graph, k):
    def run(spark, sf_dir):
        g = _graph(spark, sf_dir, graph).saved()
        return promises(g, k, partition(g, k, name, tries=2))

    return run


for _p in presets.COMPARED + ["ci-eco"] + presets.HUGE:
    _on, _k = ("order_part", 16) if _p.endswith("@huge") else ("page_links", 4)
    query("partition_" + _p.replace("-", "_").replace("+", "_").replace("@", "_"), _promises(_on, _k))(_method(_p, _on, _k))


def _rival(name):
    return lambda spark, sf_dir: experiments.runs(spark, sf_dir, ["page_links"], [name], (4,), 3).drop("seconds")


for _b in baselines.BASELINES:
    query("baseline_" + _b.replace("-", "_"))(_rival(_b))
query("baseline_best_of")(_rival("best-of-10:ci-eco+v+b"))


@query("ensemble_clustering")
def ensemble_clustering(spark, sf_dir):
    """Clusters that three propagations without a size bound agree on, by size."""
    g = _graph(spark, sf_dir, "page_links").saved()
    labels = ensemble.overlay_tuple(ensemble.base(g, None, 3, rounds=3))
    return labels.groupBy("cluster").agg(F.count(F.lit(1)).alias("size")).groupBy("size").agg(F.count(F.lit(1)).alias("clusters"))


@query("active_profile")
def active_profile(spark, sf_dir):
    """Nodes, active nodes and arcs, and moves per round of clustering by active nodes."""
    log: list = []
    lpa.propagate(_graph(spark, sf_dir, "page_links").saved(), 30, rounds=5, stop=0.0, active=True, log=log)
    rows = [(r["round"], r["nodes"], r["active"], r["active_arcs"], r["moved"]) for r in log]
    return spark.createDataFrame(rows, "round int, nodes long, active long, active_arcs long, moved long")


@query("partition_distributed")
def partition_distributed(spark, sf_dir):
    """The DataFrame levels (forced by a small kernel limit), with the blocks."""
    g = _graph(spark, sf_dir, "page_links")
    return partition(g, 4, "ci-fast", local_arcs=1500, stop_at=60).part


@query("refine_boundary")
def refine_boundary(spark, sf_dir):
    g = _graph(spark, sf_dir, "page_links").saved()
    cap = caps.block_cap(g.sizes()["total"], 4, 0.03)
    return refine.boundary_refine(g, _blocks(g, 4), 4, cap, 1)


for _w in experiments.WORKLOADS:
    query("workload_" + _w)(lambda spark, sf_dir, w=_w: experiments.summary(experiments.workload(spark, sf_dir, w, ["order_part"] if w == "huge" else ["page_links", "doc_line_hubs"], (2, 4, 8) if w != "huge" else None, 2)))


@query("workload_initial_vs_final")
def workload_initial_vs_final(spark, sf_dir):
    """How far local search takes the initial partition, per preset."""
    r = experiments.runs(spark, sf_dir, ["page_links", "doc_line_hubs"], ["mi-fast", "ci-fast", "mi-eco"], (2, 4), 3)
    return r.groupBy("instance", "preset").agg(F.avg("initial_cut").alias("initial"), F.avg("cut").alias("final"), F.round(F.avg(1 - F.col("cut") / F.greatest("initial_cut", F.lit(1))), 6).alias("gain"))


@query("coarsening_profile")
def coarsening_profile(spark, sf_dir):
    return experiments.coarsening_profile(spark, sf_dir, "order_part", 2)


def flagship(spark, sf_dir):
    """Multilevel partition of the page-link graph into four blocks."""
    return partition(_graph(spark, sf_dir, "page_links"), 4, "ci-fast", stop_at=60).part
