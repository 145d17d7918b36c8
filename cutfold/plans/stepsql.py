"""SQL text for graphs, supersteps and measures, for engines other than Spark."""

from __future__ import annotations

from cutfold.functions.hashing import part_sql, tie_sql
from cutfold.sources.builders import SQL as EDGES


def graph(name: str) -> str:
    """CTEs ``e, arcs, nodes`` of a table graph (without WITH)."""
    return (
        f"e AS ({EDGES[name]}), "
        "arcs AS (SELECT u AS src, v AS dst, w FROM e UNION ALL SELECT v, u, w FROM e), "
        "nodes AS (SELECT DISTINCT src AS id, cast(1 AS BIGINT) AS c FROM arcs)"
    )


def hash_labels(name: str, parts: int, s: int, offset: int = 0) -> str:
    """A CTE of labels by hash: ``(id, cluster, c)``."""
    return f"{name} AS (SELECT id, cast({part_sql('id', s, parts)} + {offset} AS BIGINT) AS cluster, c FROM nodes)"


def step(out: str, labels: str, cap: int | None, s: int, who: str = "SELECT id FROM nodes", arcs: str = "arcs", over: bool = False) -> str:
    """CTEs of one superstep: ``<out>_moves`` and the labels ``<out>``."""
    limit = 2**62 if cap is None else cap
    own_ok = "(n.cluster = o.cluster AND coalesce(so.size, 0) <= {0})".format(limit) if over else "n.cluster = o.cluster"
    forced = (
        f"{out}_go AS (SELECT p.*, h.size - {limit} AS shed, coalesce(sum(p.c) OVER (PARTITION BY p.source, h.size > {limit} ORDER BY p.loss, p.tie DESC, p.id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS gone "
        f"FROM {out}_wants p JOIN {out}_sizes h ON h.cluster = p.source), "
        f"{out}_prop AS (SELECT * FROM {out}_go WHERE shed <= 0 OR gone < shed OR loss < 0), "
        if over
        else f"{out}_prop AS (SELECT * FROM {out}_wants), "
    )
    return (
        f"{out}_who AS ({who}), "
        f"{out}_sizes AS (SELECT cluster, sum(c) AS size FROM {labels} GROUP BY cluster), "
        f"{out}_conn AS (SELECT a.src, l.cluster, sum(a.w) AS strength FROM {arcs} a JOIN {labels} l ON a.dst = l.id WHERE a.src IN (SELECT id FROM {out}_who) GROUP BY a.src, l.cluster), "
        f"{out}_rank AS (SELECT n.src, n.cluster, o.cluster AS own, o.c, n.strength, {tie_sql('n.src', 'n.cluster', s)} AS tie, "
        f"{own_ok} AS stays FROM {out}_conn n JOIN {labels} o ON o.id = n.src LEFT JOIN {out}_sizes so ON so.cluster = o.cluster LEFT JOIN {out}_sizes t ON t.cluster = n.cluster "
        f"WHERE {own_ok} OR (n.cluster <> o.cluster AND t.size + o.c <= {limit})), "
        f"{out}_first AS (SELECT *, row_number() OVER (PARTITION BY src ORDER BY strength DESC, tie DESC, cluster) AS rn FROM {out}_rank), "
        f"{out}_wants AS (SELECT f.src AS id, f.c, f.own AS source, f.cluster AS target, f.strength, f.tie, coalesce(i.strength, 0) - f.strength AS loss FROM {out}_first f "
        f"LEFT JOIN {out}_conn i ON i.src = f.src AND i.cluster = f.own WHERE f.rn = 1 AND f.cluster <> f.own), "
        + forced
        + f"{out}_run AS (SELECT p.*, {limit} - s.size AS room, sum(p.c) OVER (PARTITION BY p.target ORDER BY p.strength DESC, p.tie DESC, p.id ROWS UNBOUNDED PRECEDING) AS need FROM {out}_prop p JOIN {out}_sizes s ON s.cluster = p.target), "
        f"{out}_moves AS (SELECT id, c, source, target, strength, tie FROM {out}_run WHERE need <= room), "
        f"{out} AS (SELECT l.id, coalesce(m.target, l.cluster) AS cluster, l.c FROM {labels} l LEFT JOIN {out}_moves m ON m.id = l.id)"
    )


def half(s: int, which: int, parts: int = 2) -> str:
    """The ids of one hash wave."""
    return f"SELECT id FROM nodes WHERE {part_sql('id', s, parts)} = {which}"

