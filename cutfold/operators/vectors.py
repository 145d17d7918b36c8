"""The supersteps on graphs whose nodes fit a task's memory and whose arcs do not.

A value per node (label, weight, id) is an array that the driver holds and sends out;
the arcs stay in a saved table, a row per chunk of nodes, as the bytes of sorted arrays.
A wave is one scan of that table: a task proposes moves for the nodes of its chunks, the
driver admits them. So no wave shuffles, and no arc is ever a row of a table. Choices,
ties and admissions are those of :mod:`lpa`, :mod:`matching` and :mod:`contract`, and
so are the results. Nodes are numbered in the order of their ids.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutfold.functions import hashing
from cutfold.functions.storage import drop_saved, saved
from cutfold.kernels.csr import Csr
from cutfold.kernels.waves import _strengths
from cutfold.operators.graph import WeightedGraph
from cutfold.operators.matching import BIN

#: Nodes up to which a value per node is held by the driver and by every task.
NODES = 16_000_000
#: Arcs that a chunk should have, and may have at most; a node's arcs are in one chunk.
CHUNK_ARCS, MOST_ARCS = 500_000, 6_000_000

_PIECES = "chunk int, src binary, dst binary, w binary"
_CHUNKS = "arcs long, degrees binary, node binary, count binary, dst binary, w binary"


@dataclass
class VectorGraph:
    """``ids`` ascending, node weights ``c``, the table of chunks, the number of edges,
    and the histogram of degrees above 0 (``degree``, ``many``)."""

    spark: SparkSession
    ids: np.ndarray
    c: np.ndarray
    chunks: DataFrame
    m: int
    degree: np.ndarray
    many: np.ndarray
    sent: Broadcast

    @property
    def n(self) -> int:
        return len(self.ids)

    def size(self) -> dict:
        return {"n": self.n, "m": self.m, "total": int(self.c.sum()), "heaviest": int(self.c.max()) if self.n else 0}

    def drop(self) -> None:
        drop_saved(self.chunks)
        self.sent.destroy()


def _as_chunks(node: np.ndarray, chunks: int) -> np.ndarray:
    return ((node.astype(np.int64) * 2654435761 >> 15) % chunks).astype(np.uint16)


def _packed(w: np.ndarray) -> bytes:
    """Weights as bytes, of as few kinds as hold them; none where all are 1."""
    top = int(w.max(initial=1))
    return b"" if top == 1 else w.astype(np.int32 if top < 2**31 else np.int64).tobytes()


def _unpacked(data, many: int) -> np.ndarray:
    if not len(data):
        return np.ones(many, np.int64)
    return np.frombuffer(data, np.int32 if len(data) == 4 * many else np.int64).astype(np.int64)


def _dealt(src, dst, w, chunks: int) -> pa.RecordBatch:
    """The arcs by the chunk of their source, a row of bytes each."""
    at = _as_chunks(src, chunks)
    order = np.argsort(at, kind="stable")
    at, src, dst, w = at[order], src[order].astype(np.int32), dst[order].astype(np.int32), w[order]
    first = np.flatnonzero(np.concatenate((np.ones(min(len(at), 1), bool), at[1:] != at[:-1])))
    last = np.append(first[1:], len(at))
    cols = [pa.array(at[first].astype(np.int32))]
    cols += [pa.array([x[a:b].tobytes() for a, b in zip(first, last)], pa.binary()) for x in (src, dst)]
    cols.append(pa.array([_packed(w[a:b]) for a, b in zip(first, last)], pa.binary()))
    return pa.RecordBatch.from_arrays(cols, ["chunk", "src", "dst", "w"])


def _merged(n: int):
    """Pieces of one chunk -> its row. Where a chunk is too large, only its length is
    told, and the caller takes the other form."""

    def run(batches):
        pieces, arcs = [], 0
        for batch in batches:
            _, src, dst, w = (c.to_pylist() for c in batch.columns)
            for x in zip(src, dst, w):
                arcs += len(x[0]) // 4
                if arcs <= MOST_ARCS:
                    pieces.append(x)
        if not arcs:
            return
        empty = b""
        if arcs > MOST_ARCS:
            row = [arcs, empty, empty, empty, empty, empty]
        else:
            key = np.frombuffer(b"".join(x[0] for x in pieces), np.int32).astype(np.int64) * n
            key += np.frombuffer(b"".join(x[1] for x in pieces), np.int32)
            w = np.concatenate([_unpacked(x[2], len(x[0]) // 4) for x in pieces])
            del pieces
            node, dst, w = _summed(key, w, n)
            head = np.flatnonzero(np.concatenate(([True], node[1:] != node[:-1])))
            count = np.diff(np.append(head, len(node)))
            degrees = np.concatenate(np.unique(count, return_counts=True)).astype(np.int64)
            row = [len(dst), *(x.tobytes() for x in (degrees, node[head].astype(np.int32), count.astype(np.int32), dst.astype(np.int32))), _packed(w)]
        yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64() if i == 0 else pa.binary()) for i, x in enumerate(row)], ["arcs", "degrees", "node", "count", "dst", "w"])

    return run


def _summed(key: np.ndarray, w: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Arcs by source and target, those between the same two as one."""
    order = np.argsort(key)
    key, w = key[order], w[order]
    head = np.concatenate((np.ones(min(len(key), 1), bool), key[1:] != key[:-1]))
    if not head.all():
        head = np.flatnonzero(head)
        key, w = key[head], np.add.reduceat(w, head)
    src = key // n
    return src, key - src * n, w


def _made(spark, ids, c, pieces: DataFrame, chunks: int) -> VectorGraph | None:
    """None where a chunk would be too large."""
    table = saved(pieces.repartitionById(chunks, F.col("chunk")).mapInArrow(_merged(max(1, len(ids))), _CHUNKS), "chunks")
    told = table.select("arcs", "degrees").collect()
    if any(not r.degrees for r in told):
        drop_saved(table)
        return None
    both = [np.frombuffer(bytes(r.degrees), np.int64).reshape(2, -1) for r in told]
    both = np.concatenate(both, axis=1) if both else np.zeros((2, 0), np.int64)
    degree, at = np.unique(both[0], return_inverse=True)
    many = np.bincount(at, both[1], minlength=len(degree)).astype(np.int64)
    return VectorGraph(spark, ids, c, table, sum(r.arcs for r in told) // 2, degree, many, spark.sparkContext.broadcast((ids, None if (c == 1).all() else c)))


def _chunks_for(arcs: int) -> int:
    return min(30_000, max(12, -(-arcs // CHUNK_ARCS)))


def load(g: WeightedGraph, size: dict) -> VectorGraph | None:
    """The graph in this form, or None where it has too many nodes or too large hubs."""
    if size["n"] > NODES:
        return None
    spark = g.nodes.sparkSession
    nodes = g.nodes.select("id", "c").toArrow()
    ids, c = nodes.column("id").to_numpy(), nodes.column("c").to_numpy()
    del nodes
    if (c == 1).all():
        ids = np.sort(ids)
    else:
        order = np.argsort(ids)
        ids, c = ids[order], c[order]
        del order
    sent, chunks = spark.sparkContext.broadcast(ids), _chunks_for(2 * size["m"])

    def numbered(x):
        order = np.argsort(x)
        out = np.empty(len(x), np.int32)
        out[order] = np.searchsorted(sent.value, x[order])
        return out

    def dealt(rows):
        u, v, w = (pa.chunked_array([b.column(i) for b in rows]).to_numpy() for i in range(3))
        u, v = numbered(u), numbered(v)
        return _dealt(np.concatenate((u, v)), np.concatenate((v, u)), np.concatenate((w, w)), chunks)

    def pieces(batches):
        rows, held = [], 0
        for batch in batches:
            rows.append(batch)
            held += batch.num_rows
            if held >= CHUNK_ARCS // 2:
                yield dealt(rows)
                rows, held = [], 0
        if held:
            yield dealt(rows)

    out = _made(spark, ids, c, g.edges.select("u", "v", "w").mapInArrow(pieces, _PIECES), chunks)
    sent.destroy()
    return out


def _arrays(batch):
    """Per chunk ``node, count, dst, w``."""
    names = ("node", "count", "dst", "w")
    for row in zip(*(batch.column(batch.schema.get_field_index(x)) for x in names)):
        node, count, dst = (np.frombuffer(x.as_buffer(), np.int32) for x in row[:3])
        yield node, count, dst, _unpacked(row[3].as_buffer(), len(dst))


def _scanned(g: VectorGraph, work, state: dict, kinds: list) -> list[np.ndarray]:
    """``work(graph, state, node, count, dst, w)`` on every chunk, the arrays that it
    returns put together."""
    sent, graph = g.spark.sparkContext.broadcast(state), g.sent

    def run(batches):
        for batch in batches:
            for chunk in _arrays(batch):
                found = work(graph.value, sent.value, *chunk)
                if found is not None:
                    yield pa.RecordBatch.from_arrays([pa.array([x.astype(t).tobytes()], pa.binary()) for x, t in zip(found, kinds)], names)

    names = [f"x{i}" for i in range(len(kinds))]
    got = g.chunks.select("node", "count", "dst", "w").mapInArrow(run, ", ".join(f"{x} binary" for x in names)).toArrow()
    sent.destroy()
    return [np.frombuffer(b"".join(got.column(i).to_pylist()), t) for i, t in enumerate(kinds)]


def _best(row, to, strength, tie_of):
    """Per row the place of the greatest (strength, tie, smallest target); sorted input."""

    def tops(at, by):
        first = np.flatnonzero(np.concatenate(([True], row[at][1:] != row[at][:-1])))
        return at[by == np.repeat(np.maximum.reduceat(by, first), np.diff(np.append(first, len(at))))]

    at = tops(np.arange(len(row)), strength)
    tie = np.zeros(len(row), np.int64)
    tie[at] = tie_of(row[at], to[at])
    at = tops(at, tie[at])
    at = at[np.concatenate(([True], row[at][1:] != row[at][:-1]))]
    return at, tie[at]


def _pair_tie(a, b, s: int):
    return hashing.mix_array(hashing.mix_array(a, s) + hashing.mix_array(b, (s + 1) % hashing.P), (s + 2) % hashing.P)


def _proposals(graph, t, node, count, dst, w):
    """The moves that a chunk's nodes of one wave want."""
    (ids, c), label, s = graph, t["label"], t["salt"]
    who = hashing.part_array(ids[node], s, t["sub"]) == t["part"]
    if t["bucket"] is not None:
        degree, bucket, x = t["bucket"]
        who &= bucket[np.searchsorted(degree, count)] == x
    if t["moved"] is not None:
        start = np.cumsum(count, dtype=np.int64) - count
        near = np.logical_or.reduceat(t["moved"][dst], start)
        who &= near if t["heavy"] is None else near | t["heavy"][label[node]]
    if not who.any():
        return None
    arcs = np.repeat(who, count)
    node, count, dst, w = node[who], count[who], dst[arcs], w[arcs]
    src = np.repeat(np.arange(len(node)), count)
    if (side := t["within"]) is not None:
        same = side[node][src] == side[dst]
        src, dst, w = src[same], dst[same], w[same]
        if not len(src):
            return None
    few = t["few"]
    row, to, strength = _strengths(src, label[dst].astype(np.int64), w, few or len(ids), few)
    own = label[node].astype(np.int64)
    mine = np.ones(len(node), np.int64) if c is None else c[node]
    here = to == own[row]
    inside, has = np.zeros(len(node), np.int64), np.zeros(len(node), bool)
    inside[row[here]], has[row[here]] = strength[here], True
    full, size = t["full"]
    ok = ~here
    if len(full):
        at = np.minimum(np.searchsorted(full, to), len(full) - 1)
        ok &= (full[at] != to) | (size[at] + mine[row] <= t["cap"])
    row, to, strength = row[ok], to[ok], strength[ok]
    if not len(row):
        return None

    def tie_of(r, x):
        return _pair_tie(ids[node[r]], x if few else ids[x], s)

    at, tie = _best(row, to, strength, tie_of)
    row, to, strength = row[at], to[at], strength[at]
    leave = ~has[row] | (strength > inside[row])
    if t["heavy"] is not None:
        leave |= t["heavy"][own[row]]
    even = np.flatnonzero(~leave & (strength == inside[row]))
    stay = tie_of(row[even], own[row[even]])
    leave[even] = (tie[even] > stay) | ((tie[even] == stay) & (to[even] < own[row[even]]))
    row, to, strength, tie = row[leave], to[leave], strength[leave], tie[leave]
    moves = node[row], to, strength, tie
    return (*moves, inside[row] - strength) if few else moves


def _running(group, c):
    """Weight of the rows of a group up to each row; ``group`` in runs."""
    run = np.cumsum(c)
    first = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1])))
    return run - np.repeat(run[first] - c[first], np.diff(np.append(first, len(group))))


def _admitted(node, to, strength, tie, c, size, cap):
    """Of each target's proposals, by strength, tie and node, those that fit together."""
    tight = np.bincount(to, c[node])[to] > cap - size[to]
    if not tight.any():
        return node, to
    free = ~tight
    at = np.flatnonzero(tight)
    at = at[np.lexsort((node[at], -tie[at], -strength[at], to[at]))]
    at = at[_running(to[at], c[node[at]]) <= (cap - size)[to[at]]]
    return np.concatenate((node[free], node[at])), np.concatenate((to[free], to[at]))


#: Node, target, strength, tie, and between blocks the loss.
_MOVES = [np.int32, np.int32, np.int64, np.int32, np.int64]


def _moves(g: VectorGraph, label, size, cap: int, s: int, sub: int, part: int, bucket=None, moved=None, within=None, few=None):
    """The admitted moves of one wave, as :func:`lpa.superstep` finds them."""
    heavy = size > cap if few else None
    full = np.flatnonzero(size > cap - int(g.c.max(initial=0)))
    state = {"label": label, "salt": s, "sub": sub, "part": part, "bucket": bucket, "moved": moved, "within": within, "few": few, "heavy": heavy, "full": (full, size[full]), "cap": cap}
    node, to, strength, tie, *loss = _scanned(g, _proposals, state, _MOVES if few else _MOVES[:4])
    if few and heavy.any():
        loss = loss[0]
        # Only as much leaves an overloaded block against its interest as it must shed.
        own, keep = label[node].astype(np.int64), np.ones(len(node), bool)
        at = np.flatnonzero(heavy[own])
        at = at[np.lexsort((node[at], -tie[at], loss[at], own[at]))]
        if len(at):
            gone = _running(own[at], g.c[node[at]]) - g.c[node[at]]
            keep[at] = (loss[at] < 0) | (gone < (size - cap)[own[at]])
        node, to, strength, tie = node[keep], to[keep], strength[keep], tie[keep]
    return _admitted(node, to, strength, tie, g.c, size, cap)


def _move(g, label, size, node, to) -> int:
    np.subtract.at(size, label[node], g.c[node])
    np.add.at(size, to, g.c[node])
    label[node] = to
    return len(node)


def propagate(g: VectorGraph, cap: int, rounds: int = 10, stop: float = 0.05, order: str = "degree", seed: int = 0, level: int = 1, cycle: int = 1, within=None, active: bool = False, buckets: int = 2, sub: int = 2) -> np.ndarray:
    """Clusters as :func:`lpa.propagate` finds them, by degree or in random order."""
    label, size, moved, slices = np.arange(g.n, dtype=np.int32), g.c.copy(), None, None
    if order == "random":
        buckets, sub = 1, buckets * sub
    else:
        alone = g.n - int(g.many.sum())
        below = alone + np.cumsum(g.many) - g.many
        slices = below * buckets // max(1, g.n)
    for r in range(rounds):
        s, total, start = hashing.salt(seed, cycle, level, r), 0, label.copy() if active else None
        for wave in range(buckets * sub):
            bucket = None if slices is None else (g.degree, slices, wave // sub)
            total += _move(g, label, size, *_moves(g, label, size, cap, s, sub, wave % sub, bucket, moved, within))
        if not total or total < stop * g.n:
            break
        if active:
            moved = label != start
    return label


def lp_refine(g: VectorGraph, part: np.ndarray, k: int, cap: int, rounds: int = 10, seed: int = 0, level: int = 1, cycle: int = 1, waves: int = 2) -> np.ndarray:
    """Blocks as :func:`refine.lp_refine` finds them."""
    label = part.astype(np.int8 if k <= 127 else np.int32)
    size, moved = np.bincount(label, g.c, minlength=k).astype(np.int64), None
    for r in range(rounds):
        s, total, start = hashing.salt(seed, cycle, level, 500 + r), 0, label.copy()
        for wave in range(waves):
            total += _move(g, label, size, *_moves(g, label, size, cap, s, waves, wave, None, moved, None, k))
        if not total:
            break
        moved = label != start
    return label


def _heaviest_free(graph, t, node, count, dst, w):
    (ids, c), free, side = graph, t["free"], t["within"]
    src = np.repeat(np.arange(len(node)), count)
    ok = free[node][src] & free[dst]
    if c is not None:
        ok &= c[node][src] + c[dst] <= t["cap"]
    if side is not None:
        ok &= side[node][src] == side[dst]
    src, dst, w = src[ok], dst[ok].astype(np.int64), w[ok]
    if not len(src):
        return None

    def tie_of(r, x):
        mine = node[r]
        return _pair_tie(ids[np.minimum(mine, x)], ids[np.maximum(mine, x)], t["salt"])

    at, _ = _best(src, dst, w, tie_of)
    return node[src[at]], dst[at]


def heavy_edge_matching(g: VectorGraph, cap: int, rounds: int = 5, seed: int = 0, within=None) -> np.ndarray:
    """Labels as :func:`matching.heavy_edge_matching` finds them."""
    label, free = np.arange(g.n, dtype=np.int32), np.ones(g.n, bool)
    if cap < 2 * int(g.c.min(initial=1)):
        return label
    for r in range(rounds):
        node, best = _scanned(g, _heaviest_free, {"free": free, "within": within, "cap": cap, "salt": hashing.salt(seed, 0, 0, r)}, [np.int32, np.int32])
        pick = np.full(g.n, -1, np.int32)
        pick[node] = best
        one = node[(pick[best] == node) & (node < best)]
        if not len(one):
            break
        label[pick[one]] = one
        free[one] = free[pick[one]] = False
    return label


def _hub_of(graph, t, node, count, dst, w):
    who = t["free"][node]
    if not who.any():
        return None
    arcs = np.repeat(who, count)
    src, dst, w = np.repeat(np.flatnonzero(who), count[who]), dst[arcs], w[arcs]
    first = np.flatnonzero(np.concatenate(([True], src[1:] != src[:-1])))
    top = np.repeat(np.maximum.reduceat(w, first), np.diff(np.append(first, len(src))))
    return node[src[first]], np.minimum.reduceat(np.where(w == top, dst, 2**31 - 1), first)


def paired(g: VectorGraph, label: np.ndarray, bound: int, within=None) -> np.ndarray:
    """Single nodes two by two under a common heaviest neighbour, as
    :func:`matching.two_hop_pairs` does it."""
    free = (np.bincount(label, minlength=g.n) == 1)[label] & (g.c * 2 <= bound)
    node, hub = _scanned(g, _hub_of, {"free": free}, [np.int32, np.int32])
    side = np.zeros(len(node), np.int64) if within is None else within[node].astype(np.int64)
    group = np.unique(hub.astype(np.int64) * (int(side.max(initial=0)) + 1) + side, return_inverse=True)[1]
    bins = -(-np.bincount(group) // BIN)
    bin_ = hashing.mix_array(g.ids[node], 29) % bins[group]
    order = np.lexsort((node, bin_, group))
    node, group, bin_ = node[order], group[order], bin_[order]
    start = np.concatenate((np.ones(min(len(node), 1), bool), (group[1:] != group[:-1]) | (bin_[1:] != bin_[:-1])))
    begin = np.flatnonzero(start)
    place = np.arange(len(node)) - np.repeat(begin, np.diff(np.append(begin, len(node))))
    odd = np.flatnonzero(place % 2)
    out = label.copy()
    out[node[odd]] = label[node[odd - 1]]
    return out


def clusters(label: np.ndarray) -> int:
    return np.count_nonzero(np.bincount(label))


def contract(g: VectorGraph, label: np.ndarray) -> tuple[VectorGraph | None, np.ndarray]:
    """The coarse graph, its nodes named by their smallest member, and each node's
    coarse node."""
    name = np.empty(g.n, np.int32)
    name[label[::-1]] = np.arange(g.n - 1, -1, -1, dtype=np.int32)
    name = name[label]
    mask = np.zeros(g.n, bool)
    mask[name] = True
    to = (np.cumsum(mask, dtype=np.int32) - 1)[name]
    del name
    ids, chunks = g.ids[mask], _chunks_for(2 * g.m)
    n, c = len(ids), np.bincount(to, g.c).astype(np.int64)
    sent = g.spark.sparkContext.broadcast(to)

    def pieces(batches):
        to = sent.value
        for batch in batches:
            for node, count, dst, w in _arrays(batch):
                src, dst = np.repeat(to[node], count), to[dst]
                apart = src != dst
                if apart.any():
                    src, dst, w = _summed(src[apart].astype(np.int64) * n + dst[apart], w[apart], n)
                    yield _dealt(src, dst, w, chunks)

    out = _made(g.spark, ids, c, g.chunks.select("node", "count", "dst", "w").mapInArrow(pieces, _PIECES), chunks)
    sent.destroy()
    return out, to


def _cut_of(graph, t, node, count, dst, w):
    part = t["part"]
    return (np.array([w[np.repeat(part[node], count) != part[dst]].sum()]),)


def quality(g: VectorGraph, part: np.ndarray, k: int, cap: int) -> tuple[int, int]:
    """``(overload, cut)``; smaller is better."""
    cut = int(_scanned(g, _cut_of, {"part": part.astype(np.int8 if k <= 127 else np.int32)}, [np.int64])[0].sum()) // 2
    return max(0, int(np.bincount(part, g.c, minlength=k).max()) - cap), cut


def edge_weight(g: VectorGraph) -> int:
    return int(_scanned(g, lambda graph, t, node, count, dst, w: (np.array([w.sum()]),), {}, [np.int64])[0].sum()) // 2


def local(g: VectorGraph) -> Csr:
    """The graph in memory; rows are in order of the neighbours."""
    got = g.chunks.select("node", "count", "dst", "w").toArrow()
    degree = np.zeros(g.n, np.int64)
    for batch in got.to_batches():
        for node, count, _, _ in _arrays(batch):
            degree[node] = count
    ptr = np.concatenate(([0], np.cumsum(degree)))
    adj, weight = np.empty(2 * g.m, np.int64), np.empty(2 * g.m, np.int64)
    for batch in got.to_batches():
        for node, count, dst, w in _arrays(batch):
            at = np.repeat(ptr[node] - (np.cumsum(count, dtype=np.int64) - count), count)
            at += np.arange(len(dst))
            adj[at], weight[at] = dst, w
    return Csr(ptr, adj, weight, g.c)


def frame(g: VectorGraph, part: np.ndarray) -> DataFrame:
    """``(id, block)`` as a saved table, made by the tasks."""
    sent, graph, tasks = g.spark.sparkContext.broadcast(part.astype(np.int32)), g.sent, _chunks_for(2 * g.n)

    def rows(batches):
        ids, part = graph.value[0], sent.value
        for batch in batches:
            for x in batch.column(0).to_pylist():
                a, b = len(ids) * x // tasks, len(ids) * (x + 1) // tasks
                for lo in range(a, b, 100_000):
                    hi = min(b, lo + 100_000)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[lo:hi], pa.int64()), pa.array(part[lo:hi], pa.int32())], ["id", "block"])

    out = saved(g.spark.range(0, tasks, 1, tasks).mapInArrow(rows, "id long, block int"), "part")
    sent.destroy()
    return out
