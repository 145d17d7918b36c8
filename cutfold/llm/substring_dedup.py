"""Repeated passages by recompression.

Rounds of naming turn a text's words into symbols that depend only on nearby
words: runs of an equal symbol get one name, then neighbouring symbols whose
coin flips say (left, right) get a joint name. Names are hashes of what they
stand for, so equal names mean equal words in all documents without a shared
dictionary. ``caps`` bounds a symbol's words per round, which bounds how far a
symbol looks: ``reach`` words to either side.

Every window of ``window`` words is represented by the least-valued symbol among
those that lie ``reach`` words inside it, so equal windows are represented by
equal symbols at equal offsets. Windows that share a representative form one
row: ``core`` (the words that any window of this symbol must hold) and ``ctx``
(all words of its windows). Then

* cores met once, as far as a Bloom filter can tell, are dropped;
* cores whose ctx agree everywhere decide all their windows at once;
* other ctx keep one row, of the smallest document, whose windows are compared
  one by one by a 128-bit hash; its other documents lose all those windows.

Equality is decided by 128 bits throughout: core and ctx are independent 64-bit hashes
of word ranges, and windows that are compared one by one have both.

Rows are told apart by a saved row number. Hot cores are pre-aggregated before shuffles
and joined by splittable joins.

Defined cases: NULL and short texts have no window; rows repeating an id, also rows
without one, are not smaller than each other; NULL ids rank last.
"""

from __future__ import annotations

import hashlib
from itertools import compress

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.functions.storage import drop_saved, saved
from cutfold.llm._common import LAST, map_arrow, order_id, slices
from cutfold.llm.bloom import BITS, held, twice_filter

WINDOW, CAPS = 50, (2, 3)
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD1342543DE82EF95)


def mix(x: np.ndarray, salt: int) -> np.ndarray:
    """A 64-bit finaliser."""
    with np.errstate(over="ignore"):
        x = x + np.uint64((salt * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) % 2**64)
        x = (x ^ (x >> np.uint64(30))) * _M1
        x = (x ^ (x >> np.uint64(27))) * _M2
        return x ^ (x >> np.uint64(31))


def reach(caps: tuple = CAPS) -> int:
    """How many words to either side decide whether a symbol starts at a word."""
    total, before = 0, 1
    for cap in caps:
        total += 2 * cap + before
        before = cap
    return total


def recompress(words: np.ndarray, doc: np.ndarray, caps: tuple = CAPS) -> tuple[np.ndarray, np.ndarray]:
    """Start positions and names of the last round's symbols."""
    name, start, size = words, np.arange(len(words)), np.ones(len(words), np.int64)
    for r, cap in enumerate(caps):
        same = np.zeros(len(name), bool)
        same[1:] = (name[1:] == name[:-1]) & (doc[start[1:]] == doc[start[:-1]])
        first = np.flatnonzero(~same)
        count = np.diff(np.append(first, len(name)))
        joins = (count > 1) & (count * size[first] <= cap)
        keep = ~same | ~np.repeat(joins, count)
        merged = first[joins]
        name, size = name.copy(), size.copy()
        name[merged] = mix(name[merged] ^ mix(count[joins].astype(np.uint64), 91), 3 * r + 1)
        size[merged] *= count[joins]
        name, start, size = name[keep], start[keep], size[keep]
        left = (mix(name, 3 * r + 2) >> np.uint64(63)).astype(bool)
        pair = np.zeros(len(name), bool)
        pair[:-1] = left[:-1] & ~left[1:] & (size[:-1] + size[1:] <= cap) & (doc[start[:-1]] == doc[start[1:]])
        at = np.flatnonzero(pair)
        name = name.copy()
        with np.errstate(over="ignore"):
            name[at] = mix(name[at] * _B[0] + name[at + 1], 3 * r + 3)
        size[at] += size[at + 1]
        keep = np.ones(len(name), bool)
        keep[at + 1] = False
        name, start, size = name[keep], start[keep], size[keep]
    return start, name


class Hasher:
    """Hashes of word ranges ``[a, b)`` from prefix sums, two per instance."""

    def __init__(self, words: np.ndarray):
        n = len(words)
        with np.errstate(over="ignore"):
            self.sums, self.inverse = [], []
            for i, b in enumerate(_B):
                power = np.cumprod(np.concatenate(([np.uint64(1)], np.full(n, b))), dtype=np.uint64)
                inv = np.uint64(pow(int(b), -1, 2**64))
                self.inverse.append(np.cumprod(np.concatenate(([np.uint64(1)], np.full(n, inv))), dtype=np.uint64))
                self.sums.append(np.concatenate(([np.uint64(0)], np.cumsum(mix(words, 50 + i) * power[:n], dtype=np.uint64))))

    def of(self, which: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return mix((self.sums[which][b] - self.sums[which][a]) * self.inverse[which][a], 70 + which)


def word_hashes(words: list[bytes]) -> np.ndarray:
    one = xxhash.xxh3_64_intdigest
    return np.fromiter((one(w) for w in words), np.uint64, len(words))


def _anchors(texts: list[str], window: int, caps: tuple):
    """Arrays ``(text index, core, ctx, first window, last window)``."""
    split = [t.encode().split() for t in texts]
    lens = np.array([len(w) for w in split])
    words = word_hashes([w for ws in split for w in ws])
    n, inside = len(words), reach(caps)
    doc = np.repeat(np.arange(len(texts)), lens)
    base = np.concatenate(([0], np.cumsum(lens)[:-1]))
    span = window - 2 * inside - max(caps) + 1  # places a representative can start at
    if n < window:
        return (np.zeros(0, np.int64),) * 5
    start, name = recompress(words, doc, caps)
    value = np.full(n, np.uint64(2**64 - 1))
    value[start] = mix(name, 99)
    s = np.arange(n - window + 1)
    s = s[doc[s] == doc[s + window - 1]]
    if not len(s):
        return (np.zeros(0, np.int64),) * 5
    view = np.lib.stride_tricks.sliding_window_view(value, span)
    own = s + inside + np.concatenate([view[s[lo : lo + 200_000] + inside].argmin(axis=1) for lo in range(0, len(s), 200_000)])
    head = np.ones(len(s), bool)
    head[1:] = (own[1:] != own[:-1]) | (s[1:] != s[:-1] + 1) | (doc[s[1:]] != doc[s[:-1]])
    lo = np.flatnonzero(head)
    hi = np.append(lo[1:], len(s)) - 1
    p, s1, s2 = own[lo], s[lo], s[hi]
    h = Hasher(words)
    core = h.of(0, p - inside, p + inside + max(caps) - 1)
    with np.errstate(over="ignore"):
        ctx = h.of(1, s1, s2 + window) ^ mix(((p - s1) * 2**31 + (s2 - s1)).astype(np.uint64), 7)
    d = doc[s1]
    return d, core, ctx, s1 - base[d], s2 - base[d]


_FOUND = ["core", "ctx", "rid", "_d", "s", "n"]
_FOUND_DDL = ", ".join(f"{c} long" for c in _FOUND)


def _anchor_batch(window: int, caps: tuple):
    def fn(batch):
        rid, d, texts = batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(2).to_pylist()
        for lo, hi in slices(texts):
            i, core, ctx, s1, s2 = _anchors(texts[lo:hi], window, caps)
            cols = [core.view(np.int64), ctx.view(np.int64), rid[i + lo], d[i + lo], s1, s2 - s1]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], _FOUND)

    return fn


def _core_hashes(batch) -> np.ndarray:
    return batch.column(0).to_numpy().view(np.uint64)


def _suspects(shared, bits: int):
    def fn(batch):
        return batch.filter(pa.array(held(shared.value, _core_hashes(batch), bits)))

    return fn


def _pack(batch):
    z = zstandard.ZstdCompressor(level=3)
    packed = [z.compress(x.encode()) for x in batch.column(2).to_pylist()]
    return pa.RecordBatch.from_arrays([*batch.columns[:2], pa.array(packed, pa.binary())], ["rid", "doc_id", "z"])


def _window_batch(window: int):
    def fn(batch):
        z = zstandard.ZstdDecompressor()
        for rid, d, packed, asks in zip(*(c.to_pylist() for c in batch.columns)):
            words = word_hashes(z.decompress(packed).split())
            h = Hasher(words)
            a = np.unique(np.concatenate([np.arange(x["s"], x["s"] + x["n"] + 1) for x in asks]))
            cols = [h.of(0, a, a + window).view(np.int64), h.of(1, a, a + window).view(np.int64), np.full(len(a), rid), np.full(len(a), d), a]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["h1", "h2", "rid", "_d", "s"])

    return fn


def _cut(window: int, emit_text: bool):
    def fn(batch):
        z = zstandard.ZstdDecompressor()
        ids, n_words, n_removed, out = batch.column(0).to_pylist(), [], [], []
        for packed, cuts in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
            words = z.decompress(packed).split()
            if cuts:
                depth = np.zeros(len(words) + 1, np.int64)
                s, n = (np.array([x[k] for x in cuts], np.int64) for k in ("s", "n"))
                np.add.at(depth, s, 1)
                np.add.at(depth, s + n + window, -1)
                kept = list(compress(words, np.cumsum(depth[:-1]) == 0))
            else:
                kept = words
            n_words.append(len(words))
            n_removed.append(len(words) - len(kept))
            joined = b" ".join(kept)
            out.append(joined.decode() if emit_text else hashlib.sha256(joined).hexdigest())
        cols = {"doc_id": pa.array(ids, pa.int64()), "n_words": pa.array(n_words, pa.int64()), "n_removed": pa.array(n_removed, pa.int64())}
        return pa.RecordBatch.from_pydict(cols | {"text" if emit_text else "kept_sha256": pa.array(out, pa.string())})

    return fn


def remove_repeats(docs: DataFrame, window: int = WINDOW, caps: tuple = CAPS, bits: int = BITS, emit_text: bool = True) -> DataFrame:
    """Per input row ``doc_id, n_words, n_removed`` and the kept words as ``text``
    (or with ``emit_text=False`` their ``kept_sha256``)."""
    if window < 2 * reach(caps) + max(caps):
        raise ValueError("the window is too short for these caps")
    sc = docs.sparkSession.sparkContext
    text = F.coalesce(F.col("text"), F.lit("")).alias("text")
    rows = docs.select(F.monotonically_increasing_id().alias("rid"), order_id(LAST).alias("_d"), F.col("doc_id").cast("long").alias("doc_id"), text)
    rows = saved(rows, "passage-rows")
    found = saved(map_arrow(rows.select("rid", "_d", "text"), _anchor_batch(window, caps), _FOUND_DDL), "passage-anchors")
    shared = sc.broadcast(twice_filter(found.select("core"), _core_hashes, bits))
    suspects = map_arrow(found, _suspects(shared, bits), _FOUND_DDL)
    cores = suspects.groupBy("core").agg(F.min("_d").alias("low"), F.max("_d").alias("high"), F.min("ctx").alias("c1"), F.max("ctx").alias("c2")).where("low < high")
    # Saved first: a join whose sides are both dealt anew can be split where a core is hot.
    cores = saved(cores.select("core", "low", (F.col("c1") == F.col("c2")).alias("agree")), "passage-cores")
    met = saved(suspects.join(cores, "core"), "passage-met")
    drop_saved(found, cores)
    mixed = met.where("not agree").select("core", "ctx", "rid", "_d", "s", "n")
    least = saved(mixed.groupBy("core", "ctx").agg(F.min("_d").alias("low")), "passage-least")
    told = saved(mixed.join(least, ["core", "ctx"]).select("rid", "_d", "s", "n", "low"), "passage-contexts")
    drop_saved(least)
    packed = map_arrow(rows.select("rid", "doc_id", "text"), _pack, "rid long, doc_id long, z binary")
    place = F.struct("s", "n").alias("x")
    asks = told.where("_d = low").groupBy("rid", "_d").agg(F.collect_list(place).alias("asks"))
    windows = map_arrow(packed.join(asks, "rid").select("rid", "_d", "z", "asks"), _window_batch(window), "h1 long, h2 long, rid long, _d long, s long")
    windows = saved(windows, "passage-windows")
    first = windows.groupBy("h1", "h2").agg(F.min("_d").alias("low"), F.max("_d").alias("high")).where("low < high").drop("high")
    first = saved(first, "passage-first")
    single = saved(windows.join(first, ["h1", "h2"]).where("_d > low").select("rid", "s", F.lit(0).cast("long").alias("n")), "passage-single")
    drop_saved(windows, first)
    whole = met.where("agree and _d > low").select("rid", "s", "n").union(told.where("_d > low").select("rid", "s", "n"))
    cuts = whole.union(single).groupBy("rid").agg(F.collect_set(place).alias("cuts"))
    last = "text string" if emit_text else "kept_sha256 string"
    return map_arrow(packed.join(cuts, "rid", "left").select("doc_id", "z", "cuts"), _cut(window, emit_text), f"doc_id long, n_words long, n_removed long, {last}")


def op3_substring_dedup(spark, sf_dir):
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"), emit_text=False)


SQL = r"""
WITH t AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
w AS (SELECT doc_id, i, array_to_string(ws[i:i + 49], ' ') AS g
      FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS i FROM t WHERE len(ws) >= 50)),
m AS (SELECT g, min(doc_id) AS low FROM w GROUP BY g HAVING min(doc_id) < max(doc_id)),
c AS (SELECT DISTINCT doc_id, i + j AS i FROM (SELECT w.doc_id, w.i, unnest(range(0, 50)) AS j FROM w JOIN m ON w.g = m.g WHERE m.low < w.doc_id)),
p AS (SELECT doc_id, unnest(range(1, len(ws) + 1)) AS i, unnest(ws) AS word FROM t),
k AS (SELECT p.doc_id, count(*) AS n, count(c.i) AS gone,
             coalesce(string_agg(p.word, ' ' ORDER BY p.i) FILTER (WHERE c.i IS NULL), '') AS kept
      FROM p LEFT JOIN c ON p.doc_id = c.doc_id AND p.i = c.i GROUP BY p.doc_id)
SELECT t.doc_id, coalesce(n, 0) AS n_words, coalesce(gone, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM t LEFT JOIN k ON t.doc_id = k.doc_id
"""
