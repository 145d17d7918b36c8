"""Repeated lines, found through two mergeable Bloom filters.

Pass 1 keeps, per partition, a filter of keys seen once and one of keys seen
twice; pairs merge by ``twice = t1 | t2 | (o1 & o2)`` and ``once = o1 | o2`` in
a two-level tree over fixed filter segments. Pass 2 shuffles only keys that the
merged second filter holds, as SHA-256 digests, for the exact count and the
choice of the document that keeps the line; pass 3 rewrites the texts.

The filter has a fixed size (``bits``), which is the bound of what is collected
and broadcast. A filter too small for its input only lets more keys through to
the exact step; it never changes the result.

Defined cases: NULL or empty text is one empty line; rows repeating an id count
as one document; NULL ids rank below all others.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.functions.storage import saved
from cutfold.llm._common import FIRST, SPACE_CHARS, map_arrow, with_key
from cutfold.llm.bloom import BITS, held, twice_filter

MIN_CHARS, MIN_DOCS = 20, 3


def line_key(line: str) -> bytes | None:
    """The comparison key of a line, None if it is too short to count."""
    s = line.strip(SPACE_CHARS)
    return s.encode().lower() if len(s) >= MIN_CHARS else None


def _keys(text: str) -> set[bytes]:
    return {k for k in map(line_key, text.split("\n")) if k is not None}


def _hashes(batch) -> np.ndarray:
    return np.array([xxhash.xxh64_intdigest(k) for t in batch.column(0).to_pylist() for k in _keys(t)], np.uint64)


def _suspects(shared, bits: int):
    def fn(batch):
        d, t = batch.column(0).to_pylist(), batch.column(1).to_pylist()
        packed, rows, keys = shared.value, [], []
        for i, text in enumerate(batch.column(2).to_pylist()):
            own = list(_keys(text))
            if not own:
                continue
            hit = held(packed, np.array([xxhash.xxh64_intdigest(k) for k in own], np.uint64), bits)
            for j in np.flatnonzero(hit):
                rows.append(i)
                keys.append(hashlib.sha256(own[j]).digest())
        return pa.RecordBatch.from_pydict({"_d": pa.array([d[i] for i in rows], pa.int64()), "_t": pa.array([t[i] for i in rows], pa.int64()), "key": pa.array(keys, pa.binary())})

    return fn


def _rewrite(emit_text: bool):
    def fn(batch):
        ids, texts, drops = (batch.column(i).to_pylist() for i in range(3))
        n_lines, n_dropped, out = [], [], []
        for text, drop in zip(texts, drops):
            lines = text.split("\n")
            kept = lines
            if drop:
                gone = set(drop)
                kept = [x for x in lines if (k := line_key(x)) is None or hashlib.sha256(k).digest() not in gone]
            n_lines.append(len(lines))
            n_dropped.append(len(lines) - len(kept))
            joined = "\n".join(kept)
            out.append(joined if emit_text else hashlib.sha256(joined.encode()).hexdigest())
        cols = {"doc_id": pa.array(ids, pa.int64()), "n_lines": pa.array(n_lines, pa.int64()), "n_dropped": pa.array(n_dropped, pa.int64())}
        return pa.RecordBatch.from_pydict(cols | {"text" if emit_text else "kept_sha256": pa.array(out, pa.string())})

    return fn


def dedup_lines(docs: DataFrame, min_docs: int = MIN_DOCS, bits: int = BITS, emit_text: bool = True) -> DataFrame:
    """Per input row ``doc_id, n_lines, n_dropped`` and the rewritten ``text``
    (or with ``emit_text=False`` its ``kept_sha256``)."""
    spark = docs.sparkSession
    keyed = with_key(docs, FIRST)
    shared = spark.sparkContext.broadcast(twice_filter(keyed.select("text"), _hashes, bits))
    seen = saved(map_arrow(keyed.select("_d", "_t", "text"), _suspects(shared, bits), "_d long, _t long, key binary"), "line-suspects")
    keys = seen.groupBy("key", "_d").agg(F.lit(1)).groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.max("_d").alias("keep"))
    # Saved first: a join whose sides are both dealt anew can be split where a line is hot.
    keys = saved(keys.where(F.col("n") >= min_docs).select("key", "keep"), "line-keys")
    drops = seen.join(keys, "key").where("_d < keep").groupBy("_d", "_t").agg(F.collect_set("key").alias("drops"))
    both = keyed.join(drops, ["_d", "_t"], "left").select("doc_id", "text", "drops")
    last = "text string" if emit_text else "kept_sha256 string"
    return map_arrow(both, _rewrite(emit_text), f"doc_id long, n_lines long, n_dropped long, {last}")


def op5_line_dedup(spark, sf_dir):
    return dedup_lines(spark.read.parquet(f"{sf_dir}/documents.parquet"), emit_text=False)


SQL = r"""
WITH t AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
l AS (SELECT doc_id, i, ls[i] AS line, translate(regexp_replace(ls[i], '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k
      FROM (SELECT doc_id, ls, unnest(range(1, len(ls) + 1)) AS i FROM t)),
r AS (SELECT k, max(doc_id) AS keep FROM l WHERE length(k) >= 20 GROUP BY k HAVING count(DISTINCT doc_id) >= 3)
SELECT l.doc_id, count(*) AS n_lines, count(*) FILTER (WHERE r.keep > l.doc_id) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE r.keep IS NULL OR r.keep = l.doc_id), '')) AS kept_sha256
FROM l LEFT JOIN r ON l.k = r.k GROUP BY l.doc_id
"""
