"""A mergeable pair of Bloom filters: hashes seen once, hashes seen twice.

Partitions build pairs of fixed size; pairs merge by ``twice = t1 | t2 | (o1 &
o2)`` and ``once = o1 | o2``, segment by segment, in a tree of two shuffles. Only
the merged second filter, of ``bits`` bits whatever the input, is collected.
It may hold a hash seen once; it never misses one seen twice.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BITS, PROBES, SEGMENT_BYTES = 2**26, 3, 2**16
_SCHEMA = "segment int, salt int, once binary, twice binary"


def positions(hashes: np.ndarray, bits: int) -> np.ndarray:
    """``PROBES`` positions per hash by double hashing; ``bits`` is a power of 2."""
    step = (hashes >> np.uint64(32)) | np.uint64(1)
    with np.errstate(over="ignore"):
        return np.stack([(hashes + np.uint64(i) * step) & np.uint64(bits - 1) for i in range(PROBES)]).astype(np.int64)


def held(packed: np.ndarray, hashes: np.ndarray, bits: int) -> np.ndarray:
    """Which hashes the packed filter holds."""
    at = positions(hashes, bits)
    return ((packed[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1).all(axis=0)


def _blobs(segments, salt, one, two):
    return pa.RecordBatch.from_pydict(
        {
            "segment": pa.array(segments, pa.int32()),
            "salt": pa.array([salt] * len(segments), pa.int32()),
            "once": pa.array([zlib.compress(x.tobytes(), 1) for x in one], pa.binary()),
            "twice": pa.array([zlib.compress(x.tobytes(), 1) for x in two], pa.binary()),
        }
    )


def _local(bits: int, hashes_of):
    def run(batches):
        once, twice = np.zeros(bits, bool), np.zeros(bits, bool)
        for batch in batches:
            h, n = np.unique(hashes_of(batch), return_counts=True)
            for lo in range(0, len(h), 100_000):
                at = positions(h[lo : lo + 100_000], bits)
                again = once[at].all(axis=0) | (n[lo : lo + 100_000] > 1)
                twice[at[:, again]] = True
                once[at] = True
        salt = TaskContext.get().partitionId() % 1024
        one, two = (np.packbits(x).reshape(-1, SEGMENT_BYTES) for x in (once, twice))
        used = np.flatnonzero(one.any(axis=1))
        for lo in range(0, len(used), 64):
            part = used[lo : lo + 64]
            yield _blobs(part, salt, one[part], two[part])

    return run


def _merge_sorted(batches):
    """Merge neighbouring rows of equal (segment, salt); input sorted by both."""
    key, one, two = None, None, None
    for batch in batches:
        for segment, salt, a, b in zip(*(c.to_pylist() for c in batch.columns)):
            a, b = (np.frombuffer(zlib.decompress(x), np.uint8) for x in (a, b))
            if (segment, salt) == key:
                two |= b | (one & a)
                one |= a
            else:
                if key is not None:
                    yield _blobs([key[0]], key[1], [one], [two])
                key, one, two = (segment, salt), a.copy(), b.copy()
    if key is not None:
        yield _blobs([key[0]], key[1], [one], [two])


def twice_filter(df: DataFrame, hashes_of, bits: int = BITS) -> np.ndarray:
    """Packed bits of the filter of hashes seen twice; ``hashes_of`` maps a record
    batch of ``df`` to its uint64 hashes."""
    parts = df.mapInArrow(_local(bits, hashes_of), _SCHEMA)
    for by in (["segment", "salt"], ["segment"]):
        parts = parts if len(by) == 2 else parts.withColumn("salt", F.lit(0))
        parts = parts.repartition(*by).sortWithinPartitions("segment", "salt").mapInArrow(_merge_sorted, _SCHEMA)
    merged = np.zeros((bits // 8 // SEGMENT_BYTES, SEGMENT_BYTES), np.uint8)
    for row in parts.select("segment", "twice").toLocalIterator():
        merged[row.segment] = np.frombuffer(zlib.decompress(bytes(row.twice)), np.uint8)
    return merged.reshape(-1)
