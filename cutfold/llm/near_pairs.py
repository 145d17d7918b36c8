"""Candidates by shared minima and their verification, for SimHash near-dedup.

A one-word edit turns many bits of a 64-bit SimHash, so that search alone misses most
pairs at similarity 0.8. The rest share one of ``BANDS`` keys of ``PER_BAND`` minima of
salted hashes; two texts of similarity s miss all of them with probability
(1 - s**4)**32, 5e-8 at 0.8. Every candidate is verified on its whole shingle sets, so
no link is false.

Texts with equal shingle sets form one class. A bucket of a band is worked off in
rounds: all its members meet one of them, unless they are linked to it already or too
different in size; then that one is done there. The first is drawn anew per band, later
ones are those with the most links so far, which a family of near copies has gathered
around. So a round costs no more pairs than buckets have members. Labels of connected texts
are brought up to date after each round, to the end after the last. What is still in
different components after ``rounds`` rounds is peeled: a text needs ``least`` of its
shingles in other open texts, and a pair as many such shingles on either side as its
similarity asks for. Only pairs that this bound leaves meet in full, and no bucket is
cut off.

Where they meet in full, two texts first compare ``parity``, ``PARITY`` bits that tell
for each slot of shingle hashes whether an odd number of the set fell into it. A shingle
that two sets do not share turns one bit over, so the bits that differ are never more
than the shingles that do: a pair with too many of them is ruled out without its texts,
and none at the similarity asked for is lost. Sets far larger than ``PARITY`` fill the
bits by chance and pass on to the verification.

Defined cases: words and case as in SimHash; NULL and word-free texts have no key.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.functions.storage import drop_saved, saved
from cutfold.llm._common import map_arrow
from cutfold.operators.components import star_components, star_labels

BANDS, PER_BAND, HELD, PARITY = 32, 4, 2_000_000, 1024
_DRAWS = np.random.default_rng(42).integers(0, 2**64, (2, BANDS * PER_BAND, 1), np.uint64)
_XOR, _ODD, _MORE = _DRAWS[0], _DRAWS[1] | np.uint64(1), np.uint64(0x9E3779B97F4A7C15)


def band_keys(h: np.ndarray) -> list[int]:
    """One signed key per band; none for a text without shingles."""
    if not len(h):
        return []
    low = np.full(BANDS * PER_BAND, 2**64 - 1, np.uint64)
    for at in range(0, len(h), 8192):
        x = (h[at : at + 8192] ^ _XOR) * _ODD
        x ^= x >> np.uint64(32)
        low = np.minimum(low, (x * _MORE).min(axis=1))
    raw = low.astype("<u8").tobytes()
    step = 8 * PER_BAND
    return [xxhash.xxh64_intdigest(raw[i * step : (i + 1) * step], i) - 2**63 for i in range(BANDS)]


def parity(h: np.ndarray) -> list[int]:
    """Signed words of ``PARITY`` bits: bit i is set if an odd number of the distinct
    hashes ``h`` falls into slot i."""
    slot = (h.astype(np.uint64) >> np.uint64(7)) % np.uint64(PARITY)
    odd = (np.bincount(slot.astype(np.int64), minlength=PARITY) & 1).astype(np.uint8)
    return np.packbits(odd, bitorder="little").view("<i8").tolist()


def _similar(words: int, least: float):
    from cutfold.llm.simhash_dedup import shingle_hashes

    def fn(batch):
        keep, sets, held = [], {}, 0  # a text that meets many is hashed once, while HELD allows
        for pair in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            if held > HELD:
                sets, held = {}, 0
            for t in pair:
                if t not in sets:
                    sets[t] = np.unique(shingle_hashes(t or "", words))
                    held += len(sets[t])
            x, y = (sets[t] for t in pair)
            both = len(np.intersect1d(x, y, assume_unique=True))
            keep.append(both >= least * (len(x) + len(y) - both) - 1e-9)
        kept = batch.filter(pa.array(keep, pa.bool_()))
        return pa.RecordBatch.from_arrays(kept.columns[2:], kept.schema.names[2:])

    return fn


def _verified(pairs: DataFrame, texts: DataFrame, words: int, least: float) -> DataFrame:
    a = texts.select(F.col("rid").alias("u"), F.col("text").alias("tu"))
    b = texts.select(F.col("rid").alias("v"), F.col("text").alias("tv"))
    both = pairs.join(a, "u").join(b, "v").select("tu", "tv", *pairs.columns)
    return saved(map_arrow(both, _similar(words, least), pairs.schema), "near-links")


def _fits(least: float):
    """Sets whose sizes are further apart cannot be that similar."""
    return (F.col("n") >= F.col("m") * least - 1e-6) & (F.col("m") >= F.col("n") * least - 1e-6)


def _differ(a: str, b: str):
    """Bits that differ, at most the shingles that only one of two sets has."""
    bits = [F.bit_count(F.col(a)[i].bitwiseXOR(F.col(b)[i])) for i in range(PARITY // 64)]
    return sum(bits[1:], bits[0])


def _tokens(words: int):
    from cutfold.llm.simhash_dedup import shingle_hashes

    def fn(batch):
        for rid, text in zip(*(c.to_pylist() for c in batch.columns)):
            h = np.unique(shingle_hashes(text or "", words)).view(np.int64)
            for at in range(0, len(h), 65_536):
                part = h[at : at + 65_536]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), rid)), pa.array(part)], ["id", "h"])

    return fn


def _peeled(left: DataFrame, texts: DataFrame, words: int, least: float, times: int = 2) -> DataFrame:
    """``left`` without members that cannot have a partner in it, and ``s``, the number
    of a member's shingles that other open texts have."""
    ids = left.select(F.col("id").alias("rid")).distinct()
    tokens = saved(map_arrow(texts.join(ids, "rid", "left_semi").select("rid", "text"), _tokens(words), "id long, h long"), "near-tokens")
    sizes = left.select("id", "n").distinct()
    held, kept = tokens, sizes
    for _ in range(times):
        often = saved(held.groupBy("h").agg(F.count(F.lit(1)).alias("k")).where("k > 1").select("h"), "near-often")
        kept = held.join(often, "h", "left_semi").groupBy("id").agg(F.count(F.lit(1)).alias("s")).join(sizes, "id")
        kept = saved(kept.where(F.col("s") >= F.col("n") * least - 1e-6).select("id", "s"), "near-kept")
        held = tokens.join(kept.select("id"), "id", "left_semi")
    return left.join(kept, "id")


def _ordered(pairs: DataFrame, *more: str) -> DataFrame:
    return pairs.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"), *more).distinct()


def _mixed(left: DataFrame, place: list[str], *aggs) -> DataFrame:
    """The buckets whose members are not all connected yet."""
    return left.groupBy(place).agg(F.min("c").alias("a"), F.max("c").alias("b"), *aggs).where("a < b")


def links(classes: DataFrame, texts: DataFrame, words: int, least: float, more: DataFrame, rounds: int = 2) -> DataFrame:
    """Verified pairs ``(u, v)`` that connect what the candidates connect, from
    ``classes(rid, n, keys, parity)``, n the number of shingles, and ``texts(rid, text)``;
    ``more(u, v)`` are candidates too."""
    place = ["band", "key"]
    entries = saved(classes.select(F.col("rid").alias("id"), "n", F.posexplode("keys").alias("band", "key")), "near-entries")
    shared = saved(entries.groupBy(place).agg(F.count(F.lit(1)).alias("k")).where("k > 1").select(*place), "near-buckets")
    left = entries.join(shared, place).withColumn("c", F.col("id")).withColumn("deg", F.lit(0).cast("long"))
    left = saved(left, "near-open")
    drop_saved(entries, shared)
    found = _verified(saved(_ordered(more), "near-more"), texts, words, least)
    for r in range(rounds):
        draw = F.min(F.struct((-F.col("deg")).alias("rank"), F.xxhash64(F.lit(r), "band", "id").alias("h"), F.col("id").alias("v"), F.col("n").alias("m"), F.col("c").alias("cv"))).alias("x")
        drawn = saved(_mixed(left, place, draw).select(*place, "x.v", "x.m", "x.cv"), "near-drawn")
        if drawn.isEmpty():
            return found
        rest = saved(left.join(drawn, place).where("id <> v"), "near-rest")
        met = rest.where((F.col("c") != F.col("cv")) & _fits(least))
        tried = saved(_ordered(met.select(F.col("id").alias("u"), "v")), "near-tried")
        found = found.union(_verified(tried, texts, words, least))
        # Until the last round the labels need not be final: equal ones are connected.
        comps = star_components(found) if r + 1 == rounds else star_labels(found)
        degree = found.select(F.explode(F.array("u", "v")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("deg"))
        info = saved(comps.join(degree, "id"), "near-components")
        named = rest.select(*place, "id", "n").join(info, "id", "left")
        nxt = saved(named.select(*place, "id", "n", F.coalesce("component", "id").alias("c"), F.coalesce("deg", F.lit(0)).alias("deg")), "near-open")
        drop_saved(left, drawn, rest, tried, info)
        left = nxt
    mixed = saved(_mixed(left, place).select(*place), "near-mixed")
    if mixed.isEmpty():
        return found
    left = saved(left.join(mixed, place).drop("deg"), "near-open")
    sets = classes.select(F.col("rid").alias("id"), "keys", "parity")
    left = saved(_peeled(left, texts, words, least).join(sets, "id"), "near-open")
    return found.union(_verified(saved(_ordered(_met(left, least)), "near-rest"), texts, words, least))


def _met(left: DataFrame, least: float) -> DataFrame:
    """Pairs ``(u, v)`` of different components that share a bucket of ``left`` and that
    no bound rules out, each in the first band that it shares. The bounds are conditions
    of the join, so what they rule out is no row."""
    names = ["id", "c", "n", "s", "keys", "parity"]
    side = lambda *to: left.select("band", "key", *(F.col(x).alias(y) for x, y in zip(names, to)))
    share = (F.col("n") + F.col("m")) / (1 + least)
    enough = F.least("s", "t") >= share * least - 1e-6
    near = _differ("pu", "pv") <= share * (1 - least) + 1e-6
    earlier = F.exists(F.zip_with(F.slice("ku", F.lit(1), F.col("band")), F.slice("kv", F.lit(1), F.col("band")), lambda x, y: x == y), lambda same: same)
    both = side("u", "cu", "n", "s", "ku", "pu").join(side("v", "cv", "m", "t", "kv", "pv"), ["band", "key"])
    return both.where((F.col("cu") > F.col("cv")) & _fits(least) & enough & near & ~earlier)
