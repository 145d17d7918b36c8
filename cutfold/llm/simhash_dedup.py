"""SimHash near-duplicates with a generalised pigeonhole search.

A fingerprint is the bitwise majority of the XXH64 values (seed 42) of a text's
word shingles. To find all fingerprints within ``radius`` bits, the 64 bits are
grouped into parts of correlated bits (so that the parts themselves are as
independent as they can be) and each part gets a threshold of its own, -1 to
``radius``, with thresholds summing to ``radius - parts + 1``: a pair within the
radius must agree in some part up to that part's threshold. A dynamic programme
picks the thresholds with the least estimated work, from the measured number of
pairs that agree in a part and the bit statistics of all fingerprints.

Only distinct fingerprints are searched, one row each; copies join afterwards
through their fingerprint. A bucket above ``bucket`` rows is split once more by
the pigeonhole principle on the bits outside its part, which keeps every pair
within the radius. Components come from the shared star contraction.

Defined cases: NULL and word-free texts have fingerprint zero and link like any
other; fewer words than a shingle form one shingle; NULL ids rank last, and neither
they nor repeated ids join groups whose fingerprints are apart.

:func:`near_dedup` is the pipeline's stage: five-word shingles and similarity 0.8.
"""

from __future__ import annotations

import hashlib
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.functions.storage import drop_saved, saved
from cutfold.llm import near_pairs
from cutfold.llm._common import LAST, map_arrow, order_id
from cutfold.operators.components import star_components

WORDS, RADIUS, PARTS, BUCKET = 3, 2, 3, 256


def shingle_hashes(text: str, words: int = WORDS) -> np.ndarray:
    """XXH64 (seed 42) of a text's word shingles, in order and with repeats; fewer words
    than a shingle are one shingle, no words none."""
    ws = text.encode().lower().split()
    joined, one = b" ".join(ws), xxhash.xxh64_intdigest
    if len(ws) <= words:
        return np.array([one(joined, 42)] if ws else [], "<u8")
    ends = np.cumsum([len(w) + 1 for w in ws]) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    return np.array([one(joined[a:b], 42) for a, b in zip(starts[: len(ws) - words + 1].tolist(), ends[words - 1 :].tolist())], "<u8")


def majority(h: np.ndarray) -> int:
    """The unsigned number of the bits that more than half of the hashes set."""
    ones = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view("<u8")[0])


def simhash(text: str, words: int = WORDS) -> int:
    """The unsigned 64-bit fingerprint of a text."""
    return majority(shingle_hashes(text, words))


def _fingerprint_batch(words: int):
    def fn(batch):
        fp = np.array([simhash(t, words) for t in batch.column(3).to_pylist()], np.uint64).view(np.int64)
        return pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(fp, pa.int64())], ["rid", "_d", "doc_id", "fp"])

    return fn


def fingerprints(docs: DataFrame, words: int = WORDS, rid=None) -> DataFrame:
    """``rid, _d, doc_id, fp`` (fp as a signed BIGINT) of every row, saved."""
    rid = F.lit(0).cast("long") if rid is None else rid
    src = docs.select(rid.alias("rid"), order_id(LAST).alias("_d"), F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    return saved(map_arrow(src, _fingerprint_batch(words), "rid long, _d long, doc_id long, fp long"), "simhash")


def _bit_counts(batches):
    total, n = np.zeros((64, 64)), 0
    for batch in batches:
        v = batch.column(0).to_numpy(zero_copy_only=False)
        for lo in range(0, len(v), 20_000):
            x = np.unpackbits(v[lo : lo + 20_000].astype("<i8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(np.float64)
            total += x.T @ x
            n += len(x)
    if n:
        i, j = np.divmod(np.arange(64 * 64), 64)
        yield pa.RecordBatch.from_pydict({"i": pa.array(i, pa.int32()), "j": pa.array(j, pa.int32()), "n": pa.array(total.reshape(-1).astype(np.int64)), "rows": pa.array(np.full(64 * 64, n), pa.int64())})


def bit_statistics(distinct: DataFrame) -> tuple[int, np.ndarray]:
    """Row count and the 64 x 64 co-occurrence counts of set bits."""
    sums = distinct.select("fp").mapInArrow(_bit_counts, "i int, j int, n long, rows long").groupBy("i", "j").agg(F.sum("n").alias("n"), F.sum("rows").alias("rows"))
    both, rows = np.zeros((64, 64)), 0
    for r in sums.toLocalIterator():
        both[r.i, r.j], rows = r.n, r.rows
    return rows, both


def group_bits(rows: int, both: np.ndarray, parts: int) -> list[list[int]]:
    """Split the bits into ``parts`` groups, each grown from the free bit with the
    strongest ties by whichever free bit is most correlated with the group."""
    p = np.diag(both) / max(rows, 1)
    cov = both / max(rows, 1) - np.outer(p, p)
    sd = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    tie = np.abs(cov / np.outer(sd, sd))
    np.fill_diagonal(tie, 0)
    free, groups = set(range(64)), []
    for k in range(parts):
        size = len(free) // (parts - k)
        left = sorted(free)
        group = [max(left, key=lambda b: (tie[b, left].sum(), -b))]
        free.discard(group[0])
        while len(group) < size:
            nxt = max(sorted(free), key=lambda b: (tie[b, group].sum(), -b))
            group.append(nxt)
            free.discard(nxt)
        groups.append(sorted(group))
    return groups


def mask_of(bits: list[int]) -> int:
    """The signed 64-bit mask with these bits set."""
    m = sum(1 << b for b in bits)
    return m - 2**64 if m >= 2**63 else m


def allocate(radius: int, cost: list[dict[int, float]]) -> list[int]:
    """Thresholds per part, from -1 (part not used) to radius, that sum to
    ``radius - parts + 1`` at the least total cost."""
    best: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
    for options in cost:
        step: dict[int, tuple[float, list[int]]] = {}
        for total, (spent, picked) in best.items():
            for t, c in options.items():
                if total + t not in step or spent + c < step[total + t][0]:
                    step[total + t] = (spent + c, [*picked, t])
        best = step
    return best[radius - len(cost) + 1][1]


def estimated_costs(rows: int, both: np.ndarray, groups: list[list[int]], agreeing: list[int], radius: int) -> list[dict[int, float]]:
    """Rows written plus pairs met, per part and threshold. Pairs that agree in
    the whole part are counted; those within t bits follow from that count and
    the ratio that independent bits of the same frequencies would give."""
    p = np.diag(both) / max(rows, 1)
    out = []
    for bits, same in zip(groups, agreeing):
        differ = np.zeros(radius + 1)
        differ[0] = 1
        for b in bits:
            q = 2 * p[b] * (1 - p[b])
            differ = differ * (1 - q) + np.concatenate(([0], differ[:-1])) * q
        within, at_least = np.cumsum(differ), max(differ[0], 1e-30)
        options = {-1: 0.0}
        for t in range(radius + 1):
            ball = sum(comb(len(bits), i) for i in range(t + 1))
            options[t] = rows * (1 + ball) + same * within[t] / at_least
        out.append(options)
    return out


def _ball(bits: list[int], t: int) -> list[int]:
    """Masks of all ways to flip at most t of the bits."""
    masks = [0]
    frontier = [(0, -1)]
    for _ in range(t):
        frontier = [(m | 1 << b, i) for m, last in frontier for i, b in enumerate(bits) if i > last]
        masks += [m for m, _ in frontier]
    return [m - 2**64 if m >= 2**63 else m for m in masks]


def links(distinct: DataFrame, radius: int = RADIUS, parts: int = PARTS, bucket: int = BUCKET) -> DataFrame:
    """All pairs ``(u, v)`` of ``distinct(fp, d)`` rows within ``radius`` bits."""
    rows, both = bit_statistics(distinct)
    groups = group_bits(rows, both, parts)
    masks = [mask_of(g) for g in groups]
    split = F.explode(F.array(*[F.struct(F.lit(i).alias("part"), F.col("fp").bitwiseAND(F.lit(m)).alias("sig")) for i, m in enumerate(masks)]))
    sizes = distinct.select(split.alias("k")).groupBy("k.part", "k.sig").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    met = {r.part: r.pairs for r in sizes.groupBy("part").agg(F.sum(F.expr("n * (n - 1) / 2")).alias("pairs")).collect()}
    t = allocate(radius, estimated_costs(rows, both, groups, [met.get(i, 0) for i in range(parts)], radius))
    used = [i for i in range(parts) if t[i] >= 0]
    hot = saved(sizes.where((F.col("n") > bucket) & F.col("part").isin(used)).select("part", "sig"), "simhash-hot")

    def keyed(flips: bool) -> DataFrame:
        entries = []
        for i in used:
            around = _ball(groups[i], t[i]) if flips else [0]
            entries += [F.struct(F.lit(i).alias("part"), F.col("fp").bitwiseAND(F.lit(masks[i])).bitwiseXOR(F.lit(x)).alias("sig")) for x in around]
        k = distinct.select("fp", "d", F.explode(F.array(*entries)).alias("k")).select("fp", "d", "k.part", "k.sig")
        marked = k.join(hot.withColumn("h", F.lit(True)), ["part", "sig"], "left")
        rest = None
        for i in used:
            outside = [b for j, g in enumerate(groups) if j != i for b in g]
            subs = [outside[j :: radius + 1] for j in range(radius + 1)]
            again = F.array(*[F.struct(F.lit(j).alias("j"), F.col("fp").bitwiseAND(F.lit(mask_of(s))).alias("s")) for j, s in enumerate(subs)])
            rest = again if rest is None else F.when(F.col("part") == i, again).otherwise(rest)
        whole = F.array(F.struct(F.lit(-1).alias("j"), F.lit(0).cast("long").alias("s")))
        return marked.select("fp", "d", "part", "sig", F.explode(F.when(F.col("h"), rest).otherwise(whole)).alias("x")).select("fp", "d", "part", "sig", "x.j", "x.s")

    left = keyed(False).select("part", "sig", "j", "s", F.col("fp").alias("fp1"), F.col("d").alias("d1"))
    right = keyed(True).select("part", "sig", "j", "s", F.col("fp").alias("fp2"), F.col("d").alias("d2"))
    near = F.bit_count(F.col("fp1").bitwiseXOR(F.col("fp2"))) <= radius
    ordered = F.col("fp1") < F.col("fp2") if all(t[i] == 0 for i in used) else F.col("fp1") != F.col("fp2")
    pairs = left.join(right, ["part", "sig", "j", "s"]).where(near & ordered)
    return pairs.select(F.greatest("d1", "d2").alias("u"), F.least("d1", "d2").alias("v")).distinct()


def near_groups(fps: DataFrame, radius: int = RADIUS) -> DataFrame:
    """``fps(_d, fp, ...)`` with ``root``, the smallest fingerprint reachable, which
    names the group, and ``component``, the smallest ``_d`` of the group."""
    distinct = saved(fps.groupBy("fp").agg(F.min("_d").alias("least")), "simhash-classes")
    roots = star_components(links(distinct.select("fp", F.col("fp").alias("d")), radius)).select(F.col("id").alias("fp"), F.col("component").alias("root"))
    named = saved(distinct.join(roots, "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root")), "simhash-roots")
    least = named.groupBy("root").agg(F.min("least").alias("component"))
    return fps.join(named.select("fp", "root").join(least, "root"), "fp")


def _describe(words: int):
    def fn(batch):
        lists = [shingle_hashes(t or "", words) for t in batch.column(2).to_pylist()]
        sets = [np.unique(h) for h in lists]
        names = pa.array([hashlib.md5(h.tobytes()).digest() for h in sets], pa.binary())
        fps = pa.array(np.array([majority(h) for h in lists], np.uint64).view(np.int64), pa.int64())
        keys = pa.array([near_pairs.band_keys(h) for h in sets], pa.list_(pa.int64()))
        odd = pa.array([near_pairs.parity(h) for h in sets], pa.list_(pa.int64()))
        return pa.RecordBatch.from_arrays([*batch.columns[:2], names, fps, pa.array([len(h) for h in sets], pa.int64()), keys, odd], ["rid", "_d", "cls", "fp", "n", "keys", "parity"])

    return fn


def near_dedup(docs: DataFrame, words: int = 5, least: float = 0.8, radius: int = 3, parts: int = 4) -> DataFrame:
    """The input rows and columns, one row (the smallest id) of each group linked by
    Jaccard similarity ``least`` of ``words``-word shingles.

    Candidates are the pairs within ``radius`` bits by the pigeonhole search, and, as the
    bits of a fingerprint move further than any radius that still narrows the search,
    the pairs that share minima (:mod:`near_pairs`). Each is verified on its whole sets."""
    rows = saved(docs.select(F.monotonically_increasing_id().alias("rid"), F.struct("*").alias("row")), "near-rows")
    texts = rows.select("rid", F.col("row.text").alias("text"))
    src = rows.select("rid", "row.doc_id", "row.text").select("rid", order_id(LAST).alias("_d"), "text")
    sets = saved(map_arrow(src, _describe(words), "rid long, _d long, cls binary, fp long, n long, keys array<long>, parity array<long>"), "near-sets")
    classes = saved(sets.groupBy("cls").agg(F.min(F.struct("_d", "rid", "fp", "n", "keys", "parity")).alias("k")).select("k.*"), "near-classes")
    drop_saved(sets)
    heads = saved(classes.groupBy("fp").agg(F.min("rid").alias("head")), "near-heads")
    met = links(heads.select("fp", F.col("head").alias("d")), radius, parts)
    same = classes.join(heads, "fp").where("rid <> head").select(F.col("rid").alias("u"), F.col("head").alias("v"))
    found = near_pairs.links(classes, texts, words, least, met.union(same))
    comps = star_components(found).select(F.col("id").alias("rid"), "component")
    named = classes.join(comps, "rid", "left").select("_d", "rid", F.coalesce("component", "rid").alias("root"))
    kept = named.groupBy("root").agg(F.min(F.struct("_d", "rid")).alias("k")).select("k.rid")
    return rows.join(kept, "rid", "left_semi").select("row.*")


def op8_simhash_dedup(spark, sf_dir):
    out = near_groups(fingerprints(spark.read.parquet(f"{sf_dir}/documents.parquet")))
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return out.select("doc_id", hexed.alias("fingerprint"), F.when(F.col("component") != LAST, F.col("component")).alias("component_id"))
