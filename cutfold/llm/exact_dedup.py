"""Exact duplicates by distributed most-significant-digit radix partitioning.

A text's serialisation is its byte length followed by its bytes (whitespace
removed). Level 0 splits all rows by the first digit (the length and the first
24 bytes); only groups with two or more rows stay. Later digits are successive
byte ranges, each eight times longer than the one before up to 1 MB, so a level
reads only its own range of the rows still undecided. A group is finished when
it is a singleton or its bytes have ended; equality rests on the bytes
themselves. Digits are grouping keys with map-side combining, so a large group
of copies never meets in one task, and the joins that hand out group names can
be split by adaptive execution.

Defined cases: NULL text is empty; empty texts form one group; rows repeating an
id and text are members of their own, of which one stays; NULL ids rank last.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.functions.storage import drop_saved, saved
from cutfold.llm._common import LAST, SPACES, order_id

HEAD = 24
FIRST_RANGE, GROWTH, GEOMETRIC = 256, 8, 5


def _normal(text):
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACES, "").cast("binary")


def _offset(level: int) -> int:
    """Where the digit of a level starts (0-based byte)."""
    steps = min(level, GEOMETRIC)
    start = HEAD + FIRST_RANGE * (GROWTH**steps - 1) // (GROWTH - 1)
    return start + max(0, level - GEOMETRIC) * FIRST_RANGE * GROWTH ** (GEOMETRIC - 1)


def _levels(nbytes: int) -> int:
    level = 0
    while _offset(level) < nbytes:
        level += 1
    return level


def _split(base: DataFrame) -> DataFrame:
    """``(rid, gid)`` of every row whose text occurs more than once."""
    spark = base.sparkSession
    digit = base.select("rid", "nbytes", "head")
    shared = digit.groupBy("nbytes", "head").agg(F.count(F.lit(1)).alias("n"), F.min("rid").alias("gid")).where("n > 1").drop("n")
    # Names are saved before they are handed out: a join whose sides are both dealt
    # anew can be split where a digit is hot.
    shared = saved(shared, "radix-names")
    handed = [shared]
    active = saved(digit.join(shared, ["nbytes", "head"]).select("rid", "gid", "nbytes"), "radix")
    done = [active.where(F.col("nbytes") <= HEAD).select("rid", "gid")]
    longest = active.agg(F.max("nbytes")).first()[0] or 0
    if longest <= HEAD:
        return done[0]
    last = _levels(longest)
    bounds = [(_offset(i), _offset(i + 1) - _offset(i)) for i in range(last)]
    ranges = F.array(*[F.struct(F.lit(i).alias("level"), F.substring("b", lo + 1, n).alias("digit")) for i, (lo, n) in enumerate(bounds)])
    bodies = active.where(F.col("nbytes") > HEAD).select("rid").join(base.select("rid", F.col("row.text").alias("text")), "rid")
    bodies = bodies.select("rid", _normal(F.col("text")).alias("b")).select("rid", F.explode(ranges).alias("r")).select("rid", "r.level", "r.digit").where(F.length("digit") > 0)
    bodies = saved(bodies, "radix-digits", ["level"])
    cur = active.where(F.col("nbytes") > HEAD)
    held = [active]
    for level in range(last):
        digits = cur.join(bodies.where(F.col("level") == level).select("rid", "digit"), "rid")
        names = digits.groupBy("gid", "digit").agg(F.count(F.lit(1)).alias("n"), F.min("rid").alias("next")).where("n > 1").drop("n")
        names = saved(names, "radix-names")
        handed.append(names)
        cur = saved(digits.join(names, ["gid", "digit"]).select("rid", F.col("next").alias("gid"), "nbytes"), "radix")
        held.append(cur)
        ended = F.col("nbytes") <= _offset(level + 1)
        done.append(cur.where(ended).select("rid", "gid"))
        cur = cur.where(~ended)
    out = done[0]
    for part in done[1:]:
        out = out.union(part)
    out = saved(out, "radix-groups")
    drop_saved(bodies, *held, *handed)
    return out


def _grouped(docs: DataFrame, row) -> tuple[DataFrame, DataFrame]:
    """The saved rows, and per row its group's keeper."""
    b = _normal(F.col("text"))
    keyed = docs.select(row.alias("row"), F.col("doc_id").cast("long").alias("doc_id"), order_id(LAST).alias("d"), F.length(F.coalesce("text", F.lit(""))).alias("n_cp"), b.alias("b"))
    keyed = keyed.select(F.monotonically_increasing_id().alias("rid"), "row", "doc_id", "d", "n_cp", F.length("b").alias("nbytes"), F.substring("b", 1, HEAD).alias("head"), F.unhex(F.sha2("b", 256)).alias("sha"))
    base = saved(keyed, "radix-rows")
    members = _split(base).join(base.select("rid", "d", "doc_id", "n_cp"), "rid")
    best = members.groupBy("gid").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct((-F.col("n_cp")).alias("a"), "d", "rid", "doc_id")).alias("k"))
    best = saved(best, "radix-best")
    kept = members.select("rid", "gid").join(best, "gid").select("rid", "n", F.col("k.rid").alias("keep_rid"), F.col("k.doc_id").alias("keep_id"))
    return base, kept


def exact_groups(docs: DataFrame) -> DataFrame:
    """One row per input row: ``doc_id, keep_id, group_size, kept, text_sha256``."""
    base, kept = _grouped(docs, F.struct("text"))
    out = base.select("rid", "doc_id", "sha").join(kept, "rid", "left")
    alone = F.col("n").isNull()
    return out.select(
        "doc_id",
        F.when(alone, F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
        (alone | (F.col("rid") == F.col("keep_rid"))).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
    )


def exact_dedup(docs: DataFrame) -> DataFrame:
    """The input rows and columns without the rows that an equal text replaces."""
    base, kept = _grouped(docs, F.struct("*"))
    gone = kept.where("rid <> keep_rid").select("rid")
    return base.join(gone, "rid", "left_anti").select("row.*")


def op6_exact_dedup(spark, sf_dir):
    return exact_groups(spark.read.parquet(f"{sf_dir}/documents.parquet"))


SQL = r"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS body FROM documents),
n AS (SELECT doc_id, length(body) AS cp, regexp_replace(body, '[\x20\x09-\x0D]+', '', 'g') AS norm FROM t)
SELECT doc_id,
       first_value(doc_id) OVER w AS keep_id,
       count(*) OVER (PARTITION BY norm) AS group_size,
       row_number() OVER w = 1 AS kept,
       sha256(norm) AS text_sha256
FROM n WINDOW w AS (PARTITION BY norm ORDER BY cp DESC, doc_id)
"""
