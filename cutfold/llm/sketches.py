"""Bottom-k sketches of word-shingle hashes, in DataFrame expressions only.

A sketch is the sorted array of the k smallest distinct hashes of a text's word
shingles. Sketches merge by union and cut, across rows and across parts of a
corpus, and estimate resemblance, containment and the number of distinct
shingles.

Defined cases: NULL text is empty and has an empty sketch; a text with fewer words
than a shingle has one shingle; two empty sketches resemble each other by 1, an
empty and another one by 0. Repeated rows have equal sketches. Next to a repeated
id stands one of its rows, the one with the least text hash; NULL ids rank last in
descending order.
"""

from __future__ import annotations

from math import ceil

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cutfold.functions.storage import saved
from cutfold.llm._common import FIRST, SPACES, order_id

K, WORDS = 64, 5


def shingle_words(text: Column) -> Column:
    """Hashes of the words of a text, in order."""
    words = F.filter(F.split(F.coalesce(text, F.lit("")), SPACES), lambda w: w != "")
    return F.transform(words, lambda w: F.xxhash64(w))


def bottom_k(word_hashes: Column, k: int = K, words: int = WORDS) -> Column:
    """The sketch of a column made by :func:`shingle_words`; materialise that column
    under a name first, as it is used several times."""
    n = F.size(word_hashes)
    shingles = F.transform(F.sequence(F.lit(0), F.greatest(n - words, F.lit(0))), lambda i: F.xxhash64(*[F.get(word_hashes, i + j) for j in range(words)]))
    hashes = F.when(n == 0, F.array().cast("array<bigint>")).when(n < words, F.array(F.xxhash64(word_hashes))).otherwise(shingles)
    return F.slice(F.sort_array(F.array_distinct(hashes)), 1, k)


def merge(a: Column, b: Column, k: int = K) -> Column:
    return F.slice(F.sort_array(F.array_union(a, b)), 1, k)


def resemblance(a: Column, b: Column, k: int = K) -> Column:
    """Estimated Jaccard similarity of the shingle sets."""
    both = merge(a, b, k)
    return F.when(F.size(both) == 0, 1.0).otherwise(F.size(F.array_intersect(F.array_intersect(both, a), b)) / F.size(both))


def containment(a: Column, b: Column, k: int = K) -> Column:
    """Estimated share of a's shingles that b has; 1 for an empty a."""
    seen = F.array_intersect(merge(a, b, k), a)
    return F.when(F.size(seen) == 0, F.when(F.size(a) == 0, 1.0).otherwise(0.0)).otherwise(F.size(F.array_intersect(seen, b)) / F.size(seen))


def distinct_shingles(a: Column, k: int = K) -> Column:
    """Estimated number of distinct shingles; exact below k."""
    top = (F.element_at(a, F.lit(-1)).cast("double") + 2.0**63) / 2.0**64
    return F.when(F.size(a) < k, F.size(a).cast("double")).otherwise((k - 1) / top)


def sketch_documents(docs: DataFrame, *keep: Column, k: int = K, words: int = WORDS) -> DataFrame:
    """``keep`` columns and the ``sketch`` of ``text``."""
    return docs.select(*keep, shingle_words(F.col("text")).alias("_w")).withColumn("sketch", bottom_k(F.col("_w"), k, words)).drop("_w")


def merge_groups(sketches: DataFrame, by: str, k: int = K, fan_in: int = 128) -> DataFrame:
    """One merged ``sketch`` per value of ``by``, through a tree of merges of about
    ``fan_in`` sketches each, so no group is gathered at once."""
    most = sketches.groupBy(by).count().agg(F.max("count")).first()[0] or 0
    cur = sketches.select(by, "sketch", F.xxhash64("sketch", F.monotonically_increasing_id()).alias("_h"))
    while True:
        groups = max(1, ceil(most / fan_in))
        fold = F.aggregate(F.collect_list("sketch"), F.array().cast("array<bigint>"), lambda a, b: merge(a, b, k))
        cur = cur.groupBy(by, F.pmod("_h", F.lit(groups)).alias("_g")).agg(fold.alias("sketch"))
        if groups == 1:
            return cur.select(by, "sketch")
        cur = saved(cur.select(by, "sketch", F.xxhash64("_g").alias("_h")), "sketch-merge")
        most = groups


def neighbours(ids: DataFrame) -> DataFrame:
    """``ids(_d, need, ...)``, unique ``_d``; adds ``taker`` and ``taker_need``: the
    row before in descending order, which for the first row is the last. Ranges
    are ordered in parallel; only one row per range meets in one task."""
    parts = int(ids.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = saved(ids.repartitionByRange(parts, F.col("_d").desc()).withColumn("_p", F.spark_partition_id()), "sketch-ranges")
    inside = Window.partitionBy("_p").orderBy(F.col("_d").desc())
    edges = ranged.groupBy("_p").agg(F.min(F.struct("_d", "need")).alias("tail"))
    order = Window.orderBy("_p")
    last = F.last("tail").over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    edges = edges.select("_p", F.coalesce(F.lag("tail").over(order), last).alias("before"))
    linked = ranged.withColumn("mine", F.lag(F.struct("_d", "need")).over(inside)).join(edges, "_p")
    return linked.withColumn("b", F.coalesce("mine", "before")).select(*ids.columns, F.col("b._d").alias("taker"), F.col("b.need").alias("taker_need"))


def hexed(sketch: Column) -> Column:
    """A sketch as text: 16 hexadecimal digits per hash."""
    return F.array_join(F.transform(sketch, lambda h: F.lower(F.lpad(F.hex(h), 16, "0"))), "")


def fingerprint_edits(docs: DataFrame, k: int = K, words: int = WORDS) -> DataFrame:
    """Every text and its edited text (its last third replaced by the start of the
    next document's, in descending id order) with their sketches and likenesses."""
    rows = docs.select(order_id(FIRST).alias("_d"), F.coalesce("text", F.lit("")).alias("text"))
    need = F.floor(F.length("text") / 3).cast("int")
    ids = rows.select("_d", need.alias("need"), F.xxhash64("text").alias("t")).groupBy("_d").agg(F.max("need").alias("need"), F.min("t").alias("t"))
    links = saved(neighbours(ids), "sketch-links")
    # As an equality this would become a join key, and the texts would be dealt twice.
    lent = rows.join(links, "_d").where(F.xxhash64("text").bitwiseXOR(F.col("t")) == 0).select(F.col("taker").alias("_d"), F.expr("substring(text, 1, taker_need)").alias("start"), shingle_words(F.col("text")).alias("_w"))
    lent = lent.select("_d", "start", bottom_k(F.col("_w"), k, words).alias("next"))
    lent = lent.groupBy("_d").agg(F.min(F.struct("start", "next")).alias("l")).select("_d", "l.start", "l.next")
    both = rows.join(lent, "_d")
    edit = F.expr("concat(substring(text, 1, length(text) - cast(floor(length(text) / 3) as int)), substring(start, 1, cast(floor(length(text) / 3) as int)))")
    both = both.select("_d", F.length("text").cast("long").alias("n_chars"), edit.alias("edited"), "next", shingle_words(F.col("text")).alias("w"))
    both = both.select("_d", "n_chars", "next", F.sha2("edited", 256).alias("edited_sha256"), "w", shingle_words(F.col("edited")).alias("e"))
    both = both.select("_d", "n_chars", "next", "edited_sha256", bottom_k(F.col("w"), k, words).alias("own"), bottom_k(F.col("e"), k, words).alias("edit"))
    return both.select(
        F.when(F.col("_d") != FIRST, F.col("_d")).alias("doc_id"),
        "n_chars",
        "edited_sha256",
        F.col("own").alias("sketch"),
        F.col("edit").alias("edited_sketch"),
        resemblance(F.col("own"), F.col("edit"), k).alias("near_edited"),
        resemblance(F.col("own"), F.col("next"), k).alias("near_next"),
    )


def op9_fingerprints(spark, sf_dir):
    out = fingerprint_edits(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "n_chars", "edited_sha256", hexed(F.col("sketch")).alias("fingerprint"), hexed(F.col("edited_sketch")).alias("edited_fingerprint"), "near_edited", "near_next")
