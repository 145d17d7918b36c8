"""Mix sources to target weights by pivotal dependent rounding.

Every row gets ``target / source_size`` expected copies. Whole copies are certain;
the fractions of a source's rows are rounded together: two rows meet, one hands
mass (in words) to the other at random until one of them is at 0 or at a whole
copy, and the other carries on. Each meeting keeps the sum of their mass, and a last
draw decides the one row that is left, so the words taken from a source differ from
its target by less than that row's words.

Rows that repeat source, id and text are one item of the rounding, with their
copies in one sum: n of them get ``floor(n * part)`` further copies for certain, and
only the rest of that sum meets others. The first of them, in row order, take the
copies. Their ranks come from counts per input partition, so no group of repeats is
gathered at once.

The meetings form a reduction tree: items fall into blocks of about ``block`` by a
hash, meet from the largest to the smallest (so that what stays undecided is
small), a block leaves one undecided item, and the leftovers form the next level's
blocks until one per source is left, which a last draw decides. Everything is
DataFrame expressions; draws are hashes of ids and texts, so reruns agree.

Defined cases: a NULL text has no words and is never taken; NULL source is a source
of its own, ranked last; NULL ids hash as such; a source without words has target 0.
"""

from __future__ import annotations

from math import ceil

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cutfold.functions.storage import saved
from cutfold.llm._common import WORD

WEIGHTS, CAP, BLOCK, SEED = (5, 2, 1), 3.0, 64, 17
_EPS = 1e-9


def source_targets(units: DataFrame, weights: tuple = WEIGHTS, cap: float = CAP) -> DataFrame:
    """``source, source_size, rows, target``, one row per source. Raising all
    uncapped targets in step by weight ends where resharing the excess ends."""
    per = units.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.when(F.col("size") > 0, 1)).alias("rows"))
    rank = F.row_number().over(Window.orderBy(F.col("source").isNull(), F.col("source")))
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((rank - 1) % len(weights) + 1).cast("int"))
    per = per.withColumn("weight", weight).withColumn("top", F.col("source_size") * cap)
    everyone = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    by_fill = Window.orderBy(F.col("top") / F.col("weight"), F.col("source").isNull(), F.col("source"))
    upto = by_fill.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    total = F.sum("source_size").over(everyone)
    left = total - (F.sum("top").over(upto) - F.col("top"))
    level = left / (F.sum("weight").over(everyone) - F.sum("weight").over(upto) + F.col("weight"))
    per = per.withColumn("level", F.when(level <= F.col("top") / F.col("weight"), level)).withColumn("place", F.row_number().over(by_fill))
    level = F.coalesce(F.min_by("level", F.when(F.col("level").isNotNull(), F.col("place"))).over(everyone), F.lit(float("inf")))
    return per.select("source", "source_size", "rows", F.least(F.col("top"), F.col("weight") * level).alias("target"))


#: One meeting. ``s`` holds the undecided row (or none) and the decided ones; ``x``
#: is the next row; w is its size, m its mass, and a draw u decides who gives.
_MEET = f"""
(s, x) -> if(s.carry is null,
  named_struct('carry', x, 'done', s.done),
  transform(array(named_struct(
      'a', least(s.carry.w - s.carry.m, x.m),
      'b', least(s.carry.m, x.w - x.m),
      'u', shiftrightunsigned(xxhash64(s.carry.id, s.carry.h, x.id, x.h, salt), 11) / 9007199254740992D)),
    g -> transform(array(if(g.u * (g.a + g.b) < g.b,
          named_struct('c', s.carry.m + g.a, 'x', x.m - g.a),
          named_struct('c', s.carry.m - g.b, 'x', x.m + g.b))),
      r -> transform(array(named_struct(
            'c', named_struct('id', s.carry.id, 'h', s.carry.h, 'w', s.carry.w, 'm', r.c),
            'x', named_struct('id', x.id, 'h', x.h, 'w', x.w, 'm', r.x),
            'cd', r.c <= {_EPS}D * s.carry.w or r.c >= (1D - {_EPS}D) * s.carry.w,
            'xd', r.x <= {_EPS}D * x.w or r.x >= (1D - {_EPS}D) * x.w)),
        t -> named_struct(
            'carry', if(not t.cd, t.c, if(not t.xd, t.x, null)),
            'done', concat(s.done, if(t.cd, array(t.c), array()), if(t.xd and t.cd, array(t.x), array()), if(t.xd and not t.cd, array(t.x), array()))))[0])[0])[0])
"""


def _fold(items: DataFrame, level: int) -> DataFrame:
    """Blocks ``(source, block)`` of items -> the decided rows and the carry."""
    kind = "struct<id:bigint,h:bigint,w:double,m:double>"
    rows = F.sort_array(F.collect_list(F.struct((-F.col("w")).alias("big"), F.xxhash64(F.lit(SEED), F.lit(level), "id", "h").alias("o"), "id", "h", "w", "m")))
    blocks = items.groupBy("source", "block").agg(rows.alias("items")).withColumn("salt", F.lit(SEED * 1000 + level))
    start = f"named_struct('carry', cast(null as {kind}), 'done', cast(array() as array<{kind}>))"
    rows = "transform(items, x -> named_struct('id', x.id, 'h', x.h, 'w', x.w, 'm', x.m))"
    return blocks.select("source", F.expr(f"aggregate({rows}, {start}, {_MEET})").alias("s"))


def _block(level: int, blocks: Column) -> Column:
    return F.pmod(F.xxhash64(F.lit(SEED + 1), F.lit(level), "id", "h"), F.greatest(blocks, F.lit(1)))


def _items(units: DataFrame) -> DataFrame:
    """``units(rid, id, h, source, size)`` as chunks of equal rows: ``source, id, h, size,
    rids, before, n``, one row per input partition that holds some of them; ``before``
    counts those of earlier partitions and ``n`` all."""
    same = ["source", "id", "h"]
    chunk = F.shiftright("rid", 33).alias("chunk")
    parts = units.groupBy(*same, chunk).agg(F.first("size").alias("size"), F.sort_array(F.collect_list("rid")).alias("rids"))
    parts = parts.withColumn("here", F.size("rids").cast("long"))
    known = Window.partitionBy(*same)
    upto = known.orderBy("chunk").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return parts.withColumn("before", F.sum("here").over(upto) - F.col("here")).withColumn("n", F.sum("here").over(known)).drop("chunk", "here")


def mix_copies(units: DataFrame, weights: tuple = WEIGHTS, cap: float = CAP, block: int = BLOCK) -> DataFrame:
    """``units(rid, id, h, source, size)`` -> those columns and ``source_size, target,
    copies``. ``id`` and ``h`` (an id and a text hash) name a row in every draw, ``rid``
    (from ``monotonically_increasing_id``) tells rows apart."""
    goals = saved(source_targets(units, weights, cap), "mix-targets")
    share = F.when(F.col("source_size") > 0, F.least(F.lit(float(cap)), F.col("target") / F.col("source_size"))).otherwise(0.0)
    goals = goals.withColumn("share", share).withColumn("whole", F.floor("share")).withColumn("part", F.col("share") - F.col("whole"))
    most = goals.agg(F.max("rows")).first()[0] or 0
    chunks = saved(_items(units), "mix-items")
    own = goals.select(F.col("source").alias("gsource"), "source_size", "target", "rows", "whole", "part")
    told = chunks.join(own, chunks["source"].eqNullSafe(F.col("gsource"))).drop("gsource")
    told = told.withColumn("sure", F.floor(F.col("n") * F.col("part") + _EPS)).withColumn("rest", F.greatest(F.col("n") * F.col("part") - F.col("sure"), F.lit(0.0)))
    items = told.where((F.col("size") > 0) & (F.col("before") == 0) & (F.col("rest") > _EPS))
    items = items.select("source", "id", "h", F.col("size").cast("double").alias("w"), (F.col("size") * F.col("rest")).alias("m"), F.ceil(F.col("rows") / block).alias("blocks"))
    items = items.withColumn("block", _block(0, F.col("blocks")))
    taken, level, widest = None, 0, ceil(most / block)
    while True:
        folded = saved(_fold(items, level), "mix-level")
        done = folded.select("source", F.explode("s.done").alias("x"))
        taken = done if taken is None else taken.union(done)
        carried = folded.where("s.carry is not null").select("source", "s.carry.*")
        if widest <= 1:
            break
        level += 1
        shrink = block**level
        # Leftovers of a source spread over the blocks that its share of rows needs.
        counts = goals.select(F.col("source").alias("src"), F.ceil(F.col("rows") / (shrink * block)).alias("blocks"))
        items = carried.join(counts, carried["source"].eqNullSafe(counts["src"])).drop("src")
        items = items.withColumn("block", _block(level, F.col("blocks")))
        widest = ceil(widest / block)
    u = F.shiftrightunsigned(F.xxhash64(F.lit(SEED + 2), "id", "h"), 11) / F.lit(9007199254740992.0)
    last = carried.select("source", F.struct("id", "h", "w", F.when(u * F.col("w") < F.col("m"), F.col("w")).otherwise(0.0).alias("m")).alias("x"))
    chosen = taken.union(last).where(F.col("x.m") > F.col("x.w") / 2)
    chosen = chosen.select(F.col("source").alias("csource"), F.col("x.id").alias("cid"), F.col("x.h").alias("ch"), F.lit(1).alias("more"))
    match = F.col("source").eqNullSafe(F.col("csource")) & F.col("id").eqNullSafe(F.col("cid")) & (F.col("h") == F.col("ch"))
    out = told.join(chosen, match, "left").withColumn("extra", F.col("sure") + F.coalesce("more", F.lit(0)))
    out = out.select("id", "h", "source", "size", "source_size", "target", "whole", "extra", "before", F.posexplode("rids").alias("at", "rid"))
    got = F.col("whole") + F.when(F.col("before") + F.col("at") < F.col("extra"), 1).otherwise(0)
    return out.select("rid", "id", "h", "source", "size", "source_size", "target", F.when(F.col("size") > 0, got).otherwise(0).cast("long").alias("copies"))


def _units(docs: DataFrame, rid: Column) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(rid.alias("rid"), F.col("doc_id").cast("long").alias("id"), F.xxhash64(text).alias("h"), F.col("source").cast("string").alias("source"), F.regexp_count(text, F.lit(WORD)).cast("long").alias("size"))


def mix_documents(docs: DataFrame, weights: tuple = WEIGHTS, cap: float = CAP) -> DataFrame:
    """The input columns, each row as often as the mix takes it."""
    rows = saved(docs.select(F.monotonically_increasing_id().alias("rid"), F.struct("*").alias("row")), "mix-rows")
    units = saved(_units(rows.select("rid", "row.doc_id", "row.text", "row.source"), F.col("rid")), "mix-units")
    copies = mix_copies(units, weights, cap).where("copies > 0").select("rid", "copies")
    return rows.join(copies, "rid").select("row", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select("row.*")


def op1_mix_sources(spark, sf_dir):
    units = saved(_units(spark.read.parquet(f"{sf_dir}/documents.parquet"), F.monotonically_increasing_id()), "mix-units")
    mixed = mix_copies(units)
    return mixed.select(F.col("id").alias("doc_id"), "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))
