"""Shared pieces of the training-data operators.

Rows are identified by ``(_d, _t)``: the document id (NULL becomes a stated
extreme) and a hash of the text, so rows that repeat an id stay apart unless
their texts are equal too. Operators project to private columns before they
work, so extra input columns of any name cannot clash.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

LAST = 2**63 - 1
FIRST = -(2**63)
#: Words are runs of anything but these six characters; same as bytes.split().
SPACE_CHARS = " \t\n\x0b\x0c\r"
WORD = r"[^\x20\x09-\x0D]+"
SPACES = r"[\x20\x09-\x0D]+"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def order_id(null_as: int) -> Column:
    """The id as an order key; NULL ids rank as ``null_as``."""
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(null_as).cast("long"))


def with_key(docs: DataFrame, null_as: int = LAST, *extra: Column) -> DataFrame:
    """Project to ``_d, _t, doc_id, text`` (text NULL becomes empty) and extras."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(order_id(null_as).alias("_d"), F.xxhash64(text).alias("_t"), F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), *extra)


def held_out() -> Column:
    """Rows kept from every fit: crc32 of the id's digits, modulo 4, is 2."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))


def map_arrow(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch | Iterator[pa.RecordBatch]], schema: str | StructType) -> DataFrame:
    """``fn`` maps one record batch to one or several; empty input is fine."""

    def run(batches):
        for batch in batches:
            out = fn(batch)
            if isinstance(out, pa.RecordBatch):
                yield out
            else:
                yield from out

    return df.mapInArrow(run, schema)


def schema_with(src: DataFrame, skip: int, more: str) -> StructType:
    """The schema of ``src`` without its first ``skip`` fields, and ``more`` (DDL)."""
    return StructType(src.schema.fields[skip:] + StructType.fromDDL(more).fields)


def slices(texts: list[str], limit: int = 2_000_000) -> Iterator[tuple[int, int]]:
    """Index ranges of consecutive texts that hold about ``limit`` characters, so
    that per-character arrays stay small; a longer text gets a range of its own."""
    start, held = 0, 0
    for i, t in enumerate(texts):
        if held and held + len(t) > limit:
            yield start, i
            start, held = i, 0
        held += len(t)
    if start < len(texts):
        yield start, len(texts)
