"""Graph files: edge lists, adjacency text, a data source of its own, block folders,
bucketed tables and saved hierarchies."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import LongType, StructField, StructType

from cutfold.operators.graph import WeightedGraph, from_pairs

EDGES = StructType([StructField("u", LongType()), StructField("v", LongType()), StructField("w", LongType())])


def load(spark: SparkSession, path: str, fmt: str = "parquet", cols: list[str] | None = None, schema=None) -> DataFrame:
    """A table in any of Spark's formats; columns are pruned before anything else."""
    reader = spark.read.format(fmt)
    df = (reader.schema(schema) if schema is not None else reader).load(path)
    return df.select(*cols) if cols else df


def read_edges(spark: SparkSession, path: str, sep: str = "\t", weighted: bool = True) -> WeightedGraph:
    """``u<sep>v[<sep>w]`` lines; missing weights are 1."""
    schema = EDGES if weighted else StructType(EDGES.fields[:2])
    df = spark.read.schema(schema).option("sep", sep).option("comment", "#").csv(path)
    return from_pairs(df if weighted else df.withColumn("w", F.lit(1)))


def write_edges(g: WeightedGraph, path: str, sep: str = "\t") -> None:
    g.edges.select("u", "v", "w").write.option("sep", sep).csv(path)


def parse_adjacency(lines: DataFrame) -> WeightedGraph:
    """``value`` lines ``id<TAB>nbr:w nbr:w ...``; a weight may be left out and a node
    may have no neighbour. Edges may be listed at one end or at both."""
    parts = F.split("value", "\t")
    rows = lines.where(F.trim("value") != "").select(F.get(parts, F.lit(0)).cast("long").alias("u"), F.coalesce(F.get(parts, F.lit(1)), F.lit("")).alias("rest"))
    nbr = rows.select("u", F.explode(F.split(F.trim("rest"), " +")).alias("x")).where("x <> ''")
    nbr = nbr.select("u", F.split("x", ":").alias("p")).select("u", F.get("p", F.lit(0)).cast("long").alias("v"), F.coalesce(F.get("p", F.lit(1)).cast("long"), F.lit(1)).alias("w"))
    once = nbr.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "w").groupBy("u", "v").agg(F.max("w").alias("w"))
    ids = rows.select(F.col("u").alias("id")).union(nbr.select("v")).distinct().withColumn("c", F.lit(1))
    return from_pairs(once, ids)


def read_adjacency(spark: SparkSession, path: str) -> WeightedGraph:
    return parse_adjacency(spark.read.text(path))


def write_adjacency(g: WeightedGraph, path: str) -> None:
    a = g.arcs().groupBy("src").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("dst", "w"))), lambda p: F.concat_ws(":", p["dst"].cast("string"), p["w"].cast("string"))), " ").alias("x"))
    out = g.nodes.join(a, g.nodes["id"] == a["src"], "left")
    out.select(F.concat_ws("\t", F.col("id").cast("string"), F.coalesce("x", F.lit(""))).alias("value")).write.text(path)


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Synthetic(DataSourceReader):
    def __init__(self, options: dict):
        self.kind, self.n, self.parts = options.get("kind", "ring"), int(options.get("n", 10)), int(options.get("partitions", 4))

    def partitions(self):
        step = -(-self.n // self.parts)
        return [_Range(i, min(self.n, i + step)) for i in range(0, self.n, max(1, step))]

    def read(self, part: _Range):
        for i in range(part.lo, part.hi):
            if self.kind == "star":
                if i:
                    yield 0, i, 1
            elif self.kind == "path":
                if i + 1 < self.n:
                    yield i, i + 1, 1
            else:
                yield i, (i + 1) % self.n, 1


class SyntheticEdges(DataSource):
    """``spark.read.format("cutfold_edges").option("kind", "ring").option("n", 100)``."""

    @classmethod
    def name(cls) -> str:
        return "cutfold_edges"

    def schema(self):
        return EDGES

    def reader(self, schema):
        return _Synthetic(self.options)


def write_partitioned_graph(g: WeightedGraph, part: DataFrame, path: str) -> None:
    """One folder per block for nodes and for arcs (by the source's block), so that a
    worker reads its block alone."""
    block = part.select("id", "block")
    g.nodes.join(block, "id").repartition("block").write.partitionBy("block").parquet(f"{path}/nodes")
    arcs = g.arcs().join(block.select(F.col("id").alias("src"), "block"), "src").join(block.select(F.col("id").alias("dst"), F.col("block").alias("dst_block")), "dst")
    # A block's arcs may be most of the graph: split them further by source.
    arcs.repartition("block", F.pmod(F.xxhash64("src"), F.lit(16))).write.partitionBy("block").parquet(f"{path}/arcs")


def save_bucketed(df: DataFrame, key: str, buckets: int, table: str) -> DataFrame:
    """A table bucketed and sorted by a key, which later joins on it need not shuffle."""
    df.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)
    return df.sparkSession.table(table)


def save_level(g: WeightedGraph, level: int, path: str) -> None:
    """Append a hierarchy level, partitioned by level."""
    for name, df in (("nodes", g.nodes), ("edges", g.edges)):
        df.withColumn("level", F.lit(level)).write.mode("append").partitionBy("level").parquet(f"{path}/{name}")


def load_level(spark: SparkSession, path: str, level: int) -> WeightedGraph:
    read = lambda name: spark.read.parquet(f"{path}/{name}").where(F.col("level") == level).drop("level")
    return WeightedGraph(read("nodes"), read("edges"))
