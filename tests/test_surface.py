import pytest
from pyspark.sql import functions as F

from cutfold.operators.graph import validate
from cutfold.plans import sqlsurface
from cutfold.sources import builders, io
from cutfold.streaming import online

SF = "/root/testdata/sf0.001"


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_files_round_trip(spark, tmp_path):
    g = builders.planted(spark, 60, 3)
    io.write_edges(g, str(tmp_path / "e"))
    assert rows(io.read_edges(spark, str(tmp_path / "e")).edges) == rows(g.edges)
    io.write_adjacency(g, str(tmp_path / "a"))
    back = io.read_adjacency(spark, str(tmp_path / "a"))
    assert rows(back.edges) == rows(g.edges) and rows(back.nodes) == rows(g.nodes)


def test_adjacency_without_weights(spark):
    g = io.parse_adjacency(spark.createDataFrame([("1\t2 3:4",), ("2\t",), ("9",), ("",)], "value string"))
    assert rows(g.edges) == [(1, 2, 1), (1, 3, 4)] and [r.id for r in g.nodes.orderBy("id").collect()] == [1, 2, 3, 9]


def test_data_source(spark):
    spark.dataSource.register(io.SyntheticEdges)
    assert spark.read.format("cutfold_edges").option("kind", "ring").option("n", 10).load().count() == 10
    assert spark.read.format("cutfold_edges").option("kind", "star").option("n", 10).load().count() == 9


def test_block_folders_and_levels(spark, tmp_path):
    g = builders.cliques(spark, 2, 4)
    part = g.nodes.select("id", (F.col("id") >= 4).cast("int").alias("block"))
    io.write_partitioned_graph(g, part, str(tmp_path / "p"))
    arcs = spark.read.parquet(str(tmp_path / "p" / "arcs"))
    assert arcs.where("block = 0").count() == 13 and arcs.where("block <> dst_block").count() == 2
    io.save_level(g, 1, str(tmp_path / "h"))
    assert rows(io.load_level(spark, str(tmp_path / "h"), 1).edges) == rows(g.edges)


def test_other_formats(spark, tmp_path):
    df = spark.range(5).withColumn("x", F.lit("a"))
    for fmt in ("json", "orc"):
        df.write.format(fmt).save(str(tmp_path / fmt))
        assert io.load(spark, str(tmp_path / fmt), fmt, ["id"]).count() == 5


def test_sql_functions(spark):
    sqlsurface.register_functions(spark)
    assert spark.sql("select * from cutfold_ring(12)").count() == 12
    g = builders.cliques(spark, 2, 4)
    sqlsurface.register(g, "tc")
    spark.sql("create or replace temp view many as select 1 as g, u, v, w from tc_edges union all select 2, u, v, w from tc_edges")
    out = spark.sql("select * from cutfold_partition(table(many) partition by (g), 2, 0.03D)")
    assert out.count() == 16 and out.groupBy("block").count().where("count <> 8").count() == 0
    assert spark.sql("select count(*) from tc_arcs").first()[0] == 26


@pytest.mark.parametrize("name", [n for n in builders.TABLE_GRAPHS])
def test_builders_are_valid(spark, name):
    validate(builders.TABLE_GRAPHS[name](spark, SF))


def test_synthetic_sizes(spark):
    assert builders.grid(spark, 3, 4).edges.count() == 17
    assert builders.path(spark, 5).edges.count() == 4 and builders.star(spark, 5).edges.count() == 4


def stream_of(spark, tmp_path, df, name):
    df.repartition(3).write.parquet(str(tmp_path / name))
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / name))


def drain(stream, name, mode):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return stream.sparkSession.table(name)


def test_windows_match_batch(spark, tmp_path):
    e = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    for kind in ("tumbling", "sliding"):
        got = drain(online.windowed_activity(stream_of(spark, tmp_path, e, kind), kind, "40 days"), "w_" + kind, "complete")
        want = online.windowed_activity(e, kind)
        assert rows(got.select("w.start", "event_type", "n")) == rows(want.select("w.start", "event_type", "n"))


def test_stream_joins_and_state(spark, tmp_path):
    e = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    s = stream_of(spark, tmp_path, e, "ev")
    got = drain(online.clicks_to_purchases(s.where("event_type = 'click'"), s.where("event_type = 'purchase'"), "40 days"), "c2p", "append")
    want = e.alias("c").join(e.alias("p"), F.expr("c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts >= c.ts and p.ts <= c.ts + interval 1 hour"))
    assert got.count() == want.count()
    edges = spark.createDataFrame([(1, 2), (2, 1), (3, 3), (2, 5)], "u long, v long").withColumn("ts", F.lit("2024-01-01").cast("timestamp"))
    assert rows(drain(online.distinct_edges(stream_of(spark, tmp_path, edges, "ed")), "once", "append").select("u", "v")) == [(1, 2), (2, 5)]


def test_following_a_stream(spark, tmp_path):
    g = builders.planted(spark, 90, 3, 5, 1)
    edges = stream_of(spark, tmp_path, g.edges.select("u", "v"), "edges")
    online.follow(edges, str(tmp_path / "out"), 3, 0.1, str(tmp_path / "ck")).awaitTermination(240)
    part = spark.read.parquet(str(tmp_path / "out" / "part" / "2"))
    assert part.count() == 90 and part.where("block not between 0 and 2").count() == 0
    assert spark.read.parquet(str(tmp_path / "out" / "edges" / "2")).count() == g.edges.count()


def test_frequent_lines_link_their_documents(spark, tmp_path):
    common = "a line that very many documents hold"
    docs = [(i, f"{common}\n{common}\nand a line of its own, number {i}") for i in range(120)] + [(None, common)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    g = builders.TABLE_GRAPHS["doc_line_hubs"](spark, str(tmp_path))
    validate(g)
    assert [r.u for r in g.edges.orderBy("u").collect()] == [2 * i for i in range(120)]
    assert g.edges.select("v").distinct().count() == 1 and g.nodes.count() == 121
