"""Graphs derived from the given tables, and synthetic ones.

Each builder takes (spark, folder) and returns a WeightedGraph; ``SQL`` holds the
same edges for any SQL engine.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cutfold.functions.hashing import text_id, text_id_sql
from cutfold.functions.storage import saved
from cutfold.operators.graph import WeightedGraph, from_distinct, from_pairs

MAX_LINE_DOCS, MIN_LINE_CHARS = 50, 20


def load(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """A table with only the columns that are needed."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def _pairs(df: DataFrame, key: str, node: str) -> DataFrame:
    """Co-occurrence pairs of ``node`` values under a key: counts are multiplied after
    one pre-aggregation, so repeated lines do not multiply join rows."""
    n = df.groupBy(key, node).agg(F.count(F.lit(1)).alias("n"))
    b = n.select(key, F.col(node).alias("v"), F.col("n").alias("m"))
    both = n.select(key, F.col(node).alias("u"), "n").join(b, key).where("u < v")
    return both.groupBy("u", "v").agg(F.sum(F.col("n") * F.col("m")).alias("w"))


def basket(spark, sf_dir) -> WeightedGraph:
    """Parts bought in the same order."""
    return from_pairs(_pairs(load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey"), "l_orderkey", "l_partkey"))


def order_part(spark, sf_dir) -> WeightedGraph:
    """Orders and the parts on their lines, each pair once."""
    e = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey")
    return from_distinct(e.select((2 * F.col("l_orderkey")).alias("u"), (2 * F.col("l_partkey") + 1).alias("v")))


def supply(spark, sf_dir) -> WeightedGraph:
    """Parts and suppliers; weight: lines."""
    e = load(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey")
    return from_pairs(e.select((2 * F.col("l_partkey")).alias("u"), (2 * F.col("l_suppkey") + 1).alias("v"), F.lit(1).alias("w")))


def _customers(spark, sf_dir, other: str) -> WeightedGraph:
    o = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    li = load(spark, sf_dir, "lineitem", "l_orderkey", other)
    e = o.join(li, F.col("o_orderkey") == F.col("l_orderkey"))
    return from_pairs(e.select((2 * F.col("o_custkey")).alias("u"), (2 * F.col(other) + 1).alias("v"), F.lit(1).alias("w")))


def cust_part(spark, sf_dir) -> WeightedGraph:
    """Customers and the parts they bought."""
    return _customers(spark, sf_dir, "l_partkey")


def cust_supp(spark, sf_dir) -> WeightedGraph:
    """Customers and their suppliers."""
    return _customers(spark, sf_dir, "l_suppkey")


def page_links(spark, sf_dir) -> WeightedGraph:
    """Pages and the targets of their links."""
    p = load(spark, sf_dir, "pages", "page_id", "html")
    e = p.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).alias("t"))
    return from_pairs(e.select((2 * F.col("page_id")).alias("u"), (2 * text_id(F.col("t")) + 1).alias("v"), F.lit(1).alias("w")))


def page_hosts(spark, sf_dir) -> WeightedGraph:
    """Pages and the host of their address."""
    p = load(spark, sf_dir, "pages", "page_id", "url")
    host = F.regexp_extract("url", "^[a-zA-Z]+://([^/?#]+)", 1)
    e = p.select((2 * F.col("page_id")).alias("u"), (2 * text_id(host) + 1).alias("v"), F.lit(1).alias("w"))
    return from_pairs(e)


def doc_lines(spark, sf_dir) -> WeightedGraph:
    """Documents that share a line of 2 to MAX_LINE_DOCS documents, as its SQL fixes;
    ``doc_line_hubs`` keeps the more frequent lines too."""
    d = load(spark, sf_dir, "documents", "doc_id", "text")
    lines = d.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") > MIN_LINE_CHARS).distinct()
    lines = lines.select("doc_id", F.md5("line").alias("key"))
    stop = lines.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where((F.col("n") >= 2) & (F.col("n") <= MAX_LINE_DOCS))
    return from_pairs(_pairs(lines.join(stop.select("key"), "key"), "key", "doc_id"))


def doc_line_hubs(spark, sf_dir) -> WeightedGraph:
    """Documents and the lines that two or more of them hold, however many they are:
    a node per line, so a line costs one edge per document instead of all pairs."""
    d = load(spark, sf_dir, "documents", "doc_id", "text").where("doc_id is not null")
    lines = d.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") > MIN_LINE_CHARS)
    lines = lines.select("doc_id", text_id(F.col("line")).alias("key")).distinct()
    shared = lines.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n >= 2").select("key")
    return from_pairs(lines.join(shared, "key").select((2 * F.col("doc_id")).alias("u"), (2 * F.col("key") + 1).alias("v"), F.lit(1).alias("w")))


def geo_tree(spark, sf_dir) -> WeightedGraph:
    """Regions, nations, customers and suppliers as trees; ids are 4 * key + kind."""
    n = load(spark, sf_dir, "nation", "n_nationkey", "n_regionkey")
    a = n.select((4 * F.col("n_regionkey").cast("long")).alias("u"), (4 * F.col("n_nationkey").cast("long") + 1).alias("v"))
    c = load(spark, sf_dir, "customer", "c_custkey", "c_nationkey").select((4 * F.col("c_nationkey").cast("long") + 1).alias("u"), (4 * F.col("c_custkey") + 2).alias("v"))
    s = load(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey").select((4 * F.col("s_nationkey").cast("long") + 1).alias("u"), (4 * F.col("s_suppkey") + 3).alias("v"))
    return from_pairs(a.union(c).union(s).withColumn("w", F.lit(1)))


def turns(spark, sf_dir) -> WeightedGraph:
    """Consecutive turns of a conversation; nodes are all turns."""
    t = load(spark, sf_dir, "conversations", "conv_id", "turn")
    nxt = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    t = t.select((16 * F.col("conv_id") + F.col("turn")).alias("u"), (16 * F.col("conv_id") + nxt).alias("v"))
    return from_pairs(t.where("v is not null").withColumn("w", F.lit(1)), t.select(F.col("u").alias("id"), F.lit(1).alias("c")).distinct())


def user_trail(spark, sf_dir) -> WeightedGraph:
    """Users of consecutive events. Days are ordered in parallel; only each day's
    first and last event meet."""
    e = load(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("day", F.to_date("ts"))
    w = Window.partitionBy("day").orderBy("ts", "event_id")
    inside = e.select("user_id", F.lead("user_id").over(w).alias("v")).where("v is not null")
    days = e.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
    across = days.select("last", F.lead("first").over(Window.orderBy("day")).alias("v")).where("v is not null")
    return from_pairs(inside.union(across).select(F.col("user_id").alias("u"), "v", F.lit(1).alias("w")))


def user_minutes(spark, sf_dir) -> WeightedGraph:
    """Users with an event of the same type in the same minute."""
    e = load(spark, sf_dir, "events", "ts", "user_id", "event_type")
    key = F.concat_ws("|", "event_type", F.date_format(F.date_trunc("minute", "ts"), "yyyyMMddHHmm"))
    return from_pairs(_pairs(e.select(key.alias("key"), "user_id"), "key", "user_id"))


def knn(spark, sf_dir, k: int = 5, block: int = 8192) -> WeightedGraph:
    """Union of the k nearest by cosine, ties to the smaller id. Blocks of up to some
    ``block`` vectors meet in pairs, each pair of blocks once, and a vector keeps the k
    best of each block it met; so no task holds more than two blocks. Exact, and
    quadratic in the number of vectors."""
    import numpy as np
    import pyarrow as pa

    src = load(spark, sf_dir, "embeddings", "vec_id", "embedding").where("vec_id is not null")
    count = max(1, -(-src.count() // block))
    packed = src.groupBy(F.pmod(F.xxhash64("vec_id"), F.lit(count)).cast("int").alias("b")).agg(F.sort_array(F.collect_list(F.struct("vec_id", "embedding"))).alias("x"))
    packed = saved(packed.select("b", "x.vec_id", F.flatten("x.embedding").alias("values")), "knn-blocks")
    a = packed.select(F.col("b").alias("i"), F.col("vec_id").alias("ids"), F.col("values").alias("xs"))
    b = packed.select(F.col("b").alias("j"), F.col("vec_id").alias("others"), F.col("values").alias("ys"))
    tasks = spark.range(count).select(F.col("id").cast("int").alias("i")).select("i", F.explode(F.sequence(F.lit(0), "i")).alias("j"))
    met = tasks.join(a, "i").join(b, "j").select("ids", "xs", "others", "ys").repartition(max(1, count * (count + 1) // 2))

    def unit(values, n):
        x = values.to_numpy().astype(np.float64).reshape(n, -1)
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)

    def best(ids, x, others, y):
        """Per query the k best of ``others``, which are sorted by id."""
        few = min(k, len(others))
        for lo in range(0, len(ids), 512):
            q = ids[lo : lo + 512]
            sim = np.round(x[lo : lo + 512] @ y.T, 9)
            sim[q[:, None] == others] = -2
            edge = np.partition(sim, len(others) - few, axis=1)[:, len(others) - few]
            row, col = np.nonzero(sim >= edge[:, None])
            s = sim[row, col]
            order = np.lexsort((col, -s, row))
            row, col, s = row[order], col[order], s[order]
            rank = np.arange(len(row)) - np.searchsorted(row, row)
            keep = (rank < few) & (s > -1.5)
            yield pa.RecordBatch.from_pydict({"q": q[row[keep]], "o": others[col[keep]], "s": s[keep]})

    def near(batches):
        for batch in batches:
            for at in range(batch.num_rows):
                ids, others = (batch.column(c)[at].values.to_numpy() for c in (0, 2))
                x, y = unit(batch.column(1)[at].values, len(ids)), unit(batch.column(3)[at].values, len(others))
                yield from best(ids, x, others, y)
                if not np.array_equal(ids, others):
                    yield from best(others, y, ids, x)

    found = met.mapInArrow(near, "q long, o long, s double")
    top = found.groupBy("q").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("s")).alias("d"), "o"))), 1, k).alias("t"))
    pairs = top.select("q", F.explode("t").alias("t")).select(F.least("q", "t.o").alias("u"), F.greatest("q", "t.o").alias("v"), F.greatest(F.lit(1).cast("long"), (-F.col("t.d") * 1000).cast("long")).alias("w"))
    return from_pairs(pairs.distinct())


def ring(spark, n: int) -> WeightedGraph:
    return from_pairs(spark.range(n).select(F.col("id").alias("u"), ((F.col("id") + 1) % n).alias("v"), F.lit(1).alias("w")))


def path(spark, n: int) -> WeightedGraph:
    return from_pairs(spark.range(n - 1).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"), F.lit(1).alias("w")))


def star(spark, n: int) -> WeightedGraph:
    return from_pairs(spark.range(1, n).select(F.lit(0).alias("u"), F.col("id").alias("v"), F.lit(1).alias("w")))


def grid(spark, a: int, b: int) -> WeightedGraph:
    p = spark.range(a * b).select("id", F.floor(F.col("id") / b).alias("x"), (F.col("id") % b).alias("y"))
    right = p.where(F.col("y") < b - 1).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))
    down = p.where(F.col("x") < a - 1).select(F.col("id").alias("u"), (F.col("id") + b).alias("v"))
    return from_pairs(right.union(down).withColumn("w", F.lit(1)))


def cliques(spark, count: int, size: int) -> WeightedGraph:
    """A chain of cliques, neighbours joined by one edge."""
    p = spark.range(count * size).select("id", F.floor(F.col("id") / size).alias("q"))
    pairs = p.select(F.col("id").alias("u"), F.explode(F.sequence(F.col("q") * size, (F.col("q") + 1) * size - 1)).alias("v")).where("u < v")
    bridge = spark.range(count - 1).select(((F.col("id") + 1) * size - 1).alias("u"), ((F.col("id") + 1) * size).alias("v")) if count > 1 else pairs.limit(0)
    return from_pairs(pairs.union(bridge).withColumn("w", F.lit(1)))


def planted(spark, n: int, blocks: int, inside: int = 6, across: int = 1, seed: int = 0, hubs: bool = False) -> WeightedGraph:
    """Block b holds the ids equal to b modulo ``blocks``; every node draws partners
    inside its block and anywhere. With ``hubs`` partners are drawn by the cube of a
    uniform number, which gives heavy-tailed degrees."""
    from cutfold.functions.hashing import P, mix, part_of

    def draws(m, spread, salt):
        d = spark.range(n).select("id", F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("j"))
        key = F.col("id") * 64 + F.col("j")
        x = part_of(key, salt, spread)
        if hubs:
            r = mix(key, salt)
            x = F.floor(F.floor(F.floor(r * r / P) * r / P) * spread / P)
        return d, x

    d, x = draws(inside, max(1, n // blocks), seed * 2 + 1)
    near = d.select(F.col("id").alias("u"), (x * blocks + F.col("id") % blocks).cast("long").alias("v"))
    d, x = draws(across, n, seed * 2 + 2)
    far = d.select(F.col("id").alias("u"), x.cast("long").alias("v"))
    nodes = spark.range(n).select("id", F.lit(1).alias("c"))
    return from_pairs(near.union(far).where(F.col("v") < n).withColumn("w", F.lit(1)), nodes)


TABLE_GRAPHS = {
    "basket": basket,
    "order_part": order_part,
    "supply": supply,
    "cust_part": cust_part,
    "cust_supp": cust_supp,
    "page_links": page_links,
    "page_hosts": page_hosts,
    "doc_lines": doc_lines,
    "doc_line_hubs": doc_line_hubs,
    "knn": knn,
    "geo_tree": geo_tree,
    "turns": turns,
    "user_trail": user_trail,
    "user_minutes": user_minutes,
}

#: Every named graph: those of the tables, and synthetic ones with communities.
GRAPHS = TABLE_GRAPHS | {
    "communities": lambda spark, sf_dir: planted(spark, 5000, 40, 5, 2),
    "hub_communities": lambda spark, sf_dir: planted(spark, 5000, 40, 5, 2, hubs=True),
    "mesh": lambda spark, sf_dir: grid(spark, 70, 70),
}

_CANON = "SELECT least(u, v) AS u, greatest(u, v) AS v, cast(sum(w) AS BIGINT) AS w FROM ({}) p WHERE u <> v GROUP BY 1, 2"
SQL = {
    "basket": _CANON.format("SELECT a.l_partkey AS u, b.l_partkey AS v, 1 AS w FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey"),
    "order_part": _CANON.format("SELECT DISTINCT 2 * l_orderkey AS u, 2 * l_partkey + 1 AS v, 1 AS w FROM lineitem"),
    "supply": _CANON.format("SELECT 2 * l_partkey AS u, 2 * l_suppkey + 1 AS v, 1 AS w FROM lineitem"),
    "cust_part": _CANON.format("SELECT 2 * o_custkey AS u, 2 * l_partkey + 1 AS v, 1 AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey"),
    "cust_supp": _CANON.format("SELECT 2 * o_custkey AS u, 2 * l_suppkey + 1 AS v, 1 AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey"),
    "page_links": _CANON.format(f"SELECT 2 * page_id AS u, 2 * {text_id_sql('t')} + 1 AS v, 1 AS w FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS t FROM pages)"),
    "page_hosts": _CANON.format(f"SELECT 2 * page_id AS u, 2 * {text_id_sql('t')} + 1 AS v, 1 AS w FROM (SELECT page_id, regexp_extract(url, '^[a-zA-Z]+://([^/?#]+)', 1) AS t FROM pages)"),
    "doc_lines": "WITH l AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) > 20), "
    "s AS (SELECT line FROM l GROUP BY line HAVING count(*) BETWEEN 2 AND 50), k AS (SELECT l.* FROM l JOIN s USING (line)) "
    + _CANON.format("SELECT a.doc_id AS u, b.doc_id AS v, 1 AS w FROM k a JOIN k b ON a.line = b.line AND a.doc_id < b.doc_id"),
    "doc_line_hubs": "WITH l AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents WHERE doc_id IS NOT NULL) WHERE length(line) > 20), "
    "s AS (SELECT line FROM l GROUP BY line HAVING count(*) >= 2) " + _CANON.format(f"SELECT 2 * doc_id AS u, 2 * {text_id_sql('line')} + 1 AS v, 1 AS w FROM l JOIN s USING (line)"),
    "geo_tree": _CANON.format(
        "SELECT 4 * n_regionkey::BIGINT AS u, 4 * n_nationkey::BIGINT + 1 AS v, 1 AS w FROM nation UNION ALL SELECT 4 * c_nationkey::BIGINT + 1, 4 * c_custkey + 2, 1 FROM customer UNION ALL SELECT 4 * s_nationkey::BIGINT + 1, 4 * s_suppkey + 3, 1 FROM supplier"
    ),
    "turns": _CANON.format("SELECT 16 * conv_id + turn AS u, 16 * conv_id + lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS v, 1 AS w FROM conversations"),
    "user_trail": _CANON.format("SELECT user_id AS u, lead(user_id) OVER (ORDER BY ts, event_id) AS v, 1 AS w FROM events"),
    "user_minutes": _CANON.format(
        "SELECT a.user_id AS u, b.user_id AS v, 1 AS w FROM events a JOIN events b ON a.event_type = b.event_type AND date_trunc('minute', a.ts) = date_trunc('minute', b.ts) AND a.user_id < b.user_id"
    ),
}
