"""The graphs of the experiments, built from the given tables, each with the SQL of its edges for the oracle.

build(spark, sf_dir) gives a Graph; SQL gives rows (src, dst) from views of the same tables. Ids of words, pages, users
and turns come from dictionaries in the order of their keys.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from turnwise.model import Graph
from turnwise.operators.prefix import dense_ids, two_level_prefix

HREF = 'href="([^"]*)"'
#: Most copies of an edge that are made from one row at once.
REPEATS = 1 << 16


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if name == "events":
        df = df.withColumn("ts", F.col("ts").cast("timestamp"))
    return df.select(*columns) if columns else df


def _size(df: DataFrame, column: str) -> int:
    """One more than the largest id."""
    top = df.agg(F.max(column)).first()[0]
    return 0 if top is None else int(top) + 1


def tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, at, word): runs of A-Z and a-z in lower case."""
    d = table(spark, sf_dir, "documents", "doc_id", "text").where("text IS NOT NULL")
    return d.select("doc_id", F.posexplode(F.regexp_extract_all("text", F.lit("[A-Za-z]+"), 0)).alias("at", "w")).select("doc_id", "at", F.lower("w").alias("word"))


def word_successor(spark: SparkSession, sf_dir: str) -> Graph:
    t = tokens(spark, sf_dir)
    ids = dense_ids(t, "word")
    # equal pairs are counted where they are read, so that only distinct ones meet the ids; then each is as many edges again
    words = table(spark, sf_dir, "documents", "text").where("text IS NOT NULL").select(F.transform(F.regexp_extract_all("text", F.lit("[A-Za-z]+"), 0), F.lower).alias("ws"))
    pairs = words.select(F.explode(F.arrays_zip(F.col("ws").alias("word"), F.slice("ws", 2, F.size("ws")).alias("next"))).alias("p")).select("p.*").where("next IS NOT NULL")
    pairs = pairs.groupBy("word", "next").agg(F.count("*").alias("n"))
    e = pairs.join(ids.withColumnRenamed("id", "src"), "word").join(ids.select(F.col("word").alias("next"), F.col("id").alias("dst")), "next").select("src", "dst", "n")
    e = e.select("src", "dst", "n", F.explode(F.sequence(F.lit(0), F.floor((F.col("n") - 1) / REPEATS))).alias("part"))
    e = e.select("src", "dst", F.explode(F.sequence(F.lit(1), F.least(F.lit(REPEATS), F.col("n") - F.col("part") * REPEATS))).alias("i")).select("src", "dst")
    return Graph.of(e, ids.count())


def document_word(spark: SparkSession, sf_dir: str) -> Graph:
    t = tokens(spark, sf_dir)
    ids = dense_ids(t, "word")
    e = t.join(ids, "word").select(F.col("doc_id").alias("src"), F.col("id").alias("dst"))
    return Graph.of(e, _size(table(spark, sf_dir, "documents", "doc_id"), "doc_id"), ids.count())


def page_link(spark: SparkSession, sf_dir: str) -> Graph:
    p = table(spark, sf_dir, "pages", "page_id", "html")
    links = p.select(F.col("page_id").alias("src"), F.explode(F.regexp_extract_all("html", F.lit(HREF), 1)).alias("target"))
    ids = dense_ids(links, "target")
    return Graph.of(links.join(ids.withColumnRenamed("id", "dst"), "target").select("src", "dst"), _size(p, "page_id"), ids.count())


def _columns(name: str, src: str, dst: str, sizes: tuple[tuple[str, str], tuple[str, str]], *payload: str):
    def build(spark: SparkSession, sf_dir: str) -> Graph:
        e = table(spark, sf_dir, name, src, dst, *payload).select(F.col(src).alias("src"), F.col(dst).alias("dst"), *payload)
        return Graph.of(e, *(_size(table(spark, sf_dir, t, c), c) for t, c in sizes))

    return build


order_part = _columns("lineitem", "l_orderkey", "l_partkey", (("orders", "o_orderkey"), ("part", "p_partkey")))
order_part_weighted = _columns("lineitem", "l_orderkey", "l_partkey", (("orders", "o_orderkey"), ("part", "p_partkey")), "l_quantity", "l_extendedprice")
nation_region = _columns("nation", "n_nationkey", "n_regionkey", (("nation", "n_nationkey"), ("region", "r_regionkey")))
order_customer = _columns("orders", "o_orderkey", "o_custkey", (("orders", "o_orderkey"), ("customer", "c_custkey")))


def _customer(item: str, sized: tuple[str, str]):
    def build(spark: SparkSession, sf_dir: str) -> Graph:
        o, li = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), table(spark, sf_dir, "lineitem", "l_orderkey", item)
        e = li.join(o, li.l_orderkey == o.o_orderkey).select(F.col("o_custkey").alias("src"), F.col(item).alias("dst"))
        return Graph.of(e, _size(table(spark, sf_dir, "customer", "c_custkey"), "c_custkey"), _size(table(spark, sf_dir, *sized), sized[1]))

    return build


customer_part = _customer("l_partkey", ("part", "p_partkey"))
customer_supplier = _customer("l_suppkey", ("supplier", "s_suppkey"))


def copurchase(spark: SparkSession, sf_dir: str) -> Graph:
    li = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey")
    a, b = li.select("l_orderkey", F.col("l_partkey").alias("src")), li.select("l_orderkey", F.col("l_partkey").alias("dst"))
    return Graph.of(a.join(b, "l_orderkey").where("src <> dst").select("src", "dst"), _size(table(spark, sf_dir, "part", "p_partkey"), "p_partkey"), symmetric=True)


def user_next(spark: SparkSession, sf_dir: str) -> Graph:
    """The user of each event to that of the next one. Events are cut by hour, and the first of an hour follows the last before it."""
    ev = table(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("hour", F.floor(F.unix_micros("ts") / 3_600_000_000).cast("long"))
    inside = Window.partitionBy("hour").orderBy("ts", "event_id")
    firsts = ev.groupBy("hour").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"))
    # one row an hour, as many as hours the table spans
    carry = firsts.select("hour", F.lead("first").over(Window.orderBy("hour")).alias("_carry"))
    e = ev.withColumn("n", F.lead("user_id").over(inside)).join(F.broadcast(carry), "hour").select(F.col("user_id").alias("src"), F.coalesce("n", "_carry").alias("dst"))
    return Graph.of(e.where("dst IS NOT NULL"), _size(table(spark, sf_dir, "events", "user_id"), "user_id"))


def user_type(spark: SparkSession, sf_dir: str) -> Graph:
    ev = table(spark, sf_dir, "events", "user_id", "event_type")
    ids = dense_ids(ev, "event_type")
    e = ev.join(F.broadcast(ids), "event_type").select(F.col("user_id").alias("src"), F.col("id").alias("dst"))
    return Graph.of(e, _size(ev, "user_id"), ids.count())


def cubic_skew(spark: SparkSession, sf_dir: str) -> Graph:
    n = table(spark, sf_dir, "part", "p_partkey").count()
    e = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").select(F.col("l_orderkey").alias("src"), F.expr(f"(l_partkey * l_partkey * l_partkey) div {n * n}L").alias("dst"))
    return Graph.of(e, _size(table(spark, sf_dir, "orders", "o_orderkey"), "o_orderkey"), n)


def recursive_synthetic(spark: SparkSession, scale: int = 14, edge_factor: int = 16, a: float = 0.57, b: float = 0.19, c: float = 0.19, seed: int = 7, ids: DataFrame | None = None) -> Graph:
    """2^scale vertices: each bit of both ends falls into a quadrant by a hash of the edge and the level. Edges are the rows of
    ids (column id), or numbers where there are none."""
    e = spark.range(edge_factor << scale) if ids is None else ids
    src = dst = F.lit(0).cast("long")
    for level in range(scale):
        u = F.pmod(F.xxhash64("id", F.lit(seed), F.lit(level)), F.lit(1_000_000)) / 1_000_000.0
        src = src * 2 + F.when(u < a + b, 0).otherwise(1)
        dst = dst * 2 + F.when((u < a) | ((u >= a + b) & (u < a + b + c)), 0).otherwise(1)
    return Graph.of(e.select(src.alias("src"), dst.alias("dst")), 1 << scale)


def turn_parent(spark: SparkSession, sf_dir: str) -> Graph:
    """Each turn to the one before it in its conversation; ids in the order of (conversation, turn)."""
    t = table(spark, sf_dir, "conversations", "conv_id", "turn").where("conv_id IS NOT NULL AND turn IS NOT NULL").distinct()
    sizes = t.groupBy("conv_id").agg(F.count("*").alias("n"))
    starts = two_level_prefix(sizes.withColumnRenamed("conv_id", "key"), "key", "n", _size(t, "conv_id")).select(F.col("key").alias("conv_id"), "start")
    w = Window.partitionBy("conv_id").orderBy("turn")
    ids = t.join(starts, "conv_id").select("conv_id", "turn", (F.col("start") + F.row_number().over(w) - 1).alias("src"))
    e = ids.select("src", F.lag("src").over(w).alias("dst")).where("dst IS NOT NULL")
    return Graph.of(e, t.count())


def similarity(spark: SparkSession, sf_dir: str, least: float = 0.3, block: int = 4096) -> Graph:
    """Vectors whose cosine exceeds least. Blocks of vectors are a query set against all rows; scores are decided on sums of rounded integers."""
    import numpy as np
    import pyarrow as pa

    v = table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    n = _size(v, "vec_id")
    out = None
    for start in range(0, max(n, 1), block):
        rows = v.where((F.col("vec_id") >= start) & (F.col("vec_id") < start + block)).collect()
        if not rows:
            continue
        shared = spark.sparkContext.broadcast((np.array([r.vec_id for r in rows], np.int64), np.array([r.embedding for r in rows], np.float64)))

        def run(batches, shared=shared):
            ids, q = shared.value
            q = q / np.linalg.norm(q, axis=1, keepdims=True)
            for batch in batches:
                mine, x = batch.column(0).to_numpy(), np.array(batch.column(1).to_pylist(), np.float64)
                if not len(mine):
                    continue
                s = (x / np.linalg.norm(x, axis=1, keepdims=True)) @ q.T
                i, j = np.nonzero(np.round(s, 6) > least)
                keep = mine[i] != ids[j]
                yield pa.RecordBatch.from_arrays([pa.array(mine[i][keep]), pa.array(ids[j][keep])], ["src", "dst"])

        part = v.mapInArrow(run, "src bigint, dst bigint")
        out = part if out is None else out.unionByName(part)
    return Graph.of(spark.createDataFrame([], "src long, dst long") if out is None else out, n, symmetric=True)


def document_benchmark(spark: SparkSession, sf_dir: str) -> Graph:
    """Documents to benchmark passages that they contain; the passages are the small side of a nested loop and their size is checked."""
    d, b = table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text")
    items = b.select("item_id", F.col("text").alias("passage"))
    small = (items.agg(F.sum(F.length("passage"))).first()[0] or 0) < 64 << 20
    e = d.join(F.broadcast(items) if small else items, F.contains("text", "passage")).select(F.col("doc_id").alias("src"), F.col("item_id").alias("dst"))
    return Graph.of(e, _size(d, "doc_id"), _size(b, "item_id"))


GRAPHS = {
    "word_successor": word_successor,
    "document_word": document_word,
    "page_link": page_link,
    "order_part": order_part,
    "customer_part": customer_part,
    "customer_supplier": customer_supplier,
    "copurchase": copurchase,
    "user_next": user_next,
    "user_type": user_type,
    "cubic_skew": cubic_skew,
    "turn_parent": turn_parent,
    "similarity": similarity,
    "nation_region": nation_region,
    "order_customer": order_customer,
    "document_benchmark": document_benchmark,
}

_TOKENS = "tok AS (SELECT doc_id, unnest(range(len(ws))) AS k, unnest(ws) AS word FROM (SELECT doc_id, list_transform(regexp_extract_all(text, '[A-Za-z]+'), lambda x: lower(x)) AS ws FROM documents))"
_WORDS = "ids AS (SELECT word, row_number() OVER (ORDER BY word) - 1 AS id FROM (SELECT DISTINCT word FROM tok))"

#: Common table expressions that end in e(src, dst), and the numbers of sources and targets.
SQL = {
    "word_successor": (f"{_TOKENS}, {_WORDS}, p AS (SELECT word, lead(word) OVER (PARTITION BY doc_id ORDER BY k) AS nxt FROM tok), e AS (SELECT a.id AS src, b.id AS dst FROM p JOIN ids a ON p.word = a.word JOIN ids b ON p.nxt = b.word)", "(SELECT count(*) FROM ids)", "(SELECT count(*) FROM ids)"),
    "document_word": (f"{_TOKENS}, {_WORDS}, e AS (SELECT doc_id AS src, id AS dst FROM tok JOIN ids USING (word))", "(SELECT max(doc_id) + 1 FROM documents)", "(SELECT count(*) FROM ids)"),
    "page_link": (f"l AS (SELECT page_id AS src, unnest(regexp_extract_all(html, '{HREF}', 1)) AS target FROM pages), ids AS (SELECT target, row_number() OVER (ORDER BY target) - 1 AS id FROM (SELECT DISTINCT target FROM l)), e AS (SELECT src, id AS dst FROM l JOIN ids USING (target))", "(SELECT max(page_id) + 1 FROM pages)", "(SELECT count(*) FROM ids)"),
    "order_part": ("e AS (SELECT l_orderkey AS src, l_partkey AS dst FROM lineitem)", "(SELECT max(o_orderkey) + 1 FROM orders)", "(SELECT max(p_partkey) + 1 FROM part)"),
    "customer_part": ("e AS (SELECT o_custkey AS src, l_partkey AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey)", "(SELECT max(c_custkey) + 1 FROM customer)", "(SELECT max(p_partkey) + 1 FROM part)"),
    "customer_supplier": ("e AS (SELECT o_custkey AS src, l_suppkey AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey)", "(SELECT max(c_custkey) + 1 FROM customer)", "(SELECT max(s_suppkey) + 1 FROM supplier)"),
    "copurchase": ("e AS (SELECT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey)", "(SELECT max(p_partkey) + 1 FROM part)", "(SELECT max(p_partkey) + 1 FROM part)"),
    "user_next": ("o AS (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events), e AS (SELECT * FROM o WHERE dst IS NOT NULL)", "(SELECT max(user_id) + 1 FROM events)", "(SELECT max(user_id) + 1 FROM events)"),
    "user_type": ("ids AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS id FROM (SELECT DISTINCT event_type FROM events)), e AS (SELECT user_id AS src, id AS dst FROM events JOIN ids USING (event_type))", "(SELECT max(user_id) + 1 FROM events)", "(SELECT count(*) FROM ids)"),
    "cubic_skew": ("e AS (SELECT l_orderkey AS src, (l_partkey * l_partkey * l_partkey) // ((SELECT count(*) FROM part) * (SELECT count(*) FROM part)) AS dst FROM lineitem)", "(SELECT max(o_orderkey) + 1 FROM orders)", "(SELECT count(*) FROM part)"),
    "turn_parent": ("t AS (SELECT conv_id, turn, row_number() OVER (ORDER BY conv_id, turn) - 1 AS id FROM (SELECT DISTINCT conv_id, turn FROM conversations)), e AS (SELECT * FROM (SELECT id AS src, lag(id) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM t) WHERE dst IS NOT NULL)", "(SELECT count(*) FROM t)", "(SELECT count(*) FROM t)"),
    "similarity": ("e AS (SELECT a.vec_id AS src, b.vec_id AS dst FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) > 0.3)", "(SELECT max(vec_id) + 1 FROM embeddings)", "(SELECT max(vec_id) + 1 FROM embeddings)"),
    "nation_region": ("e AS (SELECT n_nationkey AS src, n_regionkey AS dst FROM nation)", "(SELECT max(n_nationkey) + 1 FROM nation)", "(SELECT max(r_regionkey) + 1 FROM region)"),
    "order_customer": ("e AS (SELECT o_orderkey AS src, o_custkey AS dst FROM orders)", "(SELECT max(o_orderkey) + 1 FROM orders)", "(SELECT max(c_custkey) + 1 FROM customer)"),
    "document_benchmark": ("e AS (SELECT doc_id AS src, item_id AS dst FROM documents d JOIN benchmark b ON contains(d.text, b.text))", "(SELECT max(doc_id) + 1 FROM documents)", "(SELECT max(item_id) + 1 FROM benchmark)"),
}
