"""Costs and accuracy: closed forms by method, and what is counted on a graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.model import Graph
from turnwise.operators.merge import merge_rounds

METHODS = ("shared", "private", "merge", "hybrid")


def degrees(g: Graph) -> DataFrame:
    return g.edges.groupBy("dst").agg(F.count("*").alias("n"))


def graph_profile(g: Graph) -> DataFrame:
    """(edges, sources, targets, max_out, max_in)."""
    out = g.edges.groupBy("src").agg(F.count("*").alias("n")).agg(F.count("*").alias("sources"), F.max("n").alias("max_out"), F.sum("n").alias("edges"))
    into = degrees(g).agg(F.count("*").alias("targets"), F.max("n").alias("max_in"))
    return out.join(F.broadcast(into), F.lit(True)).select(*[F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c) for c in ("edges", "sources", "targets", "max_out", "max_in")])


def narrow_counter_share(g: Graph, limit: int = 256) -> DataFrame:
    """(vertices, narrow, wasted_bytes): targets of a degree under limit, and bytes of four-byte counters that one byte would do for."""
    return degrees(g).agg(F.count("*").alias("vertices"), F.count_if(F.col("n") < limit).alias("narrow"), (3 * F.count_if(F.col("n") < limit)).alias("wasted_bytes"))


def coverage(g: Graph, hot: DataFrame) -> DataFrame:
    """(edges, covered): edges with a hot endpoint."""
    x = g.edges.select("dst").join(F.broadcast(hot.select("dst", F.lit(1).alias("_hot"))), "dst", "left")
    return x.agg(F.count("*").alias("edges"), F.count("_hot").alias("covered"))


def coverage_by_k(g: Graph, ks: list[int]) -> DataFrame:
    """(k, edges, covered) for the exact hot sets of each k."""
    from turnwise.operators.order import rank_by_frequency

    ranked = rank_by_frequency(degrees(g))
    cols = [F.struct(F.lit(k).cast("long").alias("k"), F.coalesce(F.sum(F.when(F.col("rank") < k, F.col("n"))), F.lit(0)).cast("long").alias("covered")) for k in ks]
    return ranked.agg(F.sum("n").cast("long").alias("edges"), F.array(*cols).alias("a")).select("edges", F.explode("a").alias("a")).select("a.k", "edges", "a.covered")


def hot_recall(sampled: DataFrame, exact: DataFrame) -> DataFrame:
    """(found, wanted): how much of the exact hot set a sampled one has."""
    return exact.select("dst").join(sampled.select("dst", F.lit(1).alias("_s")), "dst", "left").agg(F.count("_s").alias("found"), F.count("*").alias("wanted"))


def degree_histogram(g: Graph) -> DataFrame:
    """(log2_class, vertices, edges) of in-degrees."""
    c = (F.length(F.bin("n")) - 1).cast("long")
    return degrees(g).groupBy(c.alias("log2_class")).agg(F.count("*").alias("vertices"), F.sum("n").cast("long").alias("edges"))


def footprint(spark: SparkSession, n_vertices: int, n_edges: int, workers: list[int], k: int = 256, counter: int = 4, offset: int = 8, identifier: int = 4, record: int = 16, private: int = 5) -> DataFrame:
    """(method, workers, extra_bytes, graph_bytes): memory beyond input and output."""
    graph = (n_vertices + 1) * offset + n_edges * identifier
    rows = []
    for p in workers:
        rows += [("shared", p, n_vertices * counter, graph), ("private", p, p * n_vertices * (counter + offset), graph), ("merge", p, p * n_vertices * counter + n_edges * identifier, graph), ("hybrid", p, n_vertices * counter + k * (record + private * p), graph)]
    return spark.createDataFrame(rows, "method string, workers long, extra_bytes long, graph_bytes long")


def access_counts(spark: SparkSession, n_vertices: int, n_edges: int, covered: int, k: int, workers: int, sample: int = 0, fan_in: int = 2) -> DataFrame:
    """(method, edge_reads, probes, shared_updates, private_updates, slot_writes, counters_summed, count_rows, place_rows)."""
    e, v, hot = n_edges, n_vertices, min(covered, k * workers)
    rounds = merge_rounds(workers, fan_in)
    rows = [
        ("shared", 2 * e, 0, 2 * e, 0, e, v, e, e),
        ("private", 2 * e, 0, 0, 2 * e, e, workers * v, min(e, workers * v), min(e, workers * v)),
        ("merge", (1 + rounds) * e, 0, 0, 0, 0, 0, 0, rounds * e),
        ("hybrid", 2 * e + sample, 2 * e + v, 2 * (e - covered), 2 * covered, e, v - k + k * workers, e - covered + hot, e - covered + hot),
    ]
    return spark.createDataFrame(rows, "method string, edge_reads long, probes long, shared_updates long, private_updates long, slot_writes long, counters_summed long, count_rows long, place_rows long")


def private_rows(g: Graph) -> DataFrame:
    """(rows, most): rows of the private histograms over all blocks (column block), and the largest histogram."""
    x = g.edges.groupBy("block").agg(F.count_distinct("dst").alias("n"))
    return x.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("rows"), F.coalesce(F.max("n"), F.lit(0)).cast("long").alias("most"))


def block_rollup(tagged: DataFrame) -> DataFrame:
    """(block, hot, n, level): private, per-block and total counters in one pass."""
    x = tagged.select("block", F.col("hot_index").isNotNull().cast("int").alias("hot"))
    return x.rollup("block", "hot").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


def speedup_table(runs: DataFrame, baseline: str = "shared") -> DataFrame:
    """(graph, representation, method, speedup) from runs (graph, representation, method, seconds)."""
    base = runs.where(F.col("method") == baseline).select("graph", "representation", F.col("seconds").alias("_base"))
    return runs.join(base, ["graph", "representation"]).select("graph", "representation", "method", F.round(F.col("_base") / F.col("seconds"), 6).alias("speedup"))


def speedup_summary(speedups: DataFrame) -> DataFrame:
    return speedups.groupBy("method").agg(F.min("speedup").alias("least"), F.max("speedup").alias("most"), F.round(F.avg("speedup"), 6).alias("mean"), F.round(F.stddev_pop("speedup"), 6).alias("sd"))


def loss_summary(speedups: DataFrame) -> DataFrame:
    """(method, losses, mean_loss): share of time lost where a method is slower than the baseline."""
    lost = speedups.where("speedup < 1").select("method", (1 / F.col("speedup") - 1).alias("l"))
    return lost.groupBy("method").agg(F.count("*").alias("losses"), F.round(F.avg("l"), 6).alias("mean_loss"))


def parallel_efficiency(runs: DataFrame, least: int) -> DataFrame:
    """(method, cores, efficiency) from (method, cores, seconds), as a share of what the least number of cores gives each."""
    base = runs.where(F.col("cores") == least).select("method", F.col("seconds").alias("_base"))
    return runs.join(base, "method").select("method", "cores", F.round(F.col("_base") / F.col("seconds") / (F.col("cores") / least), 6).alias("efficiency"))


def edges_per_second(runs: DataFrame) -> DataFrame:
    return runs.withColumn("edges_per_second", F.round(F.col("edges") / F.col("seconds"), 3))
