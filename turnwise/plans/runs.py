"""Measured execution: seconds, CPU seconds and exchanged rows of each step of each method, in tables that plans.measures reads.

Every step is run on what the steps before have written, so that a step's time has nothing of theirs. Times are medians of
repeats, taken in turn over the methods after one run on the first form that doesn't count; it warms the code of all forms.
"""

from __future__ import annotations

import os
import time
from collections.abc import Callable
from statistics import median

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.functions.locality import representations
from turnwise.model import Graph
from turnwise.operators.blocks import edge_blocks
from turnwise.operators.hotset import exact_hot, sample_hot, tag_hot
from turnwise.operators.hybrid import hybrid_degrees, hybrid_offsets, hybrid_place, hybrid_transpose
from turnwise.operators.merge import block_merge_transpose
from turnwise.operators.prefix import prefix_offsets
from turnwise.operators.private import private_scan_transpose
from turnwise.operators.shared import shared_degrees, shared_place, shared_transpose
from turnwise.storage import dropped, stored

RUN_SCHEMA = "graph string, representation string, method string, step string, cores long, edges long, seconds double, cpu_seconds double"


def settled(g: Graph, label: str = "graph") -> Graph:
    """g with its edges written once, so that runs don't time how the edges came about."""
    return g.with_edges(stored(g.edges, label))


def _cpu(spark: SparkSession) -> float:
    """CPU seconds so far of the driver's process, which has the executors too in local mode; on a cluster the tasks' CPU times of the event log take its place."""
    pid = spark.sparkContext._jvm.java.lang.ProcessHandle.current().pid()
    with open(f"/proc/{pid}/stat") as f:
        fields = f.read().rpartition(")")[2].split()
    return (int(fields[11]) + int(fields[12])) / os.sysconf("SC_CLK_TCK")


def timed(spark: SparkSession, job: Callable[[], list[DataFrame]]) -> tuple[float, float]:
    """Seconds and CPU seconds of running all rows of the frames that job gives."""
    began, cpu = time.perf_counter(), _cpu(spark)
    for df in job():
        df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began, _cpu(spark) - cpu


def whole_methods(g: Graph, k: int, blocks: int) -> dict[str, Callable[[], list[DataFrame]]]:
    """The jobs of each method from edges to both tables; the hybrid's samples are part of it."""
    both = lambda csr: [csr.offsets, csr.endpoints]
    return {
        "shared": lambda: both(shared_transpose(g)),
        "private": lambda: both(private_scan_transpose(g, blocks)),
        "merge": lambda: both(block_merge_transpose(g, blocks)),
        "hybrid": lambda: both(hybrid_transpose(g, sample_hot(g, k), blocks=blocks)),
    }


def method_steps(g: Graph, k: int, blocks: int) -> dict[tuple[str, str], Callable[[], list[DataFrame]]]:
    """The steps of the shared method and of the hybrid, each from what is written of the ones before."""
    hot = stored(exact_hot(g, k), "hot")
    degrees = stored(shared_degrees(g), "degrees")
    offsets = stored(prefix_offsets(degrees, g.n_dst), "offsets")
    b = settled(edge_blocks(g, blocks, "range"), "blocks")
    tagged = tag_hot(b.edges, hot)
    cold, partials = (stored(x, "counts") for x in hybrid_degrees(tagged, blocks))
    _, ip = hybrid_offsets(cold, partials, g.n_dst)
    ip = stored(ip, "insertion-points")
    return {
        ("shared", "count"): lambda: [shared_degrees(g)],
        ("shared", "scan"): lambda: [prefix_offsets(degrees, g.n_dst)],
        ("shared", "place"): lambda: [shared_place(g, offsets)],
        ("shared", "place_unsorted"): lambda: [shared_place(g, offsets, sort_lists=False)],
        ("hybrid", "sample"): lambda: [sample_hot(g, k)],
        ("hybrid", "count"): lambda: list(hybrid_degrees(tagged, blocks)),
        ("hybrid", "scan"): lambda: list(hybrid_offsets(cold, partials, g.n_dst)),
        ("hybrid", "place"): lambda: [hybrid_place(b, tagged, offsets, ip, blocks)],
        ("hybrid", "place_unsorted"): lambda: [hybrid_place(b, tagged, offsets, ip, blocks, sort_lists=False)],
    }


def run_table(spark: SparkSession, graph: str, g: Graph, *, k: int = 256, blocks: int = 16, repeats: int = 3, forms: tuple[str, ...] = ("row", "row_random", "column", "column_random"), steps: bool = False, only: tuple[str, ...] | None = None) -> DataFrame:
    """The runs of all methods (or of the steps of shared and hybrid) on the forms of a graph, one row each, medians of repeats."""
    rows, cores, warm = [], spark.sparkContext.defaultParallelism, False
    for form, raw in representations(g).items():
        if form not in forms:
            continue
        x = settled(raw)
        n = x.edges.count()
        jobs = method_steps(x, k, blocks) if steps else {(m, "all"): job for m, job in whole_methods(x, k, blocks).items()}
        jobs = {key: job for key, job in jobs.items() if only is None or key[0] in only}
        seconds: dict[tuple[str, str], list[tuple[float, float]]] = {key: [] for key in jobs}
        for i in range(warm, repeats + 1):
            for key, job in jobs.items():
                took = timed(spark, job)
                if i:
                    seconds[key].append(took)
        warm = True
        rows += [(graph, form, method, step, cores, n, median(t[0] for t in took), median(t[1] for t in took)) for (method, step), took in seconds.items()]
        dropped(x.edges)
    return spark.createDataFrame(rows, RUN_SCHEMA)


def step_shares(runs: DataFrame) -> DataFrame:
    """(graph, representation, method, step, share): of the time of a method's counting, scanning and placing."""
    x = runs.where(F.col("step").isin("count", "scan", "place"))
    total = x.groupBy("graph", "representation", "method").agg(F.sum("seconds").alias("_all"))
    return x.join(total, ["graph", "representation", "method"]).select("graph", "representation", "method", "step", F.round(F.col("seconds") / F.col("_all"), 6).alias("share"))


def sort_times(runs: DataFrame) -> DataFrame:
    """(graph, representation, method, sort_seconds, sort_share): what sorted lists add to the placing step."""
    of = lambda step, name: runs.where(F.col("step") == step).select("graph", "representation", "method", F.col("seconds").alias(name))
    x = of("place", "_sorted").join(of("place_unsorted", "_plain"), ["graph", "representation", "method"])
    return x.select("graph", "representation", "method", (F.col("_sorted") - F.col("_plain")).alias("sort_seconds"), ((F.col("_sorted") - F.col("_plain")) / F.col("_sorted")).alias("sort_share"))


def cpu_reduction(runs: DataFrame, baseline: str = "shared") -> DataFrame:
    """(graph, representation, method, speedup, cpu_reduction, difference): CPU seconds saved beside time saved, both as baseline over method."""
    base = runs.where(F.col("method") == baseline).select("graph", "representation", F.col("seconds").alias("_s"), F.col("cpu_seconds").alias("_c"))
    x = runs.where(F.col("method") != baseline).join(base, ["graph", "representation"])
    x = x.select("graph", "representation", "method", (F.col("_s") / F.col("seconds")).alias("speedup"), (F.col("_c") / F.col("cpu_seconds")).alias("cpu_reduction"))
    return x.withColumn("difference", F.abs(F.col("speedup") - F.col("cpu_reduction")) / F.col("speedup"))


def exchanged_rows(df: DataFrame, column: str) -> int:
    """Rows that the exchanges of df's executed plan have written which carry this column; a reused exchange counts once, and what makes a broadcast table doesn't count."""
    execution = df._jdf.queryExecution()
    execution.toRdd().count()
    total, todo = 0, [execution.executedPlan()]
    while todo:
        node = todo.pop()
        name = node.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
        elif name in ("ShuffleQueryStageExec", "TableCacheQueryStageExec", "ResultQueryStageExec"):
            todo.append(node.plan())
        elif name not in ("ReusedExchangeExec", "BroadcastExchangeExec", "BroadcastQueryStageExec"):
            if name == "ShuffleExchangeExec" and f"{column}#" in node.output().mkString(","):
                total += node.metrics().apply("shuffleRecordsWritten").value()
            children = node.children()
            todo += [children.apply(i) for i in range(children.size())]
    return total


def edge_rows(g: Graph, hot: DataFrame, blocks: int) -> DataFrame:
    """(method, count_rows, place_rows): edges that are exchanged in the steps of the shared method and the hybrid, read from executed plans."""
    spark = g.edges.sparkSession
    x = settled(g)
    offsets = stored(prefix_offsets(shared_degrees(x), g.n_dst), "offsets")
    b = settled(edge_blocks(x, blocks, "range"), "blocks")
    tagged = tag_hot(b.edges, hot)
    cold, partials = hybrid_degrees(tagged, blocks)
    ip = stored(hybrid_offsets(cold, partials, g.n_dst)[1], "insertion-points")
    placed = (shared_place(x, offsets), hybrid_place(b, tagged, offsets, ip, blocks))
    rows = [("shared", exchanged_rows(shared_degrees(x), "dst"), exchanged_rows(placed[0], "src")), ("hybrid", exchanged_rows(cold, "dst"), exchanged_rows(placed[1], "src"))]
    for df in (x.edges, offsets, b.edges, ip):
        dropped(df)
    return spark.createDataFrame(rows, "method string, count_rows long, place_rows long")
