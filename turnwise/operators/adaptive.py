"""The full method: find hot vertices, judge both plans on a small share of the edges, run the better one."""

from __future__ import annotations

import time
from dataclasses import asdict, dataclass
from statistics import median

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.functions.cachesim import hit_ratio_direct
from turnwise.model import Csr, Graph
from turnwise.operators.blocks import edge_blocks
from turnwise.operators.hotset import exact_hot, sample_hot, tag_hot
from turnwise.operators.hybrid import hybrid_degrees, hybrid_transpose
from turnwise.operators.shared import shared_degrees, shared_transpose
from turnwise.plans.costmodel import PRINTED, AccessTimes, cost_hybrid, cost_shared, hybrid_rows, shared_rows


@dataclass(frozen=True)
class Decision:
    method: str
    k: int
    coverage: float
    h_est: float
    cost_shared: float
    cost_hybrid: float
    largest_shared: int
    largest_hybrid: int


def probe_edges(g: Graph, fraction: float) -> Graph:
    """A share of the edges by a hash of their source, so both plans and every retry see the same ones."""
    return g.with_edges(g.edges.where(F.pmod(F.xxhash64("src"), F.lit(1_000_000)) < int(fraction * 1_000_000)))


def probe_time(g: Graph, hot: DataFrame, fraction: float, blocks: int, repeats: int = 3) -> tuple[float, float]:
    """Median seconds of both counting steps on the probe's edges, run in turn after a warm-up."""
    p = probe_edges(g, fraction)
    b = edge_blocks(p, blocks, "range")
    jobs = (lambda: [shared_degrees(p)], lambda: list(hybrid_degrees(tag_hot(b.edges, hot), blocks)))
    seconds: tuple[list[float], list[float]] = ([], [])
    for i in range(repeats + 1):
        for job, into in zip(jobs, seconds, strict=True):
            began = time.perf_counter()
            for x in job():
                x.write.format("noop").mode("overwrite").save()
            if i:
                into.append(time.perf_counter() - began)
    return median(seconds[0]), median(seconds[1])


def edge_stats(g: Graph, hot: DataFrame) -> dict:
    """Edges, hot edges, hot vertices, the largest in-degree and the largest cold one, in one job over degrees."""
    deg = g.edges.groupBy("dst").agg(F.count("*").alias("n"))
    x = deg.join(F.broadcast(hot.select("dst", "hot_index")), "dst", "left")
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    r = x.agg(zero(F.sum("n")).alias("edges"), zero(F.sum(F.when(F.col("hot_index").isNotNull(), F.col("n")))).alias("covered"), F.count("hot_index").alias("k"), zero(F.max("n")).alias("largest"), zero(F.max(F.when(F.col("hot_index").isNull(), F.col("n")))).alias("largest_cold")).first()
    return r.asDict()


def decide(g: Graph, hot: DataFrame, *, blocks: int, cost: str = "rows", probe_fraction: float = 0.01, times: AccessTimes = PRINTED[16], lines: int = 256) -> Decision:
    """cost "rows" compares rows sent and breaks near ties by the largest reducer; "model" the two formulas with a simulated hit ratio; "time" measures."""
    s = edge_stats(g, hot)
    c = s["covered"] / s["edges"] if s["edges"] else 0.0
    h = 0.0
    # a hot vertex's edges are dealt over the blocks
    largest = (s["largest"], max(s["largest_cold"], -(-s["largest"] // max(1, blocks))))
    if cost == "rows":
        a, b = float(shared_rows(s["edges"])), float(hybrid_rows(s["edges"], s["covered"], s["k"], blocks))
        # looking up every endpoint has its price; it pays if a fifth of the rows stays at home or the straggler halves
        use = s["k"] > 0 and (b <= 0.8 * a or (b < a and largest[1] * 2 <= largest[0]))
    elif cost == "model":
        h = hit_ratio_direct(probe_edges(g, max(probe_fraction, 0.1)), lines).first()["hit_ratio"] or 0.0
        a, b = cost_shared(h, times), cost_hybrid(c, times)
        use = b < a
    elif cost == "time":
        a, b = probe_time(g, hot, probe_fraction, blocks)
        use = b < a
    else:
        raise ValueError(f"unknown cost: {cost}")
    return Decision("hybrid" if use else "shared", s["k"], c, h, a, b, *largest)


def adaptive_transpose(g: Graph, *, k: int = 256, blocks: int = 64, cost: str = "rows", probe_fraction: float = 0.01, hot_source: str = "sample", force: str | None = None, sort_lists: bool = True, seed: int = 1) -> tuple[Csr, Decision]:
    """(Csr, Decision). force runs one plan whatever the probe says; results are the same either way."""
    hot = sample_hot(g, k, seed=seed) if hot_source == "sample" else exact_hot(g, k)
    hot = _settled(hot)
    d = decide(g, hot, blocks=blocks, cost=cost, probe_fraction=probe_fraction)
    method = force or d.method
    if method not in ("shared", "hybrid"):
        raise ValueError(f"unknown method: {method}")
    csr = shared_transpose(g, sort_lists=sort_lists) if method == "shared" else hybrid_transpose(g, hot, blocks=blocks, sort_lists=sort_lists)
    return csr, d


def _settled(hot: DataFrame) -> DataFrame:
    """The k rows as a local table, so that a random sample isn't drawn again by each step. k is bounded by hot_capacity()."""
    return hot.sparkSession.createDataFrame([tuple(r) for r in hot.collect()], hot.schema)


def decision_row(spark: SparkSession, graph: str, d: Decision) -> DataFrame:
    row = {"graph": graph, **asdict(d)}
    return spark.createDataFrame([tuple(row.values())], "graph string, method string, k long, coverage double, h_est double, cost_shared double, cost_hybrid double, largest_shared long, largest_hybrid long").select("graph", "method", "k", "coverage", "h_est", "cost_shared", "cost_hybrid", "largest_shared", "largest_hybrid")
