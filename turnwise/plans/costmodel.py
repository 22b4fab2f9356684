"""The cost of an edge by kind of access, the number of hot vertices a budget allows, and where methods break even."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class AccessTimes:
    """Seconds (or any unit) of an update of shared state that hits or misses, of a private update and of a lookup that hit."""

    shared_hit: float
    shared_miss: float
    private_hit: float
    lookup_hit: float


#: Printed times in picoseconds at 128, 16 and 4 threads (shared miss, private hit). Lookup is the time
#: that makes full use break even at a coverage of 0.8; hits of shared updates aren't printed and are taken as private ones.
PRINTED = {128: AccessTimes(260.0, 540.0, 260.0, 224.0), 16: AccessTimes(600.0, 1600.0, 600.0, 224.0), 4: AccessTimes(2600.0, 5900.0, 2600.0, 224.0)}


def hot_capacity(budget: float, record_bytes: float, load_factor: float, private_bytes: float, owners: int) -> int:
    """Hot vertices whose lookup record and private state fit the budget, private state being held by each owner."""
    if min(budget, record_bytes, private_bytes) < 0 or not 0 < load_factor <= 1 or owners < 1:
        raise ValueError("sizes must not be negative, the load factor in (0, 1], owners 1 or more")
    per_vertex = record_bytes / load_factor + private_bytes * owners
    return int(budget // per_vertex) if per_vertex else 0


def cost_shared(h: float, t: AccessTimes) -> float:
    """Time of an edge if a share h of updates hits."""
    return t.shared_miss - h * (t.shared_miss - t.shared_hit)


def cost_hybrid(c: float, t: AccessTimes) -> float:
    """Time of an edge if a share c of edges is hot; every edge pays a lookup."""
    return t.lookup_hit + c * t.private_hit + (1 - c) * t.shared_miss


def break_even_h(c: float, t: AccessTimes) -> float:
    """The hit ratio above which the shared method is faster; may lie outside 0 to 1."""
    gain = t.shared_miss - t.shared_hit
    return (c * (t.shared_miss - t.private_hit) - t.lookup_hit) / gain if gain else math.inf


def break_even_c(h: float, t: AccessTimes) -> float:
    """The coverage above which the hybrid is faster."""
    gain = t.shared_miss - t.private_hit
    return (h * (t.shared_miss - t.shared_hit) + t.lookup_hit) / gain if gain else math.inf


def model_curves(spark: SparkSession, t: AccessTimes, coverages: list[float], steps: int = 10) -> DataFrame:
    """(h, coverage, cost_shared, cost_hybrid): a grid of both models."""
    grid = spark.range(steps + 1).select((F.col("id") / steps).alias("h"), F.explode(F.array(*[F.lit(float(c)) for c in coverages])).alias("coverage"))
    shared = F.lit(t.shared_miss) - F.col("h") * (t.shared_miss - t.shared_hit)
    hybrid = F.lit(t.lookup_hit) + F.col("coverage") * t.private_hit + (1 - F.col("coverage")) * t.shared_miss
    return grid.select(F.round("h", 6).alias("h"), "coverage", F.round(shared, 6).alias("cost_shared"), F.round(hybrid, 6).alias("cost_hybrid"))


def capacity_grid(spark: SparkSession, budgets: list[int], owners: list[int], record_bytes: int = 8, load_percent: int = 50, private_bytes: list[int] | None = None) -> DataFrame:
    """(budget, owners, private_bytes, k) by integer arithmetic."""
    lists = [F.explode(F.array(*[F.lit(x).cast("long") for x in values])) for values in (budgets, owners, private_bytes or [1, 4, 5, 8])]
    x = spark.range(1).select(lists[0].alias("budget")).select("budget", lists[1].alias("owners")).select("budget", "owners", lists[2].alias("private_bytes"))
    return x.withColumn("k", F.floor(F.col("budget") / (F.lit(record_bytes * 100 / load_percent) + F.col("private_bytes") * F.col("owners"))).cast("long"))


def shared_rows(n_edges: int, sides: int = 2) -> int:
    """Rows that the shared method sends by endpoint: all edges in the count and in the placing step."""
    return sides * n_edges


def hybrid_rows(n_edges: int, covered: int, k: int, blocks: int, at_rest: bool = False) -> int:
    """Rows that the hybrid sends: cold edges twice, private counters and insertion points, and hot edges once, to their
    block, unless the edges are at rest by block and stay there, which no plan here reaches yet."""
    partials = min(covered, k * blocks)
    return 2 * (n_edges - covered) + 2 * partials + (0 if at_rest else covered)
