"""Hot vertices: the few endpoints that get most edges."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from turnwise.model import Graph
from turnwise.operators.order import rank_by_frequency
from turnwise.operators.prefix import prefix_offsets

SAMPLE_RATE = 0.01
#: Most hot vertices that are sent to every task: 64 MB of ids and numbers.
MOST_HOT = 1 << 22


def numbered(freq: DataFrame, k: int, method: str = "sort") -> DataFrame:
    """(dst, hot_index, n): the k most frequent of (dst, n), ties to the smaller id, numbered from 0. k is bounded by hot_capacity()."""
    if k > MOST_HOT:
        raise ValueError(f"at most {MOST_HOT} hot vertices go to every task")
    if k <= 0:
        return freq.select("dst", F.lit(0).alias("hot_index"), "n").limit(0)
    if method == "counting":
        return rank_by_frequency(freq).where(F.col("rank") < k).select("dst", F.col("rank").cast("int").alias("hot_index"), "n")
    top = freq.orderBy(F.desc("n"), "dst").limit(k)
    return top.select("dst", (F.row_number().over(Window.orderBy(F.desc("n"), "dst")) - 1).alias("hot_index"), "n")


def exact_hot(g: Graph, k: int, method: str = "sort") -> DataFrame:
    return numbered(g.edges.groupBy("dst").agg(F.count("*").alias("n")), k, method)


def sample_positions(g: Graph, step: int, offset: int = 0) -> DataFrame:
    """(pos, dst): every step-th endpoint of the input's array. Positions are those of the source-ordered array, made in two levels."""
    counts = g.edges.groupBy(F.col("src").alias("dst")).agg(F.count("*").alias("n"))
    starts = prefix_offsets(counts, g.n_src).withColumnRenamed("vertex", "src")
    w = Window.partitionBy("src").orderBy("dst", *[c for c in g.order_columns()[1:]])
    x = g.edges.join(starts, "src").withColumn("pos", F.col("start") + F.row_number().over(w) - 1)
    return x.where((F.col("pos") + offset) % step == 0).select("pos", "dst")


def sample_hot(g: Graph, k: int, rate: float = SAMPLE_RATE, seed: int = 1, method: str = "hash", n_edges: int | None = None) -> DataFrame:
    """The hot vertices of about rate * |V| sampled endpoints; fewer than k where the sample has fewer.

    "hash" draws edges by Spark's seeded sampling in one scan; "systematic" takes every step-th position.
    """
    n = n_edges if n_edges is not None else g.edges.count()
    wanted = max(1, math.ceil(rate * g.n_dst))
    if method == "systematic":
        drawn = sample_positions(g, max(1, n // wanted)).select("dst")
    elif method == "hash":
        drawn = g.edges.select("dst").sample(False, min(1.0, wanted / max(1, n)), seed)
    else:
        raise ValueError(f"unknown method: {method}")
    return numbered(drawn.groupBy("dst").agg(F.count("*").alias("n")), k)


def input_side_hot(g: Graph, k: int) -> DataFrame:
    """Ids ranked by their degree on the input side: cheap from the offsets, and usually the wrong vertices."""
    starts = prefix_offsets(g.edges.groupBy(F.col("src").alias("dst")).agg(F.count("*").alias("n")), g.n_src)
    here, after = starts.alias("a"), starts.select((F.col("vertex") - 1).alias("vertex"), F.col("start").alias("next")).alias("b")
    deg = here.join(after, "vertex").select(F.col("vertex").alias("dst"), (F.col("next") - F.col("start")).alias("n"))
    return numbered(deg.where((F.col("n") > 0) & (F.col("dst") < g.n_dst)), k)


def sketch_hot(g: Graph, k: int, counters: int = 10_000) -> DataFrame:
    """From Spark's frequent-items sketch: constant state, possibly fewer than k."""
    if k <= 0:
        return numbered(g.edges.select("dst", F.lit(1).alias("n")), 0)
    top = g.edges.agg(F.expr(f"approx_top_k(dst, {k}, {max(k, counters)})").alias("t")).select(F.explode("t").alias("t"))
    return numbered(top.select(F.col("t.item").alias("dst"), F.col("t.count").alias("n")), k)


def sample_bound(phi: float, eps: float, delta: float) -> int:
    """Samples that, but for probability delta, show every endpoint of share phi with a share within eps of its own part: 3 ln(2 / delta) / (eps^2 phi)."""
    if not (0 < phi <= 1 and 0 < eps <= 1 and 0 < delta < 1):
        raise ValueError("phi and eps must be in (0, 1], delta in (0, 1)")
    return math.ceil(3 * math.log(2 / (delta * phi)) / (eps**2 * phi))


def checked_hot(hot: DataFrame) -> DataFrame:
    """hot, if it is small enough to go to every task."""
    if hot.limit(MOST_HOT + 1).count() > MOST_HOT:
        raise ValueError(f"at most {MOST_HOT} hot vertices go to every task")
    return hot


def tag_hot(edges: DataFrame, hot: DataFrame) -> DataFrame:
    """edges with hot_index, null where the endpoint is cold: one hash probe an edge. hot has at most MOST_HOT rows, which numbered() and checked_hot() see to."""
    return edges.join(F.broadcast(hot.select("dst", "hot_index")), "dst", "left")
