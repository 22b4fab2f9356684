"""Baseline with a full private histogram for each worker and static ownership of source ranges.

Its aggregate is as large as workers times vertices in the worst case, which is what limits it. A worker owns one range
of sources, so lists come out sorted.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from turnwise.model import Csr, Graph, any_payload
from turnwise.operators.blocks import edge_blocks
from turnwise.operators.hybrid import clustered
from turnwise.operators.prefix import prefix_offsets


def private_counts(g: Graph, workers: int) -> DataFrame:
    """(block, dst, n): each worker's own histogram; nothing but the clustering by worker moves edges."""
    return clustered(g.edges.select("block", "dst"), workers).groupBy("block", "dst").agg(F.count("*").alias("n"))


@any_payload
def private_scan_transpose(g: Graph, workers: int = 16) -> Csr:
    b = edge_blocks(g, workers)
    counts = private_counts(b, workers)
    offsets = prefix_offsets(counts.groupBy("dst").agg(F.sum("n").alias("n")), g.n_dst)
    w = Window.partitionBy("dst").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    ip = counts.withColumn("_before", F.coalesce(F.sum("n").over(w), F.lit(0))).join(offsets.withColumnRenamed("vertex", "dst"), "dst")
    ip = ip.select("block", "dst", (F.col("start") + F.col("_before")).cast("long").alias("base"))
    e = clustered(b.edges, workers).withColumn("_rank", F.row_number().over(Window.partitionBy("block", "dst").orderBy(*g.order_columns())) - 1)
    placed = e.join(ip, ["block", "dst"]).select((F.col("base") + F.col("_rank")).alias("pos"), F.col("src").alias("endpoint"), *g.payload)
    return Csr(offsets, placed, g.n_dst, g.n_src, "in" if g.orientation == "out" else "out")
