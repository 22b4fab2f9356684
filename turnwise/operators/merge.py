"""Baseline that transposes blocks by themselves and merges the results in rounds until one is left.

A run is a transposed block: each edge with its place in the list of its endpoint there. Each round puts fan_in
neighbouring runs together; the lists of the later ones follow those of the earlier ones, so a merge moves places by the
lengths of the lists before and compares nothing. The slots come from the last merge alone. A round is written to the
shared folder before the next one reads it. A hot endpoint's list is merged by a join on (run, endpoint), whose skew
Spark may split, since nothing is sorted there. fan_in = blocks is one round.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from turnwise.model import Csr, Graph, any_payload
from turnwise.operators.blocks import edge_blocks
from turnwise.operators.prefix import prefix_offsets
from turnwise.storage import dropped, stored


def merge_rounds(blocks: int, fan_in: int) -> int:
    n = 0
    while blocks > 1:
        blocks, n = math.ceil(blocks / fan_in), n + 1
    return n


@any_payload
def block_merge_transpose(g: Graph, blocks: int = 8, fan_in: int = 2) -> Csr:
    if fan_in < 2:
        raise ValueError("a merge needs two runs")
    x = edge_blocks(g, blocks).edges.withColumnRenamed("block", "run")
    runs = stored(x.withColumn("place", F.row_number().over(Window.partitionBy("run", "dst").orderBy(*g.order_columns())) - 1), "runs")
    lists = stored(runs.groupBy("run", "dst").agg(F.count("*").alias("n")), "lists")
    left = blocks
    while left > 1:
        left = math.ceil(left / fan_in)
        into = F.floor(F.col("run") / fan_in).cast("long")
        earlier = Window.partitionBy("into", "dst").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
        moved = lists.withColumn("into", into).withColumn("by", F.sum("n").over(earlier)).where("by > 0").select("run", "dst", "by")
        merged = runs.join(moved, ["run", "dst"], "left").select("src", "dst", *g.payload, into.alias("run"), (F.col("place") + F.coalesce("by", F.lit(0))).alias("place"))
        was, runs = (runs, lists), stored(merged, "runs")
        lists = stored(lists.groupBy(into.alias("run"), "dst").agg(F.sum("n").alias("n")), "lists")
        for old in was:
            dropped(old)
    offsets = prefix_offsets(lists.select("dst", "n"), g.n_dst)
    placed = runs.join(offsets.withColumnRenamed("vertex", "dst"), "dst").select((F.col("start") + F.col("place")).alias("pos"), F.col("src").alias("endpoint"), *g.payload)
    return Csr(offsets, placed, g.n_dst, g.n_src, "in" if g.orientation == "out" else "out")
