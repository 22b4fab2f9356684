"""Blocks of the input: the unit of ownership that counting and placing have to share.

A block comes from the data alone, never from the physical partition, since a retried or coalesced partition would not
line up with what the count has seen. Blocks grow with the source, so that lists joined block by block are sorted; a
source whose list reaches over several blocks deals it among them by endpoint, so that each endpoint still meets its
sources in order. Parallel edges stay together.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from turnwise.model import Graph
from turnwise.operators.prefix import prefix_offsets
from turnwise.storage import stored

#: Up to so many blocks their first sources are part of the plan; more are looked up by a join on the source.
PLANNED = 256


def edge_blocks(g: Graph, blocks: int, method: str = "edges") -> Graph:
    """g with a column block from 0 to blocks - 1. "edges" makes them equal in edges, long lists cut; "range" cuts the ids evenly and needs no count."""
    if blocks < 1:
        raise ValueError("there must be a block")
    if method == "range":
        return g.with_edges(g.edges.withColumn("block", F.floor(F.col("src") * blocks / max(1, g.n_src)).cast("long")))
    if method != "edges":
        raise ValueError(f"unknown method: {method}")
    counts = g.edges.groupBy(F.col("src").alias("dst")).agg(F.count("*").alias("n"))
    # counts per source are kept: both the total and the cuts are read from them, and the edges only once
    counts = stored(counts, "out-degrees")
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    width = max(1, -(-total // blocks))
    starts = prefix_offsets(counts, g.n_src).where(F.col("vertex") < g.n_src).withColumnRenamed("vertex", "src")
    lists = starts.join(counts.select(F.col("dst").alias("src"), "n"), "src").select("src", F.floor(F.col("start") / width).alias("_first"), F.floor((F.col("start") + F.col("n") - 1) / width).alias("_last"))
    if blocks > PLANNED:
        x = g.edges.join(lists, "src")
        first, last = F.col("_first"), F.col("_last")
    else:
        # a block begins inside the list of a source or with it; there are fewer such sources than blocks
        cuts = lists.where("_last > _first").select("src", "_first", "_last").unionByName(lists.groupBy("_first").agg(F.min("src").alias("src")).select("src", "_first", F.col("_first").alias("_last"))).collect()
        within = {r["src"]: (r["_first"], r["_last"]) for r in cuts if r["_last"] > r["_first"]}
        begins = {}
        for r in cuts:
            begins[r["_first"]] = min(begins.get(r["_first"], r["src"]), r["src"])
        src = F.col("src")
        first = F.coalesce(*[F.when(src >= begins[k], k) for k in sorted(begins, reverse=True)], F.lit(0)).cast("long")
        last = F.coalesce(*[F.when(src == owner, end) for owner, (_, end) in within.items()], first).cast("long")
        x = g.edges.withColumn("_first", first).withColumn("_last", last)
        first, last = F.col("_first"), F.col("_last")
    block = first + F.pmod(F.col("dst"), last - first + 1)
    return g.with_edges(x.withColumn("block", F.least(block, F.lit(blocks - 1)).cast("long")).select(*g.edges.columns, "block"))


def block_sizes(g: Graph):
    """(block, n): edges in each block."""
    return g.edges.groupBy("block").agg(F.count("*").alias("n"))
