"""Hot endpoints on private state, cold ones on shared state.

Counts of hot endpoints are summed where the edges are read and leave a task as at most k rows a block; only cold edges
travel to the owner of their endpoint. In the placing step a hot edge gets its slot from its block's own insertion point
and never travels by endpoint, so the most frequent vertex is spread over all blocks. Hot edges are sent once there, by
block and hot vertex; insertion points are k rows a block and meet them where they are then. Edges of a table bucketed by
block (sources.files.write_blocks) could stay at home, but the plans that Spark makes still exchange them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from turnwise.model import Csr, Graph, any_payload
from turnwise.operators.blocks import edge_blocks
from turnwise.operators.hotset import checked_hot, tag_hot
from turnwise.operators.prefix import prefix_offsets

LOW = 256  # fixed value: a low counter is one byte


def split_counts(n: Column) -> tuple[Column, Column]:
    """(low, high) with n = low + 256 high."""
    return n.bitwiseAND(F.lit(LOW - 1).cast("long")).cast("int").alias("low"), F.shiftright(n, 8).alias("high")


def wrap_events(counts: DataFrame, value: str = "n") -> DataFrame:
    """(wraps, vertices): how often one-byte counters overflow, and on how many vertices."""
    return counts.agg(F.coalesce(F.sum(F.floor(F.col(value) / LOW)), F.lit(0)).cast("long").alias("wraps"), F.count_if(F.col(value) >= LOW).alias("vertices"))


def clustered(tagged: DataFrame, blocks: int) -> DataFrame:
    """Rows of a block in one task; hashing by block also clusters (block, anything), so later groupings need no exchange."""
    return tagged.repartition(max(1, min(blocks, 20_000)), "block")


def hybrid_degrees(tagged: DataFrame, blocks: int) -> tuple[DataFrame, DataFrame]:
    """cold (dst, n) and hot_partials (block, hot_index, dst, low, high): step 1."""
    cold = tagged.where("hot_index IS NULL").select("dst").repartition("dst").groupBy("dst").agg(F.count("*").alias("n"))
    low, high = split_counts(F.col("n"))
    hot = tagged.where("hot_index IS NOT NULL").groupBy("block", "hot_index").agg(F.count("*").alias("n"), F.min("dst").alias("dst"))
    return cold, hot.select("block", "hot_index", "dst", low, high)


def hybrid_offsets(cold: DataFrame, hot_partials: DataFrame, n: int) -> tuple[DataFrame, DataFrame]:
    """offsets, and hot_ip (block, hot_index, base): step 2. A hot vertex starts in each block after what earlier blocks have of it."""
    whole = hot_partials.withColumn("n", F.col("low") + F.col("high") * LOW)
    counts = cold.unionByName(whole.groupBy("dst").agg(F.sum("n").alias("n")))
    offsets = prefix_offsets(counts, n)
    w = Window.partitionBy("hot_index").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    inside = whole.withColumn("_before", F.coalesce(F.sum("n").over(w), F.lit(0)))
    ip = inside.join(offsets.withColumnRenamed("vertex", "dst"), "dst").select("block", "hot_index", (F.col("start") + F.col("_before")).cast("long").alias("base"))
    return offsets, ip


def hybrid_place(g: Graph, tagged: DataFrame, offsets: DataFrame, hot_ip: DataFrame, blocks: int, sort_lists: bool = True) -> DataFrame:
    """(pos, endpoint, payload...): step 3."""
    order = g.order_columns() if sort_lists else [F.monotonically_increasing_id()]
    payload = [c for c in g.payload if c not in ("block", "hot_index")]
    cold = tagged.where("hot_index IS NULL").join(offsets.select(F.col("vertex").alias("dst"), "start"), "dst")
    cold = cold.select((F.col("start") + F.row_number().over(Window.partitionBy("dst").orderBy(*order)) - 1).alias("pos"), F.col("src").alias("endpoint"), *payload)
    hot = tagged.where("hot_index IS NOT NULL").withColumn("_rank", F.row_number().over(Window.partitionBy("block", "hot_index").orderBy(*order)) - 1)
    hot = hot.join(hot_ip, ["block", "hot_index"]).select((F.col("base") + F.col("_rank")).alias("pos"), F.col("src").alias("endpoint"), *payload)
    return cold.unionByName(hot)


def hybrid_transpose(g: Graph, hot: DataFrame, *, blocks: int = 64, sort_lists: bool = True, block_method: str = "edges") -> Csr:
    """hot is (dst, hot_index): none of them is the shared method, all of them the private one."""
    return _transposed(g, checked_hot(hot), blocks, sort_lists, block_method)


@any_payload
def _transposed(g: Graph, hot: DataFrame, blocks: int, sort_lists: bool, block_method: str) -> Csr:
    return hybrid_of_blocks(edge_blocks(g, blocks, block_method), hot, blocks=blocks, sort_lists=sort_lists)


def hybrid_of_blocks(b: Graph, hot: DataFrame, *, blocks: int, sort_lists: bool = True) -> Csr:
    """The same of edges that have their column block, such as those of sources.files.write_blocks."""
    g = b
    tagged = tag_hot(b.edges, hot)
    cold, partials = hybrid_degrees(tagged, blocks)
    offsets, ip = hybrid_offsets(cold, partials, g.n_dst)
    placed = hybrid_place(b.with_edges(b.edges.drop("block")), tagged, offsets, ip, blocks, sort_lists)
    return Csr(offsets, placed, g.n_dst, g.n_src, "in" if g.orientation == "out" else "out")
