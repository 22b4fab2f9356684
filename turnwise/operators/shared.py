"""The baseline: all endpoints share one set of counters.

A shared update has its twin in a row that travels to the task which owns its endpoint. Spark would count privately in
each task first, which is the private baseline's idea; combine="none" forces the exchange before the aggregate.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from turnwise.model import Csr, Graph, any_payload
from turnwise.operators.prefix import prefix_offsets, range_width


def shared_degrees(g: Graph, combine: str = "none") -> DataFrame:
    """(dst, n): step 1. Only the endpoint column is read."""
    e = g.edges.select("dst")
    if combine not in ("none", "map"):
        raise ValueError(f"unknown combine: {combine}")
    if combine == "none":
        e = e.repartition("dst")
    return e.groupBy("dst").agg(F.count("*").alias("n"))


def shared_place(g: Graph, offsets: DataFrame, sort_lists: bool = True) -> DataFrame:
    """(pos, endpoint, payload...): step 3. The slot is the endpoint's next free one."""
    order = g.order_columns() if sort_lists else [F.monotonically_increasing_id()]
    w = Window.partitionBy("dst").orderBy(*order)
    x = g.edges.join(offsets.select(F.col("vertex").alias("dst"), "start"), "dst")
    return x.select((F.col("start") + F.row_number().over(w) - 1).alias("pos"), F.col("src").alias("endpoint"), *g.payload)


def consumed_insertion_points(g: Graph, offsets: DataFrame, combine: str = "none") -> DataFrame:
    """(vertex, ip): what the insertion points hold once every edge is placed."""
    x = offsets.where(F.col("vertex") < g.n_dst).join(shared_degrees(g, combine).withColumnRenamed("dst", "vertex"), "vertex", "left")
    return x.select("vertex", (F.col("start") + F.coalesce("n", F.lit(0))).alias("ip"))


def restore_offsets_by_shift(ip: DataFrame, n: int) -> DataFrame:
    """(vertex, start) again from consumed insertion points: each vertex starts where the one before has stopped.

    Vertices are cut into ranges; the edge of a range is carried over by an equi-join, so no task sees all of them.
    """
    width = range_width(n)
    x = ip.withColumn("_range", F.floor(F.col("vertex") / width).cast("long"))
    inside = Window.partitionBy("_range").orderBy("vertex")
    carried = x.groupBy("_range").agg(F.max_by("ip", "vertex").alias("_carried")).withColumn("_range", F.col("_range") + 1)
    y = x.withColumn("_before", F.lag("ip").over(inside)).join(F.broadcast(carried), "_range", "left")
    out = y.select("vertex", F.coalesce("_before", "_carried", F.lit(0)).cast("long").alias("start"))
    last = ip.agg(F.coalesce(F.max("ip"), F.lit(0)).cast("long").alias("start")).select(F.lit(n).cast("long").alias("vertex"), "start")
    return out.unionByName(last)


@any_payload
def shared_transpose(g: Graph, *, sort_lists: bool = True, ip_mode: str = "copy", combine: str = "none") -> Csr:
    """Count, scan, place. ip_mode "copy" keeps offsets and insertion points apart; "shift" restores one from the other, which costs a second count here."""
    offsets = prefix_offsets(shared_degrees(g, combine), g.n_dst)
    placed = shared_place(g, offsets, sort_lists)
    if ip_mode == "shift":
        kept = restore_offsets_by_shift(consumed_insertion_points(g, offsets, combine), g.n_dst)
    elif ip_mode == "copy":
        kept = offsets
    else:
        raise ValueError(f"unknown ip_mode: {ip_mode}")
    return Csr(kept, placed, g.n_dst, g.n_src, "in" if g.orientation == "out" else "out")
