"""Sorting of lists and of skewed frequency tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from turnwise.model import Csr, Graph, edges_of
from turnwise.operators.prefix import range_width
from turnwise.operators.shared import shared_place


def sort_lists(csr: Csr) -> Csr:
    """Each list in order of its endpoints: owners are found by range, then edges are placed anew in sorted order."""
    e = edges_of(csr)
    g = Graph(e.select(F.col("endpoint").alias("src"), F.col("owner").alias("dst"), *csr.payload), csr.n_other, csr.n_vertices)
    return Csr(csr.offsets, shared_place(g, csr.offsets), csr.n_vertices, csr.n_other, csr.orientation)


def rank_by_frequency(freq: DataFrame, key: str = "dst", value: str = "n") -> DataFrame:
    """(key, value, rank): a counting sort. A histogram of the few distinct frequencies, a running total from the highest
    down, then a number inside each class, by ranges of keys; ties go to the smaller key."""
    classes = freq.groupBy(value).agg(F.count("*").alias("_size"))
    down = Window.orderBy(F.desc(value)).rowsBetween(Window.unboundedPreceding, -1)
    before = classes.select(value, F.coalesce(F.sum("_size").over(down), F.lit(0)).alias("_before"))
    return freq.join(before, value).join(number_in_class(freq, key, value), [value, key]).select(key, value, (F.col("_before") + F.col("_number")).cast("long").alias("rank"))


def number_in_class(rows: DataFrame, key: str, value: str) -> DataFrame:
    """(key, value, _number) from 0 inside each value in the order of the keys, numbers from 0 up. Classes are cut into
    ranges of keys, so that the class of most vertices, such as that of the frequency 1, is no single task."""
    width = range_width((rows.agg(F.max(key)).first()[0] or 0) + 1)
    x = rows.select(key, value).withColumn("_range", F.floor(F.col(key) / width).cast("long"))
    sizes = x.groupBy(value, "_range").agg(F.count("*").alias("_n"))
    w = Window.partitionBy(value).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    ahead = sizes.select(value, "_range", F.coalesce(F.sum("_n").over(w), F.lit(0)).alias("_ahead"))
    inside = Window.partitionBy(value, "_range").orderBy(key)
    return x.join(ahead, [value, "_range"]).select(key, value, (F.col("_ahead") + F.row_number().over(inside) - 1).alias("_number"))
