"""Exclusive running totals in two levels, so that no more rows than ranges meet in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from turnwise.storage import stored

RANGES = 4096


def range_width(n: int, ranges: int = RANGES) -> int:
    return max(1, -(-n // ranges))


def two_level_prefix(df: DataFrame, key: str, value: str, n: int, out: str = "start", ranges: int = RANGES) -> DataFrame:
    """df with out, the sum of value over all smaller keys. Keys are distinct longs from 0 to n - 1.

    Totals per range of keys are summed in one small ordered scan of at most ranges rows and go to every task; a second
    window runs inside each range.
    """
    width = range_width(n, ranges)
    x = df.withColumn("_range", F.floor(F.col(key) / width).cast("long"))
    totals = x.groupBy("_range").agg(F.sum(value).cast("long").alias("_total"))
    before = totals.select("_range", F.coalesce(F.sum("_total").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    inside = Window.partitionBy("_range").orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    y = x.join(F.broadcast(before), "_range").withColumn(out, (F.col("_before") + F.coalesce(F.sum(value).over(inside), F.lit(0))).cast("long"))
    return y.drop("_range", "_before")


def flat_prefix(df: DataFrame, key: str, value: str, out: str = "start") -> DataFrame:
    """The same by one window over all rows, in one task: for small tables and as a contrast."""
    w = Window.orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    return df.withColumn(out, F.coalesce(F.sum(value).over(w), F.lit(0)).cast("long"))


def prefix_offsets(counts: DataFrame, n: int, key: str = "dst", value: str = "n") -> DataFrame:
    """(vertex, start) for 0 to n from (key, value): vertices without edges are there, the last start is the number of edges."""
    v = counts.sparkSession.range(n + 1).withColumnRenamed("id", "vertex")
    full = v.join(counts.select(F.col(key).alias("vertex"), F.col(value).alias("_n")), "vertex", "left").select("vertex", F.coalesce("_n", F.lit(0)).alias("_n"))
    return two_level_prefix(full, "vertex", "_n", n + 1).select("vertex", "start")


def dense_ids(df: DataFrame, column: str) -> DataFrame:
    """(column, id): ids from 0 in the order of distinct non-null values.

    Values are dealt to ranges by Spark's range partitioning, whatever they have in common at their beginning; the number
    of the range is written with them, so that what follows depends on the table and no longer on the partitions.
    """
    spark = df.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    x = df.select(column).where(F.col(column).isNotNull()).distinct()
    x = stored(x.repartitionByRange(parts, column).withColumn("_range", F.spark_partition_id().cast("long")), "values")
    sizes = x.groupBy("_range").agg(F.count("*").alias("_n"))
    before = sizes.select("_range", F.coalesce(F.sum("_n").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    inside = Window.partitionBy("_range").orderBy(column)
    return x.join(F.broadcast(before), "_range").select(column, (F.col("_before") + F.row_number().over(inside) - 1).cast("long").alias("id"))
