"""Access rates of this engine: what a row costs that is counted at home, sent to its owner, or looked up."""

from __future__ import annotations

import time
from statistics import median

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.plans.costmodel import AccessTimes
from turnwise.sources.files import noop


def _seconds(job, repeats: int = 3) -> float:
    job()
    out = []
    for _ in range(repeats):
        began = time.perf_counter()
        job()
        out.append(time.perf_counter() - began)
    return median(out)


def access_rates(spark: SparkSession, rows: int = 200_000, small: int = 1_000, factor: int = 1_000, ids: DataFrame | None = None) -> DataFrame:
    """(kind, footprint, rows_per_second, normalised): random keys over a small domain and one factor times as large. Keys are
    hashes of the rows of ids (column id), all of them, or of rows numbers.

    Kinds: read (a lookup in a broadcast table of the whole domain, which is made anew each time), write (a count private to
    the task), shared_write (a count at the key's owner after an exchange). Rates are divided by that of a read in the small
    domain.
    """
    found = []
    ids = spark.range(rows) if ids is None else ids
    rows = ids.count()
    for footprint, size in (("in", small), ("out", small * factor)):
        keys = ids.select(F.pmod(F.xxhash64("id"), F.lit(size)).alias("key"))
        lookup = spark.range(size).select(F.col("id").alias("key"), F.col("id").alias("v"))
        jobs = {
            "read": lambda keys=keys, lookup=lookup: noop(keys.join(F.broadcast(lookup), "key", "left")),
            "write": lambda keys=keys: noop(keys.groupBy(F.spark_partition_id().alias("p"), "key").count()),
            "shared_write": lambda keys=keys: noop(keys.repartition("key").groupBy("key").count()),
        }
        found += [(kind, footprint, rows / _seconds(job)) for kind, job in jobs.items()]
    base = next(r for k, f, r in found if (k, f) == ("read", "in"))
    return spark.createDataFrame([(k, f, r, r / base) for k, f, r in found], "kind string, footprint string, rows_per_second double, normalised double")


def access_times(rates: DataFrame) -> AccessTimes:
    """The model's times, in seconds a row, from access_rates()."""
    r = {(x.kind, x.footprint): x.rows_per_second for x in rates.collect()}
    return AccessTimes(1 / r["shared_write", "in"], 1 / r["shared_write", "out"], 1 / r["write", "in"], 1 / r["read", "in"])
