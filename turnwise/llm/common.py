"""Helpers that the operators of this subpackage share: shared storage, null-safe input, components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

#: Words are maximal runs of anything but space and the characters 9 to 13.
WORD_SPACE = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, or a temporary one where that is unset (tests on one machine)."""
    sc = spark.sparkContext
    configured = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not configured:
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        configured = "file://" + tempfile.mkdtemp(prefix="turnwise-")
        sc.setCheckpointDir(configured)
    return configured.rstrip("/")


def new_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder through the file system that owns it."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def stored(df: DataFrame, label: str) -> DataFrame:
    """The rows of df, computed once into a Parquet table in the shared folder: its lineage ends there and no executor owns it."""
    path = new_path(df.sparkSession, label)
    df.write.parquet(path)
    released(df.sparkSession)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.stored_path = path
    return out


def released(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of plans that nothing holds any more; it does so when the JVM has collected them."""
    spark.sparkContext._jvm.System.gc()


def dropped(*frames: DataFrame) -> None:
    """Delete tables made by stored() that nothing reads any more."""
    for x in frames:
        remove(x.sparkSession, x.stored_path)


def text_of(name: str = "text") -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def slices(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """Arrow batches cut small, so that what a Python worker holds doesn't depend on the batch size of the session."""
    for batch in batches:
        for start in range(0, batch.num_rows, rows):
            yield batch.slice(start, rows)


def map_arrow(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch]], schema: str, rows: int = 512) -> DataFrame:
    """df mapped by batches; make runs once in each task and returns the function of a batch."""

    def run(batches):
        f = make()
        for x in slices(batches, rows):
            yield f(x)

    return df.mapInArrow(run, schema)


#: Links that components() takes to the driver at most, 16 bytes each.
FEW_LINKS = 100_000


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root): the smallest node that each linked node reaches.

    Links are in any order, repeats allowed. Up to FEW_LINKS distinct ones of longs are joined on the driver, in one pass; more
    by two star contractions in turn until nothing moves. Each of their rounds is written to the shared folder and the one
    before is deleted, so a lost executor costs at most a round.
    """
    x = links.select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).where("hi <> lo").distinct()
    now = stored(x, "links")
    mark = lambda e: e.agg(F.count("*").alias("n"), F.coalesce(F.bit_xor(F.xxhash64("hi", "lo")), F.lit(0)).alias("x")).first()
    was = mark(now)
    if was["n"] <= FEW_LINKS and x.schema["hi"].dataType == LongType():
        got = now.toArrow()
        dropped(now)
        return links.sparkSession.createDataFrame(_roots(got.column("hi").to_pylist(), got.column("lo").to_pylist()), "node long, root long")
    while was["n"]:
        both = now.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(now.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        low = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(low, "hi").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).where("hi <> lo").unionByName(low.select("hi", F.col("m").alias("lo"))).distinct()
        then = stored(small, "links")
        is_ = mark(then)
        dropped(now)
        now = then
        if is_ == was:
            break
        was = is_
    return now.groupBy(F.col("hi").alias("node")).agg(F.min("lo").alias("root"))


def _roots(his: list[int], los: list[int]) -> pa.Table:
    """(node, root) of the links: each node with the smallest one that it reaches."""
    above: dict[int, int] = {}

    def top(x: int) -> int:
        while (up := above.setdefault(x, x)) != x:
            above[x] = x = above[up]
        return x

    for hi, lo in zip(his, los, strict=True):
        x, y = top(hi), top(lo)
        above[max(x, y)] = min(x, y)
    nodes = [x for x in above if top(x) != x]
    return pa.table({"node": pa.array(nodes, pa.int64()), "root": pa.array([top(x) for x in nodes], pa.int64())})
