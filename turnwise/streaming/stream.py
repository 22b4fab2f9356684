"""Edges that arrive as a stream of events: an event is an edge from its user to its type."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.model import Graph
from turnwise.operators.reference import sorted_reference
from turnwise.storage import shared_dir


def event_stream(spark: SparkSession, sf_dir: str, files_per_batch: int = 1) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(f"{sf_dir}/events*.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def finish(df: DataFrame, mode: str = "complete") -> DataFrame:
    """The result of a stream once all there is has been read. Batches go to the shared folder, and no row of them to the driver.

    In complete mode each batch is the whole result, so only the last one is read.
    """
    spark, where, epochs = df.sparkSession, f"{shared_dir(df.sparkSession)}/finished-{uuid.uuid4().hex}", []

    def keep(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{where}/{epoch}")
        if epoch not in epochs:
            epochs.append(epoch)

    run_batches(df, keep, mode)
    found = epochs if mode == "append" else epochs[-1:]
    return spark.read.schema(df.schema).parquet(*[f"{where}/{e}" for e in found]) if found else spark.createDataFrame([], df.schema)


def stream_degrees(events: DataFrame) -> DataFrame:
    """(event_type, n): the counting step as the state of a stream."""
    return events.groupBy("event_type").agg(F.count("*").alias("n"))


def with_watermark(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay)


def windowed_degrees(events: DataFrame, kind: str = "tumbling", size: str = "1 hour", slide: str = "30 minutes") -> DataFrame:
    """(event_type, begins, n) by tumbling, sliding or session windows."""
    if kind == "session":
        w = F.session_window("ts", size)
    elif kind in ("tumbling", "sliding"):
        w = F.window("ts", size, slide if kind == "sliding" else None)
    else:
        raise ValueError(f"unknown window: {kind}")
    return events.groupBy("event_type", w.alias("w")).agg(F.count("*").alias("n")).select("event_type", F.col("w.start").alias("begins"), "n")


def late_rows(events: DataFrame, seen_until: DataFrame) -> DataFrame:
    """Rows of a batch older than the watermark (column until, one row): what a windowed count would drop."""
    return events.join(F.broadcast(seen_until), F.col("ts") < F.col("until")).drop("until")


def deduplicated(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def tagged(events: DataFrame, hot: DataFrame) -> DataFrame:
    """Live edges with hot_index from a static table of at most k rows."""
    return events.join(F.broadcast(hot.select(F.col("dst").alias("user_id"), "hot_index")), "user_id", "left")


def followed(events: DataFrame, within: str = "10 minutes", delay: str = "10 minutes") -> DataFrame:
    """(user_id, a, b): pairs of a user's events with b after a by at most within; both sides have watermarks, so state is bounded."""
    a = events.select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ts_a")).withWatermark("ts_a", delay)
    b = events.select(F.col("user_id").alias("user_b"), F.col("event_id").alias("b"), F.col("ts").alias("ts_b")).withWatermark("ts_b", delay)
    on = F.expr(f"user_id = user_b AND ts_b > ts_a AND ts_b <= ts_a + INTERVAL {within}")
    return a.join(b, on).select("user_id", "a", "b")


class HotSet:
    """Degrees kept over batches in a table of the shared folder, and the k most frequent users of all so far."""

    def __init__(self, spark: SparkSession):
        self.spark, self.path = spark, f"{shared_dir(spark)}/degrees-{uuid.uuid4().hex}"
        self.last = -1

    def merge(self, batch: DataFrame, epoch: int) -> None:
        """Version epoch follows from the one before it, so that a batch run again writes the same."""
        new = batch.groupBy(F.col("user_id").alias("dst")).agg(F.count("*").alias("n"))
        if epoch:
            new = new.unionByName(self.spark.read.parquet(f"{self.path}/{epoch - 1}")).groupBy("dst").agg(F.sum("n").alias("n"))
        new.write.mode("overwrite").parquet(f"{self.path}/{epoch}")
        self.last = epoch

    def degrees(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/{self.last}")


class IncrementalTransposition:
    """Each batch becomes a transposed segment; compaction merges segments, whose lists are sorted, into one."""

    def __init__(self, spark: SparkSession):
        self.spark, self.path, self.segments = spark, f"{shared_dir(spark)}/segments-{uuid.uuid4().hex}", []

    def add(self, batch: DataFrame, epoch: int) -> None:
        where = f"{self.path}/{epoch}"
        batch.select("src", "dst").repartition("dst").sortWithinPartitions("dst", "src").write.mode("overwrite").parquet(where)
        if where not in self.segments:
            self.segments.append(where)

    def compact(self, n_src: int, n_dst: int):
        edges = self.spark.read.schema("src long, dst long").parquet(*self.segments) if self.segments else self.spark.createDataFrame([], "src long, dst long")
        return sorted_reference(Graph.of(edges, n_src, n_dst))


def run_batches(stream: DataFrame, each, mode: str = "append") -> None:
    """each(batch, epoch) over all that there is; a batch that is run again after a failure overwrites its own output."""
    where = f"{shared_dir(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    q = stream.writeStream.foreachBatch(each).outputMode(mode).option("checkpointLocation", where).trigger(availableNow=True).start()
    q.awaitTermination()
