"""Edges and compressed forms in files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.model import Csr, Graph, graph_of
from turnwise.operators.blocks import edge_blocks

EDGE_SCHEMA = "src BIGINT, dst BIGINT"


def read_edges(spark: SparkSession, path: str, format: str = "parquet", schema: str = EDGE_SCHEMA, columns: tuple[str, str] = ("src", "dst"), **options) -> DataFrame:
    """(src, dst, ...) from parquet, orc, csv, json or text of two numbers a line; the schema is given, never inferred."""
    if format == "text":
        parts = F.split(F.trim("value"), r"\s+")
        raw = spark.read.text(path).where(~F.col("value").rlike(r"^\s*(#|%|$)"))
        return raw.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"))
    df = spark.read.format(format).schema(schema).options(**options).load(path)
    return df.withColumnsRenamed({columns[0]: "src", columns[1]: "dst"})


def read_coordinates(spark: SparkSession, path: str, one_based: bool = True) -> tuple[DataFrame, tuple[int, int, int]]:
    """Edges (src, dst, value) of a matrix in coordinate text, and its rows, columns and entries from the size line.

    The size line is the first without a %; a pattern matrix has the value 1.
    """
    rows = spark.read.text(path).where(~F.col("value").rlike(r"^\s*(%|$)")).withColumn("value", F.trim("value"))
    # files are read in order, so the first line is that of the first split
    first = rows.take(1)[0][0]
    size = tuple(int(x) for x in first.split()[:3])
    p = F.split("value", r"\s+")
    base = 1 if one_based else 0
    where = F.input_file_block_start() == 0
    numbered = rows.withColumn("_first", where & (F.col("value") == first) & (F.monotonically_increasing_id() == 0))
    entries = numbered.where("NOT _first").select((p[0].cast("long") - base).alias("src"), (p[1].cast("long") - base).alias("dst"), F.coalesce(F.try_element_at(p, F.lit(3)).cast("double"), F.lit(1.0)).alias("value"))
    return entries, size


def write_csr(csr: Csr, path: str, chunk_rows: int = 1 << 22) -> None:
    """Offsets and endpoints; slots are dense, so that equal stretches of positions make equal files whatever the skew."""
    csr.offsets.repartitionByRange("vertex").sortWithinPartitions("vertex").write.mode("overwrite").parquet(f"{path}/offsets")
    x = csr.endpoints.withColumn("file_id", F.floor(F.col("pos") / chunk_rows).cast("long"))
    x.repartition("file_id").sortWithinPartitions("pos").write.mode("overwrite").partitionBy("file_id").parquet(f"{path}/endpoints")


def read_csr(spark: SparkSession, path: str, n_vertices: int, n_other: int, orientation: str = "in") -> Csr:
    return Csr(spark.read.parquet(f"{path}/offsets"), spark.read.parquet(f"{path}/endpoints").drop("file_id"), n_vertices, n_other, orientation)


def csr_to_edges(csr: Csr) -> DataFrame:
    return graph_of(csr).edges


def write_bucketed(g: Graph, table: str, buckets: int, by: str = "dst") -> None:
    """A table whose files are hashed and sorted by one end: later counts and joins on it need no exchange."""
    g.edges.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def write_blocks(g: Graph, table: str, blocks: int, method: str = "edges") -> None:
    """Edges with their block in a table bucketed by it, for hybrid_of_blocks()."""
    edge_blocks(g, blocks, method).edges.write.mode("overwrite").bucketBy(min(blocks, 20_000), "block").saveAsTable(table)


def noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()
