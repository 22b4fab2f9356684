"""Arrow functions with a built-in twin, and what is registered for SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from turnwise.model import Csr, Graph
from turnwise.plans.costmodel import AccessTimes, cost_hybrid, cost_shared, hot_capacity


@F.pandas_udf(T.LongType())
def gap_bits(gap: pd.Series) -> pd.Series:
    """Bits of a gap in Elias' gamma code of gap + 1; twin: 2 * (length(bin(gap + 1)) - 1) + 1."""
    return (2 * np.floor(np.log2(gap.to_numpy(np.float64) + 1)) + 1).astype(np.int64) if len(gap) else gap.astype(np.int64)


def block_histogram(tagged: DataFrame, k: int) -> DataFrame:
    """(block, hot_index, n) by one dense counter array per block in each task: the private counters as an array kernel.

    Twin: groupBy(block, hot_index).count(). k is bounded by hot_capacity(); arrays are emptied when the block changes.
    """

    def run(batches):
        held: dict[int, np.ndarray] = {}

        def out():
            rows = [(b, np.flatnonzero(c), c) for b, c in held.items()]
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.full(len(i), b) for b, i, _ in rows] or [np.zeros(0, np.int64)]).astype(np.int64)), pa.array(np.concatenate([i for _, i, _ in rows] or [np.zeros(0)]).astype(np.int32)), pa.array(np.concatenate([c[i] for _, i, c in rows] or [np.zeros(0)]).astype(np.int64))], ["block", "hot_index", "n"])

        for batch in batches:
            blocks, hot = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            for b in np.unique(blocks).tolist():
                held[b] = held.get(b, np.zeros(k, np.int64)) + np.bincount(hot[blocks == b], minlength=k)
            if len(held) > 64:
                yield out()
        yield out()

    partial = tagged.where("hot_index IS NOT NULL").select("block", F.col("hot_index").cast("int").alias("hot_index")).mapInArrow(run, "block bigint, hot_index int, n bigint")
    return partial.groupBy("block", "hot_index").agg(F.sum("n").alias("n"))


def local_ranks(g: Graph) -> DataFrame:
    """(src, dst, rank) of edges inside their (block, dst), by a stable sort per block; twin: row_number over (block, dst order by src)."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["dst", "src"], kind="stable")
        return pdf.assign(rank=pdf.groupby("dst").cumcount())[["src", "dst", "rank"]]

    return g.edges.select("block", "src", "dst").groupBy("block").applyInPandas(run, "src long, dst long, rank long")


@F.udtf(returnType="vertex: bigint, pos: bigint")
class ExpandSpan:
    """Positions of a vertex from its start to below the next one's."""

    def eval(self, vertex: int, start: int, end: int):
        for pos in range(start, end):
            yield vertex, pos


def expanded_positions(csr: Csr) -> DataFrame:
    """(vertex, pos) by sequence and explode, the built-in twin of ExpandSpan."""
    b = csr.offsets.select((F.col("vertex") - 1).alias("vertex"), F.col("start").alias("next"))
    spans = csr.offsets.join(b, "vertex").where("next > start")
    return spans.select("vertex", F.explode(F.sequence(F.col("start"), F.col("next") - 1)).alias("pos"))


def register(spark: SparkSession) -> None:
    """hot_capacity, cost_shared, cost_hybrid and expand_span for SQL."""
    spark.udf.register("hot_capacity", lambda *x: hot_capacity(*x), T.LongType())
    spark.udf.register("cost_shared", lambda h, a, b, c, d: cost_shared(h, AccessTimes(a, b, c, d)), T.DoubleType())
    spark.udf.register("cost_hybrid", lambda h, a, b, c, d: cost_hybrid(h, AccessTimes(a, b, c, d)), T.DoubleType())
    spark.udtf.register("expand_span", ExpandSpan)
