"""Imbalance of owned blocks and the two-phase schedule that evens it out."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from turnwise.model import Graph
from turnwise.operators.hotset import tag_hot


def imbalance(work: DataFrame, value: str = "n") -> DataFrame:
    """(owners, total, most, over_mean, relative_sd): largest over mean less one, and standard deviation over mean."""
    return work.agg(F.count("*").alias("owners"), F.sum(value).cast("long").alias("total"), F.max(value).cast("long").alias("most"), F.round(F.max(value) / F.avg(value) - 1, 6).alias("over_mean"), F.round(F.stddev_pop(value) / F.avg(value), 6).alias("relative_sd"))


def two_phase_schedule(costs: DataFrame, owners: int, own_share: float = 0.8) -> DataFrame:
    """(owner, own, helped, finish): owners work off the first own_share of their blocks, then whoever is free takes the next left-over block.

    costs is (block, cost, owner), one row per block; the schedule is a simulation over the few blocks, in one group.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("block")
        busy, own, helped, rest = [0.0] * owners, [0] * owners, [0] * owners, []
        for owner, mine in pdf.groupby("owner"):
            first = int(len(mine) * own_share)
            busy[owner] = float(mine.cost.iloc[:first].sum())
            own[owner] = first
            rest += mine.cost.iloc[first:].tolist()
        for cost in rest:
            i = min(range(owners), key=busy.__getitem__)
            busy[i] += cost
            helped[i] += 1
        return pd.DataFrame({"owner": range(owners), "own": own, "helped": helped, "finish": busy})

    return costs.withColumn("_all", F.lit(0)).groupBy("_all").applyInPandas(run, "owner long, own long, helped long, finish double")


def finer_tail(g: Graph, blocks: int, own_share: float = 0.8, split: int = 4) -> Graph:
    """g with sub-blocks: the last part of the blocks is cut finer, so that late tasks are small. The number still grows with the source."""
    tail = int(blocks * own_share)
    w = g.n_src / max(1, blocks)
    inner = F.floor((F.col("src") - F.col("block") * w) * split / max(1.0, w))
    sub = F.when(F.col("block") < tail, F.lit(0)).otherwise(F.greatest(F.lit(0), F.least(inner, F.lit(split - 1))))
    return g.with_edges(g.edges.withColumn("block", (F.col("block") * split + sub).cast("long")))


def two_phase_work(g: Graph, hot: DataFrame) -> DataFrame:
    """(block, cost, hot_edges): what a block costs in the placing step, a hot edge counting once and a cold one twice."""
    x = tag_hot(g.edges.select("block", "dst"), hot)
    return x.groupBy("block").agg((F.count("*") + F.count_if(F.col("hot_index").isNull())).alias("cost"), F.count("hot_index").alias("hot_edges"))


def owner_work(blocks: DataFrame, owners: int) -> DataFrame:
    """(owner, n): blocks taken in turn, the first phase only."""
    return blocks.groupBy(F.pmod("block", F.lit(owners)).alias("owner")).agg(F.sum("cost").alias("n"))


def running_share(work: DataFrame) -> DataFrame:
    """(owner, n, share): how much of the work the largest owners have together."""
    w = Window.orderBy(F.desc("n"), "owner").rowsBetween(Window.unboundedPreceding, 0)
    return work.select("owner", "n", F.round(F.sum("n").over(w) / F.sum("n").over(Window.partitionBy()), 6).alias("share"))
