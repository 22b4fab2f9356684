"""How often an update finds its counter in a cache of given shape: the hit ratio of the endpoint stream."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from turnwise.model import Graph

COUNTERS_PER_LINE = 16  # counters of four bytes in a line of 64


def hit_ratio_direct(g: Graph, sets: int, per_line: int = COUNTERS_PER_LINE) -> DataFrame:
    """(accesses, hits, hit_ratio) of a direct-mapped cache: an access hits if the one before it in its set had the same line.

    The stream is ordered by source, then endpoint. Sets are the parallelism, as in a cache.
    """
    line = F.floor(F.col("dst") / per_line)
    x = g.edges.select("src", "dst", line.alias("line"), F.pmod(line, F.lit(sets)).alias("set"))
    w = Window.partitionBy("set").orderBy("src", "dst")
    hit = x.select((F.lag("line").over(w) == F.col("line")).alias("hit"))
    return hit.agg(F.count("*").alias("accesses"), F.count_if("hit").alias("hits")).withColumn("hit_ratio", F.round(F.col("hits") / F.col("accesses"), 6))


def hit_ratio_lru(g: Graph, sets: int, ways: int, per_line: int = COUNTERS_PER_LINE) -> DataFrame:
    """The same for sets of several ways that drop the line used longest ago; each set is simulated in stream order."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        held: dict[int, None] = {}
        hits = 0
        for line in pdf.sort_values(["src", "dst"], kind="stable").line:
            if line in held:
                hits += 1
                del held[line]
            elif len(held) >= ways:
                del held[next(iter(held))]
            held[line] = None
        return pd.DataFrame({"accesses": [len(pdf)], "hits": [hits]})

    line = F.floor(F.col("dst") / per_line)
    x = g.edges.select("src", "dst", line.alias("line"), F.pmod(line, F.lit(sets)).alias("set"))
    per_set = x.groupBy("set").applyInPandas(run, "accesses long, hits long")
    return per_set.agg(F.sum("accesses").alias("accesses"), F.sum("hits").alias("hits")).withColumn("hit_ratio", F.round(F.col("hits") / F.col("accesses"), 6))
