"""Relabellings of vertices, and measures of how close neighbours' ids are."""

from __future__ import annotations

from math import gcd

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from turnwise.model import Graph
from turnwise.operators.order import number_in_class
from turnwise.operators.prefix import two_level_prefix
from turnwise.storage import dropped, stored

MULTIPLIER, SHIFT = 7919, 13


def coprime_multiplier(n: int, a: int = MULTIPLIER) -> int:
    while gcd(a, n) > 1:
        a += 2
    return a


def relabel_affine(g: Graph, a: int = MULTIPLIER, b: int = SHIFT) -> Graph:
    """Ids permuted by (a id + b) mod n: low locality without a join, and the same in any engine."""

    def to(column: str, n: int):
        return F.pmod(F.col(column) * coprime_multiplier(n, a) + b, F.lit(n)) if n > 1 else F.col(column)

    return g.with_edges(g.edges.select(to("src", g.n_src).alias("src"), to("dst", g.n_dst).alias("dst"), *g.payload))


def relabel_by(g: Graph, ids: DataFrame) -> Graph:
    """Both ends through (old, new), a permutation of the common ids."""
    x = g.edges.join(ids.select(F.col("old").alias("src"), F.col("new").alias("_s")), "src").join(ids.select(F.col("old").alias("dst"), F.col("new").alias("_d")), "dst")
    return g.with_edges(x.select(F.col("_s").alias("src"), F.col("_d").alias("dst"), *g.payload))


def _numbered(keys: DataFrame, n: int) -> DataFrame:
    """(old, new) from (old, at): at is made dense by counting ids at each place, in two levels; ties go by id."""
    span = keys.agg(F.max("at")).first()[0]
    span = 0 if span is None else int(span)
    counts = keys.groupBy("at").agg(F.count("*").alias("n"))
    before = two_level_prefix(counts, "at", "n", span + 1)
    inside = number_in_class(keys, "old", "at")
    return keys.join(before, "at").join(inside, ["old", "at"]).select("old", (F.col("start") + F.col("_number")).alias("new"))


def relabel_first_seen(g: Graph, order: str = "src") -> Graph:
    """Ids in the order in which the edges, taken by a numeric column, show them first; ids that no edge has come last."""
    seen = g.edges.select(F.col("src").alias("old"), F.col(order).alias("k")).unionByName(g.edges.select(F.col("dst").alias("old"), F.col(order).alias("k")))
    n = max(g.n_src, g.n_dst)
    last = g.edges.agg(F.coalesce(F.max(order), F.lit(0))).first()[0] + 1
    first = g.edges.sparkSession.range(n).withColumnRenamed("id", "old").join(seen.groupBy("old").agg(F.min("k").alias("at")), "old", "left").select("old", F.coalesce("at", F.lit(last)).cast("long").alias("at"))
    return relabel_by(g, _numbered(first, n))


def relabel_degree(g: Graph) -> Graph:
    """Ids by falling in-degree."""
    n = max(g.n_src, g.n_dst)
    deg = g.edges.groupBy(F.col("dst").alias("old")).agg(F.count("*").alias("n"))
    all_ = g.edges.sparkSession.range(n).withColumnRenamed("id", "old").join(deg, "old", "left").select("old", F.coalesce("n", F.lit(0)).alias("n"))
    top = all_.agg(F.max("n")).first()[0] or 0
    return relabel_by(g, _numbered(all_.select("old", (F.lit(top) - F.col("n")).alias("at")), n))


def relabel_bfs(g: Graph) -> Graph:
    """Ids by distance from vertex 0 over edges in both directions, what is out of reach last; a round is written before the next."""
    n = max(g.n_src, g.n_dst)
    both = g.edges.select(F.col("src").alias("a"), F.col("dst").alias("b")).unionByName(g.edges.select(F.col("dst").alias("a"), F.col("src").alias("b"))).distinct()
    level = g.edges.sparkSession.range(n).select(F.col("id").alias("old"), F.when(F.col("id") == 0, 0).cast("long").alias("at"))
    step, before = 0, None
    while True:
        step += 1
        reach = both.join(level.where(F.col("at") == step - 1).select(F.col("old").alias("a")), "a").select(F.col("b").alias("old")).distinct().withColumn("_r", F.lit(step).cast("long"))
        level = stored(level.join(reach, "old", "left").select("old", F.coalesce("at", "_r").alias("at")), "levels")
        if before is not None:
            dropped(before)
        before = level
        if level.where(F.col("at") == step).isEmpty():
            break
    return relabel_by(g, _numbered(level.select("old", F.coalesce("at", F.lit(step)).alias("at")), n))


def representations(g: Graph) -> dict[str, Graph]:
    """The four forms: by row and by column, as given and permuted."""
    rnd = relabel_affine(g)
    return {"row": g, "row_random": rnd, "column": g.flip_roles(), "column_random": rnd.flip_roles()}


def bandwidth(g: Graph) -> DataFrame:
    return g.edges.agg(F.max(F.abs(F.col("src") - F.col("dst"))).alias("bandwidth"))


def mean_gap(g: Graph) -> DataFrame:
    """(edges, gap_sum): mean distance of ends as an exact fraction."""
    return g.edges.agg(F.count("*").alias("edges"), F.sum(F.abs(F.col("src") - F.col("dst"))).alias("gap_sum"))


def _gaps(g: Graph) -> DataFrame:
    w = Window.partitionBy("src").orderBy("dst")
    return g.edges.select("src", (F.col("dst") - F.lag("dst").over(w)).alias("gap"))


def bits_per_link(g: Graph) -> DataFrame:
    """(links, bits): what the gaps of each list take in Elias' gamma code, 2 floor(log2(gap + 1)) + 1 bits each, the first endpoint of a list left out.

    floor(log2) is the length of the binary form less one, so the count is exact.
    """
    x = _gaps(g).where("gap IS NOT NULL")
    return x.agg(F.count("*").alias("links"), F.coalesce(F.sum(2 * (F.length(F.bin(F.col("gap") + 1)) - 1) + 1), F.lit(0)).cast("long").alias("bits"))


def neighbor_gap(g: Graph) -> DataFrame:
    """(vertices, mean_gap): distance between neighbours in a list, by list, then over lists."""
    per = _gaps(g).where("gap IS NOT NULL").groupBy("src").agg(F.avg("gap").alias("g"))
    return per.agg(F.count("*").alias("vertices"), F.round(F.avg("g"), 4).alias("mean_gap"))

