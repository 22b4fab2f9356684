"""Selections and changes of a graph's edges."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from turnwise.model import Graph


def project_endpoint(g: Graph) -> DataFrame:
    return g.edges.select("dst")


def with_ordinal(g: Graph) -> DataFrame:
    """Edges with a stable number inside their source's list."""
    return g.edges.withColumn("ordinal", F.row_number().over(Window.partitionBy("src").orderBy("dst", *g.order_columns()[1:])) - 1)


def drop_self_loops(g: Graph) -> Graph:
    return g.with_edges(g.edges.where("src <> dst"))


def dedup(g: Graph) -> Graph:
    return g.with_edges(g.edges.distinct())


def weighted_dedup(g: Graph, weight: str | None = None) -> Graph:
    """One edge for each pair with the sum of a weight, or the number of edges."""
    value = F.sum(weight) if weight else F.count("*")
    return g.with_edges(g.edges.groupBy("src", "dst").agg(value.alias("weight")))


def filter_degree(g: Graph, least: int = 0, most: int | None = None) -> Graph:
    """Edges whose endpoint has an in-degree in these bounds."""
    d = g.edges.groupBy("dst").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    d = d if most is None else d.where(F.col("n") <= most)
    return g.with_edges(g.edges.join(d.select("dst"), "dst", "left_semi").select(*g.edges.columns))


def filter_hot(g: Graph, hot: DataFrame) -> Graph:
    return g.with_edges(g.edges.join(F.broadcast(hot.select("dst")), "dst", "left_semi").select(*g.edges.columns))


def filter_cold(g: Graph, hot: DataFrame) -> Graph:
    return g.with_edges(g.edges.join(F.broadcast(hot.select("dst")), "dst", "left_anti").select(*g.edges.columns))


def subgraph(g: Graph, vertices: DataFrame) -> Graph:
    """Edges with both ends among vertices (column id)."""
    e = g.edges.join(vertices.select(F.col("id").alias("src")), "src", "left_semi").join(vertices.select(F.col("id").alias("dst")), "dst", "left_semi")
    return g.with_edges(e.select(*g.edges.columns))


def slice_vertices(g: Graph, low: int, high: int) -> Graph:
    """Edges with sources from low to below high; the bounds reach the files' statistics."""
    return g.with_edges(g.edges.where((F.col("src") >= low) & (F.col("src") < high)))


def isolated_vertices(g: Graph) -> DataFrame:
    """(vertex): targets without an edge."""
    v = g.edges.sparkSession.range(g.n_dst).withColumnRenamed("id", "vertex")
    return v.join(g.edges.select(F.col("dst").alias("vertex")).distinct(), "vertex", "left_anti")


def symmetrize(g: Graph) -> Graph:
    """Every edge in both directions, as a set."""
    n = max(g.n_src, g.n_dst)
    back = g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *g.payload)
    return Graph.of(g.edges.unionByName(back), n, dedup=True, symmetric=True)
