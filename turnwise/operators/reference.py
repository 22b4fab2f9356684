"""Exact references: a sort of all edges, and Spark's own collected lists; and the checks that methods have to pass."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from turnwise.model import Csr, Graph, graph_of, any_payload
from turnwise.operators.prefix import prefix_offsets
from turnwise.operators.shared import shared_place
from turnwise.storage import stored


@any_payload
def sorted_reference(g: Graph) -> Csr:
    """Offsets by Spark's usual aggregate and slots by the canonical order."""
    offsets = prefix_offsets(g.edges.groupBy("dst").agg(F.count("*").alias("n")), g.n_dst)
    return Csr(offsets, shared_place(g, offsets), g.n_dst, g.n_src, "in" if g.orientation == "out" else "out")


def collect_list_reference(g: Graph) -> DataFrame:
    """(dst, sources): one row per endpoint, so a hot list is one row of one task."""
    return g.edges.groupBy("dst").agg(F.sort_array(F.collect_list("src")).alias("sources"))


def same_graph(a: Graph, b: Graph) -> bool:
    """Equal as multisets of edges."""
    x, y = a.edges, b.edges.select(*a.edges.columns)
    return x.exceptAll(y).isEmpty() and y.exceptAll(x).isEmpty()


def same_csr(a: Csr, b: Csr) -> bool:
    cols = a.endpoints.columns
    pairs = ((a.offsets, b.offsets), (a.endpoints, b.endpoints.select(*cols)))
    return all(x.exceptAll(y).isEmpty() and y.exceptAll(x).isEmpty() for x, y in pairs)


def involution_difference(g: Graph, method) -> DataFrame:
    """(differences): rows in which the graph that comes back from two transpositions differs."""
    once = graph_of(method(g))
    once = once.with_edges(stored(once.edges, "transposed"))  # else the second transposition plans the first one many times over
    back = stored(graph_of(method(once)).edges.select(*g.edges.columns), "back")
    x, y = g.edges.exceptAll(back), back.exceptAll(g.edges)
    return x.unionByName(y).agg(F.count("*").alias("differences"))


def is_symmetric(g: Graph) -> bool:
    """Whether both forms coincide."""
    return g.n_src == g.n_dst and same_graph(g, g.flip_roles())
