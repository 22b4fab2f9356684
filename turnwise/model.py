"""Graphs (or sparse matrices) as edge tables, and their compressed form as two narrow tables.

A Graph holds a multiset of edges (src, dst, payload...) over dense ids. A Csr holds offsets(vertex, start), one row for
each vertex and a last one with the number of edges, and endpoints(pos, endpoint, payload...), dense positions from 0.
Arrays per vertex are only a view, since a very frequent vertex would be one row.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import wraps

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


class InvalidEdges(ValueError):
    """Edges with null ids or ids outside their range; carries their number."""

    def __init__(self, nulls: int, outside: int):
        super().__init__(f"{nulls} edges with a null id, {outside} with an id out of range")
        self.nulls, self.outside = nulls, outside


def quoted(name: str) -> Column:
    """The column of this name, whatever marks are in it."""
    return F.col("`" + name.replace("`", "``") + "`")


@dataclass(frozen=True)
class Graph:
    edges: DataFrame
    n_src: int
    n_dst: int
    orientation: str = "out"
    symmetric: bool = False

    @classmethod
    def of(cls, edges: DataFrame, n_src: int, n_dst: int | None = None, *, dedup: bool = False, symmetric: bool = False) -> Graph:
        """Edges with columns src and dst, cast to long; dedup turns the multiset into a set."""
        edges = edges.withColumns({"src": F.col("src").cast("long"), "dst": F.col("dst").cast("long")}).select("src", "dst", *[quoted(c) for c in edges.columns if c not in ("src", "dst")])
        return cls(edges.distinct() if dedup else edges, n_src, n_src if n_dst is None else n_dst, symmetric=symmetric)

    @property
    def payload(self) -> list[str]:
        return [c for c in self.edges.columns if c not in ("src", "dst")]

    @property
    def order(self) -> list[str]:
        """The canonical order inside a list; edges equal in all of it can change places. Maps have no order and come last as text."""
        kinds = dict(self.edges.dtypes)
        return ["src", *(c if "map<" not in kinds[c] else f"to_json({c})" for c in self.payload)]

    def order_columns(self):
        return [F.expr(c) for c in self.order]

    def flip_roles(self) -> Graph:
        """The same edges stored by the other end."""
        x = self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *self.payload)
        return replace(self, edges=x, n_src=self.n_dst, n_dst=self.n_src, orientation="in" if self.orientation == "out" else "out")

    def validate(self) -> Graph:
        """self, or InvalidEdges with the counts; one pass over the two id columns."""
        bad = (F.col("src") < 0) | (F.col("src") >= self.n_src) | (F.col("dst") < 0) | (F.col("dst") >= self.n_dst)
        null = F.col("src").isNull() | F.col("dst").isNull()
        r = self.edges.agg(F.count_if(null).alias("n"), F.count_if(bad).alias("b")).first()
        if r["n"] or r["b"]:
            raise InvalidEdges(r["n"], r["b"])
        return self

    def with_edges(self, edges: DataFrame) -> Graph:
        return replace(self, edges=edges)


@dataclass(frozen=True)
class Csr:
    offsets: DataFrame
    endpoints: DataFrame
    n_vertices: int
    n_other: int
    orientation: str = "in"

    @property
    def payload(self) -> list[str]:
        return [c for c in self.endpoints.columns if c not in ("pos", "endpoint")]

    def adjacency(self) -> DataFrame:
        """(vertex, neighbors): a view for lists that fit a row."""
        owned = edges_of(self)
        item = F.struct("pos", "endpoint", *self.payload)
        lists = owned.groupBy("owner").agg(F.sort_array(F.collect_list(item)).alias("l"))
        keep = (lambda x: F.struct(x["endpoint"].alias("id"), *[x[c].alias(c) for c in self.payload])) if self.payload else (lambda x: x["endpoint"])
        v = self.offsets.where(F.col("vertex") < self.n_vertices).select("vertex")
        return v.join(lists.withColumnRenamed("owner", "vertex"), "vertex", "left").select("vertex", F.coalesce(F.transform("l", keep), F.array()).alias("neighbors"))


def any_payload(method: Callable[..., Csr]) -> Callable[..., Csr]:
    """method for graphs whose payload columns may have any names but those of the result: inside they are numbered."""

    @wraps(method)
    def run(g: Graph, *args, **kwargs) -> Csr:
        names = g.payload
        if taken := {"pos", "endpoint"} & {c.lower() for c in names}:
            raise ValueError(f"payload columns can't be named {', '.join(sorted(taken))}")
        csr = method(g.with_edges(g.edges.select("src", "dst", *[quoted(c).alias(f"payload_{i}") for i, c in enumerate(names)])), *args, **kwargs)
        return replace(csr, endpoints=csr.endpoints.select("pos", "endpoint", *[F.col(f"payload_{i}").alias(c) for i, c in enumerate(names)]))

    return run


def edges_of(csr: Csr) -> DataFrame:
    """(owner, endpoint, pos, payload...): who owns each position. Both sides meet in ranges of positions, an equi-join."""
    width = 1 << 16
    ends = csr.offsets.where(F.col("vertex") <= csr.n_vertices).select("vertex", "start")
    starts = csr.endpoints.select("pos", "endpoint", *csr.payload).withColumn("bucket", F.floor(F.col("pos") / width))
    # the owner of a position is the last non-empty vertex that starts at or before it: interleave, carry it forward within a bucket
    edge = ends.select((F.col("vertex") - 1).alias("vertex"), F.col("start").alias("next")).where("vertex >= 0")
    spans = ends.where(F.col("vertex") < csr.n_vertices).join(edge, "vertex").where("next > start").select(F.col("vertex").alias("owner"), "start", "next")
    spans = spans.select("owner", "start", "next", F.explode(F.sequence(F.floor(F.col("start") / width), F.floor((F.col("next") - 1) / width))).alias("bucket"))
    firsts = spans.select("bucket", F.greatest("start", F.col("bucket") * width).alias("pos"), "owner")
    w = Window.partitionBy("bucket").orderBy("pos", F.col("owner").isNull()).rowsBetween(Window.unboundedPreceding, 0)
    nothing = [F.lit(None).cast(csr.endpoints.schema[c].dataType).alias(c) for c in ("endpoint", *csr.payload)]
    both = firsts.select("bucket", "pos", "owner", *nothing, F.lit(False).alias("edge")).unionByName(starts.select("bucket", "pos", F.lit(None).cast("long").alias("owner"), "endpoint", *csr.payload, F.lit(True).alias("edge")))
    return both.withColumn("owner", F.last("owner", ignorenulls=True).over(w)).where("edge").select("owner", "endpoint", "pos", *csr.payload)


def graph_of(csr: Csr) -> Graph:
    """The edges that a compressed form stands for: its vertices are the sources again."""
    e = edges_of(csr).select(F.col("owner").alias("src"), F.col("endpoint").alias("dst"), *csr.payload)
    return Graph(e, csr.n_vertices, csr.n_other, csr.orientation)
