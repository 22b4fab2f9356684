"""What a transposed graph is used for."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from turnwise.model import Csr, Graph, edges_of
from turnwise.storage import dropped, stored


def spmv(g: Graph, x: DataFrame, weight: str | None = None) -> DataFrame:
    """(id, value) of y = A x, x being (id, value) over targets."""
    w = F.col(weight) if weight else F.lit(1)
    e = g.edges.join(x.select(F.col("id").alias("dst"), F.col("value").alias("_x")), "dst")
    return e.groupBy(F.col("src").alias("id")).agg(F.sum(w * F.col("_x")).alias("value"))


def spmv_t(g: Graph, y: DataFrame, weight: str | None = None) -> DataFrame:
    """The same for the transposed matrix."""
    return spmv(g.flip_roles(), y, weight)


def pagerank(csr: Csr, out_degrees: DataFrame, rounds: int = 10, damping: float = 0.85) -> DataFrame:
    """(id, rank) by pulling over the transposed form; out_degrees is (id, n). Each round is written before the next."""
    n = csr.n_vertices
    e = stored(edges_of(csr).select(F.col("owner").alias("dst"), F.col("endpoint").alias("src")), "pull")
    spark = e.sparkSession
    v = spark.range(n)
    rank = stored(v.select("id", F.lit(1.0 / max(n, 1)).alias("rank")), "rank")
    for _ in range(rounds):
        share = rank.join(out_degrees, "id").select(F.col("id").alias("src"), (F.col("rank") / F.col("n")).alias("s"))
        got = e.join(share, "src").groupBy(F.col("dst").alias("id")).agg(F.sum("s").alias("s"))
        held = rank.join(out_degrees, "id", "left_anti").agg(F.coalesce(F.sum("rank"), F.lit(0.0)).alias("lost"))
        new = v.join(got, "id", "left").join(F.broadcast(held), F.lit(True)).select("id", ((1 - damping) / n + damping * (F.coalesce("s", F.lit(0.0)) + F.col("lost") / n)).alias("rank"))
        new = stored(new, "rank")
        dropped(rank)
        rank = new
    return rank


def out_degrees(g: Graph) -> DataFrame:
    return g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("n"))


def neighbors(csr: Csr, vertices: list[int]) -> DataFrame:
    """(vertex, endpoint) of a few vertices: their stretches of positions, no scan of offsets by others."""
    spans = csr.offsets.where(F.col("vertex").isin([*vertices, *[v + 1 for v in vertices]])).alias("o")
    a, b = spans, csr.offsets.select((F.col("vertex") - 1).alias("vertex"), F.col("start").alias("next")).where(F.col("vertex").isin(vertices))
    own = a.where(F.col("vertex").isin(vertices)).join(b, "vertex")
    return csr.endpoints.join(F.broadcast(own), (F.col("pos") >= F.col("start")) & (F.col("pos") < F.col("next"))).select("vertex", "endpoint")


def two_hop(g: Graph) -> DataFrame:
    """(src, dst, paths): paths of two edges. Counted edges are joined, so parallel edges multiply without being expanded."""
    e = g.edges.groupBy("src", "dst").agg(F.count("*").alias("n"))
    a, b = e.select("src", F.col("dst").alias("mid"), "n"), e.select(F.col("src").alias("mid"), "dst", F.col("n").alias("m"))
    return a.join(b, "mid").groupBy("src", "dst").agg(F.sum(F.col("n") * F.col("m")).cast("long").alias("paths"))


def common_neighbors(g: Graph) -> DataFrame:
    """(a, b, common), a < b: sources that share targets."""
    e = g.edges.select("src", "dst").distinct()
    x, y = e.select(F.col("src").alias("a"), "dst"), e.select(F.col("src").alias("b"), "dst")
    return x.join(y, "dst").where("a < b").groupBy("a", "b").agg(F.count("*").alias("common"))


def reciprocity(g: Graph) -> DataFrame:
    """(edges, mutual): distinct edges and those whose reverse is there."""
    e = g.edges.select("src", "dst").distinct()
    back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("_b"))
    return e.join(back, ["src", "dst"], "left").agg(F.count("*").alias("edges"), F.count("_b").alias("mutual"))


def bfs(g: Graph, root: int, rounds: int | None = None) -> DataFrame:
    """(id, level) of what can be reached, within so many rounds if given; a round is written before the next."""
    e = g.edges.select("src", "dst").distinct()
    seen = stored(e.sparkSession.createDataFrame([(root, 0)], "id long, level long"), "bfs")
    step = 0
    while rounds is None or step < rounds:
        step += 1
        front = seen.where(F.col("level") == step - 1).select(F.col("id").alias("src"))
        new = e.join(front, "src").select(F.col("dst").alias("id")).distinct().join(seen, "id", "left_anti").withColumn("level", F.lit(step).cast("long"))
        grown = stored(seen.unionByName(new), "bfs")
        done = grown.where(F.col("level") == step).isEmpty()
        dropped(seen)
        seen = grown
        if done:
            break
    return seen


def components(g: Graph) -> DataFrame:
    """(id, component): smallest id reachable over edges in either direction, by spreading minima and following their labels."""
    both = g.edges.select("src", "dst").unionByName(g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
    both = stored(both, "both")
    n = max(g.n_src, g.n_dst)
    label = stored(both.sparkSession.range(n).select("id", F.col("id").alias("component")), "label")
    while True:
        least = both.join(label.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.min("component").alias("_m"))
        near = label.join(least, "id", "left").select("id", "component", F.least("component", F.coalesce("_m", "component")).alias("_c"))
        far = near.join(label.select(F.col("id").alias("_c"), F.col("component").alias("_cc")), "_c").select("id", "component", F.col("_cc").alias("new"))
        new = stored(far.select("id", F.col("new").alias("component"), (F.col("new") != F.col("component")).alias("moved")), "label")
        moved = not new.where("moved").isEmpty()
        dropped(label)
        label = new
        if not moved:
            dropped(both)
            return label.select("id", "component")


def triangles(g: Graph) -> DataFrame:
    """(triangles) of the undirected simple graph. Edges point from the lower to the higher (degree, id), which bounds what hot vertices fan out."""
    e = g.edges.where("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    deg = e.select(F.explode(F.array("a", "b")).alias("id")).groupBy("id").agg(F.count("*").alias("d"))
    x = e.join(deg.select(F.col("id").alias("a"), F.col("d").alias("da")), "a").join(deg.select(F.col("id").alias("b"), F.col("d").alias("db")), "b")
    up = F.struct("da", "a") < F.struct("db", "b")
    o = x.select(F.when(up, F.col("a")).otherwise(F.col("b")).alias("u"), F.when(up, F.col("b")).otherwise(F.col("a")).alias("v"))
    wedges = o.select("u", F.col("v").alias("v1")).join(o.select("u", F.col("v").alias("v2")), "u").where("v1 < v2")
    closed = wedges.join(e.select(F.col("a").alias("v1"), F.col("b").alias("v2")), ["v1", "v2"])
    return closed.agg(F.count("*").alias("triangles"))


def sources(g: Graph) -> DataFrame:
    """(id): vertices that nothing points to."""
    v = g.edges.sparkSession.range(g.n_src)
    return v.join(g.edges.select(F.col("dst").alias("id")).distinct(), "id", "left_anti")


def sinks(g: Graph) -> DataFrame:
    """(id): vertices that point to nothing."""
    v = g.edges.sparkSession.range(g.n_dst)
    return v.join(g.edges.select(F.col("src").alias("id")).distinct(), "id", "left_anti")
