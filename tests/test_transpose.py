import random

import pytest
from pyspark.sql import functions as F

from turnwise.model import Graph, InvalidEdges, edges_of, graph_of
from turnwise.operators import reference
from turnwise.operators.adaptive import adaptive_transpose
from turnwise.operators.hotset import exact_hot, input_side_hot, sample_bound
from turnwise.operators.hybrid import hybrid_transpose, wrap_events
from turnwise.operators.merge import block_merge_transpose, merge_rounds
from turnwise.operators.order import sort_lists
from turnwise.operators.private import private_scan_transpose
from turnwise.operators.shared import consumed_insertion_points, restore_offsets_by_shift, shared_degrees, shared_transpose

HAND = [(0, 1), (0, 2), (1, 3), (2, 1), (3, 0), (3, 2)]


def graph(spark, rows, n_src, n_dst=None):
    return Graph.of(spark.createDataFrame(rows, "src long, dst long"), n_src, n_dst)


def arrays(csr):
    return [r.start for r in csr.offsets.orderBy("vertex").collect()], [r.endpoint for r in csr.endpoints.orderBy("pos").collect()]


def plain(rows, n):
    offsets, out = [0], []
    for v in range(n):
        out += sorted(s for s, d in rows if d == v)
        offsets.append(len(out))
    return offsets, out


def methods(k=2, blocks=2):
    return {
        "shared": lambda g: shared_transpose(g),
        "copy": lambda g: shared_transpose(g, ip_mode="copy", combine="map"),
        "private": lambda g: private_scan_transpose(g, blocks),
        "merge": lambda g: block_merge_transpose(g, blocks),
        "hybrid": lambda g: hybrid_transpose(g, exact_hot(g, k), blocks=blocks),
        "adaptive": lambda g: adaptive_transpose(g, k=k, blocks=blocks, hot_source="exact")[0],
        "reference": reference.sorted_reference,
    }


@pytest.mark.parametrize("name", methods())
def test_hand_graph(spark, name):
    g = graph(spark, HAND, 4)
    csr = methods()[name](g)
    assert arrays(csr) == ([0, 1, 3, 5, 6], [3, 0, 2, 0, 3, 1])
    assert reference.same_graph(graph_of(csr), g.flip_roles())


def test_skewed_multigraph_whatever_the_hot_set_and_blocks(spark):
    r = random.Random(1)
    rows = [(r.randrange(40), 0 if r.random() < 0.5 else r.randrange(30)) for _ in range(800)]
    g, want = graph(spark, rows, 40, 30), plain(rows, 30)
    for k, blocks in ((0, 1), (1, 7), (30, 3)):
        assert arrays(hybrid_transpose(g, exact_hot(g, k), blocks=blocks)) == want
    assert arrays(hybrid_transpose(g, input_side_hot(g, 5), blocks=4, block_method="range")) == want
    csr = hybrid_transpose(g, exact_hot(g, 3), blocks=4, sort_lists=False)
    assert sorted(r.pos for r in csr.endpoints.collect()) == list(range(800))
    assert arrays(sort_lists(csr)) == want
    assert arrays(block_merge_transpose(g, 5, 3)) == want


def test_empty_isolated_and_one_target(spark):
    for n in (0, 3):
        assert arrays(shared_transpose(graph(spark, [], n))) == ([0] * (n + 1), [])
        assert arrays(hybrid_transpose(graph(spark, [], n), exact_hot(graph(spark, [], n), 2), blocks=2)) == ([0] * (n + 1), [])
    rows = [(i, 2) for i in range(5)] + [(2, 2)]
    assert arrays(hybrid_transpose(graph(spark, rows, 5, 4), exact_hot(graph(spark, rows, 5, 4), 1), blocks=2)) == ([0, 0, 0, 6, 6], [0, 1, 2, 2, 3, 4])


def test_payload_of_every_type_rides_along(spark):
    e = spark.createDataFrame(HAND, "src long, dst long").selectExpr("src", "dst", "CAST(src AS DECIMAL(9,2)) AS d", "TIMESTAMP'2024-01-01' AS t", "array(src, dst) AS a", "struct(src AS x) AS s", "map('k', dst) AS m", "CAST(dst AS STRING) AS c")
    g = Graph.of(e, 4)
    out = hybrid_transpose(g, exact_hot(g, 1), blocks=2).endpoints.orderBy("pos").collect()
    assert [(r.endpoint, r.a[0], r.m["k"], r.c) for r in out] == [(3, 3, 0, "0"), (0, 0, 1, "1"), (2, 2, 1, "1"), (0, 0, 2, "2"), (3, 3, 2, "2"), (1, 1, 3, "3")]


def test_bad_ids_are_counted(spark):
    with pytest.raises(InvalidEdges) as e:
        graph(spark, [(0, None), (5, 1), (1, -1), (1, 1)], 2).validate()
    assert (e.value.nulls, e.value.outside) == (1, 2)


def test_insertion_points_end_where_the_next_begins(spark):
    g = graph(spark, HAND, 4)
    csr = shared_transpose(g)
    ip = {r.vertex: r.ip for r in consumed_insertion_points(g, csr.offsets).collect()}
    start = {r.vertex: r.start for r in csr.offsets.collect()}
    assert all(ip[v] == start[v + 1] for v in range(4))
    assert {r.vertex: r.start for r in restore_offsets_by_shift(consumed_insertion_points(g, csr.offsets), 4).collect()} == start


def test_low_and_high_counters(spark):
    counts = spark.createDataFrame([(i, n) for i, n in enumerate([0, 1, 255, 256, 257, 65536])], "dst long, n long")
    assert tuple(wrap_events(counts).first()) == (sum(n // 256 for n in (0, 1, 255, 256, 257, 65536)), 3)


def test_involution_and_symmetry(spark):
    g = graph(spark, HAND, 4)
    assert reference.involution_difference(g, lambda x: shared_transpose(x)).first()[0] == 0
    assert not reference.is_symmetric(g)
    assert reference.is_symmetric(graph(spark, [(0, 1), (1, 0), (2, 2)], 3))


def test_plans(spark):
    g = graph(spark, HAND, 4)
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    count = plan(shared_degrees(g))
    # the exchange comes before any counting, and it is the only one
    assert count.count("Exchange") == 1 and count.index("partial_count") < count.index("Exchange")
    tagged = plan(hybrid_transpose(g, exact_hot(g, 1), blocks=2, block_method="range").endpoints)
    assert "BroadcastHashJoin" in tagged


def test_rounds_and_bounds():
    assert [merge_rounds(p, 2) for p in (1, 2, 3, 8, 9)] == [0, 1, 2, 3, 4]
    assert sample_bound(0.01, 0.5, 0.05) < sample_bound(0.001, 0.5, 0.05)


def test_owners_of_positions(spark):
    csr = shared_transpose(graph(spark, HAND, 4))
    assert sorted((r.owner, r.endpoint) for r in edges_of(csr).collect()) == sorted((d, s) for s, d in HAND)
    assert {r.vertex: r.neighbors for r in csr.adjacency().collect()} == {0: [3], 1: [0, 2], 2: [0, 3], 3: [1]}


def test_choice_by_rows(spark):
    skewed = Graph.of(spark.range(4000).select(F.col("id").alias("src"), F.when(F.col("id") % 10 < 9, 0).otherwise(F.col("id") % 50).alias("dst")), 4000, 50)
    flat = Graph.of(spark.range(4000).select(F.col("id").alias("src"), F.col("id").alias("dst")), 4000)
    assert adaptive_transpose(skewed, k=4, blocks=4, hot_source="exact")[1].method == "hybrid"
    assert adaptive_transpose(flat, k=4, blocks=4, hot_source="exact")[1].method == "shared"
