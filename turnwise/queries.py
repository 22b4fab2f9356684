"""The registered queries of the engine, with the SQL that DuckDB has to agree with where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.functions import cachesim, locality, udfs
from turnwise.model import Csr, Graph
from turnwise.operators import consumers, edges, hotset, order, prefix, reference
from turnwise.operators.adaptive import adaptive_transpose, decide, decision_row
from turnwise.operators.blocks import block_sizes, edge_blocks
from turnwise.operators.hybrid import hybrid_degrees, hybrid_transpose, wrap_events
from turnwise.operators.merge import block_merge_transpose
from turnwise.operators.private import private_counts, private_scan_transpose
from turnwise.operators.shared import consumed_insertion_points, restore_offsets_by_shift, shared_degrees, shared_transpose
from turnwise.plans import balance, calibrate, costmodel, measures, runs
from turnwise.sources import workloads
from turnwise.streaming import stream

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

K, BLOCKS = 64, 8
MAIN = ("order_part", "customer_part", "word_successor", "page_link", "cubic_skew", "user_next", "copurchase")
SMALL = ("document_word", "customer_supplier", "user_type", "turn_parent", "similarity", "nation_region", "order_customer", "document_benchmark")


def add(name: str, query: Callable[[SparkSession, str], DataFrame], oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def build(name: str) -> Callable[[SparkSession, str], Graph]:
    return workloads.GRAPHS[name]


def ctes(name: str, side: str = "row") -> str:
    """WITH ... n(n_src, n_dst), g(src, dst): the edges of a graph, by row or by column."""
    sql, n_src, n_dst = workloads.SQL[name]
    flip = side == "column"
    s, d = (n_dst, n_src) if flip else (n_src, n_dst)
    pick = "dst AS src, src AS dst" if flip else "src, dst"
    return f"WITH {sql}, n AS (SELECT CAST({s} AS BIGINT) AS n_src, CAST({d} AS BIGINT) AS n_dst), g AS (SELECT {pick} FROM e)"


OFFSETS = "SELECT v AS vertex, CAST(coalesce(sum(c) OVER (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start FROM (SELECT v, coalesce(c, 0) AS c FROM (SELECT unnest(range(n_dst + 1)) AS v FROM n) LEFT JOIN (SELECT dst, count(*) AS c FROM g GROUP BY dst) ON v = dst)"
ENDPOINTS = "SELECT row_number() OVER (ORDER BY dst, src) - 1 AS pos, src AS endpoint FROM g"


def _hot(g: Graph, k: int = K) -> DataFrame:
    return hotset.exact_hot(g, k)


METHODS: dict[str, Callable[[Graph], Csr]] = {
    "shared": lambda g: shared_transpose(g),
    "private": lambda g: private_scan_transpose(g, BLOCKS),
    "merge": lambda g: block_merge_transpose(g, BLOCKS, 2),
    "hybrid": lambda g: hybrid_transpose(g, _hot(g), blocks=BLOCKS),
    "adaptive": lambda g: adaptive_transpose(g, k=K, blocks=BLOCKS)[0],
}


def _two(name: str, method: str, side: str = "row"):
    """Queries for the offsets and endpoints of a method on a graph."""

    def csr(spark, sf_dir):
        g = build(name)(spark, sf_dir)
        return METHODS[method](g if side == "row" else g.flip_roles())

    return (lambda s, d: csr(s, d).offsets), (lambda s, d: csr(s, d).endpoints)


for _g in MAIN:
    for _m in METHODS:
        _o, _e = _two(_g, _m)
        add(f"t_{_m}_offsets_{_g}", _o, f"{ctes(_g)} {OFFSETS}")
        add(f"t_{_m}_endpoints_{_g}", _e, f"{ctes(_g)} {ENDPOINTS}")
for _g in SMALL:
    _o, _e = _two(_g, "hybrid")
    add(f"t_hybrid_offsets_{_g}", _o, f"{ctes(_g)} {OFFSETS}")
    add(f"t_hybrid_endpoints_{_g}", _e, f"{ctes(_g)} {ENDPOINTS}")
for _g in ("order_part", "customer_part", "page_link", "cubic_skew"):
    for _m in ("shared", "hybrid"):
        _o, _e = _two(_g, _m, "column")
        add(f"t_{_m}_offsets_column_{_g}", _o, f"{ctes(_g, 'column')} {OFFSETS}")
        add(f"t_{_m}_endpoints_column_{_g}", _e, f"{ctes(_g, 'column')} {ENDPOINTS}")

# variants of the shared method, unsorted and weighted forms, both references
add("t_shared_copy_offsets_order_part", lambda s, d: shared_transpose(build("order_part")(s, d), ip_mode="copy", combine="map").offsets, f"{ctes('order_part')} {OFFSETS}")
add("t_reference_endpoints_cubic_skew", lambda s, d: reference.sorted_reference(build("cubic_skew")(s, d)).endpoints, f"{ctes('cubic_skew')} {ENDPOINTS}")
add("t_sorted_afterwards_cubic_skew", lambda s, d: order.sort_lists(shared_transpose(build("cubic_skew")(s, d), sort_lists=False)).endpoints, f"{ctes('cubic_skew')} {ENDPOINTS}")
add("t_merge_at_once_endpoints_cubic_skew", lambda s, d: block_merge_transpose(build("cubic_skew")(s, d), BLOCKS, BLOCKS).endpoints, f"{ctes('cubic_skew')} {ENDPOINTS}")
add("t_hybrid_range_blocks_endpoints_cubic_skew", lambda s, d: (lambda g: hybrid_transpose(g, _hot(g), blocks=BLOCKS, block_method="range"))(build("cubic_skew")(s, d)).endpoints, f"{ctes('cubic_skew')} {ENDPOINTS}")


def unsorted_lists(s, d):
    csr = hybrid_transpose((g := build("cubic_skew")(s, d)), _hot(g), blocks=BLOCKS, sort_lists=False)
    return csr.adjacency().select("vertex", F.array_join(F.sort_array("neighbors"), ",").alias("sources"))


add("t_hybrid_unsorted_as_sets_cubic_skew", unsorted_lists, f"{ctes('cubic_skew')} SELECT v AS vertex, coalesce(l, '') AS sources FROM (SELECT unnest(range(n_dst)) AS v FROM n) LEFT JOIN (SELECT dst, string_agg(CAST(src AS VARCHAR), ',' ORDER BY src) AS l FROM g GROUP BY dst) ON v = dst")
add("collect_list_page_link", lambda s, d: reference.collect_list_reference(build("page_link")(s, d)).select("dst", F.array_join("sources", ",").alias("sources")), f"{ctes('page_link')} SELECT dst, string_agg(CAST(src AS VARCHAR), ',' ORDER BY src) AS sources FROM g GROUP BY dst")


def weighted(method: str):
    def q(s, d):
        g = workloads.order_part_weighted(s, d)
        return METHODS[method](g).endpoints

    return q


for _m in METHODS:
    add(f"t_{_m}_weighted_order_part", weighted(_m), "SELECT row_number() OVER (ORDER BY l_partkey, l_orderkey, l_quantity, l_extendedprice) - 1 AS pos, l_orderkey AS endpoint, l_quantity, l_extendedprice FROM lineitem")

for _g in ("order_part", "page_link", "cubic_skew"):
    for _m in ("shared", "hybrid"):
        add(f"involution_{_m}_{_g}", lambda s, d, g=_g, m=_m: reference.involution_difference(build(g)(s, d), METHODS[m]), "SELECT CAST(0 AS BIGINT) AS differences")
for _g in ("copurchase", "similarity", "user_next"):
    add(f"symmetric_{_g}", lambda s, d, g=_g: s.createDataFrame([(reference.is_symmetric(build(g)(s, d)),)], "symmetric boolean"), f"{ctes(_g)} SELECT NOT EXISTS ((SELECT src, dst FROM g EXCEPT ALL SELECT dst, src FROM g)) AS symmetric")

DEG = "deg AS (SELECT dst, count(*) AS n FROM g GROUP BY dst)"
RANKED = f"{DEG}, ranked AS (SELECT dst, n, row_number() OVER (ORDER BY n DESC, dst) - 1 AS rk FROM deg)"
for _g in (*MAIN, *SMALL):
    for _side in ("row", "column"):
        _f = (lambda s, d, g=_g: build(g)(s, d)) if _side == "row" else (lambda s, d, g=_g: build(g)(s, d).flip_roles())
        _name = _g if _side == "row" else f"column_{_g}"
        add(f"profile_{_name}", lambda s, d, f=_f: measures.graph_profile(f(s, d)), f"{ctes(_g, _side)} SELECT count(*) AS edges, count(DISTINCT src) AS sources, count(DISTINCT dst) AS targets, (SELECT max(c) FROM (SELECT count(*) AS c FROM g GROUP BY src)) AS max_out, (SELECT max(c) FROM (SELECT count(*) AS c FROM g GROUP BY dst)) AS max_in FROM g")
    add(f"narrow_share_{_g}", lambda s, d, g=_g: measures.narrow_counter_share(build(g)(s, d)), f"{ctes(_g)}, {DEG} SELECT count(*) AS vertices, count(*) FILTER (n < 256) AS narrow, 3 * count(*) FILTER (n < 256) AS wasted_bytes FROM deg")
    add(f"degree_histogram_{_g}", lambda s, d, g=_g: measures.degree_histogram(build(g)(s, d)), f"{ctes(_g)}, {DEG} SELECT CAST(length(bin(n)) - 1 AS BIGINT) AS log2_class, count(*) AS vertices, CAST(sum(n) AS BIGINT) AS edges FROM deg GROUP BY 1")

KS = [16, 64, 256, 1024, 4096]
for _g in ("word_successor", "document_word", "cubic_skew", "order_part", "page_link"):
    for _side in ("row", "column"):
        _f = (lambda s, d, g=_g: build(g)(s, d)) if _side == "row" else (lambda s, d, g=_g: build(g)(s, d).flip_roles())
        _name = _g if _side == "row" else f"column_{_g}"
        add(f"coverage_exact_{_name}", lambda s, d, f=_f: measures.coverage_by_k(f(s, d), KS), f"{ctes(_g, _side)}, {RANKED} SELECT CAST(k AS BIGINT) AS k, (SELECT count(*) FROM g) AS edges, CAST(coalesce(sum(n), 0) AS BIGINT) AS covered FROM (SELECT unnest({KS}) AS k) LEFT JOIN ranked ON rk < k GROUP BY k")
    add(f"coverage_random_labels_{_g}", lambda s, d, g=_g: measures.coverage_by_k(locality.relabel_affine(build(g)(s, d)), KS), f"{ctes(_g)}, {RANKED} SELECT CAST(k AS BIGINT) AS k, (SELECT count(*) FROM g) AS edges, CAST(coalesce(sum(n), 0) AS BIGINT) AS covered FROM (SELECT unnest({KS}) AS k) LEFT JOIN ranked ON rk < k GROUP BY k")
    add(f"wraps_{_g}", lambda s, d, g=_g: wrap_events(measures.degrees(build(g)(s, d))), f"{ctes(_g)}, {DEG} SELECT CAST(coalesce(sum(n // 256), 0) AS BIGINT) AS wraps, count(*) FILTER (n >= 256) AS vertices FROM deg")


def _with_hot(s, d, name: str, source: str):
    g = build(name)(s, d)
    hot = {"exact": lambda: hotset.exact_hot(g, K), "counting": lambda: hotset.exact_hot(g, K, "counting"), "systematic": lambda: hotset.sample_hot(g, K, rate=0.1, method="systematic"), "sample": lambda: hotset.sample_hot(g, K), "wrong_side": lambda: hotset.input_side_hot(g, K), "sketch": lambda: hotset.sketch_hot(g, K)}[source]()
    return g, hot


HOT_SQL = f"{RANKED}, hot AS (SELECT dst, rk AS hot_index, n FROM ranked WHERE rk < {K})"
for _g in ("word_successor", "cubic_skew", "order_part"):
    for _s in ("exact", "counting"):
        add(f"hot_{_s}_{_g}", lambda s, d, g=_g, o=_s: _with_hot(s, d, g, o)[1].withColumn("hot_index", F.col("hot_index").cast("long")), f"{ctes(_g)}, {HOT_SQL} SELECT dst, hot_index, n FROM hot")
    for _s in ("sample", "sketch"):
        add(f"coverage_{_s}_{_g}", lambda s, d, g=_g, o=_s: measures.coverage(*_with_hot(s, d, g, o)))
    add(f"coverage_wrong_side_{_g}", lambda s, d, g=_g: measures.coverage(*_with_hot(s, d, g, "wrong_side")), f"{ctes(_g)}, o AS (SELECT src AS dst, count(*) AS n FROM g GROUP BY src), hot AS (SELECT dst FROM o WHERE dst < (SELECT n_dst FROM n) ORDER BY n DESC, dst LIMIT {K}) SELECT count(*) AS edges, count(*) FILTER (dst IN (SELECT dst FROM hot)) AS covered FROM g")
    add(f"hot_recall_{_g}", lambda s, d, g=_g: measures.hot_recall(_with_hot(s, d, g, "sample")[1], _with_hot(s, d, g, "exact")[1]))
add("coverage_systematic_cubic_skew", lambda s, d: measures.coverage(*_with_hot(s, d, "cubic_skew", "systematic")), f"{ctes('cubic_skew')}, p AS (SELECT dst, row_number() OVER (ORDER BY src, dst) - 1 AS pos FROM g), drawn AS (SELECT dst FROM p WHERE pos % greatest(1, (SELECT count(*) FROM g) // CAST(ceil(0.1 * (SELECT n_dst FROM n)) AS BIGINT)) = 0), hot AS (SELECT dst FROM drawn GROUP BY dst ORDER BY count(*) DESC, dst LIMIT {K}) SELECT count(*) AS edges, count(*) FILTER (dst IN (SELECT dst FROM hot)) AS covered FROM g")
add("counting_rank_cubic_skew", lambda s, d: order.rank_by_frequency(measures.degrees(build("cubic_skew")(s, d))), f"{ctes('cubic_skew')}, {RANKED} SELECT dst, n, rk AS rank FROM ranked")

# labellings and locality
A = locality.MULTIPLIER


def _affine_sql(name: str) -> str:
    """Permuted edges; the multiplier is raised until it has no factor in common with the number of ids."""
    mult = lambda n: f"(SELECT min(a) FROM (SELECT unnest(range({A}, {A} + 400, 2)) AS a) WHERE gcd(a, (SELECT {n} FROM n)) = 1)"
    return f"{ctes(name)}, r AS (SELECT (src * {mult('n_src')} + 13) % (SELECT n_src FROM n) AS src, (dst * {mult('n_dst')} + 13) % (SELECT n_dst FROM n) AS dst FROM g)"


LABELS = {"natural": lambda g: g, "random": locality.relabel_affine}
LABEL_SQL = {"natural": lambda name: f"{ctes(name)}, r AS (SELECT * FROM g)", "random": _affine_sql}
for _g in ("word_successor", "cubic_skew", "customer_part"):
    for _l in LABELS:
        _b = lambda s, d, g=_g, lab=_l: LABELS[lab](build(g)(s, d))
        _q = LABEL_SQL[_l](_g)
        add(f"locality_bandwidth_{_l}_{_g}", lambda s, d, b=_b: locality.bandwidth(b(s, d)), f"{_q} SELECT max(abs(src - dst)) AS bandwidth FROM r")
        add(f"locality_mean_gap_{_l}_{_g}", lambda s, d, b=_b: locality.mean_gap(b(s, d)), f"{_q} SELECT count(*) AS edges, CAST(sum(abs(src - dst)) AS BIGINT) AS gap_sum FROM r")
        _gap = f"{_q}, gaps AS (SELECT src, dst - lag(dst) OVER (PARTITION BY src ORDER BY dst) AS gap FROM r)"
        add(f"locality_bits_per_link_{_l}_{_g}", lambda s, d, b=_b: locality.bits_per_link(b(s, d)), f"{_gap} SELECT count(*) AS links, CAST(coalesce(sum(2 * (length(bin(gap + 1)) - 1) + 1), 0) AS BIGINT) AS bits FROM gaps WHERE gap IS NOT NULL")
        add(f"locality_neighbor_gap_{_l}_{_g}", lambda s, d, b=_b: locality.neighbor_gap(b(s, d)), f"{_gap} SELECT count(*) AS vertices, round(avg(a), 4) AS mean_gap FROM (SELECT src, avg(gap) AS a FROM gaps WHERE gap IS NOT NULL GROUP BY src)")
        add(f"hit_ratio_direct_{_l}_{_g}", lambda s, d, b=_b: cachesim.hit_ratio_direct(b(s, d), 256), f"{_q}, w AS (SELECT dst // 16 = lag(dst // 16) OVER (PARTITION BY (dst // 16) % 256 ORDER BY src, dst) AS hit FROM r) SELECT count(*) AS accesses, count(*) FILTER (hit) AS hits, round(count(*) FILTER (hit) / count(*), 6) AS hit_ratio FROM w")
        add(f"hit_ratio_lru_{_l}_{_g}", lambda s, d, b=_b: cachesim.hit_ratio_lru(b(s, d), 64, 4))
for _l, _relabel in {"degree": locality.relabel_degree, "first_seen": locality.relabel_first_seen, "bfs": locality.relabel_bfs}.items():
    add(f"hit_ratio_{_l}_user_next", lambda s, d, r=_relabel: cachesim.hit_ratio_direct(r(build("user_next")(s, d)), 4))

# cost model, closed forms
T128 = costmodel.PRINTED[128]


def model_curve(s: SparkSession, d: str) -> DataFrame:
    """Both models at the coverages that two hot sets have of the skewed graph."""
    found = measures.coverage_by_k(build("cubic_skew")(s, d), [16, 64]).collect()
    return costmodel.model_curves(s, T128, [r.covered / r.edges for r in found])


def break_even(s: SparkSession, d: str) -> DataFrame:
    """The coverage that the hybrid needs by number of threads, beside what the hot set has."""
    needed = s.createDataFrame([(t, round(costmodel.break_even_c(0.0, x), 6)) for t, x in costmodel.PRINTED.items()], "threads long, coverage double")
    g = build("cubic_skew")(s, d)
    return needed.crossJoin(F.broadcast(measures.coverage(g, _hot(g)))).select("threads", "coverage", "edges", "covered", (F.col("covered") / F.col("edges") > F.col("coverage")).alias("pays"))


def hot_capacity_grid(s: SparkSession, d: str) -> DataFrame:
    """The hot vertices that each budget allows, and the edges of the skewed graph that these cover."""
    grid = costmodel.capacity_grid(s, BUDGETS, OWNERS)
    ks = sorted({r.k for r in grid.collect()})
    return grid.join(F.broadcast(measures.coverage_by_k(build("cubic_skew")(s, d), ks)), "k").select("budget", "owners", "private_bytes", "k", "edges", "covered")


add("model_curve", model_curve, f"{ctes('cubic_skew')}, {RANKED}, cov AS (SELECT (SELECT sum(n) FROM ranked WHERE rk < k) / (SELECT count(*) FROM g) AS c FROM (SELECT unnest([16, 64]) AS k)) SELECT round(i / 10, 6) AS h, c AS coverage, round({T128.shared_miss} - i / 10 * {T128.shared_miss - T128.shared_hit}, 6) AS cost_shared, round({T128.lookup_hit} + c * {T128.private_hit} + (1 - c) * {T128.shared_miss}, 6) AS cost_hybrid FROM (SELECT unnest(range(11)) AS i), cov")
add("break_even", break_even, f"{ctes('cubic_skew')}, {RANKED}, c AS (SELECT (SELECT count(*) FROM g) AS edges, (SELECT CAST(sum(n) AS BIGINT) FROM ranked WHERE rk < {K}) AS covered), x AS (SELECT CAST(t AS BIGINT) AS threads, round(224.0 / (m - w), 6) AS coverage FROM (VALUES (128, 540.0::DOUBLE, 260.0::DOUBLE), (16, 1600.0::DOUBLE, 600.0::DOUBLE), (4, 5900.0::DOUBLE, 2600.0::DOUBLE)) AS x(t, m, w)) SELECT threads, coverage, edges, covered, covered / edges > coverage AS pays FROM x, c")
BUDGETS, OWNERS = [64_000_000, 368_000_000, 576_000_000], [4, 16, 128]
add("hot_capacity_grid", hot_capacity_grid, f"{ctes('cubic_skew')}, {RANKED}, grid AS (SELECT CAST(b AS BIGINT) AS budget, CAST(o AS BIGINT) AS owners, CAST(p AS BIGINT) AS private_bytes, CAST(floor(b / (16 + p * o)) AS BIGINT) AS k FROM (SELECT unnest({BUDGETS}) AS b), (SELECT unnest({OWNERS}) AS o), (SELECT unnest([1, 4, 5, 8]) AS p)) SELECT grid.*, (SELECT count(*) FROM g) AS edges, (SELECT CAST(sum(n) AS BIGINT) FROM ranked WHERE rk < k) AS covered FROM grid")


def thread_sweep(s: SparkSession, d: str) -> DataFrame:
    """Hybrid against shared by number of threads: k follows from the budget, coverage from k, both costs from the printed times."""
    g = build("cubic_skew")(s, d)
    ks = {t: costmodel.hot_capacity(8_000, 8, 0.5, 5, t) for t in costmodel.PRINTED}
    c = {r.k: r.covered / r.edges for r in measures.coverage_by_k(g, sorted(set(ks.values()))).collect()}
    rows = [(t, ks[t], round(c[ks[t]], 6), round(costmodel.cost_shared(0.0, x) / costmodel.cost_hybrid(c[ks[t]], x), 6)) for t, x in costmodel.PRINTED.items()]
    return s.createDataFrame(rows, "threads long, k long, coverage double, speedup double")


add("thread_sweep_cubic_skew", thread_sweep)
for _g in ("cubic_skew", "order_part", "word_successor"):

    def _foot(s, d, g=_g):
        x = build(g)(s, d)
        return measures.footprint(s, x.n_dst, x.edges.count(), [4, 16, 64, 128])

    add(f"footprint_{_g}", _foot, f"{ctes(_g)}, s AS (SELECT (SELECT n_dst FROM n) AS v, (SELECT count(*) FROM g) AS e), pw AS (SELECT unnest([4, 16, 64, 128]) AS p), gb AS (SELECT *, (v + 1) * 8 + e * 4 AS graph_bytes FROM s, pw) SELECT m AS method, CAST(p AS BIGINT) AS workers, CAST(CASE m WHEN 'shared' THEN v * 4 WHEN 'private' THEN p * v * 12 WHEN 'merge' THEN p * v * 4 + e * 4 ELSE v * 4 + 256 * (16 + 5 * p) END AS BIGINT) AS extra_bytes, CAST(graph_bytes AS BIGINT) AS graph_bytes FROM gb, (SELECT unnest(['shared', 'private', 'merge', 'hybrid']) AS m)")

    def _access(s, d, g=_g):
        x = build(g)(s, d)
        r = measures.coverage(x, _hot(x)).first()
        return measures.access_counts(s, x.n_dst, r.edges, r.covered, K, BLOCKS)

    _cnt = f"{ctes(_g)}, {RANKED}, s AS (SELECT (SELECT n_dst FROM n) AS v, (SELECT count(*) FROM g) AS e, (SELECT CAST(coalesce(sum(n), 0) AS BIGINT) FROM ranked WHERE rk < {K}) AS c), h AS (SELECT *, least(c, {K * BLOCKS}) AS hp, least(e, {BLOCKS} * v) AS pp FROM s)"
    _row = lambda *x: "SELECT " + ", ".join(f"CAST({v} AS BIGINT) AS {n}" if n != "method" else f"'{v}' AS method" for v, n in zip(x, ("method", "edge_reads", "probes", "shared_updates", "private_updates", "slot_writes", "counters_summed", "count_rows", "place_rows"), strict=True)) + " FROM h"
    add(f"access_counts_{_g}", _access, f"{_cnt} {_row('shared', '2*e', 0, '2*e', 0, 'e', 'v', 'e', 'e')} UNION ALL {_row('private', '2*e', 0, 0, '2*e', 'e', f'{BLOCKS}*v', 'pp', 'pp')} UNION ALL {_row('merge', '4*e', 0, 0, 0, 0, 0, 0, '3*e')} UNION ALL {_row('hybrid', '2*e', '2*e+v', '2*(e-c)', '2*c', 'e', f'v-{K}+{K * BLOCKS}', 'e-c+hp', 'e-c+hp')}")
    _dec = f"{_cnt}, t AS (SELECT e, c, (SELECT count(*) FROM ranked WHERE rk < {K}) AS k, CAST(2 * e AS DOUBLE) AS a, CAST(2 * (e - c) + 2 * hp + c AS DOUBLE) AS b, (SELECT max(n) FROM deg) AS ls, (SELECT coalesce(max(n), 0) FROM ranked WHERE rk >= {K}) AS lc FROM h), u AS (SELECT *, greatest(lc, (ls + {BLOCKS - 1}) // {BLOCKS}) AS lh FROM t)"
    add(f"decision_rows_{_g}", lambda s, d, g=_g: decision_row(s, g, decide(x := build(g)(s, d), _hot(x), blocks=BLOCKS)), f"{_dec} SELECT '{_g}' AS graph, CASE WHEN k > 0 AND (b <= 0.8 * a OR (b < a AND 2 * lh <= ls)) THEN 'hybrid' ELSE 'shared' END AS method, k, c / e AS coverage, CAST(0 AS DOUBLE) AS h_est, a AS cost_shared, b AS cost_hybrid, ls AS largest_shared, CAST(lh AS BIGINT) AS largest_hybrid FROM u")
    add(f"shuffle_rows_{_g}", lambda s, d, g=_g: runs.edge_rows(x := build(g)(s, d), _hot(x), BLOCKS), f"{_cnt} SELECT 'shared' AS method, e AS count_rows, e AS place_rows FROM h UNION ALL SELECT 'hybrid', e - c, e FROM h")
    add(f"decision_model_{_g}", lambda s, d, g=_g: decision_row(s, g, decide(x := build(g)(s, d), _hot(x), blocks=BLOCKS, cost="model")))


def _blocked(s, d, name="cubic_skew"):
    return edge_blocks(build(name)(s, d), BLOCKS, "range")


BLOCK_SQL = f"{ctes('cubic_skew')}, b AS (SELECT src, dst, src * {BLOCKS} // (SELECT n_src FROM n) AS block FROM g)"
add("private_rows_cubic_skew", lambda s, d: measures.private_rows(_blocked(s, d)), f"{BLOCK_SQL} SELECT CAST(sum(c) AS BIGINT) AS rows, max(c) AS most FROM (SELECT block, count(DISTINCT dst) AS c FROM b GROUP BY block)")
add("private_counts_cubic_skew", lambda s, d: private_counts(_blocked(s, d), BLOCKS), f"{BLOCK_SQL} SELECT block, dst, count(*) AS n FROM b GROUP BY block, dst")
add("imbalance_cubic_skew", lambda s, d: balance.imbalance(block_sizes(_blocked(s, d))), f"{BLOCK_SQL} SELECT count(*) AS owners, CAST(sum(c) AS BIGINT) AS total, max(c) AS most, round(max(c) / avg(c) - 1, 6) AS over_mean, round(stddev_pop(c) / avg(c), 6) AS relative_sd FROM (SELECT block, count(*) AS c FROM b GROUP BY block)")


def _tagged(s, d):
    g = _blocked(s, d)
    return g, hotset.tag_hot(g.edges, _hot(build("cubic_skew")(s, d)))


TAG_SQL = f"{BLOCK_SQL}, {HOT_SQL}, tagged AS (SELECT b.*, hot_index FROM b LEFT JOIN hot USING (dst))"
add("rollup_block_hot", lambda s, d: measures.block_rollup(_tagged(s, d)[1]), f"{TAG_SQL} SELECT block, hot, count(*) AS n, CAST(grouping(block, hot) AS BIGINT) AS level FROM (SELECT block, CAST(hot_index IS NOT NULL AS INT) AS hot FROM tagged) GROUP BY ROLLUP (block, hot)")
add("hot_partials_cubic_skew", lambda s, d: hybrid_degrees(_tagged(s, d)[1], BLOCKS)[1].select("block", "dst", "low", "high"), f"{TAG_SQL} SELECT block, dst, CAST(count(*) % 256 AS INT) AS low, count(*) // 256 AS high FROM tagged WHERE hot_index IS NOT NULL GROUP BY block, dst")
add("block_histogram_cubic_skew", lambda s, d: udfs.block_histogram(_tagged(s, d)[1], K).withColumn("hot_index", F.col("hot_index").cast("long")), f"{TAG_SQL} SELECT block, hot_index, count(*) AS n FROM tagged WHERE hot_index IS NOT NULL GROUP BY block, hot_index")


def _two_phase(s, d, share: float):
    work = balance.two_phase_work(edge_blocks(build("cubic_skew")(s, d), 64, "range"), _hot(build("cubic_skew")(s, d)))
    costs = work.select("block", "cost", F.pmod("block", F.lit(4)).alias("owner"))
    return balance.two_phase_schedule(costs, 4, share)


add("schedule_owned_cubic_skew", lambda s, d: _two_phase(s, d, 1.0))
add("schedule_two_phase_cubic_skew", lambda s, d: _two_phase(s, d, 0.8))
add("shift_trick_word_successor", lambda s, d: (lambda g: restore_offsets_by_shift(consumed_insertion_points(g, prefix.prefix_offsets(shared_degrees(g), g.n_dst)), g.n_dst))(build("word_successor")(s, d)), f"{ctes('word_successor')} {OFFSETS}")
add("prefix_flat_nation_region", lambda s, d: prefix.flat_prefix(measures.degrees(build("nation_region")(s, d)), "dst", "n"), f"{ctes('nation_region')}, {DEG} SELECT dst, n, CAST(coalesce(sum(n) OVER (ORDER BY dst ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start FROM deg")

# selections and consumers
add("isolated_cubic_skew", lambda s, d: edges.isolated_vertices(build("cubic_skew")(s, d)), f"{ctes('cubic_skew')} SELECT v AS vertex FROM (SELECT unnest(range(n_dst)) AS v FROM n) WHERE v NOT IN (SELECT dst FROM g)")
add("weighted_dedup_document_word", lambda s, d: edges.weighted_dedup(build("document_word")(s, d)).edges, f"{ctes('document_word')} SELECT src, dst, count(*) AS weight FROM g GROUP BY src, dst")
add("filter_degree_order_part", lambda s, d: edges.filter_degree(build("order_part")(s, d), 30, 40).edges, f"{ctes('order_part')}, {DEG} SELECT src, dst FROM g WHERE dst IN (SELECT dst FROM deg WHERE n BETWEEN 30 AND 40)")
add("filter_cold_cubic_skew", lambda s, d: edges.filter_cold(g := build("cubic_skew")(s, d), _hot(g)).edges, f"{ctes('cubic_skew')}, {HOT_SQL} SELECT src, dst FROM g WHERE dst NOT IN (SELECT dst FROM hot)")
add("symmetrize_user_next", lambda s, d: edges.symmetrize(build("user_next")(s, d)).edges, f"{ctes('user_next')} SELECT src, dst FROM g UNION SELECT dst, src FROM g")
_X = "x AS (SELECT v AS id, v % 7 + 1 AS value FROM (SELECT unnest(range(n_dst)) AS v FROM n)), y AS (SELECT v AS id, v % 5 + 1 AS value FROM (SELECT unnest(range(n_src)) AS v FROM n))"
_vec = lambda s, n, m: s.range(n).select("id", (F.col("id") % m + 1).alias("value"))
add("spmv_cubic_skew", lambda s, d: consumers.spmv(g := build("cubic_skew")(s, d), _vec(s, g.n_dst, 7)), f"{ctes('cubic_skew')}, {_X} SELECT src AS id, CAST(sum(value) AS BIGINT) AS value FROM g JOIN x ON dst = id GROUP BY src")
add("spmv_transposed_cubic_skew", lambda s, d: consumers.spmv_t(g := build("cubic_skew")(s, d), _vec(s, g.n_src, 5)), f"{ctes('cubic_skew')}, {_X} SELECT dst AS id, CAST(sum(value) AS BIGINT) AS value FROM g JOIN y ON src = id GROUP BY dst")
add("reciprocity_user_next", lambda s, d: consumers.reciprocity(build("user_next")(s, d)), f"{ctes('user_next')}, u AS (SELECT DISTINCT src, dst FROM g) SELECT count(*) AS edges, count(*) FILTER (EXISTS (SELECT 1 FROM u r WHERE r.src = u.dst AND r.dst = u.src)) AS mutual FROM u")
add("two_hop_user_next", lambda s, d: consumers.two_hop(build("user_next")(s, d)), f"{ctes('user_next')} SELECT a.src, b.dst, count(*) AS paths FROM g a JOIN g b ON a.dst = b.src GROUP BY a.src, b.dst")
add("common_neighbors_nation_region", lambda s, d: consumers.common_neighbors(build("nation_region")(s, d)), f"{ctes('nation_region')}, u AS (SELECT DISTINCT src, dst FROM g) SELECT a.src AS a, b.src AS b, count(*) AS common FROM u a JOIN u b ON a.dst = b.dst AND a.src < b.src GROUP BY a.src, b.src")
add("triangles_user_next", lambda s, d: consumers.triangles(build("user_next")(s, d)), f"{ctes('user_next')}, u AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM g WHERE src <> dst) SELECT count(*) AS triangles FROM u x JOIN u y ON x.b = y.a JOIN u z ON z.a = x.a AND z.b = y.b")
add("sources_turn_parent", lambda s, d: consumers.sources(build("turn_parent")(s, d)), f"{ctes('turn_parent')} SELECT v AS id FROM (SELECT unnest(range(n_src)) AS v FROM n) WHERE v NOT IN (SELECT dst FROM g)")
add("sinks_turn_parent", lambda s, d: consumers.sinks(build("turn_parent")(s, d)), f"{ctes('turn_parent')} SELECT v AS id FROM (SELECT unnest(range(n_dst)) AS v FROM n) WHERE v NOT IN (SELECT src FROM g)")
add("components_turn_parent", lambda s, d: consumers.components(build("turn_parent")(s, d)), "WITH t AS (SELECT conv_id, row_number() OVER (ORDER BY conv_id, turn) - 1 AS id FROM (SELECT DISTINCT conv_id, turn FROM conversations)) SELECT id, min(id) OVER (PARTITION BY conv_id) AS component FROM t")
add("bfs_user_next", lambda s, d: consumers.bfs(build("user_next")(s, d), 0), f"{ctes('user_next').replace('WITH ', 'WITH RECURSIVE ', 1)}, u AS (SELECT DISTINCT src, dst FROM g), r(id, level) AS (SELECT CAST(0 AS BIGINT), CAST(0 AS BIGINT) UNION SELECT u.dst, r.level + 1 FROM r JOIN u ON r.id = u.src WHERE r.level < 6) SELECT id, min(level) AS level FROM r GROUP BY id")


def pagerank_user_next(s: SparkSession, d: str) -> DataFrame:
    g = build("user_next")(s, d)
    return consumers.pagerank(shared_transpose(g), consumers.out_degrees(g), 5).select("id", F.round("rank", 9).alias("rank"))


add("pagerank_user_next", pagerank_user_next)
add("recursive_synthetic_hybrid", lambda s, d: measures.graph_profile(workloads.recursive_synthetic(s, 10, ids=workloads.table(s, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey").select(F.xxhash64("l_orderkey", "l_partkey", "l_suppkey").alias("id")))))
add("calibrate", lambda s, d: calibrate.access_rates(s, ids=workloads.table(s, d, "orders", "o_orderkey").select(F.col("o_orderkey").alias("id"))))

# streams end in what the batch gives
add("stream_degrees", lambda s, d: stream.finish(stream.stream_degrees(stream.event_stream(s, d))), "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
add("stream_windows", lambda s, d: stream.finish(stream.windowed_degrees(stream.with_watermark(stream.event_stream(s, d))), "complete").select("event_type", F.unix_micros("begins").alias("begins"), "n"), "SELECT event_type, epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS begins, count(*) AS n FROM events GROUP BY 1, 2")
add("stream_deduplicated", lambda s, d: stream.finish(stream.deduplicated(stream.event_stream(s, d)).select("event_id"), "append"), "SELECT DISTINCT event_id FROM events")


def stream_hot(s: SparkSession, d: str) -> DataFrame:
    keep = stream.HotSet(s)
    stream.run_batches(stream.event_stream(s, d), keep.merge)
    return hotset.numbered(keep.degrees(), 16).select("dst", F.col("hot_index").cast("long").alias("hot_index"), "n")


add("stream_hot_set", stream_hot, "SELECT user_id AS dst, row_number() OVER (ORDER BY count(*) DESC, user_id) - 1 AS hot_index, count(*) AS n FROM events GROUP BY user_id ORDER BY n DESC, dst LIMIT 16")


def stream_transposed(s: SparkSession, d: str) -> DataFrame:
    parts = stream.IncrementalTransposition(s)
    stream.run_batches(stream.event_stream(s, d).select(F.col("event_id").alias("src"), F.col("user_id").alias("dst")), parts.add)
    ev = workloads.table(s, d, "events", "event_id", "user_id")
    top = ev.agg(F.max("event_id"), F.max("user_id")).first()
    return parts.compact(top[0] + 1, top[1] + 1).endpoints


add("stream_transposed", stream_transposed, "SELECT row_number() OVER (ORDER BY user_id, event_id) - 1 AS pos, event_id AS endpoint FROM events")


# measured runs: seconds differ from run to run, so there is no SQL for them
_whole = lambda s, d, g, **kw: runs.run_table(s, g, build(g)(s, d), k=K, blocks=BLOCKS, repeats=1, **kw)
add("runs_methods_cubic_skew", lambda s, d: _whole(s, d, "cubic_skew", forms=("row",)))
add("runs_representations_customer_part", lambda s, d: measures.speedup_table(_whole(s, d, "customer_part", only=("shared", "hybrid"))))
add("runs_summary_order_part", lambda s, d: measures.speedup_summary(measures.speedup_table(_whole(s, d, "order_part", forms=("row", "column")))))
add("runs_losses_order_part", lambda s, d: measures.loss_summary(measures.speedup_table(_whole(s, d, "order_part", forms=("row",)))))
add("runs_edges_per_second_cubic_skew", lambda s, d: measures.edges_per_second(_whole(s, d, "cubic_skew", forms=("row",))))
add("runs_cpu_reduction_cubic_skew", lambda s, d: runs.cpu_reduction(_whole(s, d, "cubic_skew", forms=("row",), only=("shared", "hybrid"))))
add("step_shares_cubic_skew", lambda s, d: runs.step_shares(_whole(s, d, "cubic_skew", forms=("row",), steps=True)))
add("sort_times_cubic_skew", lambda s, d: runs.sort_times(_whole(s, d, "cubic_skew", forms=("row",), steps=True)))
add("decision_time_cubic_skew", lambda s, d: decision_row(s, "cubic_skew", decide(x := build("cubic_skew")(s, d), _hot(x), blocks=BLOCKS, cost="time", probe_fraction=0.1)))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The adaptive method on the synthetic skewed graph: its endpoint array."""
    return adaptive_transpose(build("cubic_skew")(spark, sf_dir), k=K, blocks=BLOCKS)[0].endpoints

