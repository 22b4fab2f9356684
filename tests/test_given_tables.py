"""Queries that read a given table, held against their SQL, and word pairs that are counted before they are edges."""

import duckdb
import pytest

from turnwise import queries

TABLES = ("part", "lineitem", "orders", "documents")


def plain(sql, sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con.execute(sql).fetchall()


@pytest.mark.parametrize("name", ["break_even", "model_curve", "hot_capacity_grid", "shuffle_rows_word_successor", "t_adaptive_endpoints_word_successor", "profile_word_successor"])
def test_as_sql(spark, name):
    sf = "/root/testdata/sf0.001"
    assert sorted(map(tuple, queries.QUERIES[name](spark, sf).collect())) == sorted(plain(queries.ORACLES[name], sf))


def test_synthetic_edges_are_rows(spark):
    sf = "/root/testdata/sf0.001"
    n = spark.read.parquet(f"{sf}/lineitem.parquet").count()
    assert queries.QUERIES["recursive_synthetic_hybrid"](spark, sf).first().edges == n


def test_rates_are_of_given_keys(spark, monkeypatch):
    """The keys come from the orders; no numbers are made up for them."""
    from turnwise.plans import calibrate

    seen = []
    monkeypatch.setattr(calibrate, "noop", lambda df: seen.append(df.inputFiles()))
    assert queries.QUERIES["calibrate"](spark, "/root/testdata/sf0.001").count() == 6
    assert seen and all(any("orders" in f for f in files) for files in seen)


def test_rates_are_of_whole_domains(spark, monkeypatch):
    """Each order is a key of its own in a domain of a million, and every key is in the table that reads look into."""
    from pyspark.sql import functions as F

    from turnwise.plans import calibrate

    seen = []
    monkeypatch.setattr(calibrate, "_seconds", lambda job: job() or 1.0)
    monkeypatch.setattr(calibrate, "noop", lambda df: seen.append(df))
    queries.QUERIES["calibrate"](spark, "/root/testdata/sf0.001")
    n = spark.read.parquet("/root/testdata/sf0.001/orders.parquet").count()
    reads = [x.agg(F.count("*"), F.count("v"), F.countDistinct("key"), F.max("key")).first() for x in seen if "v" in x.columns]
    assert [x[:2] for x in reads] == [(n, n)] * 2
    assert reads[0][3] < 1_000 and reads[1][2] > 0.99 * n and reads[1][3] > 900_000


def test_pairs_are_counted_before_they_are_edges(spark):
    """Equal pairs are one row before anything is exchanged, and no window over the words of a text needs them sorted."""
    from turnwise.sources import workloads

    g = workloads.word_successor(spark, "/root/testdata/sf0.001")
    plan = g.edges._jdf.queryExecution().optimizedPlan().toString()
    assert "lead(" not in plan and "Aggregate [word" in plan
