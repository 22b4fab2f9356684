import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from turnwise.llm import toxicity as t


def corpus(n=400, seed=5):
    r = random.Random(seed)
    words = ["".join(r.choice("aeioulmnrstdp") for _ in range(r.randrange(2, 8))) for _ in range(200)]
    rows, labels = [], []
    for i in range(n):
        toxic = i % 4 == 0
        text = [r.choice(words) for _ in range(r.randrange(5, 60))]
        if toxic:
            text.insert(r.randrange(len(text)), r.choice(("scumbag", "moronic", "worthless idiot")))
        rows.append((i, " ".join(text)))
        labels.append((i, int(toxic)))
    return rows, labels


def test_held_out_rows_are_told_apart(spark):
    rows, labels = corpus()
    docs, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    model = t.fit(docs, marks.where(~t.held_out()))
    held = {r.doc_id for r in docs.where(t.held_out()).collect()}
    got = {r.id: r.score for r in t.score(docs, model).collect()}
    assert len(got) == len(rows) and all(0 <= x <= 1 for x in got.values()) and 40 < len(held) < 120
    right = sum((got[i] >= 0.5) == bool(y) for i, y in labels if i in held)
    assert right >= 0.95 * len(held)


def test_scores_equal_the_sum_of_weights_by_brute_force(spark):
    """Log-count ratios and scores by sets of n-grams written out, hashed one by one."""
    rows, labels = corpus(60)
    docs, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    model = t.fit(docs, marks)
    seen = np.zeros(t.BUCKETS, np.int32)

    def grams(text):
        text = f" {' '.join(text.lower().split())} "
        out = set()
        for n in t.SIZES:
            for k in range(len(text) - n + 1):
                h = 0
                for m, c in enumerate(text[k : k + n], 1):
                    h = (h * 0x01000193 + ord(c) * 0x9E3779B1 + m) & 0xFFFFFFFF
                h ^= h >> 15
                out.add(((h * 0x85EBCA6B) & 0xFFFFFFFF) >> 14)
        return out

    for _, text in rows[:20] + [(0, "Ünï çødé 中文 text"), (0, ""), (0, "ab")]:
        assert set(t.buckets_of(text, seen).tolist()) == grams(text)
        z = model.intercept + sum(float(model.weights[b]) for b in grams(text))
        assert model.score(text, seen) == pytest.approx(1 / (1 + np.exp(-z)), abs=1e-6)


def test_odd_rows_and_columns(spark):
    rows, labels = corpus(80)
    docs = spark.createDataFrame([*rows, (None, "scumbag"), (900, None), (901, ""), (902, "x" * 2_000_000), (902, "again")], "doc_id long, text string").withColumns({"score": F.lit("s"), "id": F.lit(1), "y": F.lit(2)})
    marks = spark.createDataFrame([*labels, (None, 1), (900, None), (5000, 1), (3, 7)], "doc_id long, toxic int")
    model = t.fit(docs, marks.where(~t.held_out()))
    got = t.score(docs, model).collect()
    assert len(got) == 85 and all(0 <= r.score <= 1 for r in got)
    kept = t.keep_clean(docs, model)
    assert kept.columns == docs.columns and kept.where("doc_id IN (900, 901)").count() == 2


@pytest.mark.parametrize("marks, want", [([], 0.5), ([(1, 1), (2, 1)], 0.999), ([(1, 0)], 0.001)])
def test_without_both_classes(spark, marks, want):
    docs = spark.createDataFrame([(1, "a"), (2, "b")], "doc_id long, text string")
    model = t.fit(docs, spark.createDataFrame(marks, "doc_id long, toxic int"))
    assert {round(r.score, 6) for r in t.score(docs, model).collect()} == {want}


def test_empty_table(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert t.score(docs, t.fit(docs, spark.createDataFrame([], "doc_id long, toxic int"))).count() == 0
