"""Toxicity: a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

A text is the set of its hashed character n-grams (4 to 6, lower case, white space as one space). Training takes two
passes over a sample of labelled rows, at most max_rows of them in the order of a hash of the id: the first counts for
each bucket the toxic and other rows that have it, from which come the log-count ratios and the selected buckets; the
second brings the selected buckets of each row to the driver, where logistic regression is fitted on the presence of
each bucket times its ratio. Driver memory is bounded by max_rows and features, not by the corpus. Scoring reads every
text whole and looks each distinct n-gram up once.

Edge cases: null and empty texts have no n-gram and score by the intercept; labels that are null or whose document is
missing are not trained on; without both classes among the labels every score is the share of toxic labels (0.5 without
any); repeated rows score alike; columns other than id and text are not read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.llm.common import dropped, map_arrow, slices, stored, table, text_of

SIZES = (4, 5, 6)
BUCKETS = 1 << 18
MAX_ROWS = 20_000
FEATURES = 2_048
_BLANK = re.compile(r"\s+")


def buckets_of(text: str, seen: np.ndarray) -> np.ndarray:
    """The distinct buckets of a text. seen: scratch space of BUCKETS ints, which may hold anything."""
    text = f" {_BLANK.sub(' ', text.lower()).strip()} "
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    found = []
    for start in range(0, len(codes), 1 << 20):  # very long texts piece by piece, overlapping
        part = codes[start : start + (1 << 20) + max(SIZES) - 1]
        h = np.zeros(len(part), np.uint32)
        for n in range(1, max(SIZES) + 1):
            if len(part) < n:
                break
            h = h[: len(part) - n + 1] * np.uint32(0x01000193) + part[n - 1 :] * np.uint32(0x9E3779B1) + np.uint32(n)
            if n in SIZES:
                x = h ^ (h >> np.uint32(15))
                x = (x * np.uint32(0x85EBCA6B)) >> np.uint32(14)
                found.append(x)
    if not found:
        return np.zeros(0, np.uint32)
    x = np.concatenate(found)
    order = np.arange(len(x), dtype=np.int32)
    seen[x] = order
    return x[seen[x] == order]


@dataclass
class Classifier:
    weights: np.ndarray  # by bucket, float32; 0 for what wasn't selected
    intercept: float

    def score(self, text: str, seen: np.ndarray) -> float:
        z = self.intercept + float(self.weights[buckets_of(text, seen)].sum(dtype=np.float64))
        return float(1 / (1 + np.exp(-np.clip(z, -40, 40))))


def sample(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, label_col: str, max_rows: int) -> DataFrame:
    """(id, text, y) of at most max_rows labelled rows; the ids are few enough to go to every executor."""
    some = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.max(label_col).cast("int").alias("y"))
    some = some.orderBy(F.xxhash64("id"), "id").limit(max_rows)
    return docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text")).join(F.broadcast(some), "id")


def _counts(rows: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """For each bucket, how many rows with y = 1 and y = 0 have it."""

    def run(batches):
        seen, n = np.zeros(BUCKETS, np.int32), np.zeros((2, BUCKETS), np.int32)
        for batch in batches:
            for text, y in zip(batch.column("text").to_pylist(), batch.column("y").to_pylist(), strict=True):
                n[y, buckets_of(text, seen)] += 1
        has = np.flatnonzero(n.any(axis=0))
        yield pa.RecordBatch.from_arrays([pa.array(has.astype(np.int32)), pa.array(n[1, has].astype(np.int64)), pa.array(n[0, has].astype(np.int64))], ["bucket", "toxic", "other"])

    got = rows.select("text", "y").mapInArrow(run, "bucket int, toxic bigint, other bigint").groupBy("bucket").agg(F.sum("toxic").alias("toxic"), F.sum("other").alias("other")).toPandas()
    p, q = np.zeros(BUCKETS), np.zeros(BUCKETS)
    p[got.bucket], q[got.bucket] = got.toxic, got.other
    return p, q


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", max_rows: int = MAX_ROWS, features: int = FEATURES) -> Classifier:
    """Train on at most max_rows labelled rows with at most features buckets, those whose counts tell the classes apart most."""
    rows = stored(sample(docs, labels, id_col, text_col, label_col, max_rows), "toxicity")
    size = rows.groupBy("y").count().collect()
    n = {r["y"]: r["count"] for r in size}
    if len(n) < 2:
        dropped(rows)
        share = np.clip(n.get(1, 0) / sum(n.values()), 1e-3, 1 - 1e-3) if n else 0.5
        return Classifier(np.zeros(BUCKETS, np.float32), float(np.log(share / (1 - share))))
    p, q = _counts(rows)
    # log-count ratio of the smoothed shares, and how far the counts are from what the classes' sizes would give
    ratio = np.log((p + 1) / (p + 1).sum()) - np.log((q + 1) / (q + 1).sum())
    expected = (p + q) * n[1] / (n[0] + n[1])
    gain = np.where(p + q > 1, (p - expected) ** 2 / (expected + 1), 0)
    chosen = np.sort(np.argsort(-gain, kind="stable")[:features])
    chosen = chosen[gain[chosen] > 0]
    index = np.full(BUCKETS, -1, np.int32)
    index[chosen] = np.arange(len(chosen))

    def pick(batches):
        seen = np.zeros(BUCKETS, np.int32)
        for batch in batches:
            got = [index[buckets_of(t, seen)] for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("y"), pa.array([np.sort(x[x >= 0]).astype("<i4").tobytes() for x in got], pa.binary())], ["y", "has"])

    got = rows.select("text", "y").mapInArrow(pick, "y int, has binary").toPandas()
    dropped(rows)
    has = [np.frombuffer(x, "<i4") for x in got.has]
    w, b = _logistic(has, got.y.to_numpy(np.float64), ratio[chosen])
    weights = np.zeros(BUCKETS, np.float32)
    weights[chosen] = w * ratio[chosen]
    return Classifier(weights, b)


def _logistic(has: list[np.ndarray], y: np.ndarray, scale: np.ndarray, penalty: float = 1e-2, rounds: int = 300) -> tuple[np.ndarray, float]:
    """Weights and intercept of L2-regularised logistic regression, classes weighed equally, by Nesterov's gradient steps."""
    n, row = len(y), np.repeat(np.arange(len(has)), [len(x) for x in has])
    col = np.concatenate(has) if has else np.zeros(0, np.int32)
    x = scale[col]
    balance = np.where(y == 1, 0.5 / max(y.sum(), 1), 0.5 / max(n - y.sum(), 1))
    norm = np.bincount(row, x * x, n)
    step = 1 / (0.25 * max(np.percentile(norm, 99), 1) + penalty)
    w = was = np.zeros(len(scale))
    b = b_was = 0.0
    for k in range(rounds):
        m = k / (k + 3)
        v, c = w + m * (w - was), b + m * (b - b_was)
        z = np.bincount(row, x * v[col], n) + c
        e = balance * (1 / (1 + np.exp(-np.clip(z, -40, 40))) - y)
        was, b_was = w, b
        w = v - step * 4 * (np.bincount(col, x * e[row], len(scale)) + penalty * v)
        b = c - step * 4 * e.sum()
    return w, float(b)


def score(docs: DataFrame, model: Classifier, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score) of every row."""
    kind = docs.schema[id_col].dataType.simpleString()

    def make():
        seen = np.zeros(BUCKETS, np.int32)

        def run(batch: pa.RecordBatch) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array([model.score(x, seen) for x in batch.column(1).to_pylist()], pa.float64())], ["id", "score"])

        return run

    return map_arrow(docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text")), make, f"id {kind}, score double")


def keep_clean(docs: DataFrame, model: Classifier, text_col: str = "text", limit: float = 0.5) -> DataFrame:
    """The rows of docs whose score is below limit, with all their columns; nothing is shuffled."""
    place = docs.columns.index(text_col)

    def run(batches):
        seen = np.zeros(BUCKETS, np.int32)
        for batch in slices(batches):
            yield batch.filter(pa.array([model.score(x or "", seen) < limit for x in batch.column(place).to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def held_out(id_col: str = "doc_id"):
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 5 == 0


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trained without the held-out fold; scores all documents."""
    docs = table(spark, sf_dir, "documents")
    model = fit(docs, table(spark, sf_dir, "labels").where(~held_out()))
    out = score(docs, model)
    return out.select(F.col("id").alias("doc_id"), held_out("id").alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))
