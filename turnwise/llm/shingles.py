"""Near copies by the similarity of their five-word shingles.

Texts with the same set of shingles are one class before anything is compared. Each class has BANDS keys of ROWS minimum
hashes; two classes of similarity 0.8 share a key with probability 1 - (1 - 0.8 ** ROWS) ** BANDS, 0.99993. Classes that
share a key are held against the smallest class there first; what that doesn't join is compared pair by pair, so that a
large group of near copies costs a comparison a member. Every link is verified: the shingles themselves must reach SIMILARITY.

Edge cases: null and blank texts are one class; texts of fewer than WIDTH words are one shingle; repeated rows and ids
belong to the classes of their texts; rows with a null id are in no group; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from turnwise.llm import simhash
from turnwise.llm.common import components, map_arrow, stored, text_of

WIDTH, SIMILARITY, BANDS, ROWS = 5, 0.8, 24, 5
_RANDOM = np.random.default_rng(42).integers(0, 1 << 63, (2, BANDS * ROWS), np.uint64) * np.uint64(2) + np.uint64(1)


def shingles(text: str) -> np.ndarray:
    """Distinct hashes of the runs of WIDTH words, sorted; words as in simhash.text_fingerprint."""
    words = text.encode().lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    width, digest = min(WIDTH, len(words)), xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(b" ".join(x)) for x in zip(*(words[i:] for i in range(width)), strict=False)), np.uint64))


def set_key(s: np.ndarray) -> int:
    return int(np.array([xxhash.xxh64_intdigest(s.tobytes())], np.uint64).view(np.int64)[0])


def band_keys(s: np.ndarray) -> list[int]:
    """BANDS signed keys; none for an empty set."""
    if not len(s):
        return []
    least = None
    for k in range(0, len(s), 4096):
        h = s[k : k + 4096, None] * _RANDOM[0]
        h = ((h ^ (h >> np.uint64(31))) * _RANDOM[1]).min(axis=0)
        least = h if least is None else np.minimum(least, h)
    raw = np.array([xxhash.xxh64_intdigest(x.tobytes(), i) for i, x in enumerate(least.reshape(BANDS, ROWS))], np.uint64)
    return raw.view(np.int64).tolist()


def similarity(a: np.ndarray, b: np.ndarray) -> float:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / max(len(a) + len(b) - both, 1)


def _signed(docs: DataFrame) -> DataFrame:
    def make():
        def run(batch: pa.RecordBatch) -> pa.RecordBatch:
            sets = [shingles(x) for x in batch.column(1).to_pylist()]
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(map(set_key, sets), pa.int64()), pa.array(map(band_keys, sets), pa.list_(pa.int64()))], ["id", "key", "bands"])

        return run

    return map_arrow(docs, make, f"id {docs.schema['id'].dataType.simpleString()}, key bigint, bands array<bigint>")


def _sets(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(key, shingles) of the wanted classes (key, first), read again from the texts of their first ids."""

    def make():
        def run(batch: pa.RecordBatch) -> pa.RecordBatch:
            sets = [shingles(x) for x in batch.column(1).to_pylist()]
            return pa.RecordBatch.from_arrays([pa.array(map(set_key, sets), pa.int64()), pa.array([x.tobytes() for x in sets], pa.binary())], ["key", "shingles"])

        return run

    texts = docs.join(wanted.select(F.col("first").alias("id")).distinct(), "id", "left_semi").select("id", "text")
    return map_arrow(texts, make, "key bigint, shingles binary", rows=64).join(wanted.select("key"), "key", "left_semi").dropDuplicates(["key"])


def _verified(pairs: DataFrame, docs: DataFrame, classes: DataFrame) -> DataFrame:
    """(a, b) of the pairs of classes that reach SIMILARITY."""
    keys = pairs.select(F.col("a").alias("key")).unionByName(pairs.select(F.col("b").alias("key"))).distinct()
    sets = stored(_sets(docs, classes.join(keys, "key", "left_semi").select("key", "first")), "shingles")
    x = pairs.join(sets.select(F.col("key").alias("a"), F.col("shingles").alias("x")), "a").join(sets.select(F.col("key").alias("b"), F.col("shingles").alias("y")), "b")

    def make():
        def run(batch: pa.RecordBatch) -> pa.RecordBatch:
            x, y = (batch.column(k).to_pylist() for k in (2, 3))
            near = [similarity(np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)) >= SIMILARITY for a, b in zip(x, y, strict=True)]
            return pa.RecordBatch.from_arrays(batch.columns[:2], ["a", "b"]).filter(pa.array(near, pa.bool_()))

        return run

    return map_arrow(x.select("a", "b", "x", "y"), make, "a bigint, b bigint", rows=64)


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, component_id) of every row with an id: the smallest id reachable over links of SIMILARITY or of simhash.near_duplicates."""
    texts = docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text")).where("id IS NOT NULL")
    signed = stored(_signed(texts), "signed")
    classes = stored(signed.groupBy("key").agg(F.min("id").alias("first"), F.first("bands").alias("bands")), "classes")
    buckets = stored(classes.select("key", F.explode("bands").alias("band")), "buckets")
    least = buckets.groupBy("band").agg(F.min("key").alias("a"), F.count("*").alias("n")).where("n > 1")
    stars = stored(buckets.join(least, "band").where("key <> a").select("a", F.col("key").alias("b")).distinct(), "stars")
    links = stored(_verified(stars, texts, classes), "near")
    # copies within a few bits, by fingerprints and pivots, belong together whatever their length
    ids = signed.select("id", "key").distinct()
    close = simhash.near_duplicates(texts, "id", "text").where("id <> component_id").select("id", "component_id").distinct()
    close = close.join(ids.withColumnRenamed("key", "a"), "id").join(ids.select(F.col("id").alias("component_id"), F.col("key").alias("b")), "component_id").select("a", "b")
    links = stored(links.unionByName(close).where("a <> b").distinct(), "links")
    root = stored(_roots(links), "roots")
    # only keys that several groups share are left, and there only pairs of different groups
    owned = buckets.join(root, buckets.key == root.node, "left").select("key", "band", F.coalesce("root", "key").alias("root"))
    open_ = owned.join(owned.groupBy("band").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high").select("band"), "band", "left_semi")
    x, y = open_.alias("x"), open_.alias("y")
    more = x.join(y, (F.col("x.band") == F.col("y.band")) & (F.col("x.key") < F.col("y.key")) & (F.col("x.root") != F.col("y.root")))
    more = stored(more.select(F.col("x.key").alias("a"), F.col("y.key").alias("b")).distinct().join(stars.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")), ["a", "b"], "left_anti"), "open")
    root = stored(_roots(links.unionByName(_verified(more, texts, classes))), "roots")
    member = classes.join(root, classes.key == root.node, "left").select("key", "first", F.coalesce("root", "key").alias("root"))
    label = member.join(member.groupBy("root").agg(F.min("first").alias("component_id")), "root").select("key", "component_id")
    return signed.select("id", "key").join(label, "key").select("id", "component_id")


def _roots(links: DataFrame) -> DataFrame:
    """(node, root), roots among the nodes."""
    x = components(links)
    return x.unionByName(x.select(F.col("root").alias("node"), "root")).distinct()
