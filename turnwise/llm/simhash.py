"""SimHash near-duplicates by pivot distance tables.

fingerprints() gives each text a 64-bit majority vote over its 3-word shingles. Equal fingerprints collapse into one row
before anything is compared, so a group of thousands of copies costs one comparison. Each remaining fingerprint gets a
pivot table: its Hamming distances to PIVOTS reference fingerprints. By the triangle inequality two fingerprints within
r bits differ by at most r in every coordinate of that table, so a pair with a larger difference in one coordinate is
discarded before its distance is computed. Pairs meet in exact bands: the 64 bits are cut into r + 2 blocks, r differing
bits leave at least two blocks untouched, and the value of every two blocks is one equi-join key of 32 bits (for r = 2).
No pair within r bits is missed and no band is capped.

Edge cases: null and blank texts have fingerprint 0 and link like any other; texts of one or two words use the whole
sequence as one shingle; repeated rows keep their own output row; an empty table gives an empty result; other columns of
the input, whatever their names, are not read.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.llm.common import components, map_arrow, stored, table, text_of

SEED = 42
RADIUS = 2
PIVOTS = 16


def text_fingerprint(text: str, width: int = 3, seed: int = SEED) -> int:
    """The fingerprint of one text, unsigned; bytes.lower() and bytes.split() touch exactly A-Z and the six spaces."""
    words = text.encode().lower().split()
    if not words:
        return 0
    width = min(width, len(words))
    digest = xxhash.xxh64_intdigest
    votes = None
    n = len(words) - width + 1
    for start in range(0, n, 65536):  # bounded memory for very long texts
        part = words[start : min(start + 65536, n) + width - 1]
        h = np.fromiter((digest(b" ".join(x), seed) for x in zip(*(part[i:] for i in range(width)), strict=False)), np.uint64)
        ones = _ones(h)
        votes = ones if votes is None else votes + ones
    return int((np.uint64(1) << np.arange(64, dtype=np.uint64))[votes * 2 > n].sum(dtype=np.uint64)) if (votes * 2 > n).any() else 0


def _ones(h: np.ndarray) -> np.ndarray:
    """How many of the hashes have each bit, lowest bit first."""
    bits = np.unpackbits(h.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return bits.sum(axis=0, dtype=np.int64)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3) -> DataFrame:
    """(id, fp): the signed 64-bit fingerprint of each row."""
    kind = docs.schema[id_col].dataType.simpleString()

    def make():
        def run(batch: pa.RecordBatch) -> pa.RecordBatch:
            fps = np.array([text_fingerprint(x, width) for x in batch.column(1).to_pylist()], np.uint64).view(np.int64)
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps, pa.int64())], ["id", "fp"])

        return run

    return map_arrow(docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text")), make, f"id {kind}, fp bigint")


def pivots(n: int = PIVOTS) -> list[int]:
    """Reference fingerprints: hashes of their own numbers, as signed longs."""
    return [int(x) for x in np.array([xxhash.xxh64_intdigest(f"pivot {i}", SEED) for i in range(n)], np.uint64).view(np.int64)]


def pivot_table(fp: Column, n: int = PIVOTS) -> list[Column]:
    return [F.bit_count(fp.bitwiseXOR(F.lit(p))).cast("byte").alias(f"p{i}") for i, p in enumerate(pivots(n))]


def bands(fp: Column, radius: int = RADIUS) -> Column:
    """Keys of which two fingerprints within radius share one at least: every two of radius + 2 blocks, with their number."""
    blocks = radius + 2
    cuts = [64 * i // blocks for i in range(blocks + 1)]
    masks = [((1 << b) - (1 << a)) for a, b in zip(cuts, cuts[1:], strict=False)]
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    keys = [F.struct(F.lit(k).cast("byte").alias("band"), fp.bitwiseAND(F.lit(signed(masks[i] | masks[j]))).alias("value")) for k, (i, j) in enumerate(combinations(range(blocks), 2))]
    return F.explode(F.array(*keys))


def fingerprint_links(fps: DataFrame, radius: int = RADIUS, n_pivots: int = PIVOTS) -> DataFrame:
    """(a, b), a < b: all pairs of distinct fingerprints within radius, each once.

    fps has one column fp of distinct longs. A pair that shares several bands is taken in its first shared one only.
    """
    side = fps.select("fp", *pivot_table(F.col("fp"), n_pivots), bands(F.col("fp"), radius).alias("k")).select("fp", *[f"p{i}" for i in range(n_pivots)], "k.band", "k.value")
    x, y = side.alias("x"), side.alias("y")
    near = F.greatest(*[F.abs(F.col(f"x.p{i}") - F.col(f"y.p{i}")) for i in range(n_pivots)]) <= radius
    pairs = x.join(y, (F.col("x.band") == F.col("y.band")) & (F.col("x.value") == F.col("y.value")) & (F.col("x.fp") < F.col("y.fp")) & near & (F.bit_count(F.col("x.fp").bitwiseXOR(F.col("y.fp"))) <= radius))
    return pairs.select(F.col("x.fp").alias("a"), F.col("y.fp").alias("b")).distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, radius: int = RADIUS) -> DataFrame:
    """(id, fp, component_id): one row per input row; component_id is the smallest id reachable over links of radius bits.

    Copies are never expanded into pairs: ids meet fingerprints again only through (fp -> component) rows.
    """
    fps = stored(fingerprints(docs, id_col, text_col, width), "fingerprints")
    firsts = stored(fps.groupBy("fp").agg(F.min("id").alias("first")), "classes")
    links = fingerprint_links(firsts.select("fp"), radius)
    roots = components(links)
    # classes that reach others: the smallest id of their component; all others keep their own
    linked = firsts.join(roots, firsts.fp == roots.node).select("fp", "root", "first")
    own = linked.groupBy("root").agg(F.min("first").alias("component_id"))
    root_first = firsts.join(own, firsts.fp == own.root).select("root", F.least("first", "component_id").alias("component_id"))
    moved = linked.select("fp", "root").unionByName(root_first.select(F.col("root").alias("fp"), "root")).join(root_first, "root").select("fp", "component_id")
    moved = stored(moved, "moved")
    label = firsts.join(moved, "fp", "left").select("fp", F.coalesce("component_id", "first").alias("component_id"))
    return fps.join(stored(label, "labels"), "fp").select("id", "fp", "component_id")


def op10_simhash_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, fingerprint, component_id for every row of documents."""
    out = near_duplicates(table(spark, sf_dir, "documents"))
    return out.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
