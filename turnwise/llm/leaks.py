"""Benchmark decontamination by latent semantic retrieval.

Words are hashed to FEATURES buckets, whose document frequencies are counted over all documents. The TF-IDF passages of
the benchmark span latent spaces, one for every RANK items at most, so that a space has a direction for each of its
items however many the benchmark has. A randomised SVD finds them, of which every step is a sum over partitions (a
Gaussian range finder with power rounds; orthonormal bases come from small Gram matrices). Every window of every text is
projected there. Candidates are windows whose cosine with an item reaches MIN_COSINE, windows that have SURE of the weight
which any verbatim copy puts into one window, whatever stands around it, or LIKELY of it if each of the item's words
counts no more than in the item: a paraphrase among heavier words.
Candidates are verified on the words themselves: the longest common subsequence with the item as a share of the item,
and, below SURE, the item's answer words (its rarest) found in the window. Short of both, a window is clean.

Windows have WINDOW words and overlap by half, with the words around them at hand for the check; a text is read whole.
The benchmark is taken in blocks of BLOCK items, one pass over the texts for each, so that what goes to a task has a
bound: BLOCK items, their spaces and for each space no more than FEATURES x RANK numbers.

Edge cases: null and empty texts match nothing, null or empty items match nothing; texts shorter than a window are one
window; repeated rows and repeated items are reported each; an empty benchmark or table gives an empty result; other
columns are not read.
"""

from __future__ import annotations

import re
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.llm.common import slices, table, text_of

FEATURES, RANK, OVERSAMPLE, POWER = 1 << 14, 192, 16, 1
WINDOW, BLOCK = 64, 2048
#: Halves of windows whose words are summed at a time.
NEAR = 16
MIN_COSINE, SURE, LIKELY, ANSWER_SHARE = 0.25, 0.75, 0.5, 0.6
_WORD = re.compile(r"\w+")
#: Lower case for letters, a space for all but letters, digits and _; of ASCII alone.
_PLAIN = "".join(c.lower() if _WORD.fullmatch(c) else " " for c in map(chr, range(128)))


def words_of(text: str) -> list[str]:
    """Runs of word characters in lower case; in ASCII a table finds the same ones in less time."""
    return text.translate(_PLAIN).split() if text.isascii() else _WORD.findall(text.lower())


class Buckets:
    """The bucket of each word. Nothing is remembered: a checksum takes less time than a look into a large table."""

    def of(self, words: list[str]) -> np.ndarray:
        try:
            sums = np.fromiter(map(zlib.crc32, map(str.encode, words)), np.uint32, len(words))
        except UnicodeEncodeError:
            sums = np.fromiter((zlib.crc32(w.encode("utf-8", "surrogatepass")) for w in words), np.uint32, len(words))
        return (sums % FEATURES).astype(np.int32)


@lru_cache(1)
def _worker_buckets() -> Buckets:
    """One in each Python worker, for all its tasks."""
    return Buckets()


def document_frequencies(docs: DataFrame, text_col: str = "text") -> tuple[np.ndarray, int]:
    """How many documents have each bucket, and how many documents there are."""

    def run(batches):
        buckets, df, own, rows = _worker_buckets(), np.zeros(FEATURES, np.int64), np.zeros(FEATURES, bool), 0
        for batch in slices(batches):
            for text in batch.column(0).to_pylist():
                f = buckets.of(words_of(text))
                own[f] = True
                df += own
                own[f] = False
            rows += batch.num_rows
        has = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array([*has.tolist(), -1], pa.int32()), pa.array([*df[has].tolist(), rows], pa.int64())], ["bucket", "n"])

    got = docs.select(text_of(text_col).alias("text")).mapInArrow(run, "bucket int, n bigint").groupBy("bucket").agg(F.sum("n").alias("n")).toPandas()
    df = np.zeros(FEATURES, np.int64)
    own = got[got.bucket >= 0]
    df[own.bucket] = own.n
    return df, int(got[got.bucket < 0].n.sum())


def inverse_frequencies(df: np.ndarray, n: int) -> np.ndarray:
    return np.log((n + 1) / (df + 1)).astype(np.float32) + np.float32(0.01)


def _product(passages: DataFrame, idf: np.ndarray, basis: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For A, the normalised TF-IDF rows of passages: the Gram matrix of A basis, and A' A basis, summed over partitions."""
    spark, width = passages.sparkSession, basis.shape[1]
    shared = spark.sparkContext.broadcast((idf, basis.astype(np.float32)))

    def run(batches):
        idf, basis = shared.value
        buckets, gram, back = Buckets(), np.zeros((width, width)), {}
        for batch in slices(batches):
            for text in batch.column(0).to_pylist():
                f, n = np.unique(buckets.of(words_of(text)), return_counts=True)
                if len(f) == 0:
                    continue
                a = n * idf[f]
                a /= np.linalg.norm(a)
                y = a @ basis[f]
                gram += np.outer(y, y)
                for i, x in zip(f.tolist(), a, strict=True):
                    if i in back:
                        back[i] += x * y
                    else:
                        back[i] = (x * y).astype(np.float64)
        keys = list(back)
        rows = [*(gram[i] for i in range(width)), *(back[k] for k in keys)]
        yield pa.RecordBatch.from_arrays([pa.array([*range(-width, 0), *keys], pa.int32()), pa.array([x.astype("<f8").tobytes() for x in rows], pa.binary())], ["row", "values"])

    def total(group: pa.Table) -> pa.Table:
        x = sum(np.frombuffer(v, "<f8") for v in group.column("values").to_pylist())
        return pa.table({"row": group.column("row").slice(0, 1), "values": pa.array([x.tobytes()], pa.binary())})

    got = passages.mapInArrow(run, "row int, values binary").groupBy("row").applyInArrow(total, "row int, values binary").toPandas()
    gram, back = np.zeros((width, width)), np.zeros((FEATURES, width))
    for row, values in zip(got.row, got["values"], strict=True):
        (gram if row < 0 else back)[row + width if row < 0 else row] = np.frombuffer(values, "<f8")
    return gram, back


def latent_space(passages: DataFrame, idf: np.ndarray, rank: int, seed: int = 7) -> tuple[np.ndarray, np.ndarray]:
    """(directions as columns, singular values) of the passages' TF-IDF rows: at most rank, in falling order."""
    basis = np.random.default_rng(seed).standard_normal((FEATURES, rank + OVERSAMPLE))
    basis /= np.linalg.norm(basis, axis=0)
    for _ in range(POWER):
        _, back = _product(passages, idf, basis)
        basis, _ = np.linalg.qr(back)
    gram, back = _product(passages, idf, basis)
    # A basis = Q R with R'R = gram; Q'A = R^-T (A basis)'A, whose singular vectors are those of A
    values, vectors = np.linalg.eigh(gram)
    good = values > max(values.max(initial=0) * 1e-10, 1e-12)
    whiten = vectors[:, good] / np.sqrt(values[good])
    u, s, _ = np.linalg.svd(back @ whiten, full_matrices=False)
    return u[:, :rank].astype(np.float32), s[:rank]


def common_words(a: list[str], b: list[str]) -> int:
    """Length of the longest common subsequence, bit-parallel over a."""
    at: dict[str, int] = {}
    for i, w in enumerate(a):
        at[w] = at.get(w, 0) | 1 << i
    full = (1 << len(a)) - 1
    row = full
    for w in b:
        hit = row & at.get(w, 0)
        row = (row + hit | row - hit) & full
    return len(a) - row.bit_count()


def sure_weight(own: np.ndarray) -> float:
    """The weight that some window has of each verbatim copy of an item, wherever the copy begins; own: weights of the item's words."""
    size, half = len(own), WINDOW // 2
    total = np.concatenate([[0.0], np.cumsum(own)])
    starts = np.arange(-half + 1, size)
    inside = total[np.minimum(starts + WINDOW, size)] - total[np.maximum(starts, 0)]
    best = np.zeros(half)
    np.maximum.at(best, starts % half, inside)
    return float(best.min())


class Items:
    """Items of one latent space, ready for the check of windows."""

    def __init__(self, ids: list[int], texts: list[str], used: np.ndarray, space: np.ndarray, idf: np.ndarray):
        """space: the rows of the projection that are not all zero, of the buckets used."""
        self.ids, self.words = ids, [words_of(x) for x in texts]
        buckets = Buckets()
        self.index = np.full(FEATURES, -1, np.int32)
        self.index[used] = np.arange(len(used))
        latent, sure, self.own, self.answers = [], [], [], []
        for words in self.words:
            f = buckets.of(words)
            weight = idf[f]
            count = np.bincount(f, minlength=FEATURES)
            norm = np.linalg.norm(count * idf) or 1
            at = self.index[f]
            latent.append((weight[at >= 0, None] * space[at[at >= 0]]).sum(axis=0) / norm)
            own = weight**2 * count[f] / norm
            self.own.append(own.tolist())
            sure.append(sure_weight(own) if words else np.inf)
            rare = np.argsort(-weight, kind="stable")[: max(1, len(words) // 3)]
            self.answers.append({words[i] for i in rare.tolist()})
        self.idf, self.sure, self.power = idf, SURE * np.array(sure, np.float32), idf**2
        self.likely = LIKELY * np.array(sure, np.float32)
        # what a word adds to the product of its window with each item, by way of the space
        adds = (idf[used, None] * space).astype(np.float32) @ np.array(latent, np.float32).reshape(len(ids), space.shape[1]).T
        self.adds = np.vstack([adds, np.zeros((1, len(ids)), np.float32)])

    def matches(self, words: list[str], f: np.ndarray) -> dict[int, tuple[float, float]]:
        """By item: the largest share of it in one place of the words, and the cosine there, where the check holds. f: the buckets of the words."""
        n = len(words)
        if not n or not self.ids:
            return {}
        half = WINDOW // 2
        starts = np.arange(0, n, half)
        power = np.add.reduceat(self.power[f], starts)
        # words that no item has point at the last row, which is zero; so does what fills the last half
        rows = np.full(len(starts) * half, len(self.adds) - 1, np.int32)
        rows[:n] = self.index[f]
        ones = np.ones((1, half), np.float32)
        # few halves at a time, so that their rows stay in a near cache
        few = half * NEAR
        parts = [ones @ self.adds.take(rows[a : a + few], axis=0, mode="wrap").reshape(-1, half, len(self.ids)) for a in range(0, len(rows), few)]
        weight = np.concatenate(parts)[:, 0]
        if len(starts) > 1:  # a window is two halves; fewer than one window's words are one
            weight, power = weight[:-1] + weight[1:], power[:-1] + power[1:]
        # repeated words make the true norm larger, so no cosine is too small here
        norm = np.sqrt(np.maximum(power, 1e-9))
        out: dict[int, tuple[float, float]] = {}
        enough = np.minimum(MIN_COSINE * norm[:, None], self.sure)
        for w, i in zip(*np.nonzero(weight >= np.minimum(enough, self.likely)), strict=True):
            item = self.words[i]
            if not item or weight[w, i] < enough[w, i] and not self._by_words(i, words[w * half : w * half + WINDOW]):
                continue
            # a long item reaches far beyond any one window of its copy
            margin = half + len(item) // 4 if len(item) <= 2 * WINDOW else len(item)
            near = words[max(0, w * half - margin) : w * half + WINDOW + margin]
            there = set(near)
            # no subsequence is longer than the item's words that occur at all
            if sum([x in there for x in item]) < LIKELY * len(item):
                continue
            share = common_words(item, near) / len(item)
            if share >= LIKELY and (share >= SURE or len(self.answers[i] & there) >= ANSWER_SHARE * len(self.answers[i])):
                # the true norm, by how often each bucket is in the window
                own, n_own = np.unique(f[w * half : w * half + WINDOW], return_counts=True)
                cosine = float(weight[w, i] / max(np.linalg.norm(n_own * self.idf[own]), 1e-9))
                out[int(i)] = max(out.get(int(i), (0.0, 0.0)), (share, cosine))
        return out

    def _by_words(self, i: int, words: list[str]) -> bool:
        """Whether the words have LIKELY of the weight of a copy of item i without counting any word more often than the item has it."""
        there = set(words)
        return sum([x for w, x in zip(self.words[i], self.own[i], strict=True) if w in there]) >= self.likely[i]


def find_leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """(id, item_id, share, cosine): each text that has an item or a close paraphrase of it, once for each such item."""
    spark, kind = docs.sparkSession, docs.schema[id_col].dataType.simpleString()
    texts = docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text"))
    items = benchmark.select(F.col(item_col).cast("long").alias("id"), text_of(item_text_col).alias("text"))
    schema = f"id {kind}, item_id bigint, share double, cosine double"
    idf = inverse_frequencies(*document_frequencies(texts))
    found = spark.createDataFrame([], schema)

    def search(block: list) -> DataFrame:
        parts, spaces = -(-len(block) // RANK), []
        for k in range(parts):
            part = block[k * len(block) // parts : (k + 1) * len(block) // parts]
            space, _ = latent_space(spark.createDataFrame([(r.text,) for r in part], "text string").coalesce(2), idf, len(part))
            used = np.flatnonzero(np.abs(space).max(axis=1, initial=0) > 1e-7)
            spaces.append(([r.id for r in part], [r.text for r in part], used, space[used]))
        shared = spark.sparkContext.broadcast((idf, spaces))

        def run(batches):
            (idf, spaces), buckets = shared.value, _worker_buckets()
            known = [Items(*x, idf) for x in spaces]
            for batch in slices(batches):
                out = []
                for i, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    words = words_of(text)
                    f = buckets.of(words)
                    out += [(i, x.ids[k], *y) for x in known for k, y in x.matches(words, f).items()]
                yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], batch.column(0).type), pa.array([x[1] for x in out], pa.int64()), pa.array([x[2] for x in out], pa.float64()), pa.array([x[3] for x in out], pa.float64())], ["id", "item_id", "share", "cosine"])

        return texts.mapInArrow(run, schema)

    block: list = []
    for r in items.toLocalIterator():
        block.append(r)
        if len(block) == BLOCK:
            found = found.unionByName(search(block))
            block = []
    return found.unionByName(search(block)) if block else found


def op9_benchmark_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).withColumnRenamed("id", "doc_id")
