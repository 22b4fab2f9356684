"""Token ids in binary files, packed into rows of equal length by best-fit decreasing.

Each text becomes byte-pair ids and an end id. Texts longer than a row are cut into segments that join to the same ids
again. Segments are dealt to shards by a hash of (id, place), so that neither a hot source nor one long text makes a
large shard; the number of shards follows from the bytes of all texts. A shard packs its segments by itself, longest
first, each into the row with the least room that still takes it. A segment tree over room sizes finds that row in
logarithmic time. Of each shard three files are written: ids.bin (a matrix of little-endian unsigned 16-bit ids, rows
filled up with the pad id), cu_seqlens.bin (32-bit ends of the segments of each row, from 0) and resets.bin (a bit for each
id, lowest first: set where positions start again at 0, with each segment and in the padding). position_ids() makes
the positions of a row from its bits.

Files carry a random name of their task attempt and only those named by the manifest count. Edge cases: null and empty
texts are the end id alone; ties in length go by (id, text, place); repeated rows are packed each: a hash of the text
tells rows that repeat an id apart, and rows that repeat both have equal segments; ids are of any type, nulls too; an empty
table gives no shard; columns but id and text, whatever their names, are not read.
"""

from __future__ import annotations

import base64
import hashlib
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.llm.common import new_path, slices, table, text_of
from turnwise.llm.warc import files_at

ROW = 2048
SHARD_BYTES = 8 << 20
END = 50256


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def tokenizer(path: str):
    """Ids of a text by the ranks in the file; nothing is special."""
    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f)}
    return tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary


class RoomTree:
    """Open rows by the room they have left: a segment tree of counts over room sizes 0 to size."""

    def __init__(self, size: int):
        self.leaves = 1 << size.bit_length()
        self.count = [0] * (2 * self.leaves)
        self.rows: list[list[int]] = [[] for _ in range(size + 1)]

    def _add(self, room: int, n: int) -> None:
        i = self.leaves + room
        while i:
            self.count[i] += n
            i >>= 1

    def put(self, room: int, row: int) -> None:
        self.rows[room].append(row)
        self._add(room, 1)

    def take(self, need: int) -> tuple[int, int] | None:
        """(room, row) of the row with the least room that is need or more; it leaves the tree."""
        i = self.leaves + need
        if not self.count[i]:
            while i > 1 and (i & 1 or not self.count[i + 1]):
                i >>= 1
            if i <= 1:
                return None
            i += 1
            while i < self.leaves:
                i = 2 * i + (not self.count[2 * i])
        room = i - self.leaves
        self._add(room, -1)
        return room, self.rows[room].pop()


def best_fit_decreasing(lengths: np.ndarray, size: int) -> list[list[int]]:
    """Rows of indexes into lengths, each at most size in sum; lengths are tried in falling order, equal ones as they come."""
    tree, rows = RoomTree(size), []
    for i in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[i])
        found = tree.take(n)
        if found is None:
            rows.append([i])
            room, row = size, len(rows) - 1
        else:
            room, row = found
            rows[row].append(i)
        tree.put(room - n, row)
    return rows


def segments(docs: DataFrame, shards: int, path: str, id_col: str = "doc_id", text_col: str = "text", size: int = ROW) -> DataFrame:
    """(id, text_key, start, ids, shard): the ids of each text, cut at every size of them."""

    def run(batches):
        encode = tokenizer(path)
        for batch in slices(batches, 256):
            ids, keys, starts, parts = [], [], [], []
            for i, text, key in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                got = np.array([*encode(text), END], "<u2")
                for at in range(0, len(got), size):
                    ids.append(i)
                    keys.append(key)
                    starts.append(at)
                    parts.append(got[at : at + size].tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(ids, batch.column(0).type), pa.array(keys, pa.int64()), pa.array(starts, pa.int64()), pa.array(parts, pa.binary())], ["id", "text_key", "start", "ids"])

    text = text_of(text_col)
    kind = docs.schema[id_col].dataType.simpleString()
    x = docs.select(F.col(id_col).alias("id"), text.alias("text"), F.xxhash64(text).alias("text_key")).mapInArrow(run, f"id {kind}, text_key bigint, start bigint, ids binary")
    return x.withColumn("shard", F.pmod(F.xxhash64("id", "text_key", "start"), F.lit(shards)).cast("int"))


_ROWS = "shard int, row int, n_tokens int, doc_ids array<{}>, text_keys array<bigint>, starts array<bigint>, cu_seqlens array<int>, ids_sha256 string, file string"


def pack(docs: DataFrame, folder: str, path: str | None = None, id_col: str = "doc_id", text_col: str = "text", size: int = ROW) -> DataFrame:
    """The manifest: one row for each packed row, with its segments and the files' common name below folder."""
    total = docs.agg(F.sum(F.octet_length(text_of(text_col)))).first()[0] or 0
    shards = max(1, -(-total // SHARD_BYTES))
    parts = segments(docs, shards, path or default_vocabulary(), id_col, text_col, size)

    def write(group: pa.Table) -> pa.Table:
        group = group.sort_by([("id", "ascending"), ("text_key", "ascending"), ("start", "ascending")])
        shard = group.column("shard")[0].as_py()
        ids = [np.frombuffer(x, "<u2") for x in group.column("ids").to_pylist()]
        doc, key, start = (group.column(c).to_pylist() for c in ("id", "text_key", "start"))
        rows = best_fit_decreasing(np.array([len(x) for x in ids]), size)
        matrix, resets = np.full((len(rows), size), END, "<u2"), np.zeros((len(rows), size), bool)
        out, ends = [], []
        name = f"shard-{shard:06d}-{uuid.uuid4().hex}"
        for r, members in enumerate(rows):
            at, cut = 0, [0]
            for m in members:
                n = len(ids[m])
                matrix[r, at : at + n] = ids[m]
                resets[r, at] = True
                at += n
                cut.append(at)
            resets[r, at : at + 1] = True
            ends.append(np.array(cut, "<i4"))
            out.append((shard, r, at, [doc[m] for m in members], [key[m] for m in members], [start[m] for m in members], cut, hashlib.sha256(matrix[r, :at].tobytes()).hexdigest(), name))
        store, base = files_at(folder)
        store.create_dir(base, recursive=True)
        for what, data in (("ids", matrix), ("cu_seqlens", np.concatenate(ends)), ("resets", np.packbits(resets, axis=1, bitorder="little"))):
            with store.open_output_stream(f"{base}/{name}.{what}.bin", compression=None) as f:
                f.write(data.tobytes())
        kinds = (pa.int32(), pa.int32(), pa.int32(), pa.list_(group.schema.field("id").type), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.string(), pa.string())
        return pa.table([pa.array([x[i] for x in out], t) for i, t in enumerate(kinds)], names=[x.split(" ")[0] for x in _ROWS.split(", ")])

    # as many partitions as shards, so that none waits for another
    parts = parts.repartition(min(shards, 100_000), "shard")
    return parts.groupBy("shard").applyInArrow(write, _ROWS.format(docs.schema[id_col].dataType.simpleString()))


def position_ids(resets: np.ndarray) -> np.ndarray:
    """Positions of a row that start again at each set bit."""
    at = np.arange(len(resets))
    return at - np.maximum.accumulate(np.where(resets, at, 0))


def read_shard(folder: str, name: str, size: int = ROW) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """Ids and reset bits by row, and the cumulative lengths of each row, from a shard's files."""
    store, base = files_at(folder)
    load = lambda what, kind: np.frombuffer(store.open_input_file(f"{base}/{name}.{what}.bin").read(), kind)
    ends, ids = load("cu_seqlens", "<i4"), load("ids", "<u2").reshape(-1, size)
    bits = np.unpackbits(load("resets", np.uint8).reshape(len(ids), -1), axis=1, bitorder="little")[:, :size].astype(bool)
    return ids, bits, np.split(ends, np.flatnonzero(ends == 0)[1:])


def op4_packed_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), new_path(spark, "packed")).drop("file")
