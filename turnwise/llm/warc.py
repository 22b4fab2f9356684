"""WARC archives and a two-level capture index over them.

write_archives() turns pages into gzip members, one per record, in archive files of the shared folder; of records with
equal payloads all but one are revisits. build_index() sorts the captures by reversed-host URL key, cuts them into
blocks of BLOCK_LINES lines, compresses each block by itself and keeps one directory row per block: its first capture
and where it lies. The directory of an index file lies beside it; what all tasks have is one row for each index file.
find_captures() takes captures by URL and page: a binary search names the index file, another in that file's directory
the block, which alone is read by its byte range, and a third finds the lines. read_records() then reads the byte range
of each record. CaptureIndex does the same for single keys and prefixes.

Files are named by task attempt and only those that a finished task reports are used, so a lost executor leaves at most
files that nothing refers to. A very frequent payload or host is no hot group: digests are combined before the shuffle,
frequent ones are joined apart, and index ranges are cut by (key, page_id), not by key.

Edge cases: a null html is an empty payload; null URLs have the key "-"; repeated page ids keep a record each; pages
without an id have a record of their own, always a response and never referred to; an empty table writes an index without
blocks; payloads of any length are written whole; other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from urllib.parse import urlsplit

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.llm.common import new_path, stored, table

BLOCK_LINES = 512
#: Digests with this share of all records or more are joined apart; there can't be more than its inverse.
FREQUENT = 1 / 500
#: Stands for a missing page id in the order of captures, before all others.
NO_ID = -(1 << 63) - 1
#: Fixed values of the record format.
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def files_at(uri: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(uri)


def url_key(url: str | None) -> str:
    """Reversed host, then ")" and the rest in lower case: pages of a site and its subdomains sort together."""
    try:
        x = urlsplit((url or "").strip())
        host = (x.hostname or "").lower()
        port = f":{x.port}" if x.port else ""
    except ValueError:
        return "-"
    if not host:
        return "-"
    if host.startswith("www."):
        host = host[4:]
    key = ",".join(reversed(host.split("."))) + port + ")" + (x.path or "/") + (f"?{x.query}" if x.query else "")
    return key.lower().replace("\n", "%0a").replace("\t", "%09").replace(" ", "%20")


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One WARC 1.1 record as a gzip member; a revisit has no block, as its payload is that of the record it refers to."""
    kind, body = ("response", payload) if refers_to is None else ("revisit", b"")
    head = [
        "WARC/1.1",
        f"WARC-Type: {kind}",
        f"WARC-Record-ID: <urn:page:{page_id}>",
        f"WARC-Target-URI: {url}",
        f"WARC-Date: {DATE}",
        f"WARC-Payload-Digest: sha1:{digest}",
        *([] if refers_to is None else [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: <urn:page:{refers_to}>", f"X-Payload-Length: {len(payload)}"]),
        "Content-Type: text/html; charset=utf-8",
        f"Content-Length: {len(body)}",
    ]
    z = zlib.compressobj(6, zlib.DEFLATED, 31)
    return z.compress("\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n") + z.flush()


def parse(member: bytes) -> tuple[dict[str, str], bytes]:
    """Headers in lower case and the block of a record; what doesn't fit its length is an error."""
    raw = zlib.decompress(member, 31)
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("no WARC record")
    fields = dict((k.lower(), v) for k, _, v in (x.partition(": ") for x in lines[1:]))
    n = int(fields["content-length"])
    if rest[n:] != b"\r\n\r\n":
        raise ValueError("the record's length is wrong")
    return fields, rest[:n]


def with_referrals(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", least: int = 0) -> DataFrame:
    """(page_id, url, html, digest, refers_to): the largest id of each payload of least bytes or more is the response.

    Only (digest, id) is shuffled for that, as maxima per task; the payloads stay where they are.
    """
    payload = F.coalesce(F.col(html_col).cast("string"), F.lit("")).cast("binary")
    pages = pages.select(F.col(id_col).alias("page_id"), F.coalesce(F.regexp_replace(F.col(url_col).cast("string"), r"[\r\n]", ""), F.lit("")).alias("url"), payload.alias("payload"))
    keyed = pages.withColumn("hex", F.unhex(F.sha1("payload")))
    groups = keyed.where(F.length("payload") >= least).groupBy("hex").agg(F.max("page_id").alias("first"), F.count("*").alias("n")).where("n > 1 AND first IS NOT NULL")
    groups = stored(groups, "payloads")
    # the frequent few go to every task, whose number has a bound; the others meet their rows in a shuffle of ids
    total = pages.count()
    often = groups.where(F.col("n") >= max(2, int(FREQUENT * total)))
    rare = groups.where(F.col("n") < max(2, int(FREQUENT * total)))
    x = keyed.join(F.broadcast(often.select("hex", F.col("first").alias("often"))), "hex", "left")
    ids = x.where(F.col("often").isNull()).select("hex", "page_id").join(rare, "hex").where("page_id <> first").select("hex", "page_id", F.col("first").alias("rare")).distinct()
    out = x.join(ids, ["hex", "page_id"], "left").withColumn("first", F.coalesce("often", "rare"))
    return out.select("page_id", "url", "payload", F.when(F.col("first") != F.col("page_id"), F.col("first")).alias("refers_to"))


_CAPTURE = "key string, page_id bigint, file string, at bigint, length bigint, digest string, kind string"


def write_archives(pages: DataFrame, folder: str) -> DataFrame:
    """Captures (key, page_id, file, at, length, digest, kind) of the records written below folder, one file per task."""

    def run(batches: Iterator[pa.RecordBatch]):
        store, base = files_at(folder)
        name, out, at = f"pages-{uuid.uuid4().hex}.warc.gz", None, 0
        for batch in batches:
            rows = []
            for start in range(0, batch.num_rows, 256):
                part = batch.slice(start, 256)
                for page_id, url, payload, refers_to in zip(*(part.column(i).to_pylist() for i in range(4)), strict=True):
                    if out is None:
                        store.create_dir(base, recursive=True)
                        out = store.open_output_stream(f"{base}/{name}", compression=None)
                    digest = payload_digest(payload)
                    member = record(page_id, url, payload, digest, refers_to)
                    out.write(member)
                    rows.append((url_key(url), page_id, name, at, len(member), digest, "response" if refers_to is None else "revisit"))
                    at += len(member)
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()))], ["key", "page_id", "file", "at", "length", "digest", "kind"])
        if out is not None:
            out.close()

    return stored(pages.select("page_id", "url", "payload", "refers_to").mapInArrow(run, _CAPTURE), "captures")


def _line(r: tuple) -> str:
    return "\t".join(map(str, r))


def build_index(captures: DataFrame, folder: str, parts: int | None = None) -> DataFrame:
    """The block directory (first, last, file, at, length, lines), one row per compressed block of the sorted captures."""
    fields = ["key", "page_id", "file", "at", "length", "digest", "kind"]
    parts = parts or max(1, int(captures.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def run(batches):
        store, base = files_at(folder)
        name, out, at, block = f"index-{uuid.uuid4().hex}.cdx.gz", None, 0, []

        def flush():
            nonlocal out, at
            if out is None:
                store.create_dir(base, recursive=True)
                out = store.open_output_stream(f"{base}/{name}", compression=None)
            z = zlib.compressobj(6, zlib.DEFLATED, 31)
            data = z.compress("\n".join(map(_line, block)).encode()) + z.flush()
            out.write(data)
            made.append((block[0][0], block[0][1], block[-1][0], block[-1][1], name, at, len(data), len(block)))
            at += len(data)
            block.clear()

        made: list[tuple] = []
        for batch in batches:
            for r in zip(*(batch.column(i).to_pylist() for i in range(len(fields))), strict=True):
                block.append(r)
                if len(block) == BLOCK_LINES:
                    flush()
            yield _directory([])
        if block:
            flush()
        if out is not None:
            out.close()
            with store.open_output_stream(f"{base}/{name}.directory", compression=None) as f:
                f.write(zlib.compress("\n".join(map(_line, made)).encode()))
        yield _directory(made)

    ranged = captures.select(*fields).repartitionByRange(parts, "key", "page_id").sortWithinPartitions("key", "page_id")
    return stored(ranged.mapInArrow(run, _DIRECTORY), "directory")


_DIRECTORY = "first string, first_id bigint, last string, last_id bigint, file string, at bigint, length bigint, lines bigint"


def _directory(made: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.string(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in made], t) for i, t in enumerate(kinds)], [x.split(" ")[0] for x in _DIRECTORY.split(", ")])


def _ordered(key: str, page_id: int | str | None) -> tuple[str, int]:
    """Captures in the order of the index: keys by their code points, which UTF-8 keeps, then ids, none first."""
    return key, NO_ID if page_id in (None, "None") else int(page_id)


def read_block(store: fs.FileSystem, base: str, file: str, at: int, length: int) -> list[list[str]]:
    with store.open_input_file(f"{base}/{file}") as f:
        return [x.split("\t") for x in zlib.decompress(f.read_at(length, at), 31).decode().split("\n")]


class CaptureIndex:
    """Point and prefix lookups. The directory has one row per BLOCK_LINES captures and is held sorted."""

    def __init__(self, directory: list[tuple], folder: str):
        rows = sorted((tuple(x) for x in directory), key=lambda x: _ordered(x[0], x[1]))
        self.rows = [(x[0], x[2], *x[4:7]) for x in rows]
        self.firsts = [x[0] for x in self.rows]
        self.folder = folder
        self.store, self.base = files_at(folder)

    def lines(self, key: str, prefix: bool = False) -> list[list[str]]:
        """Captures of a key (or of all keys that begin with it), from the blocks that can hold it and no others."""
        last = bisect_right(self.firsts, key + "\U0010ffff" if prefix else key)
        i = max(0, bisect_left(self.firsts, key) - 1)
        out = []
        for _, end, file, at, length in self.rows[i:last]:
            if end >= key:
                out += [x for x in read_block(self.store, self.base, file, at, length) if (x[0].startswith(key) if prefix else x[0] == key)]
        return out

    def records(self, url: str) -> list[tuple[dict[str, str], bytes]]:
        """Headers and block of each capture of a URL."""
        out = []
        for x in self.lines(url_key(url)):
            with self.store.open_input_file(f"{self.base}/{x[2]}") as f:
                out.append(parse(f.read_at(int(x[4]), int(x[3]))))
        return out


def find_captures(wanted: DataFrame, directory: DataFrame, folder: str) -> DataFrame:
    """(file, at, length, digest) of all captures of each wanted (key, page_id), which are distinct.

    What goes to all tasks is the first capture of each index file, whose number is that of the index's partitions.
    Wanted captures are dealt by index file and sorted, so that a task reads each directory and each block once.
    """
    tops = directory.groupBy("file").agg(F.min(F.struct("first", "first_id")).alias("top")).collect()
    tops = sorted((_ordered(*r["top"]), r["file"]) for r in tops)
    shared = wanted.sparkSession.sparkContext.broadcast(tops)

    def name(batches):
        firsts, files = [x[0] for x in shared.value], [x[1] for x in shared.value]
        for batch in batches:
            places = [bisect_right(firsts, _ordered(k, i)) - 1 for k, i in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([files[x] if x >= 0 else None for x in places], pa.string())], ["key", "page_id", "index_file"])

    def search(batches):
        store, base = files_at(folder)
        current, block, blocks, firsts, lines, ordered = None, None, [], [], [], []
        for batch in batches:
            found = []
            for key, page_id, file in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                if file != current:
                    with store.open_input_file(f"{base}/{file}.directory") as f:
                        blocks = [x.split("\t") for x in zlib.decompress(f.read()).decode().split("\n")]
                    current, block, firsts = file, None, [_ordered(x[0], x[1]) for x in blocks]
                sought = _ordered(key, page_id)
                # equal captures can begin in the block before the one that begins with them
                at = max(0, bisect_left(firsts, sought) - 1)
                while at < len(blocks) and firsts[at] <= sought:
                    if at != block:
                        lines = read_block(store, base, file, int(blocks[at][5]), int(blocks[at][6]))
                        block, ordered = at, [_ordered(x[0], x[1]) for x in lines]
                    found += lines[bisect_left(ordered, sought) : bisect_right(ordered, sought)]
                    at += 1
            yield pa.RecordBatch.from_arrays([pa.array([x[2] for x in found], pa.string()), pa.array([int(x[3]) for x in found], pa.int64()), pa.array([int(x[4]) for x in found], pa.int64()), pa.array([x[5] for x in found], pa.string())], ["file", "at", "length", "digest"])

    named = wanted.select("key", "page_id").mapInArrow(name, "key string, page_id bigint, index_file string").where("index_file IS NOT NULL")
    near = named.repartition("index_file").sortWithinPartitions("index_file", "key", "page_id")
    return near.mapInArrow(search, "file string, at bigint, length bigint, digest string")


def with_keys(pages: DataFrame, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """The distinct (key, page_id) of pages."""

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([url_key(x) for x in batch.column(1).to_pylist()], pa.string()), batch.column(0)], ["key", "page_id"])

    url = F.coalesce(F.regexp_replace(F.col(url_col).cast("string"), r"[\r\n]", ""), F.lit(""))
    return pages.select(F.col(id_col).cast("long").alias("page_id"), url.alias("url")).mapInArrow(run, "key string, page_id bigint").distinct()


def read_records(captures: DataFrame, folder: str) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to) of the records of (file, at, length, digest), which
    are dealt by archive file and place so that a task reads a file forwards."""

    def fetch(batches):
        store, base = files_at(folder)
        name, f = None, None
        for batch in batches:
            rows = []
            for file, at, length, digest in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if file != name:
                    if f is not None:
                        f.close()
                    name, f = file, store.open_input_file(f"{base}/{file}")
                head, body = parse(f.read_at(length, at))
                kind, said = head["warc-type"], head["warc-payload-digest"].removeprefix("sha1:")
                if said != digest or (kind == "response" and payload_digest(body) != said):
                    raise ValueError(f"the record at {at} of {file} differs from its digest")
                number = lambda k: None if (x := head[k].removeprefix("<urn:page:").rstrip(">")) == "None" else int(x)
                rows.append((number("warc-record-id"), len(body) if kind == "response" else int(head["x-payload-length"]), said, kind, None if kind == "response" else number("warc-refers-to")))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()))], ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])
        if f is not None:
            f.close()

    near = captures.repartition(F.col("file"), F.floor(F.col("at") / (4 << 20))).sortWithinPartitions("file", "at")
    return near.mapInArrow(fetch, "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint")


def op3_warc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page looked up in the index and read back from the archives."""
    folder, pages = new_path(spark, "archive"), table(spark, sf_dir, "pages")
    directory = build_index(write_archives(with_referrals(pages), folder), folder)
    return read_records(find_captures(with_keys(pages), directory, folder), folder)
