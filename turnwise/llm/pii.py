"""Personal data by bootstrapped contextual extraction.

Four base kinds are found by fixed patterns in every whole text, and keys of well-known formats (long hexadecimal digests
and the tokens of public services) as seeds of a fifth kind, secret. They seed a graph of contexts and values: a context
is the two words before something identifier-shaped, of any length, a value is the text of that: a word with @, digits
or a long mix of letters and digits, or a run of digits joined by spaces, brackets, dots and dashes. Rounds of scoring run in Spark: the
confidence of a context is the summed score of what fills it divided by how often the context occurs before any word
of the corpus, and the score of a value that is no seed is the chance that one of its confident contexts is right.
Contexts count only with MIN_VALUES different identifiers, MIN_SEEDS of them seeds of one kind. Values that reach
MIN_SCORE become spans of their contexts' kind: identifiers that the fixed patterns don't know, such as misspelt
addresses after the words that usually come before an address, phones without a country code, keys of unknown formats.
Seeds of the kind secret are added spans too.

Corpus frequencies of contexts are exact. What goes to all tasks for counting them is a bitmap of BITMAP_BITS bits,
whose size doesn't grow; its false hits fall out in the join by the 64-bit context.

Edge cases: null and empty texts have no spans; equal starts sort by kind; repeated rows are reported each; an empty
table gives an empty result; very long texts and tokens are read whole; columns other than id and text are not read.
"""

from __future__ import annotations

import re
import zlib
from bisect import bisect_right

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.llm.common import dropped, map_arrow, stored, table, text_of

KINDS = ("email", "ip", "card", "phone")
SECRET = "secret"
MIN_VALUES, MIN_SEEDS, MIN_CONFIDENCE, MIN_SCORE, ROUNDS = 8, 4, 0.5, 0.8, 3
BITMAP_BITS = 1 << 22

_AT = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_LIKELY = re.compile(r"[0-9]{2}|@|[0-9][^\s0-9]{1,3}[0-9]")
#: Formats of digests and of access tokens that their services publish.
_SECRET = re.compile(r"(?<![A-Za-z0-9_-])(?:[0-9a-f]{40}|[0-9a-f]{64}|AKIA[0-9A-Z]{16}|gh[opsur]_[A-Za-z0-9]{36}|xox[abpr]-[A-Za-z0-9-]{10,}|eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,})(?![A-Za-z0-9_-])")
_RUN = re.compile(r"[(+]?[0-9](?:[ ().-]{0,2}[0-9]){6,}")
_TOKEN = re.compile(r"\S+")
_EDGE = "\"'`.,;:!?()[]{}<>|*#$%&="


def luhn(digits: str) -> bool:
    """Whether the check digit is right: every second digit from the right counts twice, its own digits added."""
    odd = sum(map(int, digits[-1::-2]))
    return (odd + sum(sum(divmod(2 * int(d), 10)) for d in digits[-2::-2])) % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) by start, then kind as listed; matches of a kind don't overlap."""
    out = []
    if "@" in text:
        last = 0
        for m in _AT.finditer(text):
            start = at = m.start()
            while start > last and text[start - 1] in _LOCAL:
                start -= 1
            if start < at:
                out.append((start, m.end(), "email"))
                last = m.end()
    for m in _IP.finditer(text):
        if all(len(x) <= 3 and int(x or 0) <= 255 for x in (y.lstrip("0") for y in m.group().split("."))):
            out.append((m.start(), m.end(), "ip"))
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 12:
            digits = m.group().replace(" ", "").replace("-", "")
            if 12 <= len(digits) <= 19 and luhn(digits):
                out.append((m.start(), m.end(), "card"))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 9 <= sum(c.isdigit() for c in m.group()) <= 15:
                out.append((m.start(), m.end(), "phone"))
    out.sort(key=lambda x: (x[0], KINDS.index(x[2])))
    return out


def written(spans) -> str:
    return ",".join(f"{kind}:{start}:{end}" for start, end, kind in spans)


class Contexts:
    """The context of places in a text: a signed hash of the two words before the word there, and its place in the bitmap."""

    def __init__(self, text: str):
        self.text, self.words = text, [(m.start(), m.end()) for m in _TOKEN.finditer(text)]
        self.starts = [a for a, _ in self.words]
        self.known: dict[int, tuple[int | None, int | None]] = {}

    def before(self, at: int) -> tuple[int | None, int | None]:
        """None twice if there aren't two words."""
        i = bisect_right(self.starts, at) - 1
        if i < 2:
            return None, None
        if i not in self.known:
            two = [self.text[a:b] for a, b in self.words[i - 2 : i]]
            self.known[i] = context_key(*two), int(_bits(two)[0])
        return self.known[i]


def context_key(a: str, b: str) -> int:
    h = xxhash.xxh64_intdigest(f"{a.lower()} {b.lower()}".encode("utf-8", "surrogatepass"))
    return h - (1 << 64) if h >> 63 else h


def _bits(words: list[str]) -> np.ndarray:
    """A place in the bitmap for each two neighbouring words."""
    x = np.fromiter((zlib.crc32(w.lower().encode("utf-8", "surrogatepass")) for w in words), np.uint32, len(words))
    return ((x[:-1] * np.uint32(0x9E3779B1)) ^ x[1:]) % np.uint32(BITMAP_BITS)


def secret_spans(text: str) -> list[tuple[int, int, str]]:
    """Keys of known formats."""
    return [(m.start(), m.end(), SECRET) for m in _SECRET.finditer(text)]


def candidates(text: str, spans: list[tuple[int, int, str]]) -> list[tuple[int, int]]:
    """What looks like an identifier and touches none of the sorted spans: runs of seven digits or more, and words with @ or digits, of six characters or more without marks at the edges."""
    runs = [m.span() for m in _RUN.finditer(text)]
    out = _clear(runs, sorted(s[:2] for s in spans))
    words, done, size = [], 0, len(text)
    for m in _LIKELY.finditer(text):
        if m.start() < done:
            continue
        a, b = m.start(), m.end()
        while a > done and not text[a - 1].isspace():
            a -= 1
        while b < size and not text[b].isspace():
            b += 1
        done = b
        while a < b and text[a] in _EDGE:
            a += 1
        while b > a and text[b - 1] in _EDGE:
            b -= 1
        if b - a >= 6 and ("@" in text[a:b] or sum(c.isdigit() for c in text[a:b]) >= 2):
            words.append((a, b))
    return sorted([*out, *_clear(words, sorted([*(s[:2] for s in spans), *runs]))])


def _clear(found: list[tuple[int, int]], taken: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Those of found, by start, that overlap none of taken, by start."""
    out, k, reach = [], 0, 0
    for a, b in found:
        while k < len(taken) and taken[k][0] < b:
            reach = max(reach, taken[k][1])
            k += 1
        if reach <= a:
            out.append((a, b))
    return out


_SPANS = "array<struct<start:bigint,end:bigint,kind:string>>"
_FOUND = "array<struct<kind:string,start:bigint,end:bigint,value:bigint,context:bigint,bit:bigint>>"


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, found): base spans with their kind and other identifier-shaped words without one."""
    id_type = docs.schema[id_col].dataType.simpleString()
    kind = pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("value", pa.int64()), ("context", pa.int64()), ("bit", pa.int64())])

    def one(text: str) -> list[dict]:
        spans = base_spans(text)
        spans += secret_spans(text)
        found = [*spans, *((s, e, None) for s, e in candidates(text, spans))]
        out, contexts = [], Contexts(text) if found else None
        for s, e, k in found:
            v = xxhash.xxh64_intdigest(text[s:e].lower().encode("utf-8", "surrogatepass"))
            context, bit = contexts.before(s)
            out.append({"kind": k, "start": s, "end": e, "value": v - (1 << 64) if v >> 63 else v, "context": context, "bit": bit})
        return out

    def make():
        return lambda batch: pa.RecordBatch.from_arrays([batch.column(0), pa.array([one(x) for x in batch.column(1).to_pylist()], pa.list_(kind))], ["id", "found"])

    return map_arrow(docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text")), make, f"id {id_type}, found {_FOUND}")


def context_totals(docs: DataFrame, contexts: DataFrame, text_col: str = "text") -> DataFrame:
    """(context, total): how often each of these contexts comes before a word, over all texts.

    contexts: (context, bit). Only the bitmap of their bits is sent to the tasks.
    """
    spark = docs.sparkSession
    words = contexts.select((F.col("bit") / 64).cast("int").alias("w"), F.expr("shiftleft(1L, CAST(bit % 64 AS INT))").alias("b")).groupBy("w").agg(F.bit_or("b").alias("b")).toPandas()
    bitmap = np.zeros(BITMAP_BITS // 64, np.int64)
    bitmap[words.w] = words.b
    shared = spark.sparkContext.broadcast(bitmap.astype("<i8").tobytes())

    def run(batches):
        has = np.unpackbits(np.frombuffer(shared.value, np.uint8), bitorder="little").astype(bool)
        for batch in batches:
            n: dict[int, int] = {}
            for text in batch.column(0).to_pylist():
                w = text.split()
                if len(w) > 2:
                    for i in np.flatnonzero(has[_bits(w[:-1])]).tolist():
                        key = context_key(w[i], w[i + 1])
                        n[key] = n.get(key, 0) + 1
            yield pa.RecordBatch.from_arrays([pa.array(list(n), pa.int64()), pa.array(list(n.values()), pa.int64())], ["context", "total"])

    return docs.select(text_of(text_col).alias("text")).mapInArrow(run, "context bigint, total bigint").groupBy("context").agg(F.sum("total").alias("total"))


def _frequent_contexts(found: DataFrame) -> DataFrame:
    """(context, bit) of contexts with MIN_VALUES identifiers."""
    x = found.select(F.explode("found").alias("f")).select("f.*").where("context IS NOT NULL")
    often = x.groupBy("context", "bit", "value").agg(F.lit(1).alias("n")).groupBy("context").agg(F.sum("n").alias("n"), F.min("bit").alias("bit"))
    return often.where(F.col("n") >= MIN_VALUES).select("context", "bit")


def discover(docs: DataFrame, found: DataFrame, text_col: str = "text") -> DataFrame:
    """(id, start, end, kind) of identifiers that confident contexts add. found: what scan() gave, stored."""
    contexts = stored(_frequent_contexts(found), "contexts")
    totals = stored(context_totals(docs, contexts, text_col), "totals")
    x = found.select("id", F.explode("found").alias("f")).select("id", "f.*")
    x = stored(x.join(totals, "context"), "instances")
    dropped(contexts)
    seeds = x.where("kind IS NOT NULL").groupBy("context", "kind").agg(F.count_distinct("value").alias("seeds"))
    kinds = seeds.groupBy("context").agg(F.max(F.struct("seeds", "kind")).alias("top")).select("context", "top.*").where(F.col("seeds") >= MIN_SEEDS)
    kinds = stored(kinds, "kinds")
    values = x.groupBy("value").agg(F.max(F.when(F.col("kind").isNotNull(), 1.0).otherwise(0.0)).alias("score"))
    for _ in range(ROUNDS):
        values = stored(values, "values")
        confident = x.join(values, "value").groupBy("context").agg((F.sum("score") / F.max("total")).alias("confidence")).join(kinds, "context").where(F.col("confidence") >= MIN_CONFIDENCE)
        confident = stored(confident, "confident")
        told = x.select("value", "context").distinct().join(confident, "context").groupBy("value").agg((1 - F.exp(F.sum(F.log(F.greatest(1 - F.col("confidence"), F.lit(1e-9)))))).alias("told"))
        values = values.join(told, "value", "left").select("value", F.greatest("score", F.coalesce("told", F.lit(0.0))).alias("score"))
    last = values.where(F.col("score") >= MIN_SCORE)
    return x.where("kind IS NULL").drop("kind").join(last, "value").join(confident.select("context", "kind"), "context").select("id", "start", "end", "kind").distinct()


def extract(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, base, added) of every row: arrays of (start, end, kind), the second what the contexts add."""
    found = stored(scan(docs, id_col, text_col), "found")
    more = discover(docs, found, text_col).groupBy("id").agg(F.sort_array(F.collect_list(F.struct("start", "end", "kind"))).alias("added"))
    of = lambda keep: F.transform(F.filter("found", lambda f: f["kind"].isNotNull() & keep(f["kind"])), lambda f: F.struct(f["start"].alias("start"), f["end"].alias("end"), f["kind"].alias("kind")))
    base, secrets = of(lambda k: k != SECRET), of(lambda k: k == SECRET)
    x = found.select("id", base.alias("base"), secrets.alias("secrets")).join(more, "id", "left")
    return x.select("id", "base", F.sort_array(F.concat("secrets", F.coalesce("added", F.array().cast(_SPANS)))).alias("added"))


def op1_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = extract(table(spark, sf_dir, "documents").select("doc_id", "text"))
    order = {k: i for i, k in enumerate((*KINDS, SECRET))}
    rank = lambda k: sum((F.when(k == name, i).otherwise(0) for name, i in order.items()), F.lit(0))
    join = lambda a: F.array_join(F.transform(a, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    both = F.sort_array(F.transform(F.concat("base", "added"), lambda s: F.struct(s["start"].alias("start"), rank(s["kind"]).alias("rank"), s["end"].alias("end"), s["kind"].alias("kind"))))
    count = lambda k: F.size(F.filter("base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    return x.select(F.col("id").alias("doc_id"), *map(count, KINDS), F.sha2(join(F.col("base")).cast("binary"), 256).alias("base_sha256"), join(both).alias("spans"), F.size("added").cast("long").alias("n_added"))
