"""SentencePiece encoding and decoding with source offsets, from the model file alone.

Normaliser compiles nothing itself: it reads the double-array character map stored in the model, takes the longest
matching prefix at each position and records, for every byte it emits, the source byte it came from. Codec merges
pieces by score inside stretches that no piece of the vocabulary can cross, and projects each piece through that
alignment to a byte span of the source text. For many texts at once, where no spans are asked for, the library merges
the stretches not seen yet (without its normaliser); tests hold both ways against the whole library.
"""

from __future__ import annotations

import hashlib
import heapq
import re
import struct
from array import array
from dataclasses import dataclass
from functools import lru_cache
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.llm.common import map_arrow, table, text_of

#: Fixed values of the model format.
SPACE = "▁"
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
BAD = "�".encode()

MARKS = ".,;:!?|$%&*#()\"'-/"

#: Stretches up to so many characters are remembered, and so many of them in a worker.
LONGEST_KEPT, MOST_KEPT = 48, 600_000
NO_PIECE = float("-inf")


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class CharMap:
    """The compiled character map: a double-array trie over UTF-8 bytes and a block of zero-ended replacements."""

    def __init__(self, blob: bytes):
        size = struct.unpack_from("<I", blob)[0] if blob else 0
        self.units = struct.unpack_from(f"<{size // 4}I", blob, 4) if blob else ()
        self.texts = blob[4 + size :]

    def longest(self, data: bytes, at: int) -> tuple[int, bytes] | None:
        """The length of the longest key that data has at this place, and its replacement."""
        if not self.units:
            return None
        units, found = self.units, None
        node = 0
        offset = lambda u: (u >> 10) << ((u & (1 << 9)) >> 6)
        node ^= offset(units[node])
        for i in range(at, len(data)):
            node ^= data[i]
            if node >= len(units) or (units[node] & ((1 << 31) | 0xFF)) != data[i]:
                break
            u = units[node]
            node ^= offset(u)
            if (u >> 8) & 1:
                found = (i + 1 - at, units[node] & ((1 << 31) - 1))
        if found is None:
            return None
        return found[0], self.texts[found[1] : self.texts.index(b"\0", found[1])]


@dataclass
class Model:
    pieces: list[tuple[str, float, int]]
    charsmap: bytes
    dummy_prefix: bool
    trim_spaces: bool
    escape_spaces: bool
    byte_fallback: bool
    blob: bytes = b""

    @classmethod
    def load(cls, path: str) -> Model:
        from sentencepiece import sentencepiece_model_pb2 as proto

        m = proto.ModelProto()
        with open(path, "rb") as f:
            m.ParseFromString(blob := f.read())
        if m.trainer_spec.model_type != 2:
            raise ValueError("only models of merged pairs (BPE) are supported")
        n = m.normalizer_spec
        return cls([(p.piece, p.score, p.type) for p in m.pieces], n.precompiled_charsmap, n.add_dummy_prefix, n.remove_extra_whitespaces, n.escape_whitespaces, m.trainer_spec.byte_fallback, blob)


_SURROGATE = re.compile("[\ud800-\udfff]")


class Normaliser:
    def __init__(self, model: Model):
        self.m, self.map = model, CharMap(model.charsmap)
        #: Without a map and trimming, normalising only writes spaces as SPACE: alignment follows from lengths.
        self.plain = not model.charsmap and not model.trim_spaces

    def _next(self, data: bytes, at: int) -> tuple[int, bytes]:
        hit = self.map.longest(data, at)
        if hit:
            return hit
        first = data[at]
        n = 1 if first < 0x80 else 2 if first < 0xE0 else 3 if first < 0xF0 else 4
        char = data[at : at + n]
        try:
            char.decode()
        except UnicodeDecodeError:
            return 1, BAD
        return n, char

    def __call__(self, text: str) -> tuple[bytes, list[int]]:
        """The normalised bytes, and for each of them (and the end) the source byte where it starts."""
        data, out, source = text.encode("utf-8", "surrogatepass"), bytearray(), []
        space = SPACE.encode() if self.m.escape_spaces else b" "
        at, trim = 0, self.m.trim_spaces
        if trim:
            while at < len(data):
                n, got = self._next(data, at)
                if got != b" ":
                    break
                at += n
        if at == len(data):
            return b"", [len(data) if trim else 0]
        if self.m.dummy_prefix:
            out += space
            source += [at] * len(space)
        spaced = trim
        while at < len(data):
            n, got = self._next(data, at)
            if spaced:
                got = got.lstrip(b" ")
            if got:
                for c in (got[i : i + 1] for i in range(len(got))):
                    c = space if c == b" " else c
                    out += c
                    source += [at] * len(c)
                spaced = trim and got.endswith(b" ")
            at += n
        if trim:
            while out.endswith(space):
                del out[-len(space) :], source[-len(space) :]
        return bytes(out), [*source, len(data)]


class Codec:
    def __init__(self, model: Model):
        self.m, self.normalise = model, Normaliser(model)
        self.id_of = {p: i for i, (p, _, kind) in enumerate(model.pieces) if kind in (NORMAL, USER_DEFINED)}
        self.score = {p: s for p, s, kind in model.pieces if kind in (NORMAL, USER_DEFINED)}
        self.byte_id = {int(p[3:5], 16): i for i, (p, _, kind) in enumerate(model.pieces) if kind == BYTE}
        self.unknown = next(i for i, (_, _, kind) in enumerate(model.pieces) if kind == UNKNOWN)
        self.end = next(i for i, (p, _, kind) in enumerate(model.pieces) if kind == CONTROL and p == "</s>")
        self.bytes_of = [bytes([int(p[3:5], 16)]) if kind == BYTE else b"" if kind == CONTROL else " ⁇ ".encode() if kind == UNKNOWN else p.replace(SPACE, " ").encode() for p, _, kind in model.pieces]
        self.is_byte = [kind == BYTE for _, _, kind in model.pieces]
        self.first_byte_id, self.last_byte_id = min(self.byte_id.values(), default=1 << 31), max(self.byte_id.values(), default=-1)
        if any(kind in (USER_DEFINED, UNUSED) for _, _, kind in model.pieces) or any(SPACE in p.lstrip(SPACE) for p in self.id_of):
            raise ValueError("pieces of this vocabulary can cross a space; stretches can't be cut there")
        long = [p for p in self.id_of if len(p) > 1]
        before: dict[str, set] = {}
        for p in long:
            for x, y in pairwise(p):
                before.setdefault(y, set()).add(x)
        joined = "".join(long)
        #: Characters that no longer piece holds, of those that are frequent in text, stand alone.
        alone = re.escape("".join(c for c in "\n\r\t" if c not in joined))
        #: Marks that follow no letter or digit inside a piece begin a stretch; the few odd characters that a piece has before them switch that off.
        marks = {c for c in MARKS if not any(x.isascii() and x.isalnum() for x in before.get(c, ()))}
        self.odd = {x for c in marks for x in before.get(c, ())} - marks - {SPACE}
        first = re.escape("".join(sorted(marks)))
        rest = f"|[{alone}]" if alone else ""
        self.coarse = re.compile(f"{SPACE}*[^{SPACE}{alone}]+|{SPACE}+{rest}")
        self.fine = re.compile(f"{SPACE}*[{first}]*[^{SPACE}{alone}{first}]+|{SPACE}*[{first}]+|{SPACE}+{rest}") if marks else self.coarse
        self.kept: dict[str, tuple] = {}
        self.known: dict[str, tuple] = {}
        self.older: dict[str, tuple] = {}
        self.size_of = [len(p.encode()) for p, _, _ in model.pieces]
        self._library = None

    def stretches(self, norm: str) -> list[str]:
        return (self.coarse if any(c in norm for c in self.odd) else self.fine).findall(norm)

    def merge(self, stretch: str) -> list[str]:
        """The pieces of a stretch: the best-scored adjacent pair is merged until none is a piece; ties go to the left."""
        if len(stretch) <= LONGEST_KEPT:
            return self._merge_short(stretch)
        parts: list[str | None] = list(stretch)
        n = len(parts)
        left, right = list(range(-1, n - 1)), [*range(1, n), -1]
        score, heap = self.score, []

        def offer(i: int, j: int) -> None:
            if i >= 0 and j >= 0 and (s := score.get(both := parts[i] + parts[j])) is not None:
                heapq.heappush(heap, (-s, i, j, both))

        for i in range(n - 1):
            offer(i, i + 1)
        while heap:
            _, i, j, both = heapq.heappop(heap)
            if parts[i] is None or parts[j] is None or right[i] != j or len(parts[i]) + len(parts[j]) != len(both):
                continue
            parts[i], parts[j] = both, None
            right[i] = right[j]
            if right[j] >= 0:
                left[right[j]] = i
            offer(left[i], i)
            offer(i, right[i])
        return [p for p in parts if p is not None]

    def _merge_short(self, stretch: str) -> list[str]:
        """The same by rescanning the scores of all adjacent pairs, which is faster for a word."""
        parts, score = list(stretch), self.score.get
        values = [score(x + y, NO_PIECE) for x, y in pairwise(parts)]
        while values:
            best = max(values)
            if best == NO_PIECE:
                break
            i = values.index(best)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del values[i]
            if i:
                values[i - 1] = score(parts[i - 1] + parts[i], NO_PIECE)
            if i < len(values):
                values[i] = score(parts[i] + parts[i + 1], NO_PIECE)
        return parts

    def stretch_ids(self, stretch: str) -> tuple[list[int], list[int]]:
        """Ids, and how many normalised bytes each stands for (0 for all but the last byte id of a character)."""
        ids, sizes = [], []
        for p in self.merge(stretch):
            i = self.id_of.get(p)
            if i is not None:
                ids.append(i)
                sizes.append(self.size_of[i])
                continue
            raw = p.encode("utf-8", "surrogatepass")
            if self.m.byte_fallback:
                ids += [self.byte_id[b] for b in raw]
                sizes += [0] * (len(raw) - 1) + [len(raw)]
            else:
                ids.append(self.unknown)
                sizes.append(len(raw))
        return ids, sizes

    def learn(self, stretches) -> dict[str, tuple]:
        """(ids as text, number of ids, their decoded bytes) of the stretches that aren't remembered, whose pairs the library merges many at a time; short ones are remembered."""
        if len(self.kept) > MOST_KEPT:
            self.kept.clear()
        new = [x for x in stretches if x not in self.kept]
        if self._library is None:
            self._library = self._merger()
        got = {x: (" ".join(map(str, ids)), len(ids), self.plain_bytes(ids)) for x, ids in zip(new, self._library.encode(new, num_threads=1), strict=True)} if new else {}
        self.kept.update((x, y) for x, y in got.items() if len(x) <= LONGEST_KEPT)
        return {x: y for x, y in got.items() if len(x) > LONGEST_KEPT}

    def _merger(self):
        """The library over the same pieces without any normalising, so that it does nothing but merge."""
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2 as proto

        m = proto.ModelProto()
        m.ParseFromString(self.m.blob)
        m.normalizer_spec.precompiled_charsmap = b""
        m.normalizer_spec.add_dummy_prefix = m.normalizer_spec.remove_extra_whitespaces = m.normalizer_spec.escape_whitespaces = False
        return sentencepiece.SentencePieceProcessor(model_proto=m.SerializeToString())

    def plain_bytes(self, ids: list[int]) -> bytes:
        """What ids stand for, with runs of byte ids read as UTF-8 and each bad byte replaced."""
        if self.first_byte_id > max(ids, default=0) or min(ids) > self.last_byte_id:
            return b"".join([self.bytes_of[i] for i in ids])
        out, run = [], bytearray()
        for i in ids:
            if self.is_byte[i]:
                run += self.bytes_of[i]
                continue
            if run:
                out.append(_mended(bytes(run)))
                run.clear()
            out.append(self.bytes_of[i])
        if run:
            out.append(_mended(bytes(run)))
        return b"".join(out)

    def decode(self, ids: list[int]) -> str:
        """The text of ids; one leading space goes if the model writes a dummy prefix."""
        return self._unprefixed(self.plain_bytes(ids), ids).decode("utf-8", "surrogatepass")

    def _unprefixed(self, raw: bytes, ids: list[int] | np.ndarray) -> bytes:
        if self.m.dummy_prefix and raw[:1] == b" " and not self.is_byte[next((i for i in ids if self.bytes_of[i]), self.unknown)]:
            return raw[1:]
        return raw

    def encode(self, text: str, add_end: bool = False) -> list[int]:
        norm = self._normalised(text)
        ids = [i for x in self.stretches(norm) for i in self.stretch_ids(x)[0]]
        return [*ids, self.end] if add_end else ids

    def _normalised(self, text: str) -> str:
        if self.normalise.plain:
            return (SPACE * bool(text and self.m.dummy_prefix)) + text.replace(" ", SPACE)
        return self.normalise(text)[0].decode("utf-8", "surrogatepass")

    def encode_with_spans(self, text: str) -> list[tuple[int, int, int]]:
        """(id, start, end): each piece and the source bytes it covers, end exclusive; ends never fall behind starts."""
        return list(zip(*(x.tolist() for x in self.aligned(text)), strict=True))

    def aligned(self, text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids, starts and ends of encode_with_spans."""
        ids, sizes, source, _, _ = self._found(text)
        return self._placed(ids, sizes, source)

    def digested(self, text: str) -> tuple[np.ndarray, str, str, str]:
        """The ids of aligned(), and SHA-256 of the ids with the end id in decimal, of the text they decode to and of their starts, then ends."""
        ids, sizes, source, decimal, raw = self._found(text)
        ids, starts, ends = self._placed(ids, sizes, source)
        spans = hashlib.sha256(starts.astype("<i8", copy=False).tobytes() + ends.astype("<i8", copy=False).tobytes())
        digest = hashlib.sha256(" ".join((*decimal, str(self.end))).encode())
        return ids, digest.hexdigest(), hashlib.sha256(self._unprefixed(b"".join(raw), ids)).hexdigest(), spans.hexdigest()

    def _found(self, text: str) -> tuple:
        """By stretches of the text: bytes of the ids, bytes of their sizes, (the source of each normalised byte,) ids in decimal, what they stand for.

        A character never lies in two stretches, so byte ids of different stretches don't complete each other.
        """
        norm, source = self._alignment(text)
        stretches, known = self.stretches(norm), self.known
        got = list(map(known.get, stretches))
        if None in got:
            if len(known) > MOST_KEPT // 2:  # those not asked for since the last time are forgotten
                self.older, self.known = known, {}
            for k, x in enumerate(got):
                if x is None:
                    got[k] = self._remembered(stretches[k])
        ids, sizes, decimal, raw = zip(*got, strict=True) if got else ((), (), (), ())
        return ids, sizes, source, decimal, raw

    def _remembered(self, stretch: str) -> tuple[bytes, bytes, str, bytes]:
        got = self.known.get(stretch) or self.older.get(stretch)
        if got is None:
            ids, sizes = self.stretch_ids(stretch)
            got = array("i", ids).tobytes(), array("i", sizes).tobytes(), " ".join(map(str, ids)), self.plain_bytes(ids)
        if len(stretch) <= LONGEST_KEPT:
            self.known[stretch] = got
        return got

    @staticmethod
    def _placed(ids: tuple, sizes: tuple, source: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        sizes = np.frombuffer(b"".join(sizes), np.int32)
        at = np.zeros(len(sizes) + 1, np.int64)
        np.cumsum(sizes, out=at[1:])
        edges = source[at]
        return np.frombuffer(b"".join(ids), np.int32), edges[:-1], edges[1:]

    def _alignment(self, text: str) -> tuple[str, np.ndarray]:
        """The normalised text, and the source byte of each of its bytes and of its end; without a map by the lengths alone."""
        if self.normalise.plain and self.m.escape_spaces and not _SURROGATE.search(text):
            raw = np.frombuffer(text.encode(), np.uint8)
            at = np.maximum.accumulate(np.where(raw & 0xC0 != 0x80, np.arange(len(raw)), 0))
            source = np.repeat(at, np.where(raw == 0x20, len(SPACE.encode()), 1))
            prefix = np.zeros(len(SPACE.encode()) * bool(text and self.m.dummy_prefix), np.int64)
            return self._normalised(text), np.concatenate([prefix, source, [len(raw)]])
        norm, source = self.normalise(text)
        return norm.decode("utf-8", "surrogatepass"), np.array(source, np.int64)

    def summaries(self, texts: list[str], with_ids: bool = False) -> list[tuple]:
        """Of each text: ids with the end id, SHA-256 of the ids in decimal, SHA-256 of the text decoded from them; the ids themselves if asked for."""
        cut = [self.stretches(self._normalised(x)) for x in texts]
        long = self.learn(set().union(*cut))
        kept, out = self.kept, []
        for stretches in cut:
            got = [kept[x] if x in kept else long[x] for x in stretches]
            ids = " ".join([*[x[0] for x in got], str(self.end)])
            raw = b"".join([x[2] for x in got])
            if self.m.dummy_prefix and stretches and raw[:1] == b" " and stretches[0][0] == SPACE:
                raw = raw[1:]
            out.append((sum([x[1] for x in got]) + 1, hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(raw).hexdigest(), np.array(ids.split(" "), np.int32) if with_ids else None))
        return out


@lru_cache(1)
def _worker_codec(path: str) -> Codec:
    """One codec in each Python worker, so that what a task has remembered serves the next."""
    return Codec(Model.load(path))


def _mended(run: bytes) -> bytes:
    """run if it is UTF-8; else each byte that starts no whole character becomes the replacement character."""
    try:
        run.decode()
        return run
    except UnicodeDecodeError:
        pass
    out, at = [], 0
    while at < len(run):
        b = run[at]
        n = 1 if b < 0x80 else 2 if 0xC2 <= b < 0xE0 else 3 if 0xE0 <= b < 0xF0 else 4 if 0xF0 <= b < 0xF5 else 0
        try:
            run[at : at + n].decode() or 1 / 0
            out.append(run[at : at + n])
            at += n
        except (UnicodeDecodeError, ZeroDivisionError):
            out.append(BAD)
            at += 1
    return b"".join(out)


def encode_documents(docs: DataFrame, model_path: str | None = None, id_col: str = "doc_id", text_col: str = "text", spans: bool = True, digests: bool = False, with_ids: bool = True) -> DataFrame:
    """(id, ids, starts, ends): the ids of each text with an end id, and the source byte span of each (empty for the end).
    With digests, the columns of encoding_digests() in place of the arrays, made where they are.

    Null texts count as empty and give the end id alone; an empty table gives no rows; repeated rows are encoded each;
    columns other than the two named are not read. A text of any length is encoded whole.
    """
    if digests:
        return _digested(docs, model_path, id_col, text_col, with_ids)
    path = model_path or default_model()
    kind = docs.schema[id_col].dataType.simpleString()

    def make():
        codec = _worker_codec(path)

        def run(batch: pa.RecordBatch) -> pa.RecordBatch:
            ids, starts, ends = [], [], []
            for text in batch.column(1).to_pylist():
                if spans:
                    got = codec.aligned(text)
                else:
                    own = np.array(codec.encode(text), np.int32)
                    got = own, np.zeros(len(own), np.int64), np.zeros(len(own), np.int64)
                size = len(text.encode())
                for column, values, last in zip((ids, starts, ends), got, (codec.end, size, size), strict=True):
                    column.append(np.append(values, values.dtype.type(last)))
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.list_(pa.int32())), pa.array(starts, pa.list_(pa.int64())), pa.array(ends, pa.list_(pa.int64()))], ["id", "ids", "starts", "ends"])

        return run

    return map_arrow(docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text")), make, f"id {kind}, ids array<int>, starts array<bigint>, ends array<bigint>", rows=64)


def encoding_digests(docs: DataFrame, model_path: str | None = None, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """(id, n_tokens, ids_sha256, decoded_sha256, spans_sha256) of each text, and its ids if asked for.

    All come from the ids and spans that encode_documents gives of the text, in the task that encodes it, so that the
    spans need not be sent on: spans_sha256 is over the little-endian 64-bit starts, then the ends, of all ids but the end.
    """
    return encode_documents(docs, model_path, id_col, text_col, digests=True, with_ids=with_ids)


def _digested(docs: DataFrame, model_path: str | None, id_col: str, text_col: str, with_ids: bool) -> DataFrame:
    path = model_path or default_model()
    kind = docs.schema[id_col].dataType.simpleString()
    names, kinds = ["n_tokens", "ids_sha256", "decoded_sha256", "spans_sha256", "ids"][: 4 + with_ids], (pa.int64(), pa.string(), pa.string(), pa.string(), pa.list_(pa.int32()))

    def make():
        codec = _worker_codec(path)

        def run(batch: pa.RecordBatch) -> pa.RecordBatch:
            got = []
            for text in batch.column(1).to_pylist():
                ids, *digests = codec.digested(text)
                got.append((len(ids) + 1, *digests, np.append(ids, np.int32(codec.end)) if with_ids else None))
            return pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([x[k] for x in got], kinds[k]) for k in range(len(names)))], ["id", *names])

        return run

    schema = f"id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string, spans_sha256 string" + ", ids array<int>" * with_ids
    return map_arrow(docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text")), make, schema, rows=64)


def op6_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encoding_digests(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")
