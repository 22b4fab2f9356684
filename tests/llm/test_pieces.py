import hashlib
import random

import pytest
import sentencepiece

from turnwise.llm import pieces


@pytest.fixture(scope="module")
def codec():
    return pieces.Codec(pieces.Model.load(pieces.default_model()))


@pytest.fixture(scope="module")
def library():
    return sentencepiece.SentencePieceProcessor(model_file=pieces.default_model())


def texts():
    r = random.Random(3)
    yield from ["", " ", "  ", "\n", "a", " a", "a ", "▁", "▁▁a ▁", "<s> </s> <unk> <0x0A>", "x\0y", "\U0001f600́ z", "a" * 500, "�", "\t\t a", "m². x². a.b (c) ...d --e", "   \n  b   c"]
    alphabet = "abcdefgh  ethin or\n\t.,éñ中\U0001f600▁<0x>#1234 "
    for _ in range(400):
        yield "".join(r.choice(alphabet) for _ in range(r.randrange(1, 90)))


def test_ids_and_decoded_text_equal_the_library(codec, library):
    for x in texts():
        want = library.encode(x, add_eos=True)
        assert codec.encode(x, add_end=True) == want, repr(x)
        assert codec.decode(want) == library.decode(want), repr(x)
        assert codec.summaries([x], True)[0][:3] == (len(want), hashlib.sha256(" ".join(map(str, want)).encode()).hexdigest(), hashlib.sha256(library.decode(want).encode()).hexdigest())


def test_bad_byte_runs_decode_as_the_library_does(codec, library):
    r = random.Random(5)
    for _ in range(300):
        ids = [r.choice([*(codec.byte_id[r.randrange(256)] for _ in range(3)), r.randrange(259, 2000)]) for _ in range(r.randrange(1, 9))]
        assert codec.decode(ids) == library.decode(ids), ids


def test_spans_cover_the_source_in_order(codec):
    for x in texts():
        got, size = codec.encode_with_spans(x), len(x.encode())
        assert [i for i, _, _ in got] == codec.encode(x)
        assert all(a <= b for _, a, b in got) and all(p[2] == q[1] for p, q in zip(got, got[1:]))
        assert not got or (got[0][1] == 0 and got[-1][2] == size)


def test_what_is_remembered_has_a_bound_and_changes_nothing(monkeypatch, library):
    """Stretches that are asked for again stay, the others are forgotten; ids and digests are those of a fresh codec. Tasks of a worker share it."""
    monkeypatch.setattr(pieces, "MOST_KEPT", 40)
    own, sizes = pieces.Codec(pieces.Model.load(pieces.default_model())), []
    for x in texts():
        ids, ids_sha, text_sha, _ = own.digested(x)
        want = library.encode(x)
        assert ids.tolist() == want == own.aligned(x)[0].tolist(), repr(x)
        assert ids_sha == hashlib.sha256(" ".join(map(str, [*want, own.end])).encode()).hexdigest()
        assert text_sha == hashlib.sha256(library.decode(want).encode()).hexdigest()
        own.digested("often")
        sizes.append(len(own.known) + len(own.older))
    assert max(sizes) < 40 + 2 * 90 and "▁often" in own.known
    assert pieces._worker_codec(pieces.default_model()) is pieces._worker_codec(pieces.default_model())


@pytest.mark.parametrize("rule", ["nfkc", "nmt_nfkc", "nmt_nfkc_cf", "identity"])
def test_normaliser_reads_the_compiled_map_as_the_library_does(rule):
    from sentencepiece import sentencepiece_model_pb2 as proto

    for trim in (True, False):
        lib = sentencepiece.SentencePieceNormalizer(rule_name=rule, add_dummy_prefix=True, escape_whitespaces=True, remove_extra_whitespaces=trim)
        m = proto.ModelProto()
        m.ParseFromString(lib.serialized_model_proto())
        ours = pieces.Normaliser(pieces.Model([], m.normalizer_spec.precompiled_charsmap, True, trim, True, True))
        for x in [*texts(), "ＡＢＣ ① ﬁn", " 　 a  b  ", "éẛ̣", "क़"]:
            got, source = ours(x)
            assert got.decode() == lib.normalize(x), (rule, trim, x)
            assert len(source) == len(got) + 1 and source == sorted(source)


def test_alignment_by_lengths_equals_the_normaliser(codec):
    for x in texts():
        norm, source = codec.normalise(x)
        got, at = codec._alignment(x)
        assert got.encode() == norm and at.tolist() == source, repr(x)


def test_digests_come_from_the_operator_that_gives_spans(spark, monkeypatch, codec, library):
    rows = list(enumerate([None, *texts()]))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    used, real = [], pieces.encode_documents
    monkeypatch.setattr(pieces, "encode_documents", lambda *a, **b: used.append(1) or real(*a, **b))
    got = {r.id: r for r in pieces.encoding_digests(docs, with_ids=True).collect()}
    spans = {r.id: r for r in real(docs).collect()}
    assert used and len(got) == len(rows)
    for i, t in rows:
        want, size = library.encode(t or "", add_eos=True), len((t or "").encode())
        assert got[i].ids == spans[i].ids == want and got[i].n_tokens == len(want)
        assert got[i].ids_sha256 == hashlib.sha256(" ".join(map(str, want)).encode()).hexdigest() and got[i].decoded_sha256 == hashlib.sha256(library.decode(want).encode()).hexdigest()
        own = b"".join(x.to_bytes(8, "little") for x in [*spans[i].starts[:-1], *spans[i].ends[:-1]])
        assert got[i].spans_sha256 == hashlib.sha256(own).hexdigest()
        assert list(zip(spans[i].starts, spans[i].ends)) == [*((a, b) for _, a, b in codec.encode_with_spans(t or "")), (size, size)]
