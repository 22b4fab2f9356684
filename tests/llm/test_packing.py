import random

import numpy as np

from turnwise.llm import packing
from turnwise.llm.common import new_path


def test_best_fit_decreasing_as_by_trying_every_row():
    r = random.Random(1)
    for _ in range(200):
        size = r.choice((1, 7, 8, 64, 100))
        lengths = np.array([r.randrange(1, size + 1) for _ in range(r.randrange(60))], int)
        rows = packing.best_fit_decreasing(lengths, size)
        room = []
        for i in np.argsort(-lengths, kind="stable"):
            fits = [x for x in room if x >= lengths[i]]
            if fits:
                room.remove(min(fits))
                room.append(min(fits) - lengths[i])
            else:
                room.append(size - lengths[i])
        assert sorted(size - sum(lengths[i] for i in x) for x in rows) == sorted(room)
        assert sorted(i for x in rows for i in x) == list(range(len(lengths)))


def test_files_give_every_text_back(spark, monkeypatch):
    monkeypatch.setattr(packing, "SHARD_BYTES", 4000)
    r = random.Random(2)
    texts = ["", None, "é\U0001f600" * 40, "word " * 3000, *["".join(r.choice("abc de\n") for _ in range(r.randrange(300))) for _ in range(80)]]
    docs = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, shard string")
    folder = new_path(spark, "packed")
    rows = packing.pack(docs, folder, size=128).cache().collect()
    assert len({x.shard for x in rows}) > 2
    got, encode = {}, packing.tokenizer(packing.default_vocabulary())
    for x in rows:
        ids, resets, ends = packing.read_shard(folder, x.file, 128)
        places = packing.position_ids(resets[x.row])
        assert ends[x.row].tolist() == x.cu_seqlens and x.n_tokens <= 128
        for k, (d, s) in enumerate(zip(x.doc_ids, x.starts)):
            a, b = x.cu_seqlens[k : k + 2]
            assert places[a:b].tolist() == list(range(b - a))
            got.setdefault(d, []).append((s, ids[x.row, a:b].tolist()))
        assert (ids[x.row, x.n_tokens :] == packing.END).all()
    for i, t in enumerate(texts):
        assert [y for _, part in sorted(got[i]) for y in part] == [*encode(t or ""), packing.END]


def test_repeated_and_missing_ids_give_every_text_back(spark):
    texts = [("a", "one two " * 200), ("a", "three four " * 150), ("a", "one two " * 200), (None, "five"), ("b", None)]
    docs = spark.createDataFrame([(*t, "k", "s") for t in texts], "doc_id string, text string, text_key string, start string")
    folder = new_path(spark, "packed")
    encode = packing.tokenizer(packing.default_vocabulary())
    parts = {}
    for x in packing.pack(docs, folder, size=128).collect():
        ids, _, _ = packing.read_shard(folder, x.file, 128)
        for k, key in enumerate(zip(x.doc_ids, x.text_keys, x.starts)):
            parts.setdefault(key, []).append(tuple(ids[x.row, x.cu_seqlens[k] : x.cu_seqlens[k + 1]].tolist()))
    whole = {}
    for (d, t, _), same in sorted(parts.items(), key=lambda x: (str(x[0][0]), *x[0][1:])):
        assert len(set(same)) == 1
        whole.setdefault((d, t), [[] for _ in same])
        for copy, piece in zip(whole[d, t], same, strict=True):
            copy += piece
    got = sorted((str(d), tuple(c)) for (d, _), copies in whole.items() for c in copies)
    assert got == sorted((str(d), (*encode(t or ""), packing.END)) for d, t in texts)


def test_empty_table(spark):
    assert packing.pack(spark.createDataFrame([], "doc_id long, text string"), new_path(spark, "packed")).count() == 0
