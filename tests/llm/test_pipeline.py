import random
import re

import numpy as np
import sentencepiece

import corpus_pipeline
from tests.llm.test_lines import brute as brute_lines
from turnwise.llm import pieces, simhash, toxicity


def test_run_equals_brute_force(spark, tmp_path):
    r = random.Random(11)
    vocab = ["".join(r.choice("abcdefghijklmno") for _ in range(r.randrange(3, 8))) for _ in range(150)]
    say = lambda n: " ".join(r.choice(vocab) for _ in range(n))
    items = [(i, say(25)) for i in range(4)]
    docs, labels = [], []
    for i in range(90):
        text = "\n".join(say(r.randrange(2, 18)) for _ in range(r.randrange(1, 4)))
        if i % 3 == 0:
            text = f"you are an idiotic {r.choice(('scumbag', 'moronic'))} {text}"
        labels.append((i, 1, int(i % 3 == 0)))
        if i % 10 == 1:
            text += f" {items[i % 4][1]} "
        docs.append((i, text, "en", "s", len(text)))
    docs += [(200 + i, docs[i + 1][1] + ("" if i % 2 else " x"), "en", "s", 9) for i in range(0, 20, 4)]
    docs += [(300, None, None, None, None), (301, "", "en", "s", 0), (302, " ", "en", "s", 1)]
    for name, rows, schema in (("documents", docs, "doc_id long, text string, lang string, source string, n_chars long"), ("labels", labels, "doc_id long, quality int, toxic int"), ("benchmark", items, "item_id long, text string")):
        spark.createDataFrame(rows, schema).coalesce(2).write.parquet(f"{tmp_path}/{name}.parquet")
    got = {x.doc_id: x for x in corpus_pipeline.run(spark, str(tmp_path)).collect()}

    read = lambda n: spark.read.parquet(f"{tmp_path}/{n}.parquet")
    model = toxicity.fit(read("documents"), read("labels").where(~toxicity.held_out()))
    seen = np.zeros(toxicity.BUCKETS, np.int32)
    kept = [(i, t) for i, t, *_ in docs if model.score(t or "", seen) < 0.5]
    assert 50 < len(kept) < 80
    left = brute_lines(spark, kept)
    fp = {i: simhash.text_fingerprint(t) for i, t in left.items()}
    root = {i: i for i in fp}
    changed = True
    while changed:
        changed = False
        for a in fp:
            for b in fp:
                if (fp[a] ^ fp[b]).bit_count() <= 2 and root[b] < root[a]:
                    root[a], changed = root[b], True
    firsts = [i for i in root if root[i] == i]
    words = lambda t: " " + " ".join(re.findall(r"\w+", t.lower())) + " "
    clean = [i for i in firsts if not any(words(b) in words(left[i]) for _, b in items)]
    assert len(clean) < len(firsts) < len(left)
    assert sorted(got) == sorted(clean)
    library = sentencepiece.SentencePieceProcessor(model_file=pieces.default_model())
    assert all(got[i].ids == library.encode(left[i], add_eos=True) and got[i].n_tokens == len(got[i].ids) for i in clean)


def test_stages_return_the_columns_of_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").limit(40)
    for _, stage in corpus_pipeline.STAGES[1:3]:
        assert stage(spark, docs, "/root/testdata/sf0.001").schema.names == docs.columns
