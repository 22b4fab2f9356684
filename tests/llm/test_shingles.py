import random

import corpus_pipeline
from turnwise.llm import shingles


def jaccard(a, b):
    x, y = ({tuple(t.lower().split()[i : i + 5]) for i in range(max(1, len(t.split()) - 4))} for t in (a, b))
    return len(x & y) / len(x | y)


def test_near_copies_of_similarity_0_8_leave_the_corpus_and_nothing_else(spark):
    r = random.Random(2)
    vocab = ["".join(r.choice("abcdefghijkl") for _ in range(r.randrange(3, 8))) for _ in range(2000)]
    docs = [(i, [r.choice(vocab) for _ in range(r.randrange(150, 500))]) for i in range(60)]
    for i in range(60):
        words = list(docs[i][1])
        for _ in range(round(len(words) * r.choice((0.002, 0.005, 0.01, 0.02, 0.05)))):
            words[r.randrange(len(words))] = r.choice(vocab)
        docs.append((100 + i, words))
    chain = list(docs[0][1])  # a group whose ends are less alike than 0.8
    for k in range(12):
        chain[k * 9] = "changed"
        docs.append((300 + k, list(chain)))
    docs = [(i, " ".join(w)) for i, w in docs] + [(500, "short text"), (501, "short text"), (502, "other text"), (503, None), (504, "")]
    root = {i: i for i, _ in docs}
    linked, moved = [(a, b) for k, (a, s) in enumerate(docs) for b, t in docs[k + 1 :] if jaccard(s or "", t or "") >= 0.8], True
    while moved:
        moved = False
        for a, b in linked:
            low = min(root[a], root[b])
            moved |= root[a] != low or root[b] != low
            root[a] = root[b] = low
    assert 40 < len(linked)
    frame = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in docs], "doc_id long, text string, lang string, source string, n_chars long")
    kept = {x.doc_id for x in corpus_pipeline.drop_near_copies(spark, frame, "").collect()}
    assert kept == {i for i in root if root[i] == i}


def test_empty_table(spark):
    assert shingles.near_copies(spark.createDataFrame([], "doc_id long, text string")).count() == 0
