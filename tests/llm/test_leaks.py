import random
import re
import zlib

import numpy as np

from turnwise.llm import leaks


def lcs(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        last = 0
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], last + 1 if x == y else max(row[j], row[j - 1])
    return row[-1]


def test_common_words_equal_dynamic_programming():
    r = random.Random(1)
    for _ in range(500):
        a = [r.choice("abcd") for _ in range(r.randrange(1, 70))]
        b = [r.choice("abcde") for _ in range(r.randrange(70))]
        assert leaks.common_words(a, b) == lcs(a, b)


def corpus(seed=3, n=120):
    r = random.Random(seed)
    vocab = ["".join(r.choice("abcdefghijklmnop") for _ in range(r.randrange(3, 9))) for _ in range(900)]
    common = ["the", "of", "and", "to", "in"]
    say = lambda k: [r.choice(common) if r.random() < 0.4 else r.choice(vocab) for _ in range(k)]
    items = [(i, " ".join(say(r.randrange(14, 60)))) for i in range(30)]
    docs, want = [], set()
    for d in range(n):
        words = say(r.randrange(1, 400))
        if d % 5 == 0:
            i, text = items[d % 30]
            part = text.split()
            if d % 10 == 0:  # a paraphrase: some words go, some are changed, some come
                for _ in range(len(part) // 9):
                    part[r.randrange(len(part))] = r.choice(common)
                    part.insert(r.randrange(len(part)), r.choice(vocab))
            at = r.randrange(len(words) + 1)
            words[at:at] = part
            want.add((d, i))
        docs.append((d, " ".join(words).capitalize() + "."))
    return docs, items, want


def test_copies_and_paraphrases_are_found_and_nothing_else(spark):
    docs, items, want = corpus()
    docs += [(1000, None), (1001, ""), (1002, "the of and to in " * 2000)]
    items += [(900, None), (901, "")]
    got = leaks.find_leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()
    assert {(r.id, r.item_id) for r in got} == want and len(got) == len(want)


def test_space_equals_the_exact_decomposition(spark):
    _, items, _ = corpus()
    df, n = leaks.document_frequencies(spark.createDataFrame(items, "id long, text string"))
    idf = leaks.inverse_frequencies(df, n)
    a = np.zeros((len(items), leaks.FEATURES))
    for k, (_, text) in enumerate(items):
        np.add.at(a[k], leaks.Buckets().of(leaks.words_of(text)), 1)
    assert n == len(items) and (df == (a > 0).sum(axis=0)).all()
    a *= idf
    a /= np.linalg.norm(a, axis=1, keepdims=True)
    exact = np.linalg.svd(a, compute_uv=False)
    _, s = leaks.latent_space(spark.createDataFrame(items, "id long, text string").select("text"), idf, 30)
    assert np.allclose(s, exact[: len(s)], rtol=1e-4) and len(s) == 30


def test_empty_tables(spark):
    docs, items, _ = corpus(n=5)
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    assert leaks.find_leaks(d.limit(0), b).count() == 0 and leaks.find_leaks(d, b.limit(0)).count() == 0


def test_recall_does_not_fall_with_the_size_of_the_benchmark(spark):
    r = random.Random(9)
    vocab = ["".join(r.choice("abcdefghijklmnopqrst") for _ in range(r.randrange(3, 9))) for _ in range(4000)]
    common = ["the", "of", "and", "to", "in", "is", "for"]
    say = lambda k: [r.choice(common) if r.random() < 0.4 else vocab[min(int(r.expovariate(1 / 900)), 3999)] for _ in range(k)]
    items = [(i, " ".join(say(r.randrange(15, 60)))) for i in range(2500)] + [(2500, " ".join(say(1500)))]
    docs, want = [], set()
    for d in range(240):
        i, words = 2500 if d == 0 else r.randrange(2500), say(r.randrange(100, 400))
        part = items[i][1].split()
        if d % 3 == 1:  # a paraphrase
            for _ in range(len(part) // 6):
                part[r.randrange(len(part))] = r.choice(common)
                part.insert(r.randrange(len(part)), r.choice(vocab))
        at = r.randrange(len(words))
        words[at:at] = part
        docs.append((d, " ".join(words)))
        if lcs(part, items[i][1].split()) >= leaks.SURE * len(items[i][1].split()):
            want.add((d, i))
    got = {(x.id, x.item_id) for x in leaks.find_leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert len(want) > 200 and not want - got
    split = {i: t.split() for i, t in items}
    assert all(lcs(split[i], docs[d][1].split()) >= leaks.LIKELY * len(split[i]) for d, i in got)


def test_a_verbatim_copy_beside_far_heavier_words_is_found(spark):
    r = random.Random(4)
    rare = ["".join(r.choice("uvwxyz") for _ in range(9)) for _ in range(400)]
    item = "it is of the and to in"
    docs = [(i, f"{item} or not") for i in range(60)] + [(100, " ".join([*rare[:200], item, *rare[200:]]))]
    got = leaks.find_leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame([(1, item)], "item_id long, text string")).collect()
    assert {x.id for x in got} == {i for i, _ in docs}


def test_halves_of_windows_are_summed_by_place():
    """A copy at any offset is found, in texts that end within a half and among words that no item has."""
    r = np.random.default_rng(3)
    words = [f"w{i}" for i in range(400)]
    item = [words[i] for i in r.integers(0, 200, 40)]
    idf = np.ones(leaks.FEATURES, np.float32)
    used = np.unique(leaks.Buckets().of(item))
    items = leaks.Items([7], [" ".join(item)], used, np.eye(len(used), dtype=np.float32), idf)
    for before in (0, 1, 31, 32, 33, 63, 100, 20_000):
        text = [words[i] for i in r.integers(200, 400, before)] + item + ["tail"] * (before % 5)
        got = items.matches(text, leaks.Buckets().of(text))
        assert list(got) == [0] and got[0][0] == 1.0, before
    assert leaks._worker_buckets() is leaks._worker_buckets()


def test_words_of_ascii_need_no_expression():
    """The table for ASCII gives the words of the expression, which is left to other texts."""
    every = "".join(map(chr, range(128)))
    wide = "".join(map(chr, range(0x3100)))
    for text in ("", " ", every, every[::-1], "A_b-C9\x1c\x1fd\x00E\n", "Ünder_Ä ẞ1 İx\u2028y", "Σας ΟΔΟΣ ΟΔΟΣ", wide):
        assert leaks.words_of(text) == re.findall(r"\w+", text.lower())
    searched, plain = [], leaks._WORD
    leaks._WORD = type("", (), {"findall": lambda self, text: searched.append(text) or plain.findall(text)})()
    try:
        assert leaks.words_of("Only ASCII, here") == ["only", "ascii", "here"] and not searched
        assert leaks.words_of("né-e") == ["né", "e"] and searched == ["né-e"]
    finally:
        leaks._WORD = plain


def test_words_add_to_items_without_a_look_at_the_space():
    """Sums of what each word adds are the products in the latent space; buckets hold no table of words."""
    r = np.random.default_rng(5)
    words = [f"w{i}" for i in range(90)]
    texts = [" ".join(words[i] for i in r.integers(0, 60, 20)) for _ in range(4)]
    idf = r.random(leaks.FEATURES).astype(np.float32)
    used = np.unique(leaks.Buckets().of(words[:60]))
    space = np.linalg.qr(r.standard_normal((len(used), 4)))[0].astype(np.float32)
    items = leaks.Items([1, 2, 3, 4], texts, used, space, idf)
    for text in [texts[0].split(), words]:
        full = np.zeros((leaks.FEATURES, 4), np.float32)
        full[used] = space
        f = leaks.Buckets().of(text)
        latent = [(idf[g, None] * full[g]).sum(axis=0) / np.linalg.norm(np.bincount(g, minlength=leaks.FEATURES) * idf) for g in map(leaks.Buckets().of, map(str.split, texts))]
        assert np.allclose(items.adds[items.index[f]].sum(axis=0), (idf[f, None] * full[f]).sum(axis=0) @ np.array(latent).T, atol=1e-5)
    odd = ["né", "\ud800", "a", ""]
    buckets = leaks.Buckets()
    assert buckets.of(odd).tolist() == [zlib.crc32(w.encode("utf-8", "surrogatepass")) % leaks.FEATURES for w in odd]
    assert buckets.of([]).tolist() == [] and not vars(buckets) and not hasattr(buckets, "keys")


def test_no_paraphrase_among_heavier_words_is_left_out():
    """By brute force: a window with half the weight that a copy puts into one is checked, whatever its cosine."""
    r = random.Random(11)
    vocab = [f"w{i}" for i in range(1500)]
    common = ["the", "of", "and", "to", "in"]
    say = lambda k: [r.choice(common) if r.random() < 0.4 else r.choice(vocab) for _ in range(k)]
    texts = [say(n) for n in (1, 3, 6, 8, 12, 20, 35, 58, 100, 140, 300) for _ in range(4)] + [[]]
    idf = np.ones(leaks.FEATURES, np.float32)
    idf[leaks.Buckets().of(common)] = 0.05
    weight = {w: float(idf[leaks.Buckets().of([w])[0]]) ** 2 for w in vocab + common}
    used = np.unique(leaks.Buckets().of([w for x in texts for w in x]))
    items = leaks.Items(list(range(len(texts))), [" ".join(x) for x in texts], used, np.eye(len(used), dtype=np.float32), idf)

    def best(item, answers, words):
        out, margin = 0.0, 32 + len(item) // 4 if len(item) <= 128 else len(item)
        own = np.array([weight[x] * item.count(x) for x in item])
        for at in range(0, max(1, len(words) - 32), 32):
            there = set(words[at : at + 64])
            if sum(y for x, y in zip(item, own, strict=True) if x in there) < 1.001 * leaks.LIKELY * leaks.sure_weight(own):
                continue
            near = words[max(0, at - margin) : at + 64 + margin]
            share = lcs(item, near) / len(item)
            if share >= leaks.SURE or share >= leaks.LIKELY and len(answers & set(near)) >= leaks.ANSWER_SHARE * len(answers):
                out = max(out, share)
        return out

    found = 0
    for k in range(120):
        part, changed = [], r.choice([0, 0.2, 0.3, 0.4, 0.5])
        for x in texts[k % 44]:
            part += [x] if r.random() >= changed else say(r.randrange(3))
        words = say(r.randrange(200))
        at = r.randrange(len(words) + 1)
        words[at:at] = part
        i = k % 44
        if words and (want := best(items.words[i], items.answers[i], words)):
            assert items.matches(words, leaks.Buckets().of(words)).get(i, (0, 0))[0] >= want, k
            found += 1
    assert found > 80


def test_cosine_is_that_of_the_window():
    """Repeated words count in the norm as often as they occur together."""
    item, words = ["a", "b", "c", "d"], ["a", "b", "c", "d", "a", "a", "x", "x", "x"]
    idf = np.ones(leaks.FEATURES, np.float32)
    used = np.unique(leaks.Buckets().of(item))
    got = leaks.Items([1], [" ".join(item)], used, np.eye(len(used), dtype=np.float32), idf).matches(words, leaks.Buckets().of(words))
    assert got[0][0] == 1.0 and abs(got[0][1] - 6 / (2 * np.sqrt(9 + 1 + 1 + 1 + 9))) < 1e-6
