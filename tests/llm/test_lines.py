import random
import re

import pytest
from pyspark.sql import functions as F

from turnwise.llm import lines as L


def edit(a, b):
    """Edit distance, all of a at once in the bits of one number."""
    if not a:
        return len(b)
    at, full, last = {}, (1 << len(a)) - 1, 1 << (len(a) - 1)
    for i, c in enumerate(a):
        at[c] = at.get(c, 0) | 1 << i
    up, down, score = full, 0, len(a)
    for c in b:
        eq = at.get(c, 0)
        x = eq | down
        d = (((eq & up) + up) ^ up) | eq
        more, less = down | (~(d | up) & full), up & d
        score += bool(more & last) - bool(less & last)
        more, less = (more << 1 | 1) & full, (less << 1) & full
        up, down = less | (~(x | more) & full), more & x
    return score


def plain_norm(line):
    norm = re.sub(r"\d", "0", re.sub(r"[^\w]|_", " ", line.lower()))
    return " ".join(norm.split()) or line.strip(" ")


def similar(a, b):
    most = int(max(len(a), len(b)) * (1 - L.SIMILARITY) + 1e-9)
    return abs(len(a) - len(b)) <= most and edit(a, b) <= most


def keys_of(spark, norms):
    rows = spark.createDataFrame([(i, n) for i, n in enumerate(norms)], "doc_id long, text string")
    at, keys = {}, {}
    for x in L.occurrences(rows).collect():
        if x.at is not None:
            at[x.at.first_id] = x.key
        else:
            keys.setdefault(x.key, set()).add(x.k)
    return {n: keys.get(at[i], set()) for i, n in enumerate(norms)}


def brute(spark, rows):
    """What is left of each text by all pairs of lines; the keys on which lines meet come from Spark, all else is plain Python."""
    first = {}
    for i, text in rows:
        first[text or ""] = min(first.get(text or "", i), i)
    occ = [(i, p, plain_norm(line)) for t, i in first.items() for p, line in enumerate(t.split("\n")) if re.search(r"[^\x20\x09-\x0D]", line)]
    norms = sorted({n for _, _, n in occ})
    keys = keys_of(spark, norms)
    root = {n: n for n in norms}

    def find(n):
        while root[n] != n:
            n = root[n]
        return n

    for k, a in enumerate(norms):
        for b in norms[k + 1 :]:
            if keys[a] & keys[b] and similar(a, b):
                root[find(a)] = find(b)
    best = {}
    for i, p, n in occ:
        best[find(n)] = min(best.get(find(n), (i, p)), (i, p))
    stays = {(i, p) for i, p, n in occ if best[find(n)] == (i, p)}
    worded = {(i, p) for i, p, _ in occ}
    out = {}
    for i, t in rows:
        lines = (t or "").split("\n")
        own = first[t or ""] == i
        out[i] = "\n".join(x for p, x in enumerate(lines) if ((i, p) in stays or (i, p) not in worded if own else not re.search(r"[^\x20\x09-\x0D]", x)))
    return out


def noisy_corpus(seed=6):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdefghij") for _ in range(r.randrange(2, 8)))
    vocab = [word() for _ in range(80)]
    base = [" ".join(r.choice(vocab) for _ in range(r.choice((1, 2, 3, 6, 20, 30)))) for _ in range(18)]

    def noisy(x):
        w = x.split(" ")
        k = r.randrange(4)
        if k == 0:
            w[r.randrange(len(w))] = r.choice(vocab)
        elif k == 1:
            w.insert(r.randrange(len(w)), "12")
        elif k == 2:
            return x.upper() + "!"
        return " ".join(w)

    return [(i, "\n".join(r.choice(["", "  ", "!", *[noisy(r.choice(base)) for _ in range(6)]]) for _ in range(r.randrange(0, 9)))) for i in range(30)]


def test_equal_and_fuzzy_lines_as_by_brute_force(spark):
    rows = noisy_corpus()
    rows += [(100, None), (101, ""), (102, "long " * 300), (103, "long " * 300 + "er"), (104, rows[3][1])]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumns({c: F.lit(f"clash {c}") for c in ("key", "gone", "own_key", "own_lines", "_gone", "first_own_id")})
    got = {x.doc_id: x for x in L.dedup_lines(docs).collect()}
    want = brute(spark, rows)
    assert got[100].text is None and got[100].key == "clash key" and got[3].own_lines == "clash own_lines" and got[3].gone == "clash gone"
    for i, _ in rows:
        assert (got[i].text or "") == want[i], i
    assert sum(x.n_removed for x in got.values()) > 10


@pytest.mark.parametrize("size", [(2, 3), (4, 6), (8, 12), (14, 20), (30, 60), (150, 200)])
def test_similar_lines_meet(spark, size):
    """Recall by edit similarity alone, of lines with up to a tenth of the words replaced or a typo in short ones."""
    r = random.Random(sum(size))
    word = lambda: "".join(r.choice("etaoinshrdlu") for _ in range(r.randrange(2, 9)))
    pairs = []
    while len(pairs) < 60:
        w = [word() for _ in range(r.randrange(*size))]
        v = list(w)
        if len(w) < 8:
            k = r.randrange(len(v))
            at = r.randrange(len(v[k]))
            v[k] = v[k][:at] + r.choice("xyz") + v[k][at + 1 :]
        else:
            for _ in range(max(1, len(w) // 10)):
                v[r.randrange(len(v))] = word()
        a, b = " ".join(w), " ".join(v)
        if a != b and similar(a, b):
            pairs.append((a, b))
    keys = keys_of(spark, sorted({x for p in pairs for x in p}))
    assert sum(bool(keys[a] & keys[b]) for a, b in pairs) >= 0.9 * len(pairs)


def test_recall_on_given_lines(spark):
    """At least 0.9 of all pairs of lines of the smallest table that are similar by edits meet."""
    rows = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").distinct().collect()
    norms = sorted({plain_norm(x) for r in rows for x in (r.text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)}, key=len)
    norms = [n for n in norms if 4 < len(n) < 400]
    grams = [{n[i : i + 2] for i in range(len(n) - 1)} for n in norms]
    pairs = []
    for i, a in enumerate(norms):
        for j in range(i + 1, len(norms)):
            b = norms[j]
            most = int(len(b) * (1 - L.SIMILARITY) + 1e-9)
            if len(b) - len(a) > most:
                break
            # an edit changes two grams at most
            if len(grams[i] - grams[j]) <= 2 * most and len(grams[j] - grams[i]) <= 2 * most and len(grams[i] & grams[j]) > len(grams[i]) // 2 and edit(a, b) <= most:
                pairs.append((a, b))
    assert len(pairs) > 10
    keys = keys_of(spark, sorted({x for p in pairs for x in p}))
    assert sum(bool(keys[a] & keys[b]) for a, b in pairs) >= 0.9 * len(pairs)


def test_similar_lines_without_a_common_third_of_words(spark):
    """A typo in most words leaves few of them in common, but the characters are similar."""
    r = random.Random(5)
    word = lambda n: "".join(r.choice("etaoinshrdlu") for _ in range(n))
    w = [word(9) for _ in range(24)]
    v = w[:6] + [x[:4] + "z" + x[5:] for x in w[6:]]
    a, b = " ".join(w), " ".join(v)
    assert similar(a, b) and 3 * len(set(w) & set(v)) < len(set(w))
    norm = spark.createDataFrame([(1, a), (2, b)], "key long, norm string").withColumn("pieces", L.pieces())
    assert L._verified(spark.createDataFrame([(1, 2)], "a long, b long"), norm).count() == 1


def test_every_block_is_a_key_where_asked(spark):
    """With keys=None no block of a long line is left out, and pairs are found by these keys alone."""
    r = random.Random(11)
    word = lambda: "".join(r.choice("etaoinshrdlu") for _ in range(r.randrange(5, 9)))
    w = [word() for _ in range(240)]
    docs = spark.createDataFrame([(1, " ".join(w))], "doc_id long, text string")
    ten = {x.k for x in L.occurrences(docs).where("k IS NOT NULL").collect()}
    every = {x.k for x in L.occurrences(docs, keys=None).where("k IS NOT NULL").collect()}
    assert ten < every and len(every) > 2 * len(ten)
    two = spark.createDataFrame([(1, " ".join(w)), (2, " ".join([*w[:100], "other", *w[101:]]))], "doc_id long, text string")
    removed = lambda keys: [x.n_removed for x in L.dedup_lines(two, keys=keys).orderBy("doc_id").collect()]
    assert removed(None) == [0, 1] and removed(0) == [0, 0]


def test_pairs_that_meet_after_the_tenth_block_are_found(spark, tmp_path):
    """op7 and the pipeline's line stage use every block: lines that share none of the first ten still meet."""
    from corpus_pipeline import drop_repeated_lines

    r = random.Random(2)
    word = lambda: "".join(r.choice("etaoinshrdlu") for _ in range(r.randrange(5, 9)))
    rows = []
    while len(rows) < 40:
        w = [word() for _ in range(280)]
        v = list(w)
        for k in r.sample(range(280), 36):
            v[k] = word()
        a, b = " ".join(w), " ".join(v)
        if similar(a, b):
            rows += [(len(rows), a), (len(rows) + 1, b)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("n_chars", F.length("text"))
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    few = sum(x.n_removed for x in L.dedup_lines(docs).collect())
    got = sum(x.n_removed for x in L.op7_fuzzy_lines(spark, str(tmp_path)).collect())
    staged = drop_repeated_lines(spark, docs, str(tmp_path)).where("text = ''").count()
    assert few < got == staged == 20


def test_edits_are_counted_by_characters(spark):
    """The quick count agrees with Spark's also beyond the basic plane, where a character is two units."""
    r = random.Random(4)
    line = lambda: "".join(r.choice("ab é中😀") for _ in range(r.randrange(0, 12)))
    rows = [(line(), line(), r.randrange(6)) for _ in range(400)]
    got = spark.createDataFrame(rows, "a string, b string, most int").selectExpr(f"{L.within('a', 'b', 'most')} AS near", "levenshtein(a, b) <= most AS true_near", "a", "b", "most").collect()
    assert {x.near for x in got} == {True, False}
    assert all(x.near == x.true_near == (edit(x.a, x.b) <= x.most) for x in got)


def test_rows_that_repeat_an_id(spark):
    docs = spark.createDataFrame([(1, "first line of the text\nshared by both rows"), (1, "unique line one two three four\nshared by both rows"), (2, "shared by both rows"), (2, "shared by both rows"), (None, "only here\n\nshared by both rows")], "doc_id long, text string")
    got = sorted((x.doc_id or 0, x.text) for x in L.dedup_lines(docs).collect())
    assert sum("shared by both rows" in t for _, t in got) == 1
    assert {t.split("\n")[0] for i, t in got if i == 1} == {"first line of the text", "unique line one two three four"}
    assert [t for i, t in got if i == 2] == ["", ""] and got[0][1].startswith("only here")


def test_extreme_lines(spark):
    rows = [(1, "a " * 40_000), (2, "b"), (3, "éè 中文 " * 20), (4, "!!!\n???"), (5, "12345"), (6, "98765"), (7, "x" * 50_000), (8, "😀")]
    got = {x.doc_id: x.text for x in L.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == dict(rows) | {6: ""}


def test_empty_table(spark):
    assert L.dedup_lines(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_components_on_the_driver_as_by_contractions(spark, monkeypatch):
    from turnwise.llm import common as C

    r = random.Random(8)
    rows = [(r.randrange(-300, 300), r.randrange(-300, 300)) for _ in range(260)] + [(5, 5), (2**62, -(2**63)), (None, 3), (1, 2), (2, 1)]
    links = spark.createDataFrame(rows, "a long, b long")
    few = sorted(map(tuple, C.components(links).collect()))
    monkeypatch.setattr(C, "FEW_LINKS", -1)
    assert few == sorted(map(tuple, C.components(links).collect())) and len(few) > 100
    assert C.components(links.limit(0)).count() == 0
    monkeypatch.undo()
    assert C.components(links.limit(0)).count() == 0


def test_members_of_a_group_are_not_all_compared(spark, monkeypatch):
    """Lines near many of a group join it after a few comparisons; the groups are those of all pairs that meet."""
    r = random.Random(3)
    word = lambda: "".join(r.choice("etaoinshrdlu") for _ in range(r.randrange(5, 9)))
    base = [word() for _ in range(60)]

    def near(share):
        return " ".join(word() if r.random() < share else w for w in base)

    norms = sorted({near(0.1 + 0.12 * r.random()) for _ in range(300)} | {" ".join([*base[:20], *(word() for _ in range(40))]) for _ in range(6)})
    docs = spark.createDataFrame(list(enumerate(norms)), "doc_id long, text string")
    compared, verified = [], L._verified

    def counted(pairs, *args):
        compared.append(pairs.count())
        return verified(pairs, *args)

    monkeypatch.setattr(L, "_verified", counted)
    got = {x.doc_id: x.n_removed for x in L.dedup_lines(docs, keys=None).collect()}
    keys = {}
    for x in L.occurrences(docs, keys=None).collect():
        if x.at is not None:
            keys.setdefault(x.key, [x.at.first_id, set()])[0] = x.at.first_id
    for x in L.occurrences(docs, keys=None).where("k IS NOT NULL").collect():
        keys[x.key][1].add(x.k)
    of = dict(keys.values())
    root = list(range(len(norms)))

    def find(n):
        while root[n] != n:
            n = root[n]
        return n

    met = [(i, j) for j in range(len(norms)) for i in range(j) if of[i] & of[j]]
    for i, j in met:
        if find(i) != find(j) and similar(norms[i], norms[j]):
            root[max(find(i), find(j))] = min(find(i), find(j))
    assert got == {i: int(find(i) != i) for i in range(len(norms))}
    # 15,124 where all pairs between the groups of the first round are compared at once
    assert sum(compared) < 10_000


def test_bags_rule_out_no_similar_pair_and_many_others(spark):
    """Pairs that open_pairs leaves out by the counts of characters are never within their edits; equal keys alone don't pair lines."""
    r = random.Random(7)
    line = lambda letters: "".join(r.choice(letters) for _ in range(r.randrange(8, 60)))
    norms = set()
    for letters in ("ab ", "etaoin shrdlu", "abcdefgh 0", "éßñ 中a", "xyzé😀 "):
        for _ in range(12):
            a = line(letters)
            b = list(a)
            for _ in range(r.randrange(len(a) // 3)):
                b[r.randrange(len(b))] = r.choice(letters)
            norms |= {a.strip(), "".join(b).strip()}
    norms = sorted(norms | {"e" * 70_000, "e" * 90_000, "e" * 66_000 + "z" * 20_000})
    norm = spark.createDataFrame(list(enumerate(norms)), "key long, norm string")
    mixed = spark.createDataFrame([(1, i, len(x), i) for i, x in enumerate(norms)], "k long, key long, size int, root long")
    got = {(x.a, x.b) for x in L.open_pairs(mixed, norm).collect()}
    by_length = {(i, j) for j, b in enumerate(norms) for i, a in enumerate(norms[:j]) if abs(len(a) - len(b)) <= int(max(len(a), len(b)) * (1 - L.SIMILARITY) + 1e-9)}
    short = {(i, j) for i, j in by_length if len(norms[i]) < 100}
    near = {(i, j) for i, j in short if similar(norms[i], norms[j])}
    assert got < by_length and near <= got and len(near) > 20 and len(got) < 0.6 * len(by_length)
    bags = lambda x: [sum(1 for c in x if c == k) for k in L.COUNTED] + [sum(1 for c in x if c not in L.COUNTED)]
    for i, j in short:
        a, b = bags(norms[i]), bags(norms[j])
        most = int(max(sum(a), sum(b)) * (1 - L.SIMILARITY) + 1e-9)
        assert ((i, j) in got) == (max(sum(max(x - y, 0) for x, y in zip(a, b)), sum(max(y - x, 0) for x, y in zip(a, b))) <= most)
    at = {x: i for i, x in enumerate(norms)}
    assert tuple(sorted((at["e" * 70_000], at["e" * 66_000 + "z" * 20_000]))) not in got
