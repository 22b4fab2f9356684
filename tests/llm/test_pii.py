import random
import re

from turnwise.llm import pii


def plain(text):
    """The base kinds as the patterns say, by re alone."""
    out = []
    for kind, pattern in (("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")):
        for m in re.finditer(pattern, text):
            digits = re.sub(r"[^0-9]", "", m.group())
            if kind == "ip" and any(int(x) > 255 for x in m.group().split(".")):
                continue
            if kind == "card":
                total = 0
                for i, d in enumerate(reversed(digits)):
                    v = int(d) * (1 + i % 2)
                    total += v - 9 if v > 9 else v
                if not 12 <= len(digits) <= 19 or total % 10:
                    continue
            if kind == "phone" and not 9 <= len(digits) <= 15:
                continue
            out.append((m.start(), m.end(), kind))
    return sorted(out, key=lambda x: (x[0], pii.KINDS.index(x[2])))


def test_base_spans_equal_the_plain_patterns():
    r = random.Random(1)
    for _ in range(6000):
        x = "".join(r.choice(["a", "b.", "@", "@x.y", "1", "23", ".4", " ", "-", "+", "+1 (", ")", "é", "256", "4111 1111 1111 1111", "4111111111111111", "\n", "c.d@e-f.g"]) for _ in range(r.randrange(1, 14)))
        assert pii.base_spans(x) == plain(x), repr(x)


def test_contexts_of_confident_seeds_add_unseen_identifiers(spark):
    rows = [(i, f"text number {i} write to user{i}@mail.example.org about it") for i in range(12)]
    rows += [(100, "please write to user77(at)mail now"), (101, "she saw order77at now"), (102, None), (103, ""), (104, "x" * 5000 + " 12")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumnRenamed("doc_id", "doc_id")
    got = {r.id: r for r in pii.extract(docs).collect()}
    assert len(got) == len(rows)
    assert [(s.start, s.end, s.kind) for s in got[100].added] == [(16, 30, "email")]
    assert not any(got[i].added for i in got if i != 100)
    assert all(len(got[i].base) == 1 for i in range(12)) and got[102].base == got[103].base == []


def test_numbers_of_any_length():
    assert pii.base_spans("0" * 5000 + "1.2.3.4") == [(0, 5007, "ip")]
    assert pii.base_spans("9" * 5000 + ".2.3.4") == [] and pii.base_spans("1." * 3000 + "1") == plain("1." * 3000 + "1")


def test_identifiers_with_spaces_and_keys_of_unknown_formats_are_found(spark):
    digits = lambda i, n: "".join(str((i * 7 + k * 3) % 10) for k in range(n))
    rows = [(i, f"on day {i} please call me at +1 ({digits(i, 3)}) 555-{digits(i, 4)} or pay with card {4000000000000002 + 10 * i} set api token {digits(i, 8)}{'abcdef' * 5}{i:02d} end") for i in range(14)]
    rows += [(100, "but call me at (017) 555-7713 please"), (101, "set api token Zx91-plk2-unknown now"), (102, "at (017) 555-7713 he said"), (103, "pay with card 4111 1111 1111 1112 soon")]
    got = {r.id: r for r in pii.extract(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    spans = lambda i: [(rows[[x for x, _ in rows].index(i)][1][s.start : s.end], s.kind) for s in got[i].added]
    assert spans(100) == [("(017) 555-7713", "phone")] and spans(102) == []
    assert spans(101) == [("Zx91-plk2-unknown", "secret")]
    assert all(("secret" in [s.kind for s in got[i].added]) for i in range(14))


def test_planted_unseen_identifiers_are_mostly_found(spark):
    """Recall and precision of what the contexts add, on misspelt addresses after the usual words and the same words elsewhere."""
    r = random.Random(3)
    words = ["".join(r.choice("aeioulmnrst") for _ in range(5)) for _ in range(60)]
    say = lambda n: " ".join(r.choice(words) for _ in range(n))
    rows, planted = [], set()
    for i in range(300):
        odd = i % 5 == 0
        name = f"{r.choice(words)}{r.randrange(100, 999)}" + ("(at)mail" if odd else "@mail.example")
        rows.append((i, f"{say(20)} reach us: {name} {say(20)} item no{r.randrange(100, 999)}x {say(5)}"))
        planted |= {i} if odd else set()
    got = {x.id: [s.kind for s in x.added] for x in pii.extract(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    found = {i for i, k in got.items() if k}
    assert len(found & planted) >= 0.9 * len(planted) and not found - planted


def test_context_totals_are_exact(spark):
    r = random.Random(2)
    texts = [" ".join(r.choice("red blue green token =".split()) for _ in range(60)) for _ in range(40)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = {}
    for x in texts:
        w = x.split()
        for a, b in zip(w[:-2], w[1:-1]):
            want[pii.context_key(a, b)] = want.get(pii.context_key(a, b), 0) + 1
    pairs = [(a, b) for a in "red blue".split() for b in "green token =".split()]
    contexts = spark.createDataFrame([(pii.context_key(a, b), int(pii._bits([a, b])[0])) for a, b in pairs], "context long, bit long")
    got = {r.context: r.total for r in pii.context_totals(docs, contexts).collect()}
    assert all(got[pii.context_key(a, b)] == want[pii.context_key(a, b)] for a, b in pairs)


def test_empty_table(spark):
    assert pii.extract(spark.createDataFrame([], "doc_id long, text string")).count() == 0
