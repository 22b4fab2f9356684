import random
import re

from pyspark.sql import functions as F

from turnwise.llm import quality as q


def plain(text):
    text = text or ""
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", text) if w]
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    seen = {w: windows.count(w) for w in set(windows)}
    repeated = {k for i, w in enumerate(windows) if seen[w] > 1 for k in (i, i + 1, i + 2)}
    return dict(n_words=len(words), word_chars=sum(map(len, words)), n_symbols=len(re.findall(r"[#*$%&|<>]", text)), n_dup_lines=len(lines) - len(set(lines)), n_repeat_words=len(repeated), n_lines=len(lines), n_marks=text.count("!"))


def texts(seed=3):
    r = random.Random(seed)
    out = [None, "", " \n\t", "a", "a b", "a b a b a b", "x\ny\nx\n\nx", "é 中 \u00a0 #!", "w " * 20_000, "$" * 5000, "one two three " * 40]
    for _ in range(60):
        out.append("".join(r.choice(["a", "b", "cc ", " ", "\n", "# ", "! ", "dd ee ", "é"]) for _ in range(r.randrange(0, 300))))
    return out


def test_measurements_failures_and_verdicts_as_by_brute_force(spark):
    rows = [(i, t, i) for i, t in enumerate(texts())] + [(3, "a", 9), (None, "b", 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_words long").withColumns({"failures": F.lit("x"), "own": F.lit("kept")})
    got = q.ledger(docs).collect()
    assert len(got) == len(rows) and {r.own for r in got} == {"kept"}
    rules = [lambda m: m["n_words"] < 50, lambda m: 100 * m["n_repeat_words"] > 50 * m["n_words"], lambda m: 10 * m["n_symbols"] > m["n_words"], lambda m: 2 * m["n_dup_lines"] > m["n_lines"], lambda m: 2 * m["word_chars"] < 5 * m["n_words"], lambda m: m["word_chars"] > 12 * m["n_words"], lambda m: 10 * m["n_marks"] > 3 * m["n_words"], lambda m: m["n_words"] > 100_000]
    for r in got:
        m = plain(r.text)
        assert {k: r[k] for k in m} == m, r.text
        assert r.failures == sum(1 << b for b, rule in enumerate(rules) if rule(m))


def test_ablation_as_by_counting(spark):
    rows = q.ledger(spark.createDataFrame(list(enumerate(texts(8))), "doc_id long, text string")).select("failures")
    masks = [r.failures for r in rows.collect()]
    bit = {r.name: 1 << r.bit for r in q.RULES}
    got = q.ablation(rows).collect()
    assert {(r.policy, r.rule) for r in got} == {(p, x) for p, names in q.POLICIES.items() for x in names}
    for r in got:
        whole, one = q.policy_mask(r.policy), bit[r.rule]
        want = (len(masks), sum(bool(m & one) for m in masks), sum(m & whole == one for m in masks), sum(m & whole == 0 for m in masks), sum(m & (whole & ~one) == 0 for m in masks))
        assert (r.n_rows, r.fails, r.fails_alone, r.kept, r.kept_without) == want


def test_empty_table(spark):
    rows = q.ledger(spark.createDataFrame([], "doc_id long, text string"))
    assert rows.count() == 0 and q.ablation(rows).count() == 0
