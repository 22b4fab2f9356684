import random

import pytest
import xxhash

from turnwise.llm import simhash as s


def plain_fingerprint(text):
    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    words = [w for w in __import__("re").split(r"[\x20\x09-\x0D]+", low) if w]
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute(rows, radius=2):
    fp = [(i, plain_fingerprint(t)) for i, t in rows]
    label = {f: min(i for i, g in fp if g == f) for _, f in fp}
    while True:
        new = {f: min(label[g] for g in label if (f ^ g).bit_count() <= radius) for f in label}
        if new == label:
            return sorted((i, f, label[f]) for i, f in fp)
        label = new


def test_components_as_by_brute_force(spark):
    r = random.Random(9)
    words = ["".join(r.choice("abcdeÉ") for _ in range(r.randrange(1, 6))) for _ in range(40)]
    base = [[r.choice(words) for _ in range(r.choice((1, 2, 3, 8, 60, 400)))] for _ in range(25)]
    rows = []
    for i in range(220):
        w = list(r.choice(base))
        for _ in range(r.randrange(0, 3)):
            w[r.randrange(len(w))] = r.choice(words)
        rows.append((1000 - i, r.choice((" ", "  \n", "\t")).join(w)))
    rows += [(5, None), (6, ""), (7, " \n"), (8, "A b"), (9, "a  B"), (10, "Ä b"), (11, "x " * 70_000), (12, "x " * 70_001)]
    got = s.near_duplicates(spark.createDataFrame([(*x, "f", "c") for x in rows], "doc_id long, text string, fp string, component_id string"))
    got = sorted((x.id, x.fp & (1 << 64) - 1, x.component_id) for x in got.collect())
    assert got == brute(rows)
    assert len({c for *_, c in got}) < len({f for _, f, _ in got}) - 2


@pytest.mark.parametrize("radius", [1, 2, 3])
def test_pivots_and_bands_miss_no_pair(spark, radius):
    r = random.Random(radius)
    fps = {r.getrandbits(64) for _ in range(60)}
    for f in list(fps):
        for _ in range(4):
            g = f
            for b in r.sample(range(64), r.randrange(1, radius + 2)):
                g ^= 1 << b
            fps.add(g)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    got = {tuple(x) for x in s.fingerprint_links(spark.createDataFrame([(signed(x),) for x in fps], "fp long"), radius).collect()}
    want = {tuple(sorted((signed(a), signed(b)))) for a in fps for b in fps if a < b and (a ^ b).bit_count() <= radius}
    assert got == want


def test_repeated_ids_and_empty_table(spark):
    got = s.near_duplicates(spark.createDataFrame([(1, "a b c d"), (1, "a b c d"), (1, "other words here now")], "doc_id long, text string")).collect()
    assert len(got) == 3 and {x.component_id for x in got} == {1}
    assert s.near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0
