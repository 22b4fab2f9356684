import random

from turnwise.llm import warc
from turnwise.llm.common import new_path


def brute(rows):
    payload = {i: (h or "").encode() for i, _, h in rows}
    best = {}
    for i, p in payload.items():
        best[p] = max(i, best.get(p, i))
    return sorted((i, len(p), warc.payload_digest(p), "response" if best[p] == i else "revisit", None if best[p] == i else best[p]) for i, p in payload.items())


def made(spark, rows):
    folder = new_path(spark, "archive")
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    directory = warc.build_index(warc.write_archives(warc.with_referrals(pages), folder), folder, 3)
    return folder, directory, warc.read_records(warc.find_captures(warc.with_keys(pages), directory, folder), folder)


def test_round_trip_equals_brute_force(spark):
    r = random.Random(4)
    rows = [(i, f"http://www.s{i % 7}.example.org/p/{i % 50}?q={i % 3}", r.choice(["<p>same</p>", f"<p>é {i}</p>", "", None, "x\r\n\r\ny" * (i % 5)])) for i in range(1500)]
    rows += [(5000, None, "a" * 300_000), (5001, "not a url", "<b>"), (5002, "http://[bad", "<i>")]
    _, directory, records = made(spark, rows)
    assert directory.count() >= 3
    assert sorted(map(tuple, records.collect()), key=lambda x: x[0]) == brute(rows)


def test_repeated_and_missing_ids_and_clashing_columns(spark):
    rows = [(1, "http://a.example/", "x"), (1, "http://a.example/", "x"), (1, "http://b.example/", "y"), (None, None, "x"), (None, "http://a.example/", None), (2, None, "z")]
    folder = new_path(spark, "archive")
    pages = spark.createDataFrame([(*r, "k", 1) for r in rows], "page_id long, url string, html string, key string, first int")
    directory = warc.build_index(warc.write_archives(warc.with_referrals(pages), folder), folder, 2)
    got = warc.read_records(warc.find_captures(warc.with_keys(pages), directory, folder), folder).collect()
    assert len(got) == len(rows) and {r.record_type for r in got} == {"response"}
    assert sorted((r.page_id or 0, r.payload_bytes) for r in got) == [(0, 0), (0, 1), (1, 1), (1, 1), (1, 1), (2, 1)]


def test_equal_captures_over_many_blocks(spark):
    rows = [(7, "http://hot.example/", f"<p>{i}</p>") for i in range(2000)] + [(i, "http://hot.example/", f"{i}") for i in range(100, 900)]
    _, _, records = made(spark, rows)
    assert records.count() == 2800 and records.where("page_id = 7").count() == 2000


def test_lookup_reads_only_blocks_that_can_hold_the_key(spark):
    rows = [(i, f"https://a{i % 40}.example.net/x/{i % 300}", f"<p>{i}</p>") for i in range(4000)]
    folder, directory, _ = made(spark, rows)
    index = warc.CaptureIndex(directory.collect(), folder)
    for n in (0, 7, 39):
        url = f"https://a{n}.example.net/x/{n}"
        want = sorted(i for i, u, _ in rows if u == url)
        assert sorted(int(x[1]) for x in index.lines(warc.url_key(url))) == want
        assert sorted(body.decode() for _, body in index.records(url)) == sorted(f"<p>{i}</p>" for i in want)
    assert len(index.lines("net,example,a3)", prefix=True)) == sum(u.startswith("https://a3.") for _, u, _ in rows)
    assert index.lines("zz,none)/") == []


def test_url_keys():
    assert warc.url_key("HTTP://WWW.B.Example.com:8080/A?B=1#c") == "com,example,b:8080)/a?b=1"
    assert warc.url_key(None) == warc.url_key("x y") == "-"


def test_empty_table(spark):
    _, directory, records = made(spark, [])
    assert directory.count() == 0 and records.count() == 0
