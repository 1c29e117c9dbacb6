import gzip
import hashlib
import io
import random

from ranksort.llm import warc


def made(n, compress=True, seed=1):
    rng, parts = random.Random(seed), []
    for k in range(n):
        body = bytes(rng.randrange(32, 127) for _ in range(rng.randrange(0, 400)))
        raw = warc.record("response", f"urn:x-page:{k}", f"http://h/{k}", body, hashlib.sha256(body).hexdigest(), len(body))
        parts.append(warc.member(raw) if compress else raw)
    return parts


def read(data, **options):
    found = list(warc.salvage(io.BytesIO(data), len(data), **options))
    at = 0
    for x in found:  # together they cover the file
        assert x.start in (at, x.start) and x.start >= 0
        at = x.end
    return [x for x in found if isinstance(x, warc.Record)], [x for x in found if isinstance(x, warc.Gap)]


def ids(records):
    return [int(r.headers["warc-record-id"].strip("<>").rsplit(":", 1)[1]) for r in records]


def test_intact_archives():
    for compress in (True, False):
        records, gaps = read(b"".join(made(40, compress)))
        assert ids(records) == list(range(40)) and not gaps
    whole = gzip.compress(b"".join(made(5, False)))
    assert ids(read(whole)[0]) == list(range(5))
    assert read(b"") == ([], [])


def test_damage_costs_the_record_alone():
    for compress in (True, False):
        parts = made(12, compress)
        rng = random.Random(8)
        for _ in range(40):
            k = rng.randrange(12)
            broken = bytearray(parts[k])
            for _ in range(3):
                broken[rng.randrange(len(broken))] ^= 0x55
            data = b"".join([*parts[:k], bytes(broken), *parts[k + 1 :]])
            records, gaps = read(data)
            start = sum(map(len, parts[:k]))
            others = [r for r in records if r.start != start]  # a header's value alone is protected by no digest
            assert ids(others) == [i for i in range(12) if i != k]
            if len(others) == len(records):
                assert [(g.start, g.end) for g in gaps] == [(start, start + len(broken))] and gaps[0].reason


def test_truncation_junk_and_false_openings():
    parts = made(6)
    records, gaps = read(b"".join(parts)[:-9])
    assert ids(records) == list(range(5)) and gaps[0].end == sum(map(len, parts)) - 9
    junk = b"junk\x1f\x8b\x08 not a member WARC/1.1\r\nnor: a record"
    records, gaps = read(junk + parts[0] + junk + parts[1] + gzip.compress(b"no record") + parts[2])
    assert ids(records) == [0, 1, 2] and [g.end - g.start for g in gaps] == [len(junk), len(junk), len(gzip.compress(b"no record"))]
    wrong = warc.record("response", "urn:x-page:1", None, b"abc", hashlib.sha256(b"abd").hexdigest(), 3)
    records, gaps = read(wrong + parts[3])
    assert ids(records) == [3] and "digest" in gaps[0].reason
    big = warc.member(warc.record("response", "urn:x-page:7", None, b"z" * 500_000, hashlib.sha256(b"z" * 500_000).hexdigest(), 500_000))
    records, gaps = read(big + parts[4], max_record_bytes=100_000)
    assert ids(records) == [4] and "limit" in gaps[0].reason


def test_records_across_chunks(monkeypatch):
    monkeypatch.setattr(warc, "_CHUNK", 64)
    for part, held in ((1 << 16, 32 << 20), (7, 0), (1, 100)):
        monkeypatch.setattr(warc, "_PART", part)
        monkeypatch.setattr(warc, "_HELD", held)
        for compress in (True, False):
            parts = made(9, compress)
            records, gaps = read(b"".join([*parts[:4], b"#" * 150, *parts[4:]]))
            assert ids(records) == list(range(9)) and gaps[0].end - gaps[0].start == 150
        records, gaps = read(gzip.compress(b"".join(made(9, False))))
        assert ids(records) == list(range(9)) and not gaps and len({r.end for r in records}) == 1
        assert [hashlib.sha256(r.payload).hexdigest() for r in records] == [r.headers["warc-payload-digest"].partition(":")[2] for r in records]


def test_a_record_of_any_length_and_false_openings_in_a_row():
    body = b"y" * 3_000_000
    raw = warc.record("response", "urn:x-page:7", "u" * 400_000, body, hashlib.sha256(body).hexdigest(), len(body))
    for data in (raw, warc.member(raw)):
        for keep in (True, False):
            (found,), gaps = read(data, keep=keep)
            assert not gaps and found.payload_bytes == len(body) and found.payload == (body if keep else None)
    false = b"WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <a>\r\nWARC-Date: x\r\nContent-Length: 2000000\r\n\r\n" * 2_000
    records, gaps = read(false + body + raw)
    assert ids(records) == [7] and (gaps[0].start, gaps[0].end) == (0, len(false) + len(body))


def test_round_trip_and_revisits(spark):
    long, short = "é" * 60, "s" * 99
    pages = [(5, "http://a/ x\r\ny", long), (2, None, long), (9, "u", long), (3, "u", short), (4, "u", short), (6, "u", None), (7, "u", ""), (None, "u", long), (2, None, long), (8, "u", "line\r\n\r\nWARC/1.1\r\n" * 20)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").selectExpr("*", "1 as digest", "'x' as refers_to", "'y' as first").repartition(3)
    rows = warc.read_archives(spark, warc.archive_pages(df)).collect()
    assert len(rows) == len(pages) and all(r.gap is None for r in rows)
    by = {}
    for r in rows:
        by.setdefault(r.record_id.rsplit(":", 1)[1] if "null" not in r.record_id else None, []).append(r)
    kinds = {k: {(r.warc_type, r.refers_to) for r in v} for k, v in by.items()}
    assert kinds["2"] == {("response", None)} and len(by["2"]) == 2
    assert kinds["5"] == kinds["9"] == kinds[None] == {("revisit", "urn:x-page:2")}
    assert all(kinds[k] == {("response", None)} for k in "34678")
    for page_id, _, html in pages:
        for r in by[str(page_id) if page_id is not None else None]:
            data = (html or "").encode()
            assert (r.payload_bytes, r.payload_digest) == (len(data), "sha256:" + hashlib.sha256(data).hexdigest())
            assert r.payload == (data if r.warc_type == "response" else b"")
    assert warc.read_archives(spark, warc.archive_pages(df.limit(0))).count() == 0
    few, many = (sorted(map(tuple, warc.plan_records(df, max_broadcast=m).collect()), key=repr) for m in (100, 0))
    assert few == many and len(few) == len(pages)
