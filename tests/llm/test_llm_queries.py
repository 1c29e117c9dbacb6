"""Each query over its whole table, against SQL where there is a twin and a brute-force version otherwise."""

import hashlib
import math
import re
import zlib

import duckdb
import pytest
from test_decontamination import all_overlaps
from test_kneserney import Brute, tokens
from test_pii import brute as brute_spans
from test_pii import expected as base_spans
from test_quality import base as base_counts
from test_quality import verdict
from test_simhash import brute_components, brute_fingerprint

from ranksort.llm import decontamination, queries


@pytest.fixture(scope="module")
def docs(spark, sf):
    return {r.doc_id: r.text or "" for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}


def rows(spark, sf, name):
    return queries.QUERIES[name](spark, sf).collect()


@pytest.mark.parametrize("name", sorted(queries.ORACLE_SQL))
def test_twins(spark, sf, name):
    database = duckdb.connect()
    for table in ("documents", "pages", "conversations"):
        database.execute(f"CREATE VIEW {table} AS SELECT * FROM read_parquet('{sf}/{table}.parquet')")
    result = database.execute(queries.ORACLE_SQL[name])
    names = [d[0] for d in result.description]
    found = queries.QUERIES[name](spark, sf)
    assert sorted(found.columns) == sorted(names)
    assert sorted((tuple(r[c] for c in names) for r in found.collect()), key=repr) == sorted(result.fetchall(), key=repr)


def test_op7_with_copies(spark, tmp_path):
    """The query over pages of which some repeat, held against its SQL twin."""
    pages = [(i, f"http://h/{i}", html) for i, html in enumerate(["a" * 120, "b" * 99, "a" * 120, None, "", "é" * 50, "b" * 99, "a" * 120, "é" * 50, "c" * 100])]
    spark.createDataFrame(pages, "page_id long, url string, html string").repartition(3).write.parquet(f"{tmp_path}/pages.parquet")
    database = duckdb.connect()
    database.execute(f"CREATE VIEW pages AS SELECT * FROM read_parquet('{tmp_path}/pages.parquet/*.parquet')")
    result = database.execute(queries.ORACLE_SQL["op7_warc"])
    names = [d[0] for d in result.description]
    found = sorted((tuple(r[c] for c in names) for r in rows(spark, str(tmp_path), "op7_warc")), key=repr)
    assert found == sorted(result.fetchall(), key=repr) and sum(r[names.index("record_type")] == "revisit" for r in found) == 3


def test_op3(spark, sf, docs):
    found = rows(spark, sf, "op3_pii")
    assert len(found) == len(docs)
    for r in found:
        spans = base_spans(docs[r.doc_id])
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [len(x) for x in spans.values()]
        said = ",".join(f"{k}:{a}:{b}" for k, places in spans.items() for a, b in places)
        assert r.base_sha256 == hashlib.sha256(said.encode()).hexdigest()
        assert r.spans == ",".join(f"{k}:{a}:{b}" for k, a, b in brute_spans(docs[r.doc_id]))


def test_op4(spark, sf, docs):
    items = {r.item_id: decontamination.tokens(r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    found = {(r.doc_id, r.item_id): r.matched for r in rows(spark, sf, "op4_decontamination")}
    assert found == all_overlaps({i: decontamination.tokens(t) for i, t in docs.items()}, items)


def test_op5(spark, sf, docs):
    found = rows(spark, sf, "op5_quality")
    assert len(found) == len(docs)
    for r in found:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == base_counts(docs[r.doc_id])
        assert r.base_failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words)
        assert r.kept == verdict(docs[r.doc_id])


def test_op6(spark, sf, docs):
    from sentencepiece import SentencePieceProcessor

    library = SentencePieceProcessor(model_file=queries.PIECES)
    for r in rows(spark, sf, "op6_sentencepiece"):
        ids = library.encode(docs[r.doc_id])
        packed = b"".join(i.to_bytes(4, "little") for i in ids)
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(packed).hexdigest(), hashlib.sha256(library.decode(ids).encode()).hexdigest())


def test_op8(spark, sf, docs):
    held = {i: zlib.crc32(str(i).encode()) % 10 == 0 for i in docs}
    brute = Brute([t for i, t in docs.items() if not held[i]], queries.LM_ORDER)
    n, v = sum(brute.words.values()), len(brute.words)
    for r in rows(spark, sf, "op8_lm"):
        own = tokens(docs[r.doc_id])
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[r.doc_id], len(own), sum(w in brute.words for w in own), n)
        padded = ["<s>"] * (queries.LM_ORDER - 1) + own
        assert r.score == pytest.approx(sum(math.log10(brute.p(tuple(padded[i : i + queries.LM_ORDER - 1]), w)) for i, w in enumerate(own)), rel=1e-9)
        assert r.base_score == pytest.approx(sum(math.log10((brute.words[w] + 0.1) / (n + 0.1 * (v + 1))) for w in own), rel=1e-9)


def test_op9(spark, sf, docs):
    prints = {i: brute_fingerprint(t) for i, t in docs.items()}
    components = brute_components(prints, 2)
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in rows(spark, sf, "op9_simhash")} == {i: (f"{prints[i]:016x}", components[i]) for i in docs}


def test_every_operator_has_a_query():
    assert sorted(int(re.match(r"op(\d+)_", name)[1]) for name in queries.QUERIES) == list(range(1, 11))
