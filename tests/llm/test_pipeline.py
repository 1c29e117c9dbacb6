import pytest
from test_decontamination import all_overlaps
from test_pii import brute_redacted
from test_quality import verdict
from test_simhash import brute_lanes

import corpus_pipeline
from ranksort.llm import decontamination, queries


def one_of_each_group(docs):
    """Ids that are the least of their group: pairs that agree on a block and are within the budget."""
    wide, width = 64 * corpus_pipeline.LANES, corpus_pipeline.WIDTH
    prints = {i: brute_lanes(t, corpus_pipeline.SHINGLE, corpus_pipeline.LANES) for i, t in docs.items()}
    root = {i: i for i in prints}

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in prints:
        for j in prints:
            other = prints[i] ^ prints[j]
            if i < j and other.bit_count() <= corpus_pipeline.BUDGET and any(not other >> at & ((1 << width) - 1) for at in range(0, wide, width)):
                a, b = top(i), top(j)
                root[max(a, b)] = min(a, b)
    return {i for i in prints if top(i) == i}


def test_run_against_brute_force(spark, sf):
    """All five stages worked out without the operators, from the documents to the decoded texts."""
    from sentencepiece import SentencePieceProcessor

    docs = {r.doc_id: r.text or "" for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    items = {r.item_id: decontamination.tokens(r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    kept = {i: t for i, t in docs.items() if verdict(t)}
    first = one_of_each_group(kept)
    kept = {i: t for i, t in kept.items() if i in first}
    dirty = {i for i, _ in all_overlaps({i: decontamination.tokens(t) for i, t in kept.items()}, items)}
    clean = {i: brute_redacted(t) for i, t in kept.items() if i not in dirty}
    library = SentencePieceProcessor(model_file=queries.PIECES)
    rows = {r.doc_id: r for r in corpus_pipeline.run(spark, sf).collect()}
    assert rows.keys() == clean.keys() and 0 < len(dirty) and len(first) < len(docs)
    for doc_id, text in clean.items():
        assert list(rows[doc_id].ids) == library.encode(text) and rows[doc_id].n_tokens == len(rows[doc_id].ids)
        assert rows[doc_id].round_trip


@pytest.mark.parametrize("similarity,least", [(0.95, 1.0), (0.9, 0.95), (0.85, 0.9)])
def test_recall_of_near_copies(spark, similarity, least):
    """Pairs of texts of a known similarity in five-word shingles: how many share a group."""
    import random

    rng, pairs = random.Random(5), 60
    rows, word = [], lambda: f"w{rng.randrange(50_000)}"
    for k in range(pairs):
        words = [word() for _ in range(rng.choice([120, 300, 700]))]
        other, shingles = list(words), lambda w: {tuple(w[i : i + 5]) for i in range(len(w) - 4)}
        own = shingles(words)
        while True:
            near = list(other)
            near[rng.randrange(len(near))] = word()
            theirs = shingles(near)
            if len(own & theirs) / len(own | theirs) < similarity:
                break
            other = near
        rows += [(2 * k, " ".join(words)), (2 * k + 1, " ".join(other))]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    kept = {r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, "").collect()}
    assert all(2 * k in kept for k in range(pairs)) and sum(2 * k + 1 not in kept for k in range(pairs)) >= least * pairs


def test_no_pair_of_the_share_is_left_out(spark):
    """Pairs just at four fifths of their five-word shingles, many of which fingerprints miss; of short and long texts."""
    import random

    rng, rows = random.Random(11), []
    word = lambda: f"w{rng.randrange(50_000)}"
    grams = lambda w: {tuple(w[i : i + 5]) for i in range(len(w) - 4)}
    for k in range(150):
        words = [word() for _ in range(rng.choice([40, 60, 120, 300]))]
        near, own = list(words), grams(words)
        while True:
            other = list(near)
            other[rng.randrange(len(other))] = word()
            if len(own & grams(other)) * 5 < len(own | grams(other)) * 4:
                break
            near = other
        rows += [(2 * k, " ".join(words)), (2 * k + 1, " ".join(near))]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    kept = {r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, "").collect()}
    assert kept == {2 * k for k in range(150)}


def test_stages_keep_the_columns(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(30)
    extra = docs.selectExpr("*", "'x' as fingerprint", "1 as component_id", "2 as work", "3 as _work", "4 as __stage")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, extra, sf).columns == extra.columns, name


def test_defined_cases(spark, sf):
    schema = spark.read.parquet(f"{sf}/documents.parquet").schema
    words = " ".join(f"word{i}" for i in range(60))
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (3, words, "en", "s", 9), (3, words, "en", "s", 9), (4, words, None, None, None), (None, words + " tail", "en", "s", 1)]
    docs = spark.createDataFrame(rows, schema)
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.limit(0), sf).count() == 0, name
        assert stage(spark, docs, sf).count() >= 2, name
    quality_kept = corpus_pipeline.quality_rules(spark, docs, sf)
    assert quality_kept.count() == 4
    assert [r.doc_id for r in corpus_pipeline.near_duplicates(spark, quality_kept, sf).where("doc_id is not null").collect()] == [3]
