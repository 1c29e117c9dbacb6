import os
import random

import pyarrow.parquet as pq
import pytest

from ranksort.llm import sentencepiece as own

PATH = "/opt/tokenizers/piece_bpe_32k.model"
pytestmark = pytest.mark.skipif(not os.path.exists(PATH), reason="no vocabulary file")
ODD = ["", " ", "   ", "  a", "a  b   c ", "tab\tnew\nline", "日本語 🎉👩‍👩‍👧", "\x00\x7f", "a\u2581b \u2581\u2581", "<s></s><0x0A>", "    if x:\n        return", "y" * 5000, "hello" * 800]


@pytest.fixture(scope="module")
def model():
    return own.load_model(PATH)


def texts(sf):
    return pq.read_table(f"{sf}/documents.parquet")["text"].to_pylist() + pq.read_table(f"{sf}/pages.parquet")["html"].to_pylist() + ODD


def test_same_ids_and_texts_as_the_library(model, sf):
    from sentencepiece import SentencePieceProcessor

    library, vocabulary, all_texts = SentencePieceProcessor(model_proto=model), own.Vocabulary(model), texts(sf)
    rng = random.Random(4)
    all_texts += ["".join(rng.choice(["a", "th", "e", " ", "ing", "é", "1", ".", "\u2003"]) for _ in range(40)) for _ in range(300)]
    ids, starts = vocabulary.encode(all_texts)
    expected = library.encode(all_texts)
    assert [ids[a:b].tolist() for a, b in zip(starts, starts[1:])] == expected
    assert [vocabulary.decode(x) for x in expected] == [library.decode(x) for x in expected]


def test_unigram_scores_against_the_library(model):
    from sentencepiece import SentencePieceProcessor
    from sentencepiece.sentencepiece_model_pb2 import ModelProto

    spec = ModelProto.FromString(model)
    spec.trainer_spec.model_type = 1
    for piece in spec.pieces:  # 32-bit sums of the library stay exact
        piece.score = max(piece.score, -40_000.0)
    data = spec.SerializeToString()
    library, vocabulary = SentencePieceProcessor(model_proto=data), own.Vocabulary(data)
    rng = random.Random(9)
    words = [" ".join("".join(rng.choice("abcdefghilmnoprstuvw") for _ in range(rng.randrange(1, 14))) for _ in range(30)) for _ in range(60)]
    ids, starts = vocabulary.encode(words)
    score = lambda x: sum(library.get_score(i) for i in x)
    for text, a, b in zip(words, starts, starts[1:]):
        assert score(ids[a:b].tolist()) == score(library.encode(text)) and library.decode(ids[a:b].tolist()) == text


def test_prefixes_are_shared(model):
    vocabulary = own.Vocabulary(model)
    made, step = [], vocabulary._surviving
    vocabulary._surviving = lambda cells, word: made.append(len(word) + 1 - len(cells)) or step(cells, word)
    vocabulary.learn(sorted(["\u2581walking", "\u2581walked", "\u2581walker"]))
    assert made == [len("\u2581walked"), 1, 3]


def test_operator_and_defined_cases(spark, model):
    df = spark.createDataFrame([*enumerate(ODD), (90, None), (91, "twice"), (91, "twice")], "doc_id long, text string").selectExpr("*", "1 as ids", "2 as read")
    ids = own.encode(df, model)
    rows = own.decode(ids, model).collect()
    assert all(r.decoded == (r.text or "").replace("\u2581", " ") for r in rows)
    assert [r.read.n_tokens for r in own.read_back(ids, model).collect()] == [len(r.ids) for r in rows]
    checked = own.encode_checked(df, model).collect()
    assert [(r.doc_id, r.ids) for r in checked] == [(r.doc_id, r.ids) for r in ids.collect()]
    assert all(r.n_tokens == len(r.ids) and r.round_trip for r in checked)
    assert own.encode(df.limit(0), model).count() == 0 == own.encode_checked(df.limit(0), model).count()


def test_forgetting_changes_nothing(model, monkeypatch):
    all_texts = ["alpha beta gamma", "beta delta", "alpha epsilon"]
    ids, _ = own.Vocabulary(model).encode(all_texts)
    monkeypatch.setattr(own, "_REMEMBERED", 2)
    small = own.Vocabulary(model)
    assert [i for t in all_texts for i in small.encode([t])[0].tolist()] == ids.tolist()
