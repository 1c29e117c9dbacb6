import math
import random
from collections import Counter

import numpy as np
import pytest

from ranksort.llm import kneserney as kn


def tokens(text):
    lowered = (text or "").translate({i: i + 32 for i in range(65, 91)})
    return [w.decode() for w in lowered.encode().split()] + ["</s>"]


class Brute:
    def __init__(self, texts, order):
        self.order = order
        all_tokens = [tokens(t) for t in texts]
        self.words = Counter(w for t in all_tokens for w in t)
        grams = Counter(tuple((["<s>"] * (order - 1) + t)[i : i + order]) for t in all_tokens for i in range(len(t)))
        self.counts = {order: grams}
        for k in range(order - 1, 0, -1):
            self.counts[k] = Counter(g[1:] for g in self.counts[k + 1])
        self.d = {k: (0.0, *kn.discounts([sum(x == n for x in c.values()) for n in (1, 2, 3, 4)])) for k, c in self.counts.items()}
        self.total, self.gamma = {}, {}
        for k, c in self.counts.items():
            for g, n in c.items():
                key = (k, g[:-1])
                self.total[key] = self.total.get(key, 0) + n
                self.gamma[key] = self.gamma.get(key, 0) + self.d[k][min(n, 3)]

    def p(self, context, word, k=None):
        k = self.order if k is None else k
        if k == 0:
            return 1 / (len(self.words) + 1)
        context = context[len(context) - k + 1 :]
        lower, total = self.p(context, word, k - 1), self.total.get((k, context), 0)
        if not total:
            return lower
        n = self.counts[k].get((*context, word), 0)
        return (n - self.d[k][min(n, 3)]) / total + self.gamma[k, context] / total * lower


def corpus(seed, n=120):
    rng = random.Random(seed)
    return [" ".join(rng.choice(["the", "The", "a", "of", f"w{rng.randrange(30)}", f"rare{rng.randrange(500)}"]) for _ in range(rng.randrange(25))) for _ in range(n)]


@pytest.mark.parametrize("order", [2, 3])
def test_scores_against_brute_force(spark, monkeypatch, order):
    texts = [*corpus(1), None, "", "the the the"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    monkeypatch.setattr(kn, "_IN_BUCKET", 150)
    model = kn.train(df, order=order)
    brute, unseen = Brute([t or "" for t in texts], order), corpus(2, 40) + ["never seen words", None, ""]
    assert model.buckets > 3 and model.n_tokens == sum(brute.words.values()) and model.n_types == len(brute.words)
    scored = kn.score(spark.createDataFrame(list(enumerate(unseen)), "doc_id long, text string").selectExpr("*", "1 as lm"), model).collect()
    for r in scored:
        own = tokens(unseen[r.doc_id])
        padded = ["<s>"] * (order - 1) + own
        expected = sum(math.log10(brute.p(tuple(padded[i : i + order - 1]), w)) for i, w in enumerate(own))
        base = sum(math.log10((brute.words[w] + 0.1) / (model.n_tokens + 0.1 * (model.n_types + 1))) for w in own)
        assert r.lm.score == pytest.approx(expected, rel=1e-9) and r.lm.base_score == pytest.approx(base, rel=1e-9)
        assert (r.lm.n_tokens, r.lm.n_known) == (len(own), sum(w in brute.words for w in own))


def test_probabilities_sum_to_one(spark):
    df = spark.createDataFrame([(t,) for t in corpus(3)], "text string")
    model = kn.train(df)
    text = " ".join({w for t in corpus(3) for w in tokens(t)[:-1]})
    known, arrays = kn.number([text.encode()]), kn.Arrays(model)
    unknown = np.uint64(12345)
    assert len(known.hashes) == model.n_types + 1  # and the start mark
    hashes = np.sort(np.append(known.hashes, unknown))
    at = {int(h): i for i, h in enumerate(hashes)}
    every = [i for i, h in enumerate(hashes) if h != kn.START]
    for before in (hashes[2], hashes[9], kn.END, kn.START, unknown):
        # each text: the word before, then one of all words, whose p is the second of its text
        pairs = np.array([[at[int(before)], i] for i in every])
        if before == kn.START:
            found = kn.Numbered(hashes, pairs[:, 1].copy(), np.arange(len(every) + 1), at[int(kn.START)])
            p = arrays.probability(found)
        else:
            found = kn.Numbered(hashes, pairs.ravel(), np.arange(0, 2 * len(every) + 1, 2), at[int(kn.START)])
            p = arrays.probability(found)[1::2]
        assert p.sum() == pytest.approx(1.0, abs=1e-9)


def test_held_out_texts_are_better_than_base(spark, sf):
    documents = spark.read.parquet(f"{sf}/documents.parquet")
    held = kn.held_out(documents["doc_id"])
    scored = kn.score(documents.where(held), kn.train(documents.where(~held))).selectExpr("sum(lm.score) s", "sum(lm.base_score) b").first()
    assert scored.s > scored.b


def test_packing_and_empty_training(spark):
    rng = np.random.default_rng(1)
    columns, counts = kn.add_up([rng.integers(0, 50, 900).astype(np.uint64), rng.integers(0, 1 << 63, 900).astype(np.uint64)], np.ones(900, np.int64))
    again, n = kn.unpack(kn.pack(columns, counts), 2)
    assert all((a == b).all() for a, b in zip(again, columns)) and (n == counts).all()
    empty = spark.createDataFrame([], "text string")
    model = kn.train(empty)
    row = kn.score(spark.createDataFrame([("a b",)], "text string"), model).first().lm
    assert (row.n_tokens, row.n_known, row.score) == (3, 0, 0.0)
    assert kn.score(empty, model).count() == 0
    with pytest.raises(ValueError):
        kn.train(empty, order=1)


def test_hot_contexts_of_two_words_are_dealt(spark, monkeypatch):
    texts = [" ".join(["of the"] * 40 + [f"w{i}"]) for i in range(60)] + corpus(4)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    monkeypatch.setattr(kn, "_IN_BUCKET", 400)
    model = kn.train(df, order=3)
    from xxhash import xxh64_intdigest

    pair = kn.context_hash([np.array([xxh64_intdigest(w)], np.uint64) for w in ("of", "the")], 1)[0]
    assert int(pair) in model.dealt and int(pair) in model.hot[3] and model.buckets > 4
    brute = Brute(texts, 3)
    for r in kn.score(df, model).collect()[::7]:
        own = ["<s>", "<s>", *tokens(texts[r.doc_id])]
        assert r.lm.score == pytest.approx(sum(math.log10(brute.p(tuple(own[i - 2 : i]), own[i])) for i in range(2, len(own))), rel=1e-9)


def test_a_lost_file_is_an_error(spark, monkeypatch):
    import os

    df = spark.createDataFrame([(t,) for t in corpus(5)], "text string")
    monkeypatch.setattr(kn, "_IN_BUCKET", 100)
    model = kn.train(df)
    folder = model.folder.removeprefix("file:")
    names = [n for n in os.listdir(folder) if not n.startswith(".")]
    assert sorted(names) == sorted(f"{kind}-{v}" for kind, volumes in model.volumes.items() for v in volumes)
    monkeypatch.setattr(kn, "_MAPPED", 1)
    arrays = kn.Arrays(model)
    found = kn.number([t.encode() for t in corpus(5)])
    assert (arrays.probability(found) == kn.Arrays(model).probability(found)).all() and len(arrays._maps) == 1
    os.remove(f"{folder}/{names[0]}")
    with pytest.raises(Exception, match="No such file"):
        kn.score(df, model).collect()
