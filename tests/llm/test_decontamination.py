import random

import numpy as np

from ranksort.llm import decontamination as d


def brute(text, item, evidence):
    """Best evidence over all diagonals."""
    best = 0
    for shift in range(-len(item) + 1, len(text)):
        equal = np.array([0 <= shift + k < len(text) and text[shift + k] == w for k, w in enumerate(item) if 0 <= shift + k < len(text)], bool)
        if equal.any():
            a, b = d.best_segment(equal)
            matched = int(equal[a:b].sum())
            if evidence.holds(matched, b - a, len(item)):
                best = max(best, matched)
    return best


def all_overlaps(texts, items):
    """(text, item): matched, by comparing every text with every item on every diagonal that could be evidence."""
    evidence, out, numbers = d.Evidence(), {}, {}
    number = lambda words: np.array([numbers.setdefault(w, len(numbers)) for w in words], np.int64)
    items = {j: number(w) for j, w in items.items() if w}
    for i, words in texts.items():
        ids = number(words)
        for j, own in items.items():
            if len(own) < 7:
                raise ValueError("items of seven tokens and more")
            least = min(evidence.min_tokens, int(np.ceil(evidence.min_share * len(own))))
            where = {}
            for k, w in enumerate(own.tolist()):
                where.setdefault(w, []).append(k)
            hits = {}
            for place, w in enumerate(ids.tolist()):
                for k in where.get(w, ()):
                    hits[place - k] = hits.get(place - k, 0) + 1
            best = 0
            for shift, n in hits.items():
                if n >= least:
                    a, b = max(shift, 0), min(shift + len(own), len(ids))
                    equal = ids[a:b] == own[a - shift : b - shift]
                    begin, end = d.best_segment(equal)
                    matched = int(equal[begin:end].sum())
                    if evidence.holds(matched, end - begin, len(own)):
                        best = max(best, matched)
            if best:
                out[i, j] = best
    return out


def corpus(seed=2):
    rng = random.Random(seed)
    word = lambda: f"w{rng.randrange(60)}"
    items = [[word() for _ in range(rng.choice([3, 8, 16, 30, 50]))] for _ in range(30)]
    texts = []
    for k in range(120):
        text = [word() for _ in range(rng.randrange(120))]
        if k % 2:
            part = list(rng.choice(items))
            for _ in range(rng.randrange(0, 1 + len(part) // 8)):
                part[rng.randrange(len(part))] = "swapped"
            at = rng.randrange(len(text) + 1)
            text[at:at] = part
        texts.append(text)
    return items, texts


def test_all_evidence_that_exists_is_found(spark):
    items, texts = corpus()
    evidence = d.Evidence()
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    bench = spark.createDataFrame([(i, " ".join(t).upper()) for i, t in enumerate(items)], "item_id long, text string")
    whole = lambda t, w: any(t[k : k + len(w)] == w for k in range(len(t) - len(w) + 1))
    expected = {(i, j): m for i, t in enumerate(texts) for j, w in enumerate(items) if (len(w) >= 7 or whole(t, w)) and (m := brute(t, w, evidence))}
    assert any(len(items[j]) < 7 for _, j in expected)
    found = {}
    for tokens, broadcast in ((1_000_000, 0), (200, 0), (0, 10**6)):
        d._BROADCAST = broadcast
        rows = d.find_overlaps(docs.unionByName(docs), bench, block_tokens=tokens).collect()
        assert {(r.doc_id, o.item): o.matched for r in rows for o in r.overlaps} == expected and len(rows) == 2 * len(texts)
        found[tokens] = sorted((r.doc_id, sorted(map(tuple, r.overlaps))) for r in rows)
    assert found[0] == found[200] == found[1_000_000]


def test_substitutions_case_and_punctuation():
    item = [f"t{i}" for i in range(20)]
    index = d.SeedIndex([(5, item)])
    changed = [("x" if i in (4, 11, 17) else w) for i, w in enumerate(item)]
    ((found,),) = index.search([["before"] * 9 + changed + ["after"]])
    assert found == (5, 15, 17, 20, 9, 0)  # the last two do not make up for the third
    assert index.search([item[:6], [], item[:12]]) == [[], [], [(5, 12, 12, 20, 0, 0)]]
    short = d.SeedIndex([(1, ["a", "b", "c"]), (2, ["yes"]), (3, []), (4, ["a", "b", "c", "d", "e", "f"])])
    assert short.search([["x", "a", "b", "c", "a"], ["a", "b", "x", "yes"], ["a", "b", "c", "d", "e", "f"]]) == [[(1, 3, 3, 3, 1, 0)], [(2, 1, 1, 1, 3, 0)], [(1, 3, 3, 3, 0, 0), (4, 6, 6, 6, 0, 0)]]
    assert d.tokens("A-b, C's\n_d É") == ["a", "b", "c", "s", "_d", "é"]


def test_defined_cases(spark):
    docs = spark.createDataFrame([(1, None, 0), (2, "", 0), (2, "", 0), (3, "same words " * 50_000, 0)], "doc_id long, text string, overlaps long")
    bench = spark.createDataFrame([(1, None), (2, ""), (3, "too short"), (4, "same words " * 8), (4, "same words " * 8)], "item_id long, text string")
    for tokens in (1_000_000, 0):
        rows = {r.doc_id: [o.item for o in r.overlaps] for r in d.find_overlaps(docs, bench, block_tokens=tokens).collect()}
        assert rows == {1: [], 2: [], 3: [4, 4]}
        assert d.find_overlaps(docs.limit(0), bench, block_tokens=tokens).count() == 0
    assert all(r.overlaps == [] for r in d.find_overlaps(docs, bench.limit(0)).collect())
    clash = docs.selectExpr("*", "1 as k1", "2 as k2", "3 as all", "4 as number", "5 as _k1")
    assert d.find_overlaps(clash, bench, block_tokens=0).columns == [c for c in clash.columns if c != "overlaps"] + ["overlaps"]
