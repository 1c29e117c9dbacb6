import random
import re

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from ranksort.llm import simhash as sh


def brute_fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(prints, budget):
    ids = sorted(prints)
    parent = {i: i for i in ids}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in ids:
        for j in ids:
            if i < j and (prints[i] ^ prints[j]).bit_count() <= budget:
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    return {i: root(i) for i in ids}


@pytest.mark.parametrize("bits,n", [(9, 200), (16, 900), (63, 300)])
def test_trie_pairs_against_all_pairs(bits, n):
    rng = np.random.default_rng(n)
    values = np.unique(rng.integers(0, 1 << bits, n, dtype=np.uint64))
    values = np.unique(np.concatenate([values, values ^ (np.uint64(1) << rng.integers(0, 63, len(values)).astype(np.uint64))]))
    cut = len(values) // 3
    for budget in range(4):
        pairs = np.concatenate([np.empty((0, 2), np.int64), *sh.trie_pairs(values[:, None], np.array([0, cut, len(values)]), budget)])
        i, j = np.triu_indices(len(values), 1)
        near = (np.bitwise_count(values[i] ^ values[j]) <= budget) & ((i < cut) == (j < cut))
        assert sorted(map(tuple, pairs.tolist())) == sorted(zip(i[near].tolist(), j[near].tolist()))


def test_fingerprints(sf):
    import pyarrow.parquet as pq

    texts = pq.read_table(f"{sf}/documents.parquet")["text"].to_pylist()[:40] + ["", " \t", "One", "one two", "A b C", "é" * 9, "x y z " * 40_000]
    assert [int(sh.fingerprint(t.encode())[0]) for t in texts] == [brute_fingerprint(t) for t in texts]
    assert [int(sh.fingerprint(t.encode(), lanes=5)[0]) for t in texts[::9]] == [brute_fingerprint(t) for t in texts[::9]]


@pytest.mark.parametrize("budget", [0, 2, 3])
def test_links_connect_what_brute_force_connects(spark, budget):
    rng = random.Random(budget)
    values = {rng.getrandbits(64) for _ in range(60)}
    for _ in range(3):
        values |= {v ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) for v in rng.sample(sorted(values), 50)}
    values |= {0, 1, (1 << 64) - 1, 1 << 63}
    prints = dict(enumerate(sorted(values)))
    df = spark.createDataFrame([(i, v - (1 << 64) if v >> 63 else v) for i, v in prints.items()], "id long, fingerprint long")
    for hot_group, broadcast in ((10**6, 10), (3, 10**6), (1, 1)):
        sh._HOT_BROADCAST = broadcast
        edges = sh.links(df.select("fingerprint"), budget=budget, hot_group=hot_group)
        check(df, edges, prints, budget)


def check(df, edges, prints, budget):
    named = df.join(sh.components(edges).withColumnRenamed("node", "fingerprint"), "fingerprint", "left").withColumn("root", F.coalesce("root", "fingerprint"))
    groups = {}
    for r in named.collect():
        groups.setdefault(r.root, []).append(r.id)
    assert {i: min(g) for g in groups.values() for i in g} == brute_components(prints, budget)


def test_components_of_chains_stars_and_nothing(spark):
    edges = [(i, i + 1) for i in range(60)] + [(1000, 1000 + i) for i in range(1, 200)] + [(5000, 5000)]
    found = {r.node: r.root for r in sh.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(found[i] == 0 for i in range(1, 61)) and all(found[1000 + i] == 1000 for i in range(1, 200))
    assert sh.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_operator_and_defined_cases(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    extra = spark.createDataFrame([(-5, None), (-4, ""), (-4, ""), (-3, "word"), (None, "")], docs.schema)
    rows = sh.near_duplicates(docs.unionByName(extra).selectExpr("*", "1 as fingerprint", "2 as component_id", "3 as first")).collect()
    prints = {r.doc_id: brute_fingerprint(r.text) for r in docs.unionByName(extra).collect() if r.doc_id is not None}
    expected = brute_components(prints, 2)
    assert len(rows) == docs.count() + 5
    assert all(r.component_id == expected[r.doc_id] for r in rows if r.doc_id is not None)
    assert [r.component_id for r in rows if r.doc_id is None] == [-5]
    assert sh.near_duplicates(docs.limit(0)).count() == 0
    monkeypatch.setattr(sh, "_MANY_COPIES", 1)
    copied = docs.unionByName(docs.limit(5)).unionByName(extra)
    assert {(r.doc_id, r.component_id) for r in sh.near_duplicates(copied).collect()} == {(r.doc_id, r.component_id) for r in rows}


def brute_lanes(text, shingle, lanes):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    hashes = [xxhash.xxh64_intdigest(" ".join(words[i : i + shingle]).encode(), 42) for i in range(max(1, len(words) - shingle + 1))] if words else []
    out, full = 0, (1 << 64) - 1
    for lane in range(lanes):
        own = []
        for h in hashes:
            z = (h + lane * 0x9E3779B97F4A7C15) & full
            if lane:
                z = (z ^ z >> 30) * 0xBF58476D1CE4E5B9 & full
                z = (z ^ z >> 27) * 0x94D049BB133111EB & full
                z ^= z >> 31
            own.append(z)
        out = out << 64 | sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in own) > len(own))
    return out


def test_lanes_against_brute_force(spark, monkeypatch):
    """Links over several lanes are the pairs within the budget that agree on a block."""
    rng, word, lanes, width, budget = random.Random(7), lambda: f"w{rng.randrange(4000)}", 4, 8, 40
    texts = [[word() for _ in range(80)] for _ in range(40)]
    for t in list(texts):
        for changes in (1, 2, 3):
            near = list(t)
            for _ in range(changes):
                near[rng.randrange(80)] = word()
            texts.append(near)
    texts = [" ".join(t) for t in texts] + ["", None, "one"]
    prints = {i: brute_lanes(t, 5, lanes) for i, t in enumerate(texts)}
    assert [sum(int(x) << 64 * (lanes - 1 - k) for k, x in enumerate(sh.fingerprint((t or "").encode(), 5, lanes=lanes))) for t in texts] == list(prints.values())
    parent = {i: i for i in prints}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in prints:
        for j in prints:
            other = prints[i] ^ prints[j]
            if i < j and other.bit_count() <= budget and any(other >> at & 255 == 0 for at in range(0, 64 * lanes, width)):
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    for together in (200_000, 10):
        monkeypatch.setattr(sh, "_TOGETHER", together)
        found = {r.doc_id: r.component_id for r in sh.near_duplicates(df, budget=budget, shingle=5, lanes=lanes, width=width).collect()}
        assert found == {i: root(i) for i in prints} and 43 <= len(set(found.values())) < 120
    marked = sh.fingerprints(df, shingle=5, lanes=lanes).selectExpr("doc_id as node", "fingerprint").where("node < 160")
    hot = {r.node: r.root for r in sh.components(sh.links(marked, node="node", budget=budget, lanes=lanes, width=width, hot_group=1)).collect()}
    assert all(root(a) == root(b) for a, b in hot.items()) and len(hot) > 60


def test_forest_keeps_components(spark):
    rng = np.random.default_rng(3)
    edges = rng.integers(0, 300, (400, 2))
    whole, parts = sh.Forest(300), sh.Forest(300)
    whole.add(edges)
    for at in range(0, 400, 7):
        parts.add(edges[at : at + 7])
    assert (whole.root == parts.root).all() and len(whole.links()) == len(parts.links()) == 300 - len(set(whole.root.tolist()))
    again = sh.Forest(300)
    again.add(parts.links())
    assert (again.root == whole.root).all()
