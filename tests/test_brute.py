"""Queries that SQL cannot express, against plain Python over the whole table.

Hashes come from Spark, as data; everything that is decided by them is worked out here.
"""

import math
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from ranksort import catalog
from ranksort.catalog import fixtures as fx

P, LEVELS = fx.P, 3


@pytest.fixture(scope="module")
def lines(spark, sf):
    """(rank, value, tie, seeded hash) of every line item."""
    rows = fx.UNIFORM.rows(spark, sf)
    tie = F.xxhash64("l_orderkey", "l_linenumber")
    return [tuple(r) for r in rows.select("__rank", "l_extendedprice", tie, F.xxhash64(F.lit(5), "l_extendedprice", tie)).collect()]


def parts_of(rows, ranks=lambda r: r[0]):
    out = defaultdict(list)
    for r in rows:
        out[ranks(r)].append(r)
    return out


def tree(rows, choose):
    """Pivots of all levels in heap order, by a choice for each segment's rows, or its parent's pivot; equal keys go left."""
    segments, pivots = [rows], []
    for level in range(LEVELS):
        chosen = [choose(s) if s else pivots[(1 << level) // 2 - 1 + k // 2] for k, s in enumerate(segments)]
        pivots += chosen
        segments = [half for s, x in zip(segments, chosen) for half in ([r for r in s if r[1] <= x], [r for r in s if r[1] > x])]
    return pivots, segments


def lower_median(values):
    return sorted(values)[(len(values) + 1) // 2 - 1]


def sample(part, s, by=3):
    return sorted(part, key=lambda r: (r[by], r[1]))[:s]


def ends(s):
    def choose(rows):
        values = [r[1] for part in parts_of(rows).values() for r in sample(part, s)]
        return (min(values) + max(values)) / 2

    return choose


def pool(s):
    return lambda rows: lower_median([r[1] for part in parts_of(rows).values() for r in sample(part, s)])


CHOICES = {
    "pivots_sample": ends(20),
    "pivots_pool": pool(20),
    "pivots_random_element": lambda rows: lower_median([min(part, key=lambda r: (r[3], r[1]))[1] for part in parts_of(rows).values()]),
    "pivots_first_element": lambda rows: (lambda parts: min(parts[min(parts)], key=lambda r: (r[2], r[1]))[1])(parts_of(rows)),
}


def pivots(spark, sf, name):
    found = catalog.QUERIES[name](spark, sf).collect()
    assert len(found) == P - 1 and sorted(r["inorder_slot"] for r in found) == list(range(1, P))
    return [r["pivot"] for r in sorted(found, key=lambda r: (r["level"], r["segment"]))]


@pytest.mark.parametrize("name", CHOICES)
def test_pivots_of_seeded_samples(spark, sf, lines, name):
    assert pivots(spark, sf, name) == tree(lines, CHOICES[name])[0]


@pytest.mark.parametrize("name,error", [("pivots_approximate_middle", 0.05), ("pivots_sketch_rounds", 0.001), ("pivots_kll_rounds", 0.01), ("pivots_sketch", 0.001), ("pivots_on_sample", 0.06)])
def test_pivots_divide_within_their_error(spark, sf, lines, name, error):
    """Approximate pivots are elements, and leave every segment its share within the method's error."""
    found, values = pivots(spark, sf, name), sorted(r[1] for r in lines)
    assert set(found) <= set(values)
    inorder = [None] * (P - 1)
    for level in range(LEVELS):
        for s in range(1 << level):
            inorder[((2 * s + 1) * P >> (level + 1)) - 1] = found[(1 << level) + s - 1]
    assert inorder == sorted(inorder)
    for i, x in enumerate(inorder, 1):
        assert abs(sum(v <= x for v in values) / len(values) - i / P) <= error + 1 / len(values), (i, x)


def test_ties_even_hashed(spark, sf):
    """A key equal to a level's pivot goes by the hash's bit of that level."""
    spec = fx.DUPLICATES.spec
    rows = fx.DUPLICATES.rows(spark, sf).select("l_discount", F.xxhash64(*spec.tiebreak)).collect()
    segments, pivots_ = [[r[0] for r in rows]], []
    for level in range(LEVELS):
        chosen = [(min(s) + max(s)) / 2 if s else pivots_[(1 << level) // 2 - 1 + k // 2] for k, s in enumerate(segments)]
        pivots_ += chosen
        segments = [half for s, x in zip(segments, chosen) for half in ([v for v in s if v <= x], [v for v in s if v > x])]
    sizes = defaultdict(int)
    for value, h in rows:
        slot = 1
        for level in range(LEVELS):
            x = pivots_[slot - 1]
            slot = 2 * slot + (value > x or (value == x and h >> level & 1))
        sizes[slot - P] += 1
    assert {r["segment"]: r["n"] for r in catalog.QUERIES["ties_even_hashed"](spark, sf).collect()} == dict(sizes)


def test_sample_size_sweep(spark, sf, lines):
    skewed = fx.SKEWED.rows(spark, sf)
    tie = F.xxhash64("event_id")
    skewed = [tuple(r) for r in skewed.select("__rank", "value", tie, F.xxhash64(F.lit(5), "value", tie)).collect()]
    found = {(r["input"], r["sample"], r["s"]): r["max_over_mean"] for r in catalog.QUERIES["sample_size_sweep"](spark, sf).collect()}
    assert len(found) == 16
    for name, rows in (("uniform", lines), ("skewed", skewed)):
        for s in (1, 20):
            for kind, choose in (("ends", ends(s)), ("pool", pool(s))):
                segments = tree(rows, choose)[1]
                assert found[name, kind, s] == pytest.approx(max(map(len, segments)) * P / len(rows)), (name, kind, s)


def test_participation(spark, sf, lines):
    """In the exchange variant a level's sample is drawn from the ranks as they are after the exchanges before."""
    found = {(r["variant"], r["level"]): r["worst"] for r in catalog.QUERIES["participation"](spark, sf).collect()}
    for variant in ("exchange", "exchange_free"):
        segments = [lines]
        for level in range(LEVELS):
            rest, chosen = P >> level, []
            for s, rows in enumerate(segments):
                parts = parts_of(rows, lambda r, s=s: s * rest + r[0] % rest if variant == "exchange" else r[0])
                values = [r[1] for part in parts.values() for r in sample(part, 20)]
                chosen.append((min(values) + max(values)) / 2)
            halves = [([r for r in rows if r[1] <= x], [r for r in rows if r[1] > x]) for rows, x in zip(segments, chosen)]
            worst = max(abs(len(a) / (len(a) + len(b)) - 0.5) for a, b in halves)
            assert found[variant, level] == pytest.approx(worst), (variant, level)
            segments = [half for pair in halves for half in pair]


def test_approximate_aggregates(spark, sf):
    rows = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_returnflag", "l_partkey", "l_extendedprice", "l_orderkey").collect()
    groups = parts_of(rows)
    for r in catalog.QUERIES["agg_approximate"](spark, sf).collect():
        own = groups[r["l_returnflag"]]
        parts, prices = {x[1] for x in own}, sorted(x[2] for x in own)
        assert abs(r["parts"] - len(parts)) <= 0.08 * len(parts)
        assert abs(sum(x <= r["median"] for x in prices) / len(prices) - 0.5) <= 0.001 + 1 / len(prices)
    for r in catalog.QUERIES["agg_extremes_sample"](spark, sf).collect():
        prices = [x[2] for x in groups[r["l_returnflag"]]]
        assert (r["lo"], r["hi"], r["sampled"]) == (min(prices), max(prices), 20)


def test_xxhash(spark, sf):
    """The published algorithm on the eight bytes of each key, least first, with seed 42."""
    import xxhash

    for r in catalog.QUERIES["fn_xxhash"](spark, sf).collect():
        own = xxhash.xxh64_intdigest(int(r["o_orderkey"]).to_bytes(8, "little", signed=True), 42)
        assert r["x"] % (1 << 64) == own


def test_times_of_a_sweep():
    """Speed-up, efficiency, factor and crossover of a measured sweep."""
    from ranksort import ledger

    sweep = [(10, 1.0, 2.0), (100, 4.0, 4.1), (1000, 9.0, 7.0), (10_000, 40.0, 31.0)]
    assert ledger.crossover(sweep) == 1000 and ledger.relative_factor(9.0, 7.0) == pytest.approx(9 / 7)
    assert math.isclose(ledger.efficiency(64.0, 4.0, 32), 0.5) and ledger.speedup(64.0, 4.0) == 16.0
