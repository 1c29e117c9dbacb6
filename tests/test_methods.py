"""All sorting methods, pivot choices and rules for ties against sorted()."""

import math
import random
from datetime import date, datetime, timedelta
from decimal import Decimal

import pytest
from pyspark.sql import functions as F

from ranksort import verify
from ranksort.keys import KeySpec, midpoint
from ranksort.placement import place
from ranksort.plans import ordered
from ranksort.plans import pivots as pv
from ranksort.plans import variants as v
from ranksort.plans.pivot_tree import SEGMENT
from ranksort.plans.redistribute import POSITION, split_evenly, with_segments
from ranksort.plans.rounds import agree

SPEC = KeySpec("k", ("id",))


def frame(spark, values, kind="double", p=4):
    rows = [(i, x) for i, x in enumerate(values)]
    return place(spark.createDataFrame(rows, f"id long, k {kind}"), p, F.col("id") * 7 + 3)


def inputs():
    rng = random.Random(1)
    return {
        "empty": [],
        "one": [3.0],
        "fewer than ranks": [2.0, 1.0],
        "all equal": [5.0] * 40,
        "reversed": [float(x) for x in range(50, 0, -1)],
        "skewed": [math.exp(rng.random() * 9) for _ in range(120)],
        "negative and repeated": [float(rng.randrange(-3, 3)) for _ in range(90)],
        "infinite": [math.inf, -math.inf, 0.0, 1.0, 2.0] * 5,
    }


METHODS = {
    "local": lambda df, p: v.local_sort(df, SPEC),
    "exchange_quicksort": lambda df, p: v.exchange_quicksort(df, SPEC, p),
    "exchange_sort_first": lambda df, p: v.exchange_sort_first(df, SPEC, p),
    "exchange_sort_first_merge": lambda df, p: v.exchange_sort_first(df, SPEC, p, order="merge"),
    "exchange_free_quicksort": lambda df, p: v.exchange_free_quicksort(df, SPEC, p),
    "exchange_free_on_sample": lambda df, p: v.exchange_free_quicksort(df, SPEC, p, plan="sample"),
    "exchange_free_sketch": lambda df, p: v.exchange_free_quicksort(df, SPEC, p, plan="sketch"),
    "exchange_free_sort_first": lambda df, p: v.exchange_free_sort_first(df, SPEC, p),
    "exchange_free_sort_first_heap": lambda df, p: v.exchange_free_sort_first(df, SPEC, p, merge="heap"),
    "combined_quicksort": lambda df, p: v.combined_quicksort(df, SPEC, p, c=10),
    "combined_fused": lambda df, p: v.combined_quicksort(df, SPEC, p, c=10, fused=True),
    "combined_sort_first": lambda df, p: v.combined_sort_first(df, SPEC, p, c=10, merge="heap"),
    "sample_sort": lambda df, p: v.sample_sort(df, SPEC, p, per_rank=5),
    "sample_sort_regular": lambda df, p: v.sample_sort(df, SPEC, p, per_rank=5, method="regular"),
}


@pytest.mark.parametrize("name", METHODS)
def test_methods_sort(spark, name):
    chosen = inputs() if name in ("exchange_free_quicksort", "exchange_free_sort_first_heap") else {k: x for k, x in inputs().items() if k in ("skewed", "negative and repeated", "empty")}
    for label, values in chosen.items():
        df = frame(spark, values)
        done = METHODS[name](df, 4)
        found = [(r["k"], r["id"]) for r in sorted(done.with_positions().collect(), key=lambda r: r[POSITION])]
        assert found == sorted((x, i) for i, x in enumerate(values)), label
        assert [r[POSITION] for r in sorted(done.with_positions().collect(), key=lambda r: r[POSITION])] == list(range(len(values)))
        assert verify.check_sorted(done.rows, SPEC).first()["violations"] == 0, label
        if name != "local":
            assert verify.placed_right(done.rows) and done.rows.rdd.getNumPartitions() in ((4,) if values else (0, 4)), label
        assert verify.same_rows(df, done.rows)


CHOOSERS = {
    "midpoint": pv.MIDPOINT,
    "sampled": pv.Chooser(pv.SampleExtremes(3), pv.Midpoint()),
    "neutral": pv.Chooser(pv.Extremes(), pv.Midpoint("neutral")),
    "middle": pv.MIDDLE,
    "designated": pv.Chooser(pv.MiddleElement(), pv.Designated(2)),
    "mean": pv.Chooser(pv.MiddleElement(), pv.MeanOfCandidates()),
    "random": pv.Chooser(pv.RandomElement(), pv.MedianOfCandidates()),
    "first": pv.Chooser(pv.FirstElement(), pv.Designated()),
    "pool": pv.Chooser(pv.SamplePool(4), pv.MedianOfCandidates()),
    "approximate": pv.Chooser(pv.ApproximateMiddle(), pv.MedianOfCandidates()),
    "exact": pv.ExactMedian(),
    "sketch": pv.Sketch(),
}


@pytest.mark.parametrize("name", CHOOSERS)
def test_choosers_order_segments(spark, name):
    for values in (inputs()["skewed"], inputs()["negative and repeated"]):
        df = frame(spark, values, p=8)
        tree = agree(df, SPEC, 8, CHOOSERS[name])
        assert len(tree.pivots) == 7 and tree.in_order() == sorted(tree.in_order())
        rows = with_segments(df, SPEC, tree).collect()
        for r in rows:
            assert r[SEGMENT] == sum(r["k"] > x for x in tree.in_order())


def test_empty_segments_agree_either_way_and_inherit(spark):
    df = frame(spark, [0.0, 0.1, 100.0], p=8)
    skip, neutral = (agree(df, SPEC, 8, pv.Chooser(pv.Extremes(), pv.Midpoint(e))) for e in ("skip", "neutral"))
    assert skip.pivots == neutral.pivots == agree(df, SPEC, 8).pivots and None not in skip.pivots
    assert skip.in_order() == sorted(skip.in_order())


@pytest.mark.parametrize("ties", ["left", "even", "three_way", "total_order"])
def test_ties_keep_the_order_of_keys(spark, ties):
    values = [float(i % 3) for i in range(200)]
    df = frame(spark, values, p=8)
    tree = agree(df, SPEC, 8, pv.MIDDLE, ties="total_order" if ties == "total_order" else "left")
    rows = with_segments(df, SPEC, tree, ties).collect()
    by = {s: [r["k"] for r in rows if r[SEGMENT] == s] for s in range(8)}
    full = [by[s] for s in range(8) if by[s]]
    assert all(max(a) <= min(b) for a, b in zip(full, full[1:])) and len(rows) == 200
    if ties == "left":
        assert len(full) <= 3
    elif ties == "total_order":
        assert max(map(len, full)) <= 30 and len(full) == 8
    else:
        assert len(full) > 3


def test_rows_equal_to_a_pivot_are_halved(spark):
    df = frame(spark, [1.0] * 31 + [2.0] * 5, p=2)
    tree = agree(df, SPEC, 2, pv.ExactMedian())
    rows = split_evenly(df, SPEC, tree).collect()
    left, right = (sum(r["k"] == 1.0 and r[SEGMENT] == s for r in rows) for s in (0, 1))
    assert abs(left - right) <= 1 and all(r[SEGMENT] == 1 for r in rows if r["k"] == 2.0)


def test_all_variants_agree_on_extremes(spark):
    df = frame(spark, inputs()["skewed"], p=8)
    trees = [f(df, SPEC, 8, chooser=pv.MIDPOINT).tree.pivots for f in (v.exchange_quicksort, v.exchange_sort_first, v.exchange_free_quicksort, v.exchange_free_sort_first)]
    trees += [v.combined_quicksort(df, SPEC, 8, c=c).tree.pivots for c in (0, 20, math.inf)]
    assert all(t == trees[0] for t in trees)
    other = place(df.drop("__rank"), 8, "random", seed=99)
    assert agree(other, SPEC, 8).pivots == trees[0]


def test_nulls_nan_and_downward_orders(spark):
    values = [None, 2.0, math.nan, -1.0, None, math.inf, 5.0, 0.5]
    for first, down in ((True, False), (False, False), (True, True), (False, True)):
        spec = KeySpec("k", ("id",), ("k",) if down else (), first)
        done = v.exchange_free_quicksort(frame(spark, values), spec, 4)
        found = [r["k"] for r in sorted(done.with_positions().collect(), key=lambda r: r[POSITION])]
        numbers = [-1.0, 0.5, 2.0, 5.0, math.inf, math.nan]
        expected = numbers[::-1] if down else numbers
        expected = [None, None, *expected] if first else [*expected, None, None]
        assert str(found) == str(expected)


@pytest.mark.parametrize(
    "kind,values",
    [
        ("int", [3, -2, 2**31 - 1, -(2**31), 7]), ("long", [2**63 - 1, -(2**63), 5, 6]), ("decimal(12,2)", [Decimal("1.25"), Decimal("-3.50"), Decimal("9.99")]),
        ("timestamp", [datetime(2024, 1, d) for d in (5, 1, 9)]), ("date", [date(2024, 1, d) for d in (5, 1, 9)]), ("boolean", [True, False, True]), ("float", [1.5, 0.5, 2.5]),
    ],
)
def test_midpoints_of_key_types(spark, kind, values):
    done = v.exchange_free_quicksort(frame(spark, values, kind), SPEC, 4)
    found = [(r["k"], r["id"]) for r in sorted(done.with_positions().collect(), key=lambda r: r[POSITION])]
    assert found == sorted((x, i) for i, x in enumerate(values))


def test_element_pivots_of_other_types(spark):
    df = place(spark.createDataFrame([(i, f"s{i * 7 % 10}", [i % 3, i], i % 2) for i in range(30)], "id long, s string, a array<int>, b int"), 4, F.col("id"))
    for spec in (KeySpec("s", ("id",)), KeySpec("a", ("id",)), KeySpec(("b", "id"), (), ("id",)), KeySpec("s", ("id",), ("s",))):
        done = v.exchange_free_quicksort(df, spec, 4, pv.MIDDLE)
        found = [r["id"] for r in sorted(done.with_positions().collect(), key=lambda r: r[POSITION])]
        assert found == [r["id"] for r in df.orderBy(*spec.orders()).collect()]
        with pytest.raises(TypeError):
            agree(df, spec, 4)


def test_refusals(spark):
    df = frame(spark, [1.0])
    with pytest.raises(ValueError):
        place(df, 6)
    with pytest.raises(ValueError):
        v.exchange_free_quicksort(df, SPEC, 4, plan="other")
    with pytest.raises(TypeError):
        KeySpec("m").check(spark.createDataFrame([({"a": 1},)], "m map<string,int>"))
    with pytest.raises(TypeError):
        midpoint(F.col("s"), F.col("s"), spark.createDataFrame([("a",)], "s string").schema["s"].dataType)
    with pytest.raises(ValueError):
        KeySpec("k", (), ("other",))


def test_one_rank_is_a_local_sort(spark):
    df = frame(spark, inputs()["skewed"], p=1)
    done = v.exchange_free_quicksort(df, SPEC, 1)
    assert done.tree.pivots == () and [r["k"] for r in done.rows.collect()] == [r["k"] for r in v.local_sort(df, SPEC).rows.collect()]


def test_many_segments_walk_alike(spark):
    rng = random.Random(2)
    values = [rng.random() for _ in range(3000)]
    from pyspark.sql import types as T

    from ranksort.plans.pivot_tree import PivotTree

    for p in (16, 256, 2048):
        for reverse in (False, True):
            splitters = sorted((rng.choice(values) for _ in range(p - 1)), reverse=reverse)
            tree = PivotTree.from_sorted(splitters, T.DoubleType(), reverse)
            assert tree.in_order() == splitters
            found = frame(spark, values).select("k", tree.segment(F.col("k")).alias("s")).collect()
            assert all(r["s"] == sum((r["k"] < x) if reverse else (r["k"] > x) for x in splitters) for r in found[:300])


def test_positions_of_many_segments(spark, monkeypatch):
    from ranksort.plans import redistribute

    monkeypatch.setattr(redistribute, "FOLDED", 2)
    done = v.exchange_free_quicksort(frame(spark, inputs()["skewed"]), SPEC, 4)
    assert sorted(r[POSITION] for r in done.with_positions().collect()) == list(range(120))
    assert [r["k"] for r in sorted(done.with_positions().collect(), key=lambda r: r[POSITION])] == sorted(inputs()["skewed"])


MANY = 2048


def many_keys():
    nan = float("nan")
    start = datetime(2020, 1, 1)
    return {
        "string": ([f"k{(i * 7919) % 30_011:05d}" for i in range(6_000)], "string", ()),
        "timestamp": ([start + timedelta(seconds=(i * 7919) % 30_011) for i in range(6_000)], "timestamp", ()),
        "decimal": ([Decimal((i * 7919) % 30_011) / 100 for i in range(6_000)], "decimal(12,2)", ()),
        "long": ([(i * 7919) % 30_011 - 15_000 for i in range(6_000)], "long", ()),
        "descending with NaN": ([nan if i % 97 == 0 else float((i * 7919) % 30_011) for i in range(6_000)], "double", ("k",)),
        "NaN": ([nan if i % 97 == 0 else float((i * 7919) % 30_011) for i in range(6_000)], "double", ()),
    }


@pytest.mark.parametrize("name", [*many_keys(), "total order"])
def test_many_segments_agree_with_few(spark, name, monkeypatch):
    """Beyond a thousand segments a key lies where the nested conditions would put it."""
    values, kind, down = many_keys()["long" if name == "total order" else name]
    values = [x % 5 for x in values] if name == "total order" else values
    spec, ties = KeySpec("k", ("id",), down), "total_order" if name == "total order" else "left"
    df = frame(spark, values, kind, 8)
    tree = v.exchange_free_quicksort(df, spec, MANY, plan="sample", per_rank=8, ties=ties).tree
    assert tree.segments == MANY
    value = spec.total() if ties == "total_order" else spec.value()
    found = [r[0] for r in df.select(tree.segment(value).alias("s")).collect()]
    monkeypatch.setattr("ranksort.plans.pivot_tree.FOLDED", MANY)
    folded = [r[0] for r in df.select(tree.segment(value).alias("s")).collect()]
    assert found == folded and len(set(found)) > 1_000
    if ties == "left":
        beyond = (lambda k, x: k < x) if down else (lambda k, x: k > x)
        for k, s in list(zip(values, found))[::301]:
            plain = not (isinstance(k, float) and math.isnan(k))
            assert s == (sum(beyond(k, x) for x in tree.in_order()) if plain else (0 if down else MANY - 1))


@pytest.mark.parametrize("kind", ["double", "long", "string", "timestamp", "date", "decimal(12,2)", "boolean", "binary"])
@pytest.mark.parametrize("down", [False, True])
def test_places_in_sorted_ranks_are_what_windows_find(spark, kind, down):
    rng = random.Random(4)
    make = {
        "double": lambda: rng.choice([float(rng.randrange(40)), float("nan"), -0.0, math.inf]), "long": lambda: rng.randrange(-50, 50), "string": lambda: rng.choice(["", "é", "a", "Z"]) + str(rng.randrange(9)),
        "timestamp": lambda: datetime(2020, 1, 1) + timedelta(hours=rng.randrange(900)), "date": lambda: date(2020, 1, 1) + timedelta(days=rng.randrange(99)),
        "decimal(12,2)": lambda: Decimal(rng.randrange(9_999)) / 100, "boolean": lambda: rng.random() < 0.4, "binary": lambda: bytes([rng.randrange(256)]),
    }[kind]
    values = [None if rng.random() < 0.1 else make() for _ in range(150)]
    spec = KeySpec("k", ("id",), ("k",) if down else ())
    df = frame(spark, values, kind, 4)
    local = df.repartitionById(4, F.col("__rank")).sortWithinPartitions(*spec.orders()).cache()
    for chooser in (pv.MIDDLE, pv.Chooser(pv.MiddleElement(), pv.Designated(1)), *([pv.MIDPOINT] if kind in ("double", "long", "timestamp") else [])):
        assert agree(local, spec, 4, chooser, in_order=True).pivots == agree(df, spec, 4, chooser).pivots
    tree = agree(local, spec, 4, pv.MIDDLE, in_order=True)
    counts = {(r["rank"], r["segment"]): r["stop"] - r["start"] for r in ordered.bounds(local, spec, tree).collect()}
    known = with_segments(df.where("k is not null and not (cast(k as string) <=> 'NaN')" if kind == "double" else "k is not null"), spec, tree).groupBy("__rank", SEGMENT).count().collect()
    assert counts == {(r["__rank"], r[SEGMENT]): r["count"] for r in known}
    local.unpersist()


def test_places_of_composite_and_total_keys(spark):
    rng = random.Random(9)
    rows = [(i, rng.choice([None, "a", "b"]), rng.choice([None, 1.0, 2.5]), datetime(2020, 1, 1 + rng.randrange(9))) for i in range(200)]
    df = place(spark.createDataFrame(rows, "id long, a string, b double, t timestamp"), 4, F.col("id") * 5 + 1)
    for spec, ties in ((KeySpec(("a", "b", "t"), ("id",)), "left"), (KeySpec("a", ("t", "id")), "total_order")):
        local = df.repartitionById(4, F.col("__rank")).sortWithinPartitions(*spec.orders())
        assert agree(local, spec, 4, pv.MIDDLE, ties=ties, in_order=True).pivots == agree(df, spec, 4, pv.MIDDLE, ties=ties).pivots
    with pytest.raises(ValueError):
        agree(df, KeySpec("b", ("id",), ("b",)), 4, pv.MIDDLE, ties="total_order")


@pytest.mark.parametrize("nulls_first", [True, False])
def test_merging_runs_with_nulls_and_ties(spark, nulls_first):
    rng = random.Random(2)
    for kind, values in (("double", [rng.choice([None, 1.0, 2.0, float("nan"), float(rng.randrange(30))]) for _ in range(300)]), ("long", [rng.choice([None, rng.randrange(20)]) for _ in range(300)]), ("string", [rng.choice([None, "a", "b", "ab"]) for _ in range(300)])):
        if kind == "string" and not nulls_first:
            continue
        spec = KeySpec("k", ("id",), nulls_first=nulls_first)
        done = v.exchange_free_sort_first(frame(spark, values, kind), spec, 4, merge="heap")
        plain = v.exchange_free_sort_first(frame(spark, values, kind), spec, 4)
        assert [(repr(r["k"]), r["id"]) for r in done.rows.collect()] == [(repr(r["k"]), r["id"]) for r in plain.rows.collect()]


def test_two_runs_and_many():
    import numpy as np

    from ranksort.plans.redistribute import merge_places, merge_two

    keys = np.array([1, 4, 4, 9, 0, 4, 5, 9])
    assert keys[merge_two(keys, np.arange(4), np.arange(4, 8))].tolist() == sorted(keys.tolist())
    assert merge_two(keys, np.arange(4), np.arange(4, 8)).tolist() == [4, 0, 1, 2, 5, 6, 3, 7]
    rng = np.random.default_rng(1)
    for n in (0, 1, 2, 500):
        keys = rng.integers(0, 50, n)
        assert merge_places(keys).tolist() == np.argsort(keys, kind="stable").tolist()


@pytest.mark.parametrize("kind", ["double", "long", "string"])
def test_exact_medians(spark, kind):
    rng = random.Random(8)
    values = [rng.randrange(300) // rng.choice([1, 40]) for _ in range(700)]
    values = [{"double": float, "long": int, "string": str}[kind](x) for x in values]
    df = frame(spark, values, kind, 8)
    tree, parts = agree(df, SPEC, 4, pv.ExactMedian(50)), [sorted(values)]
    for level in range(2):
        for s, part in enumerate(parts):
            assert tree.pivots[(1 << level) + s - 1] == part[(len(part) + 1) // 2 - 1]
        parts = [half for s, part in enumerate(parts) for half in ([x for x in part if x <= tree.pivots[(1 << level) + s - 1]], [x for x in part if x > tree.pivots[(1 << level) + s - 1]])]


def test_splitters_by_ranges_and_in_one_task(spark, monkeypatch):
    df = frame(spark, [float((i * 7919) % 1_009) for i in range(900)], p=8)
    for down in ((), ("k",)):
        spec = KeySpec("k", ("id",), down)
        one = v.sample_sort(df, spec, 16, per_rank=20).tree
        monkeypatch.setattr("ranksort.plans.rounds._IN_ONE_TASK", 0)
        assert v.sample_sort(df, spec, 16, per_rank=20).tree == one and len(set(one.pivots)) == 15
        every = sorted((r["k"] for r in df.collect()), reverse=bool(down))
        assert v.sample_sort(df, spec, 16, per_rank=10_000).tree.in_order() == [every[900 * i // 16 - 1] for i in range(1, 16)]
        monkeypatch.undo()
