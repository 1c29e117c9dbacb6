"""Counts and plans: what the fixtures pin down, and how many shuffles a method takes."""

import math

import pytest
from pyspark.sql import functions as F

from ranksort import ledger, verify
from ranksort.catalog import fixtures as fx
from ranksort.placement import partner, schedule
from ranksort.plans import pivots as pv
from ranksort.plans import variants as v
from ranksort.plans.pivot_tree import slots
from ranksort.plans.redistribute import count_matrix, with_segments
from ranksort.plans.rounds import agree

FOLDER = "/root/testdata/sf0.01"


def segmented(spark, fixture, p, chooser=pv.MIDPOINT, ties="left"):
    rows = fixture.rows(spark, FOLDER, p)
    return with_segments(rows, fixture.spec, agree(rows, fixture.spec, p, chooser, ties=ties), ties)


@pytest.mark.parametrize(
    "fixture,p,moved,largest,smallest,full",
    [
        (fx.UNIFORM, 8, (90_406, 52_466, 75_193), 7_617, 7_313, 8), (fx.UNIFORM, 32, (150_312, 58_148, 86_386), 1_994, 1_811, 32), (fx.SKEWED, 8, (14_986, 8_774, 12_477), 7_067, 1, 8),
        (fx.SKEWED, 32, (24_793, 9_675, 14_377), 2_596, 1, 27), (fx.PERMUTATION, 8, (22_421, 13_125, 18_699), 1_875, 1_875, 8), (fx.PERMUTATION, 32, (37_518, 14_517, 21_520), 469, 468, 32),
    ],
)
def test_pinned_counts(spark, fixture, p, moved, largest, smallest, full):
    rows = segmented(spark, fixture, p).cache()
    depth = p.bit_length() - 1
    assert tuple(ledger.rows_moved(rows, p, levels).first()[0] for levels in (depth, 0, 1)) == moved
    assert tuple(ledger.imbalance(rows, p).first()) == (largest, smallest, p - full)
    assert sum(r["rows_moved"] for r in ledger.rows_moved_by_level(rows, p).collect()) == moved[0]
    matrix = count_matrix(rows).collect()
    assert sum(r["n"] for r in matrix if r["src_rank"] != r["dst_rank"]) == moved[1]
    rows.unpersist()


def test_physical_exchanges_move_what_the_formula_says(spark):
    from ranksort.plans.exchange import exchange_levels

    rows = fx.UNIFORM.rows(spark, FOLDER)
    keyed, total = rows.withColumn("__first", F.col("__rank")), 0
    for level in range(1, 4):
        after, _ = exchange_levels(keyed, fx.UNIFORM.spec, 8, level)
        before, _ = exchange_levels(keyed, fx.UNIFORM.spec, 8, level - 1)
        on = ["l_orderkey", "l_linenumber", "l_extendedprice"]
        joined = after.select(*on, F.col("__rank").alias("b")).join(before.select(*on, F.col("__rank").alias("a")), on)
        total += joined.where("a <> b").count()
    assert total == 90_406


def test_middle_pivots(spark):
    tree = agree(fx.UNIFORM.rows(spark, FOLDER), fx.UNIFORM.spec, 8, pv.MIDDLE)
    assert tree.pivots == (53066.96, 26743.82, 79126.18, 13856.3, 39879.29, 66279.59, 92047.66)


@pytest.mark.parametrize("p,ties,chooser,expected", [(8, "left", pv.MIDPOINT, 1.616), (32, "left", pv.MIDPOINT, 3.252), (8, "total_order", pv.ExactMedian(), 1.0), (32, "total_order", pv.ExactMedian(), 1.0)])
def test_balance_of_repeated_keys(spark, p, ties, chooser, expected):
    assert ledger.balance(segmented(spark, fx.DUPLICATES, p, chooser, ties), p) == pytest.approx(expected, abs=0.001)


def test_switch_levels():
    known = {(60_000, 8): 0, (60_000, 16): 0, (60_000, 32): 1, (60_000, 64): 3, (60_000, 128): 5, (60_000, 256): 7, (600_000, 64): 0, (600_000, 128): 2, (600_000, 256): 4,
             (6_000, 8): 1, (6_000, 16): 3, (6_000, 32): 5, (10**8, 1024): 0, (10**8, 2048): 2, (10**8, 4096): 4, (10**8, 8192): 6, (10_000 * 8192, 8192): 6, (200_000 * 8192, 8192): 2, (640_000 * 8192, 8192): 0}
    assert {k: v.switch_level(*k) for k in known} == known
    assert v.switch_level(1000, 16, 0) == 0 and v.switch_level(1000, 16, math.inf) == 4 and v.switch_level(1, 16) == 0


def test_shuffles(spark):
    free = v.exchange_free_quicksort(fx.UNIFORM.rows(spark, FOLDER), fx.UNIFORM.spec, 8)
    plan = free.rows._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "shufflepartitionidpassthrough" in plan and "ArrowEvalPython" not in plan
    placed = free.with_positions()._jdf.queryExecution().executedPlan().toString()
    assert placed.count("Exchange") == 1
    from ranksort.operators import joins

    orders, lines = spark.read.parquet(f"{FOLDER}/orders.parquet"), spark.read.parquet(f"{FOLDER}/lineitem.parquet")
    tree = agree(fx.PERMUTATION.rows(spark, FOLDER), fx.PERMUTATION.spec, 8)
    joined = joins.merge_join(orders.select("o_orderkey"), lines.select("l_orderkey"), "o_orderkey", "l_orderkey", tree, 8)
    plan = joined._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 2 and "SortMergeJoin" in plan


def test_rounds_read_the_key_alone(spark):
    from ranksort.plans.rounds import compared

    docs = fx.LARGE_ROWS.rows(spark, FOLDER)
    value, kind = compared(docs, fx.LARGE_ROWS.spec, "left")
    rows = pv.round_rows(docs, value, kind, F.lit(0), F.lit(0).cast("long"))
    plan = pv.MIDPOINT.choose(rows, kind, 8)._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<n_chars:bigint>" in plan.replace("doc_id:bigint,", "")


def test_rounds_over_sorted_ranks_move_no_keys(spark):
    from ranksort.plans import ordered

    local = fx.UNIFORM.rows(spark, FOLDER).repartitionById(8, F.col("__rank")).sortWithinPartitions(*fx.UNIFORM.spec.orders()).checkpoint()
    tree = agree(local, fx.UNIFORM.spec, 8, pv.MIDDLE, levels=2, in_order=True)
    keys, kind = ordered.ranks_in_order(local, fx.UNIFORM.spec, "left")
    read = ordered.proposals(keys, kind, tree)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in read and "Sort" not in read and "Window" not in read
    agreed = pv.MIDDLE.agreed.agree(ordered.proposals(keys, kind, tree), kind, 8)._jdf.queryExecution().executedPlan().toString()
    assert agreed.count("Exchange") == 1 and "Window" not in agreed
    assert ordered.proposals(keys, kind, tree).count() == 8 * 4  # what is reduced: a row a rank and segment


def test_a_sample_is_one_narrow_pass(spark):
    from ranksort.plans.rounds import agree_on_sample

    rows = fx.UNIFORM.rows(spark, FOLDER)
    tree = agree_on_sample(rows, fx.UNIFORM.spec, 8, per_rank=500)
    sizes = [r["n"] for r in with_segments(rows, fx.UNIFORM.spec, tree).groupBy("__segment").agg(F.count("*").alias("n")).collect()]
    assert len(sizes) == 8 and max(sizes) < 1.2 * sum(sizes) / 8


def test_schedule_and_slots(spark):
    assert schedule(spark, 8).where(partner(F.col("rank"), 1, 8) != F.col("partner")).where("level = 1").count() == 0
    assert schedule(spark, 1).count() == 0 and slots(spark, 1).count() == 0
    assert sorted(r["inorder_slot"] for r in slots(spark, 16).collect()) == list(range(1, 16))


def test_models_and_times():
    assert ledger.predict("exchange_quicksort", 1e8, 64)["row_exchange"] == 6 * ledger.predict("exchange_free_quicksort", 1e8, 64)["row_exchange"]
    rows = [2.0**k for k in range(8, 24)]
    sweep = [(r, ledger.predicted_time("exchange_quicksort", r * 8192, 8192), ledger.predicted_time("exchange_free_quicksort", r * 8192, 8192)) for r in rows]
    assert rows[0] < ledger.crossover(sweep) < rows[-1]
    assert ledger.crossover([(1, 1.0, 2.0)]) is None and ledger.speedup(8.0, 2.0) == 4.0 and ledger.efficiency(8.0, 2.0, 8) == 0.5
    timing = ledger.best_of(lambda: None, 3, 1)
    assert len(timing.runs) == 3 and timing.best == min(timing.runs)


def test_sortedness_check_finds_disorder(spark):
    df = fx.UNIFORM.rows(spark, FOLDER)
    assert verify.check_sorted(df.repartition(4), fx.UNIFORM.spec).first()["violations"] > 0
