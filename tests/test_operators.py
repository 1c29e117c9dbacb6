"""Operators, sources, sinks and streams on small inputs."""

import random
from datetime import datetime, timedelta

import pytest
from pyspark.sql import functions as F

from ranksort import ledger, verify
from ranksort.functions import surface
from ranksort.keys import KeySpec
from ranksort.operators import joins, order
from ranksort.placement import place
from ranksort.plans import pivots as pv
from ranksort.plans import variants as v
from ranksort.plans.pivot_tree import SEGMENT
from ranksort.plans.redistribute import POSITION, with_segments
from ranksort.plans.rounds import agree, agree_fused
from ranksort.sources import tables
from ranksort.streaming import routing

SPEC = KeySpec("k", ("id",))


def frame(spark, n=300, seed=1, repeat=40):
    rng = random.Random(seed)
    return place(spark.createDataFrame([(i, float(rng.randrange(repeat))) for i in range(n)], "id long, k double"), 8, F.col("id"))


def test_order_statistics(spark):
    df = frame(spark)
    done = v.exchange_free_quicksort(df, SPEC, 8)
    rows = sorted((r["k"], r["id"]) for r in df.collect())
    for k in (0, 17, 299):
        (found,) = order.select_kth(done, k).collect()
        assert (found["k"], found["id"]) == rows[k]
    assert order.select_kth(done, 300).count() == 0
    assert [(r["k"], r["id"]) for r in order.top_k(df, SPEC, done.tree, 25).collect()] == rows[:25]
    assert sorted((r["k"], r["id"]) for r in order.page(done, 290, 50).collect()) == rows[290:]
    found = {r["share"]: r["value"] for r in order.quantiles(done, [0.0, 0.5, 1.0]).collect()}
    assert found == {0.0: rows[0][0], 0.5: rows[149][0], 1.0: rows[-1][0]}
    assert sorted((r["k"], r["id"]) for r in order.range_scan(done.segmented, SPEC, done.tree, 5.0, 9.0).collect()) == [r for r in rows if 5 <= r[0] <= 9]
    keys = sorted({r[0] for r in rows})
    assert sorted(r["k"] for r in order.dedup_sorted(done.segmented, SPEC).collect()) == keys
    for r in order.global_ranks(done).collect():
        assert r["rank"] == 1 + sum(x[0] < r["k"] for x in rows) and r["dense_rank"] == 1 + keys.index(r["k"])
    groups = order.top_k_group(df.withColumn("g", F.col("id") % 3), SPEC, ["g"], 4, salts=3).collect()
    assert all(sorted((r["k"], r["id"]) for r in groups if r["g"] == g) == [x for x in rows if x[1] % 3 == g][:4] for g in range(3))
    empty = v.exchange_free_quicksort(df.where("id < 0"), SPEC, 8)
    assert empty.with_positions().count() == order.global_ranks(empty).count() == order.quantiles(empty, [0.5]).count() == 0


def test_joins(spark):
    a, b = frame(spark, 200, 2), frame(spark, 100, 3)
    a_rows, b_rows = a.collect(), b.collect()
    expected = sorted((x["id"], y["id"]) for x in a_rows for y in b_rows if x["k"] == y["k"])
    left, right = a.select("id", "k"), b.select(F.col("id").alias("id2"), F.col("k").alias("k2"))
    tree = agree(a, KeySpec("k"), 8)
    assert sorted((r["id"], r["id2"]) for r in joins.merge_join(left, right, "k", "k2", tree, 8).collect()) == expected
    for strategy in (None, "broadcast", "hash", "merge"):
        assert sorted((r["id"], r["id2"]) for r in joins.join(left, right, F.col("k") == F.col("k2"), strategy=strategy).collect()) == expected
    assert joins.join(left, right, F.col("k") == F.col("k2"), strategy="broadcast", max_broadcast_rows=3).count() == len(expected)
    ranges = spark.createDataFrame([(i, float(i), float(i + w)) for i in range(0, 40, 3) for w in (0, 1, 9, 50)], "r long, lo double, hi double")
    found = sorted((r["id"], r["r"], r["hi"]) for r in joins.range_join(left, ranges, "k", "lo", "hi", tree).collect())
    all_ranges = ranges.collect()
    assert found == sorted((x["id"], y["r"], y["hi"]) for x in a.collect() for y in all_ranges if y["lo"] <= x["k"] < y["hi"])
    for strict in (True, False):
        for parts in (None, tree):
            by_one = right.select("id2", F.col("k2").alias("k"), F.lit(1).alias("u")).withColumn("k2", F.col("k"))
            got = {r["id"]: r["k2"] for r in joins.asof_join(left.withColumn("u", F.lit(1)), by_one, "k", "u", "k2", strict=strict, parts=parts).collect()}
            for x in a_rows:
                before = [y["k"] for y in b_rows if (y["k"] < x["k"] if strict else y["k"] <= x["k"])]
                assert got[x["id"]] == (max(before) if before else None)
    with pytest.raises(ValueError):
        joins.join(left, right, "k", strategy="other")


def test_merge_sorted_and_fused_rounds(spark):
    a, b = frame(spark, 150, 4).drop("__rank"), frame(spark, 70, 5).drop("__rank")
    merged = order.merge_sorted(a, b.withColumn("id", F.col("id") + 1000), SPEC, 8)
    found = [(r["k"], r["id"]) for r in sorted(merged.with_positions().collect(), key=lambda r: r[POSITION])]
    assert found == sorted(found) and len(found) == 220
    df = frame(spark, 4000, 6, 10**6)
    for width in (1, 2, 3, 5):
        tree = agree_fused(df, SPEC, 16, levels_a_pass=width)
        assert tree.in_order() == sorted(tree.in_order()) and ledger.balance(with_segments(df, SPEC, tree), 16) < 1.05
    with pytest.raises(TypeError):
        agree_fused(df.withColumn("k", F.col("k").cast("string")), SPEC, 8)


def test_sketches_and_metrics(spark):
    df = frame(spark, 3000, 7, 10**6)
    for sketch in (pv.Sketch(), pv.Sketch(2048, "kll")):
        assert ledger.balance(with_segments(df, SPEC, agree(df, SPEC, 8, sketch)), 8) < 1.1
    done = v.exchange_free_quicksort(df, SPEC, 8)
    counted = ledger.shuffle_metrics(spark, lambda: ledger.execute(done.rows))
    assert counted["shuffle_bytes"] > 0 and counted["tasks"] >= 8 and counted["spilled_bytes"] == 0


def test_sources_and_sinks(spark, tmp_path):
    values = sorted(r["key"] for r in tables.permutation(spark, 1000).collect())
    assert values == list(range(1000)) and tables.permutation(spark, 1).count() == 1
    drawn = [r["key"] for r in tables.uniform(spark, 5000).collect()]
    assert 0 <= min(drawn) and max(drawn) <= 4999 and abs(sum(drawn) / 5000 - 2500) < 100
    assert drawn == [r["key"] for r in tables.uniform(spark, 5000).collect()]
    done = v.exchange_free_quicksort(frame(spark), SPEC, 8)
    tables.write_sorted(done, str(tmp_path / "sorted"))
    back = tables.read_sorted(spark, str(tmp_path / "sorted"))
    assert back.count() == 300 and {r["rank"] for r in back.select("rank").distinct().collect()} <= set(range(8))
    plan = back.where("rank = 2")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(rank" in plan
    for name in ("left_rows", "right_rows"):
        tables.write_bucketed(frame(spark).select("id", "k"), name, 4, "id")
    joined = spark.table("left_rows").hint("merge").join(spark.table("right_rows"), "id")
    assert joined.count() == 300 and "Exchange hashpartitioning" not in joined._jdf.queryExecution().executedPlan().toString()
    with pytest.raises(ValueError):
        tables.read_file(spark, str(tmp_path), "other", "a int")


def test_sql_surface(spark):
    df = frame(spark)
    tree = agree(df, SPEC, 8)
    surface.register_segment_of(spark, tree, "segment_of_test")
    df.createOrReplaceTempView("numbers")
    found = surface.sql(spark, "SELECT k, segment_of_test(k) AS s FROM numbers WHERE id < :n", n=100).collect()
    assert len(found) == 100 and all(r["s"] == sum(r["k"] > x for x in tree.in_order()) for r in found)
    surface.register_table_functions(spark)
    assert spark.sql("SELECT * FROM pivot_slots(8)").count() == 7 and spark.sql("SELECT * FROM rank_schedule(1)").count() == 0
    (ends,) = df.agg(surface.extremes_sample(F.col("k"), F.col("id"), 5).alias("x")).collect()
    assert ends["x"]["lo"] == df.agg(F.min("k")).first()[0] and len(ends["x"]["sample"]) == 5


@pytest.fixture
def arrivals(spark, tmp_path):
    """Events in five files, and the same as a table."""
    begin = datetime(2024, 1, 1)
    rows = [(i, begin + timedelta(minutes=7 * i), i % 5, float(i * 37 % 101)) for i in range(400)]
    table = spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long, k double")
    path = str(tmp_path / "arrivals")
    table.repartitionByRange(5, "ts").write.parquet(path)
    return table, lambda: tables.read_stream(spark, path, table.schema, files_per_batch=5), tmp_path


def test_streams_equal_batches(spark, arrivals):
    table, stream, path = arrivals
    spec = KeySpec("k", ("event_id",))
    tree = agree(place(table, 8, F.col("event_id")), spec, 8)
    routed = routing.route_stream(stream(), spec, tree)
    found = routing.run_to_end(routed.select("event_id", SEGMENT), "routed_test", str(path / "c1"))
    assert {(r["event_id"], r[SEGMENT]) for r in found.collect()} == {(r["event_id"], r[SEGMENT]) for r in routing.route_stream(table, spec, tree).collect()}
    for name, options in {"tumbling": {}, "sliding": {"slide": "15 minutes"}, "session": {"gap": "30 minutes"}}.items():
        flat = lambda df: df.select(F.unix_seconds("window.start").alias("w"), "segment", "n")
        load = routing.segment_load(routed, "ts", late="30 days", **options)
        got = routing.run_to_end(flat(load), f"load_{name}", str(path / f"c_{name}"), "complete")
        want = flat(routing.segment_load(routing.route_stream(table, spec, tree), "ts", **options))
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())), name
    query = routing.run_sink(stream(), spec, tree, str(path / "runs"), str(path / "c2"))
    query.awaitTermination()
    merged = routing.compact_runs(spark, str(path / "runs"), spec, tree)
    assert merged.count() == 400 and verify.check_sorted(merged, spec).first()["violations"] == 0


def test_stream_monitors(spark, arrivals):
    table, stream, path = arrivals
    spec = KeySpec("k", ("event_id",))
    tree = agree(place(table, 8, F.col("event_id")), spec, 8)
    told = routing.run_to_end(routing.drift(routing.route_stream(stream(), spec, tree), 8, 1.5), "drift_test", str(path / "d1")).collect()
    assert max(r["rows"] for r in told) == 400 and all(r["worst"] >= 1.0 for r in told) and not told[-1]["repivot"]
    kept = routing.run_to_end(routing.deduplicate(stream(), ["user_id"], "ts", "30 days"), "dedup_test", str(path / "d2"))
    assert kept.count() == 5
    names = spark.createDataFrame([(u, f"u{u}") for u in range(3)], "user_id long, name string")
    joined = routing.run_to_end(routing.enrich(stream(), names, "user_id"), "enrich_test", str(path / "d3"))
    assert joined.count() == 400 and joined.where("name is null").count() == 160
    pairs = routing.run_to_end(routing.pair_within(stream(), stream(), "user_id", "ts", "ts", "35 minutes", "30 days").select("a.event_id", F.col("b.event_id").alias("other")), "pair_test", str(path / "d4"))
    assert {(r["event_id"], r["other"]) for r in pairs.collect()} == {(i, j) for i in range(400) for j in (i, i + 5) if j < 400}


def test_appended_rows_stay_off_the_driver(spark, tmp_path):
    """What a stream appends lies in files that executors read, not in rows that the driver holds; also where nothing came."""
    spark.range(1000).select("id", (F.col("id") % 7).alias("v")).write.parquet(str(tmp_path / "in"))
    spark.range(0).select("id", (F.col("id") % 7).alias("v")).write.parquet(str(tmp_path / "none"))
    for folder, n in (("in", 1000), ("none", 0)):
        stream = spark.readStream.schema("id long, v long").parquet(str(tmp_path / folder))
        found = routing.run_to_end(stream.select("v"), f"appended_{folder}", str(tmp_path / f"state_{folder}"))
        assert found.count() == n and found.columns == ["v"]
        assert not n or found.inputFiles()
