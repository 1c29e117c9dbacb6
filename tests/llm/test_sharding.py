import pytest
from pyspark.sql import functions as F

from ranksort.llm.sharding import Run, ShardStore


def store(spark, tmp_path, **options):
    return ShardStore(spark, str(tmp_path / "store"), **({"first_tier_bytes": 2000, "target_bytes": 1 << 20} | options))


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_compaction_keeps_all_rows_and_merges_similar_sizes(spark, tmp_path):
    s = store(spark, tmp_path, fanout=3)
    whole = spark.range(900).withColumn("text", F.concat(F.lit("row "), "id"))
    for k in range(7):
        s.append(whole.where(F.pmod("id", F.lit(7)) == k).repartition(2))
    before = s.manifest()
    assert len(before.runs) == 7 and all(r.files == 2 for r in before.runs)
    committed = s.compact()
    after = s.manifest()
    assert committed and after.version == committed[-1] and len(after.runs) < 7
    assert max(sum(s.tier(r) == t for r in after.runs) for t in range(9)) < 3
    assert rows(s.read()) == rows(whole) and rows(s.read(before.version)) == rows(whole)
    assert len(s.vacuum()) == 7 and rows(s.read()) == rows(whole)


def test_large_runs_wait_for_their_own_tier(spark, tmp_path):
    s = store(spark, tmp_path, fanout=2)
    assert [s.tier(Run("", 1, size, 1)) for size in (1, 2000, 2001, 4000, 4001)] == [0, 0, 1, 1, 2]
    s.append(spark.range(100_000).repartition(1))
    s.append(spark.range(5).repartition(1))
    assert s.compact() == [] and s.read().count() == 100_005


def test_merged_files_reach_the_target(spark, tmp_path):
    s = store(spark, tmp_path, fanout=4, target_bytes=300_000)
    for k in range(4):
        s.append(spark.range(50_000).select(F.sha2(F.concat("id", F.lit(k)).cast("string"), 256).alias("h")).repartition(8))
    small = sum(r.files for r in s.manifest().runs)
    s.compact()
    (run,) = s.manifest().runs
    assert small == 32 and run.files < small and run.rows == 200_000


def test_a_taken_version_is_not_overwritten(spark, tmp_path):
    s = store(spark, tmp_path)
    s.append(spark.range(3))
    s.files.write(s.files.at("manifests", ".draft-x"), "{}")
    assert not s.files.publish(s.files.at("manifests", ".draft-x"), s._manifest_path(1))
    assert s.read().count() == 3
    other, seen = ShardStore(spark, str(tmp_path / "store")), []

    def late(now):
        if not seen:
            seen.append(now.version)
            other.append(spark.range(4))
        return type(now)(now.version + 1, now.schema, now.runs)

    assert s._commit(late) == 3 and s.read().count() == 7


def test_defined_cases(spark, tmp_path):
    s = store(spark, tmp_path)
    with pytest.raises(ValueError):
        s.read()
    empty = spark.createDataFrame([], "doc_id long, text string, name string")
    s.append(empty)
    assert s.manifest().runs == () and s.read().count() == 0 and s.compact() == []
    odd = spark.createDataFrame([(None, None, "a"), (1, "", "a"), (1, "", "a"), (2, "x" * 100_000, None)], empty.schema)
    s.append(odd)
    assert rows(s.read()) == rows(odd)
    with pytest.raises(ValueError):
        s.append(spark.range(2))
    with pytest.raises(ValueError):
        ShardStore(spark, str(tmp_path / "other"), fanout=1)
