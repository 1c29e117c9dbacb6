"""The engine from SQL: registered functions, table functions and aggregates."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..placement import levels_of
from ..plans.pivot_tree import PivotTree, inorder_slot


def register_segment_of(spark: SparkSession, tree: PivotTree, name: str = "segment_of") -> None:
    """A SQL function of a numeric key: its segment in this tree.  From DataFrames, ``tree.segment`` is the compiled form."""
    import numpy as np

    if not isinstance(tree.kind, T.NumericType) or any(x is None for x in tree.pivots) or tree.reverse:
        raise TypeError("the SQL function serves complete numeric trees that run upwards")
    splitters = spark.sparkContext.broadcast(np.array([float(x) for x in tree.in_order()]))

    def search(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for keys in batches:
            found = np.searchsorted(splitters.value, keys.cast(pa.float64()).to_numpy(zero_copy_only=False), "left")
            yield pa.array(np.where(keys.is_null().to_numpy(zero_copy_only=False), 0, found).astype(np.int32))

    spark.udf.register(name, F.arrow_udf(search, "int"))


def register_table_functions(spark: SparkSession) -> None:
    """rank_schedule(p): level, rank, partner, grp.  pivot_slots(p): level, segment, heap_slot, inorder_slot."""

    class RankSchedule:
        def eval(self, p: int):
            depth = levels_of(p)
            for level in range(depth):
                for rank in range(p):
                    yield level, rank, rank ^ (p >> (level + 1)), rank >> (depth - level)

    class PivotSlots:
        def eval(self, p: int):
            for level in range(levels_of(p)):
                for segment in range(1 << level):
                    yield level, segment, (1 << level) + segment, inorder_slot(level, segment, p)

    spark.udtf.register("rank_schedule", F.udtf(RankSchedule, returnType="level int, rank int, partner int, grp int"))
    spark.udtf.register("pivot_slots", F.udtf(PivotSlots, returnType="level int, segment int, heap_slot int, inorder_slot int"))


def extremes_sample(key: Column, tie: Column, s: int = 20, seed: int = 5) -> Column:
    """A mergeable aggregate: lo, hi and at most s keys of least seeded hash."""
    hashed = F.struct(F.xxhash64(F.lit(seed), key, tie).alias("h"), key.alias("k"))
    sample = F.transform(F.slice(F.array_sort(F.collect_set(F.when(key.isNotNull(), hashed))), 1, s), lambda x: x["k"])
    return F.struct(F.min(key).alias("lo"), F.max(key).alias("hi"), sample.alias("sample"))


def sql(spark: SparkSession, text: str, **parameters) -> DataFrame:
    """SQL over the registered views and functions, with named parameters."""
    return spark.sql(text, args=parameters)
