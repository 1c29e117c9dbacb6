"""Checks of what a sort promises."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .keys import KeySpec
from .plans.pivot_tree import SEGMENT


def check_sorted(sorted_rows: DataFrame, spec: KeySpec) -> DataFrame:
    """(rank_pairs, violations): neighbours out of order within ranks, and borders between ranks that overlap.

    Looks at rows as they lie in their partitions; the borders are a row a rank.
    """
    value = spec.value()
    rows = sorted_rows.select(F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("place"), value.alias("v"))
    inside = Window.partitionBy("part").orderBy("place")
    wrong = F.col("v") < F.lag("v").over(inside) if not spec.reversed else F.col("v") > F.lag("v").over(inside)
    ranks = rows.withColumn("wrong", F.coalesce(wrong, F.lit(False))).groupBy("part").agg(F.count_if("wrong").alias("wrong"), F.min("v").alias("lo"), F.max("v").alias("hi"))
    across = Window.orderBy("part")  # a row a rank
    border = F.col("lo") < F.lag("hi").over(across) if not spec.reversed else F.col("hi") > F.lag("lo").over(across)
    both = ranks.withColumn("border", F.coalesce(border, F.lit(False)).cast("long"))
    return both.agg(F.greatest(F.count("*") - 1, F.lit(0)).cast("long").alias("rank_pairs"), F.coalesce(F.sum(F.col("wrong") + F.col("border")), F.lit(0)).cast("long").alias("violations"))


def same_rows(a: DataFrame, b: DataFrame) -> bool:
    """Whether two relations hold the same rows as often."""
    columns = [c for c in a.columns if not c.startswith("__")]
    digest = lambda df: df.agg(F.count("*"), F.sum(F.xxhash64(*columns).cast("decimal(38,0)"))).first()
    return digest(a) == digest(b)


def placed_right(segmented_rows: DataFrame) -> bool:
    """Whether each partition holds one segment alone."""
    return segmented_rows.where(F.spark_partition_id() != F.col(SEGMENT)).limit(1).count() == 0


def shuffles(df: DataFrame) -> int:
    """How many exchanges a plan has."""
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange ")
