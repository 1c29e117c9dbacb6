"""Joins that use segments."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..keys import KeySpec
from ..plans.pivot_tree import SEGMENT, PivotTree

HINTS = {"broadcast": "broadcast", "hash": "shuffle_hash", "merge": "merge", "loop": "shuffle_replicate_nl"}


def join(left: DataFrame, right: DataFrame, on, how: str = "inner", strategy: str | None = None, *, max_broadcast_rows: int = 1_000_000) -> DataFrame:
    """A join by a named strategy; ``broadcast`` first counts the right side, and beyond the bound leaves the choice to Spark."""
    if strategy is None:
        return left.join(right, on, how)
    if strategy not in HINTS:
        raise ValueError(f"no join strategy is called {strategy}")
    if strategy == "broadcast" and right.limit(max_broadcast_rows + 1).count() > max_broadcast_rows:
        return left.join(right, on, how)
    return left.join(right.hint(HINTS[strategy]), on, how)


def merge_join(left: DataFrame, right: DataFrame, left_key: str, right_key: str, tree: PivotTree, p: int) -> DataFrame:
    """An inner join of two relations that one pivot tree deals: equal keys meet on one rank, in order.

    Both sides are delivered by the tree, and the join condition holds the segment, so the merge join
    needs no exchange of its own.  All rows of one key meet in one task; where a key is hot, ``join`` without
    a strategy leaves its splitting to Spark.
    """
    if tree.reverse:
        raise ValueError("the tree runs upwards here")
    a = left.withColumn(SEGMENT, tree.segment(F.col(left_key))).repartitionById(p, F.col(SEGMENT))
    b = right.withColumn("__right", tree.segment(F.col(right_key))).repartitionById(p, F.col("__right"))
    met = a.hint("merge").join(b, (F.col(SEGMENT) == F.col("__right")) & (F.col(left_key) == F.col(right_key)))
    return met.drop("__right")


def range_join(points: DataFrame, ranges: DataFrame, at: str, low: str, high: str, tree: PivotTree) -> DataFrame:
    """Points with low <= at < high: each range is copied to the segments it covers, then met there by equality."""
    covered = F.sequence(tree.segment(F.col(low)), tree.segment(F.col(high)))
    cut = ranges.where(F.col(low) < F.col(high)).withColumn("__part", F.explode(covered))
    placed = points.where(F.col(at).isNotNull()).withColumn("__at", tree.segment(F.col(at)))
    return placed.join(cut, (F.col("__at") == F.col("__part")) & (F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("__part", "__at")


def asof_join(left: DataFrame, right: DataFrame, on: str, by: str, value: str, *, strict: bool = True, parts: PivotTree | None = None) -> DataFrame:
    """Adds ``value`` of the last right row of the same ``by`` before each left row (at or before it unless ``strict``); null if none.

    Both sides lie in one sorted sequence of each ``by`` and the last value is carried on, so nothing is
    paired.  With ``parts`` the sequence is cut by a pivot tree of the times, each part a task's, and what a part carries on from the
    parts before it is a row a part and ``by``; so a hot ``by`` is spread over the parts.
    """
    name, mark = f"__{value}", "__side"
    first, second = (0, 1) if strict else (1, 0)
    a = left.withColumns({name: F.lit(None).cast(right.schema[value].dataType), mark: F.lit(first)})
    b = right.select(F.col(on), F.col(by), F.col(value).alias(name)).withColumn(mark, F.lit(second))
    both = a.unionByName(b, allowMissingColumns=True)
    if parts is None:
        before = Window.partitionBy(by).orderBy(on, mark).rowsBetween(Window.unboundedPreceding, Window.currentRow)
        return both.withColumn(value, F.last(name, ignorenulls=True).over(before)).where(F.col(mark) == first).drop(name, mark)
    cut = both.withColumn("__part", parts.segment(F.col(on)))
    inside = Window.partitionBy(by, "__part").orderBy(on, mark).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    own = cut.withColumn(value, F.last(name, ignorenulls=True).over(inside))
    # equal times lie in one part, so a part's last value comes before all rows of the next
    last = cut.where(F.col(name).isNotNull()).groupBy(by, "__part").agg(F.max_by(name, on).alias("__last"))
    upto = Window.partitionBy(by).orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    every = cut.where(F.col(mark) == first).select(by, "__part").distinct().join(last, [by, "__part"], "full")
    handed = every.withColumn("__handed", F.last("__last", ignorenulls=True).over(upto)).select(F.col(by).alias("__by"), F.col("__part").alias("__of"), "__handed")
    met = own.where(F.col(mark) == first).join(handed, F.col(by).eqNullSafe(F.col("__by")) & (F.col("__part") == F.col("__of")), "left")
    return met.withColumn(value, F.coalesce(value, "__handed")).drop(name, mark, "__part", "__by", "__of", "__handed")


def segment_column(spec: KeySpec, tree: PivotTree) -> Column:
    return tree.segment(spec.value(), spec.nulls_first)
