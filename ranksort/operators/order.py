"""Order statistics and other questions that a sorted, ranked relation answers."""

from __future__ import annotations

from typing import Any

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..keys import KeySpec
from ..plans.pivot_tree import SEGMENT, PivotTree
from ..plans.redistribute import POSITION, add_offsets, with_segments
from ..plans.rounds import agree
from ..plans.variants import Sorted


def range_scan(segmented: DataFrame, spec: KeySpec, tree: PivotTree, low: Any = None, high: Any = None) -> DataFrame:
    """Rows with low <= key <= high: the pivots name the segments, whose files alone are read if rows were written by rank."""
    first, last = tree.overlapping(low, high)
    key = F.col(spec.key[0])
    out = segmented.where(F.col(SEGMENT).between(first, last))
    if low is not None:
        out = out.where(key >= low)
    return out if high is None else out.where(key <= high)


def select_kth(result: Sorted, k: int) -> DataFrame:
    """The row at zero-based position k: the counts name its segment, and only that one is sorted."""
    counts = {r[SEGMENT]: r["n"] for r in result.segmented.groupBy(SEGMENT).agg(F.count("*").alias("n")).collect()}  # p rows
    for s in sorted(counts):
        if k < counts[s]:
            part = result.segmented.where(F.col(SEGMENT) == s)
            return part.withColumn(POSITION, F.row_number().over(Window.orderBy(*result.spec.orders())) - 1).where(F.col(POSITION) == k)
        k -= counts[s]
    return result.segmented.withColumn(POSITION, F.lit(0)).where(F.lit(False))


def quantiles(result: Sorted, shares: list[float]) -> DataFrame:
    """(share, value): exact quantiles, the element at position ceil(share * n) - 1 and at least 0.

    The counts name the segments that hold the positions, and only these are ordered.
    """
    from math import ceil

    spec, key = result.spec, F.col(result.spec.key[0])
    counts = {r[SEGMENT]: r["n"] for r in result.segmented.groupBy(SEGMENT).agg(F.count("*").alias("n")).collect()}  # p rows
    n, before, asked = sum(counts.values()), 0, []
    for s in sorted(counts):
        for share in shares:
            at = max(0, ceil(share * n) - 1)
            if before <= at < before + counts[s]:
                asked.append((float(share), s, at - before + 1))
        before += counts[s]
    wanted = result.segmented.sparkSession.createDataFrame(asked, f"share double, {SEGMENT} int, __at int")
    inside = F.row_number().over(Window.partitionBy(SEGMENT).orderBy(*spec.orders()))
    some = result.segmented.where(F.col(SEGMENT).isin([s for _, s, _ in asked])).select(SEGMENT, *spec.columns()).withColumn("__place", inside)
    return some.join(F.broadcast(wanted), SEGMENT).where(F.col("__place") == F.col("__at")).select("share", key.alias("value"))  # a row a share


def histogram(segmented: DataFrame, spec: KeySpec) -> DataFrame:
    """(rank, n, lo, hi): the ranks as an equi-depth histogram."""
    key = F.col(spec.key[0])
    return segmented.groupBy(F.col(SEGMENT).alias("rank")).agg(F.count("*").alias("n"), F.min(key).alias("lo"), F.max(key).alias("hi"))


def top_k(df: DataFrame, spec: KeySpec, tree: PivotTree, k: int) -> DataFrame:
    """The first k rows: only the leading segments that hold them are looked at."""
    segmented = with_segments(df, spec, tree)
    counts = {r[SEGMENT]: r["n"] for r in segmented.groupBy(SEGMENT).agg(F.count("*").alias("n")).collect()}  # p rows
    seen, last = 0, -1
    for s in sorted(counts):
        if seen >= k:
            break
        seen, last = seen + counts[s], s
    return segmented.where(F.col(SEGMENT) <= last).orderBy(*spec.orders()).limit(k)


def top_k_group(df: DataFrame, spec: KeySpec, by: list[str], k: int, salts: int = 32) -> DataFrame:
    """The first k rows of each group, first within salted parts, so that no task orders a hot group alone."""
    part = Window.partitionBy(*by, F.pmod(F.xxhash64(*spec.columns()), F.lit(salts))).orderBy(*spec.orders())
    some = df.withColumn("__k", F.row_number().over(part)).where(F.col("__k") <= k)
    return some.withColumn("__k", F.row_number().over(Window.partitionBy(*by).orderBy(*spec.orders()))).where(F.col("__k") <= k).withColumnRenamed("__k", "place")


def page(result: Sorted, offset: int, length: int) -> DataFrame:
    """Rows at positions offset to offset + length - 1."""
    placed = result.with_positions()
    return placed.where((F.col(POSITION) >= offset) & (F.col(POSITION) < offset + length))


def global_ranks(result: Sorted) -> DataFrame:
    """Adds rank, dense_rank and percent_rank over the whole relation, from places within segments and offsets.

    Equal keys lie in one segment (ties go left), so a key's rank is its segment's offset and its rank there.
    """
    spec, inside = result.spec, Window.partitionBy(SEGMENT).orderBy(*(o for o in KeySpec(result.spec.key, (), result.spec.descending, result.spec.nulls_first).orders()))
    key = F.struct(*(F.col(c) for c in spec.key))
    sizes = result.segmented.groupBy(SEGMENT).agg(F.count("*").alias("n"), F.count_distinct(key).alias("d")).collect()  # p rows
    total = sum(r["n"] for r in sizes)
    out = result.rows.withColumns({"rank": F.rank().over(inside).cast("long"), "dense_rank": F.dense_rank().over(inside).cast("long")})
    out = add_offsets(out, "rank", {r[SEGMENT]: r["n"] for r in sizes})
    out = add_offsets(out, "dense_rank", {r[SEGMENT]: r["d"] for r in sizes})
    return out.withColumn("percent_rank", (F.col("rank") - 1).cast("double") / max(total - 1, 1))


def dedup_sorted(segmented: DataFrame, spec: KeySpec) -> DataFrame:
    """The first row of each key: the neighbour before it in its segment differs."""
    inside = Window.partitionBy(SEGMENT).orderBy(*spec.orders())
    before = F.lag(F.struct(*(F.col(c) for c in spec.key))).over(inside)
    fresh = ~F.struct(*(F.col(c) for c in spec.key)).eqNullSafe(before)
    return segmented.withColumn("__fresh", fresh | before.isNull()).where("__fresh").drop("__fresh")


def merge_sorted(a: DataFrame, b: DataFrame, spec: KeySpec, p: int) -> Sorted:
    """Two relations of the same columns as one sorted relation: pivots of both together, one delivery."""
    from ..placement import RANK, place
    from ..plans.redistribute import deliver

    both = a.unionByName(b)
    if RANK not in both.columns:
        both = place(both, p)
    tree = agree(both, spec, p)
    segmented = with_segments(both, spec, tree)
    return Sorted(deliver(segmented, spec, p), segmented, tree, spec)
