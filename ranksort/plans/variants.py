"""The sorting methods.  Each takes rows with a starting rank and returns them in order, segment j on partition j."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..keys import KeySpec, comparable
from ..placement import RANK, levels_of
from ..shared import keep
from .exchange import as_segments, exchange_levels
from .pivot_tree import SEGMENT, PivotTree
from .pivots import MIDDLE, MIDPOINT
from .redistribute import POSITION, deliver, merge_runs, positions, with_segments
from .rounds import agree, agree_fused, agree_on_sample, compared, sketch_splitters, splitters_of


@dataclass(frozen=True)
class Sorted:
    """A sorted relation: its rows with their segment, before and after delivery, and the pivots."""

    rows: DataFrame
    segmented: DataFrame
    tree: PivotTree
    spec: KeySpec

    def with_positions(self) -> DataFrame:
        return positions(self.segmented, self.rows, self.spec)


def local_sort(df: DataFrame, spec: KeySpec) -> Sorted:
    """The reference for speed-up: one partition, one sort."""
    spec.check(df)
    one = df.withColumn(SEGMENT, F.lit(0))
    return Sorted(one.coalesce(1).sortWithinPartitions(*spec.orders()), one, PivotTree(), spec)


def exchange_quicksort(df: DataFrame, spec: KeySpec, p: int, chooser=MIDPOINT, ties: str = "left", tie: Column | None = None) -> Sorted:
    """Rows move at every level; a sort at the end."""
    spec.check(df)
    moved, tree = exchange_levels(df, spec, p, levels_of(p), chooser, ties=ties, tie=tie)
    done = as_segments(moved)
    return Sorted(done.repartitionById(p, F.col(SEGMENT)).sortWithinPartitions(SEGMENT, *spec.orders()), done, tree, spec)


def exchange_sort_first(df: DataFrame, spec: KeySpec, p: int, chooser=MIDDLE, ties: str = "left", order: str = "sort") -> Sorted:
    """Ranks sort first and keep their rows in order through every swap, by a merge or a new sort."""
    spec.check(df)
    moved, tree = exchange_levels(df, spec, p, levels_of(p), chooser, ties=ties, order=order)
    done = as_segments(moved)
    return Sorted(done.repartitionById(p, F.col(SEGMENT)).sortWithinPartitions(SEGMENT, *spec.orders()), done, tree, spec)


def exchange_free_quicksort(df: DataFrame, spec: KeySpec, p: int, chooser=MIDPOINT, ties: str = "left", plan: str = "iterative", per_rank: int = 400, n: int | None = None, tie: Column | None = None) -> Sorted:
    """Only pivots travel; each row moves once, at the end.

    plan: ``iterative`` (a round a level), ``fused`` (three levels a round, by sketches), ``sample`` (all levels on
    one sample; ``n`` spares it a count) or ``sketch`` (one pass).
    """
    spec.check(df)
    if plan == "iterative":
        tree = agree(df, spec, p, chooser, ties=ties, tie=tie)
    elif plan == "sample":
        tree = agree_on_sample(df, spec, p, per_rank=per_rank, ties=ties, n=n)
    elif plan == "fused":
        tree = agree_fused(df, spec, p)
    elif plan == "sketch":
        tree = sketch_splitters(df, spec, p)
    else:
        raise ValueError(f"no plan is called {plan}")
    segmented = with_segments(df, spec, tree, ties)
    return Sorted(deliver(segmented, spec, p), segmented, tree, spec)


def _keys(local: DataFrame, spec: KeySpec) -> DataFrame:
    """What rounds read of sorted ranks, so that they do not read whole rows at every level."""
    thin = [RANK, *spec.columns()]
    return local if set(thin) == set(local.columns) else keep(local.select(*thin))


def exchange_free_sort_first(df: DataFrame, spec: KeySpec, p: int, chooser=MIDDLE, ties: str = "left", merge: str = "sort") -> Sorted:
    """The same on ranks that sort first, so that pivots are read by place and segments split by binary search; ends in a p-way merge.

    The rounds read a copy of the sorted keys alone.  merge: ``heap`` merges the runs that arrive; ``sort`` leaves it to Spark's sort, which merges runs too.
    """
    spec.check(df)
    if merge not in ("heap", "sort"):
        raise ValueError(f"no merge is called {merge}")
    local = keep(df.repartitionById(p, F.col(RANK)).sortWithinPartitions(*spec.orders()))
    tree = agree(_keys(local, spec), spec, p, chooser, ties=ties, in_order=True)
    segmented = with_segments(local, spec, tree, ties)
    rows = merge_runs(deliver(segmented, spec, p, sort=False), spec) if merge == "heap" else deliver(segmented, spec, p)
    return Sorted(rows, segmented, tree, spec)


def switch_level(n: int, p: int, c: float = 1500, *, log_base: float = 2.0, log_of: str = "input") -> int:
    """How many exchange levels come before the switch: the first at which n / p > c * ranks / log n.

    n / p stays the same through the levels while a group's ranks halve.  c = 0 switches at once, c =
    infinity never.  log_of: ``input`` takes the whole n, ``group`` the rows of the group.
    """
    depth = levels_of(p)
    if n < 2:
        return 0
    for level in range(depth + 1):
        ranks, rows = p >> level, (n >> level if log_of == "group" else n)
        if ranks == 1 or n / p > c * ranks / max(math.log(max(rows, 2), log_base), 1e-12):
            return level
    return depth


def _combined(df: DataFrame, spec: KeySpec, p: int, c: float, n: int | None, chooser, ties: str, order: str | None, fused: bool, merge: str, tie: Column | None = None) -> Sorted:
    spec.check(df)
    level = switch_level(df.count() if n is None else n, p, c)
    if fused and level:
        # the exchange levels as one shuffle of 2^level ways, from pivots agreed where the rows lie
        tree = agree(df, spec, p, chooser, levels=level, ties=ties, tie=tie)
        value, _ = compared(df, spec, ties)
        low = levels_of(p) - level
        group = tree.segment(value, spec.nulls_first)
        own = F.col(RANK).bitwiseAND(F.lit((1 << low) - 1))
        moved = keep(df.withColumn(RANK, (group * (1 << low) + own).cast("int")).repartitionById(p, F.col(RANK)))
    else:
        moved, tree = exchange_levels(df, spec, p, level, chooser, ties=ties, order=order, tie=tie)
    if order and not level:
        moved = keep(moved.repartitionById(p, F.col(RANK)).sortWithinPartitions(*spec.orders()))
    tree = agree(_keys(moved, spec) if order else moved, spec, p, chooser, tree=tree if level else None, ties=ties, in_order=order is not None, tie=tie)
    segmented = with_segments(moved, spec, tree, ties)
    rows = merge_runs(deliver(segmented, spec, p, sort=False), spec) if order and merge == "heap" else deliver(segmented, spec, p)
    return Sorted(rows, segmented, tree, spec)


def combined_quicksort(df: DataFrame, spec: KeySpec, p: int, c: float = 1500, *, n: int | None = None, chooser=MIDPOINT, ties: str = "left", fused: bool = False, tie: Column | None = None) -> Sorted:
    """Exchange levels until groups are small enough for their rows, then exchange-free inside each group."""
    return _combined(df, spec, p, c, n, chooser, ties, None, fused, "sort", tie)


def combined_sort_first(df: DataFrame, spec: KeySpec, p: int, c: float = 1500, *, n: int | None = None, chooser=MIDDLE, ties: str = "left", order: str = "sort", merge: str = "sort") -> Sorted:
    """The same on ranks that sort first."""
    return _combined(df, spec, p, c, n, chooser, ties, order, False, merge)


def sample_sort(df: DataFrame, spec: KeySpec, p: int, per_rank: int = 32, method: str = "random", ties: str = "left", n: int | None = None) -> Sorted:
    """Splitters drawn at once: ``random`` takes a seeded sample of each rank, ``regular`` evenly spaced rows of each sorted rank."""
    from pyspark.sql import Window

    spec.check(df)
    if method == "random":
        tree = agree_on_sample(df, spec, p, per_rank=per_rank, ties=ties, n=n)
    elif method == "regular":
        value, kind = compared(df, spec, ties)
        part = Window.partitionBy(RANK)
        ranked = df.select(RANK, comparable(value, kind).alias("v")).where("v is not null")
        ranked = ranked.withColumns({"n": F.count("*").over(part), "k": F.row_number().over(part.orderBy("v"))})
        step = F.greatest(F.lit(1), F.floor(F.col("n") / per_rank))
        tree = splitters_of(ranked.where((F.col("k") - 1) % step == 0).select("v"), p, kind, spec.reversed, expected=2 * p * per_rank)
    else:
        raise ValueError(f"no sampling method is called {method}")
    segmented = with_segments(df, spec, tree, ties)
    return Sorted(deliver(segmented, spec, p), segmented, tree, spec)


def native_sort(df: DataFrame, spec: KeySpec, p: int) -> DataFrame:
    """Spark's own global sort, for comparison: sampled splitters, one shuffle."""
    spec.check(df)
    return df.repartitionByRange(p, *spec.orders()).sortWithinPartitions(*spec.orders())


def native_positions(df: DataFrame, spec: KeySpec, p: int) -> DataFrame:
    """Spark's own sort with global positions, by its partitions' counts."""
    ranged = keep(native_sort(df, spec, p).withColumn(SEGMENT, F.spark_partition_id()))
    return positions(ranged, ranged, spec)


def rdd_sort(df: DataFrame, spec: KeySpec, p: int, tree: PivotTree) -> DataFrame:
    """The row-at-a-time form of delivery, for a paired comparison of shuffles: partition by the pivots, sort in the shuffle; with positions."""
    import bisect

    names, splitters, schema = spec.columns(), tree.in_order(), T.StructType(list(df.schema))
    if spec.descending or len(spec.key) != 1:
        raise ValueError("this form sorts one key upwards")
    keyed = df.rdd.map(lambda row: (tuple(row[n] for n in names), tuple(row)))
    done = keyed.repartitionAndSortWithinPartitions(p, lambda key: bisect.bisect_left(splitters, key[0]))
    return df.sparkSession.createDataFrame(done.zipWithIndex().map(lambda found: (*found[0][1], found[1])), schema.add(POSITION, "long"))
