"""Delivery: the one shuffle that brings each segment to its rank, and what can be read off before it."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..keys import KeySpec
from ..placement import RANK
from .ordered import sortable
from .pivot_tree import FOLDED, SEGMENT, PivotTree, literal

POSITION = "__pos"


def with_segments(df: DataFrame, spec: KeySpec, tree: PivotTree, ties: str = "left", deal: Column | None = None) -> DataFrame:
    """Adds the segment of each row under a rule for ties.

    left: a key equal to a pivot goes left.  even: keys equal to a pivot go left and right in turn, by a
    bit of the ties' hash at each level, so that equal keys spread over neighbouring segments.  three_way:
    a key that equals pivots may lie in any segment from the first of them to the last, and its rows are
    dealt over these.  total_order: ties are part of what is compared.  deal: a whole number that tells
    equal keys apart, by default a hash of the ties.
    """
    value = spec.total() if ties == "total_order" else spec.value()
    if ties in ("left", "total_order"):
        return df.withColumn(SEGMENT, tree.segment(value, spec.nulls_first))
    if deal is None and not spec.tiebreak:
        raise ValueError("dealing equal keys needs columns that tell them apart")
    hashed = F.xxhash64(*spec.tiebreak) if deal is None else deal.cast("long")
    if ties == "even":
        return df.withColumn(SEGMENT, _even(tree, value, hashed, spec.nulls_first))
    if ties == "three_way":
        low = tree.segment(value, spec.nulls_first)
        equal = F.lit(0)
        for x in dict.fromkeys(x for x in tree.pivots if x is not None):  # how many splitters a key equals
            equal = F.when(value == literal(x, tree.kind), tree.in_order().count(x)).otherwise(equal)
        return df.withColumn(SEGMENT, (low + F.pmod(hashed, (equal + 1).cast("long"))).cast("int"))
    raise ValueError(f"no rule for ties is called {ties}")


def _even(tree: PivotTree, value: Column, hashed: Column, nulls_first: bool) -> Column:
    def walk(slot: int) -> Column:
        if slot > len(tree.pivots):
            return F.lit(slot - tree.segments)
        if tree.pivots[slot - 1] is None:
            return walk(2 * slot)
        pivot, level = literal(tree.pivots[slot - 1], tree.kind), slot.bit_length() - 1
        odd = F.shiftrightunsigned(hashed, level).bitwiseAND(F.lit(1).cast("long")) == 1
        right = ((value < pivot) if tree.reverse else (value > pivot)) | ((value == pivot) & odd)
        return F.when(right, walk(2 * slot + 1)).otherwise(walk(2 * slot))

    return F.when(value.isNull(), 0 if nulls_first else tree.segments - 1).otherwise(walk(1)).cast("int")


def split_evenly(df: DataFrame, spec: KeySpec, tree: PivotTree) -> DataFrame:
    """Segments of a tree in which the rows equal to a pivot are halved exactly, whichever pivot it is.

    At each level the equal rows of a segment are numbered by their ties; even numbers go right.  One
    window a level, over the equal rows' partitions alone: a testing aid and for moderate sizes.
    """
    out, value = df.withColumn(SEGMENT, F.lit(0)), spec.value()
    for level in range(tree.levels):
        pivot = F.lit(None).cast(tree.kind)
        for s in range(1 << level):
            pivot = F.when(F.col(SEGMENT) == s, literal(tree.pivots[(1 << level) + s - 1], tree.kind)).otherwise(pivot)
        out = out.withColumn("__pivot", pivot)
        equal = value == F.col("__pivot")
        turn = F.row_number().over(Window.partitionBy(SEGMENT, equal).orderBy(*spec.orders()))
        right = ((value < F.col("__pivot")) if tree.reverse else (value > F.col("__pivot"))) | (equal & (turn % 2 == 0))
        out = out.withColumn("__right", F.coalesce(right, F.lit(False))).withColumn(SEGMENT, F.col(SEGMENT) * 2 + F.col("__right").cast("int")).drop("__pivot", "__right")
    return out


def count_matrix(segmented: DataFrame) -> DataFrame:
    """(src_rank, dst_rank, n): how many rows each rank sends to each."""
    return segmented.groupBy(F.col(RANK).alias("src_rank"), F.col(SEGMENT).alias("dst_rank")).agg(F.count("*").alias("n"))


def run_bounds(segmented: DataFrame) -> DataFrame:
    """(rank, segment, start, stop): where each segment lies in its rank's sorted rows.

    What a binary search for every pivot gives, read off the counts: p numbers a rank.
    """
    counts = segmented.groupBy(F.col(RANK).alias("rank"), F.col(SEGMENT).alias("segment")).agg(F.count("*").alias("n"))
    stop = F.sum("n").over(Window.partitionBy("rank").orderBy("segment").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return counts.withColumn("stop", stop).select("rank", "segment", (F.col("stop") - F.col("n")).alias("start"), "stop")


def deliver(segmented: DataFrame, spec: KeySpec, p: int, sort: bool = True) -> DataFrame:
    """Partition j of the result is segment j, in order if ``sort``."""
    sent = segmented.repartitionById(p, F.col(SEGMENT))
    return sent.sortWithinPartitions(SEGMENT, *spec.orders()) if sort else sent


def positions(segmented: DataFrame, delivered: DataFrame, spec: KeySpec) -> DataFrame:
    """Adds the zero-based global position: the place in the segment, plus the rows of the segments before.

    The counts are at most p rows, which is what the driver reads and the plan carries.
    """
    counts = {r[SEGMENT]: r["n"] for r in segmented.groupBy(SEGMENT).agg(F.count("*").alias("n")).collect()}
    place = F.row_number().over(Window.partitionBy(SEGMENT).orderBy(*spec.orders())).cast("long") - 1
    return add_offsets(delivered.withColumn(POSITION, place), POSITION, counts)


def add_offsets(df: DataFrame, column: str, sizes: dict[int, int]) -> DataFrame:
    """Adds to ``column`` the sizes of the segments before a row's own: from a map in the plan, or for many segments a broadcast table of p rows."""
    before, total = {}, 0
    for s in sorted(sizes):
        before[s], total = total, total + sizes[s]
    if not before:
        return df
    if len(before) <= FOLDED:
        offsets = F.create_map(*(F.lit(x) for s, n in before.items() for x in (s, n)))
        return df.withColumn(column, (F.col(column) + F.element_at(offsets, F.col(SEGMENT))).cast("long"))
    table = df.sparkSession.createDataFrame(list(before.items()), f"{SEGMENT} int, __before long")
    return df.join(F.broadcast(table), SEGMENT).withColumn(column, F.col(column) + F.col("__before")).select(*df.columns)


def merge_two(keys: np.ndarray, first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """Two sorted runs of places as one: each place's new position is its own and its rank in the other run; ties go to the first."""
    out = np.empty(len(first) + len(second), np.int64)
    out[np.arange(len(first)) + np.searchsorted(keys[second], keys[first], "left")] = first
    out[np.arange(len(second)) + np.searchsorted(keys[first], keys[second], "right")] = second
    return out


def merge_places(keys: np.ndarray) -> np.ndarray:
    """The order of numbers by merging their natural runs pairwise, log2 of the number of runs times over."""
    cuts = [0, *(np.flatnonzero(keys[1:] < keys[:-1]) + 1).tolist(), len(keys)]
    runs = [np.arange(a, b) for a, b in zip(cuts, cuts[1:])]
    while len(runs) > 1:
        runs = [merge_two(keys, runs[i], runs[i + 1]) if i + 1 < len(runs) else runs[i] for i in range(0, len(runs), 2)]
    return runs[0]


def _merged(table: pa.Table, spec: KeySpec) -> pa.Array:
    """The places of a partition's rows in order."""
    names = spec.columns()
    first = table[names[0]].combine_chunks()
    flat = (pa.types.is_integer(first.type) or pa.types.is_floating(first.type)) and not spec.descending
    if flat and len(spec.key) == 1:
        known = np.flatnonzero(first.is_valid().to_numpy(zero_copy_only=False))
        nulls = np.flatnonzero(first.is_null().to_numpy(zero_copy_only=False))
        keys = first.take(pa.array(known)).to_numpy(zero_copy_only=False)
        strange = np.flatnonzero(keys != keys)  # NaN, which comes last
        plain = np.flatnonzero(keys == keys)
        order = known[plain[merge_places(keys[plain])]] if len(plain) else known[:0]
        parts = [order, known[strange]]
        order = np.concatenate([nulls, *parts] if spec.nulls_first else [*parts, nulls])
        if len(names) == 1:
            return pa.array(order)
        values = first.take(pa.array(order))
        same = pc.fill_null(pc.equal(values[1:], values[:-1]), False).to_numpy(zero_copy_only=False)
        odd = ~(pc.fill_null(pc.equal(values, values), False).to_numpy(zero_copy_only=False))  # nulls and NaN: each one kind
        lone = ~np.concatenate(([False], same | (odd[1:] & odd[:-1] & (values.is_null().to_numpy(zero_copy_only=False)[1:] == values.is_null().to_numpy(zero_copy_only=False)[:-1]))))
        group = np.cumsum(lone)
        tied = np.flatnonzero(np.bincount(group)[group] > 1)
        if len(tied):  # only equal keys are put in order by their ties
            ties = table.select(names[1:]).take(pa.array(order[tied])).add_column(0, "__group", pa.array(group[tied]))
            order[tied] = order[tied][pc.sort_indices(ties, [(c, "ascending") for c in ties.column_names], null_placement="at_start").to_numpy()]
        return pa.array(order)
    keys = list(zip(*([sortable(x) for x in table[n].to_pylist()] for n in names)))
    cuts = [0, *(i for i in range(1, len(keys)) if keys[i] < keys[i - 1]), len(keys)]
    runs = [[(keys[i], i) for i in range(a, b)] for a, b in zip(cuts, cuts[1:])]
    return pa.array([i for _, i in heapq.merge(*runs)])


def merge_runs(delivered: DataFrame, spec: KeySpec) -> DataFrame:
    """Order each partition by merging its natural runs: the stretches that arrive in order.

    One numeric key is merged in arrays, pair by pair of runs; other keys by a heap over the runs, row
    after row.  Right whatever order blocks arrive in; the more of the senders' order survives, the fewer
    the runs.  For orders that run upwards, nulls first in all but a single numeric key; a task holds its
    partition.  ``deliver(sort=True)`` is the way for the others, and spills.
    """
    if spec.descending:
        raise ValueError("runs are merged upwards")

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if held:
            table = pa.Table.from_batches(held).combine_chunks()
            yield from table.take(_merged(table, spec)).to_batches(max_chunksize=10_000)

    return delivered.mapInArrow(merge, delivered.schema)
