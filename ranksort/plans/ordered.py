"""Rounds over ranks whose rows lie in order: pivots are read by place, segments are split by binary search.

A rank is one partition, sorted.  A pass reads each rank's keys once where they lie and gives a row a
segment and rank; no key is shuffled or sorted again.  A task holds one rank's keys.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from datetime import UTC, datetime, timedelta
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..keys import KeySpec, comparable
from ..placement import RANK
from .pivot_tree import SEGMENT, PivotTree
from .pivots import Extremes, MiddleElement

_PROBED = "__probed"
_FLAT = (T.IntegralType, T.DoubleType, T.FloatType)


def readable(chooser) -> bool:
    """Whether a chooser's proposals are places in an ordered segment: its ends or its middle."""
    return isinstance(getattr(chooser, "local", None), (Extremes, MiddleElement))


def _probed(value: Column, kind: T.DataType) -> Column:
    """The value as the search compares it: an instant as a number, which no time zone changes."""
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(value)
    if isinstance(kind, T.StructType):
        return F.when(value.isNotNull(), F.struct(*(_probed(value[f.name], f.dataType).alias(f.name) for f in kind)))
    return value


def _pivot(value: Any, kind: T.DataType) -> Any:
    """A collected pivot in the same form."""
    if value is None:
        return None
    if isinstance(kind, T.TimestampType):
        return (value.astimezone(UTC) - datetime(1970, 1, 1, tzinfo=UTC)) // timedelta(microseconds=1)
    if isinstance(kind, T.StructType):
        return tuple(_pivot(value[i], f.dataType) for i, f in enumerate(kind))
    return value


def sortable(value: Any) -> Any:
    """Spark's order of values as Python's: nulls first, NaN last."""
    if value is None:
        return (0,)
    if isinstance(value, dict):
        return (1, tuple(sortable(x) for x in value.values()))
    if isinstance(value, (tuple, list)):
        return (1, tuple(sortable(x) for x in value))
    if isinstance(value, float) and value != value:
        return (2,)
    return (1, value)


def search(keys: pa.Array, pivots: list, reverse: bool, flat: bool) -> np.ndarray:
    """Where each segment starts in the sorted keys of a rank, and their number: p log(n / p) probes; equal keys go left."""
    n = len(keys)
    if flat:
        values, wanted = keys.to_numpy(zero_copy_only=False), np.array(pivots, keys.type.to_pandas_dtype())
        stops = n - np.searchsorted(values[::-1], wanted, "left") if reverse else np.searchsorted(values, wanted, "right")
    elif reverse:
        stops = [n - bisect_left(range(n), sortable(x), key=lambda i: sortable(keys[n - 1 - i].as_py())) for x in pivots]
    else:
        stops = [bisect_right(range(n), sortable(x), key=lambda i: sortable(keys[i].as_py())) for x in pivots]
    return np.concatenate(([0], np.asarray(stops, np.int64), [n])).astype(np.int64)


def ranks_in_order(local: DataFrame, spec: KeySpec, ties: str) -> tuple[DataFrame, T.DataType]:
    """(rank, value, probed) of the rows that can be pivots, as they lie."""
    from .rounds import compared

    value, kind = compared(local, spec, ties)
    kept = local.select(RANK, comparable(value, kind).alias("value")).where("value is not null")
    return kept.withColumn(_PROBED, _probed(F.col("value"), kind)), kind


def _each_rank(batches: Iterator[pa.RecordBatch]) -> tuple[pa.Table, np.ndarray, list[int]] | None:
    held = [b for b in batches if b.num_rows]
    if not held:
        return None
    table = pa.Table.from_batches(held).combine_chunks()
    ranks = table[RANK].to_numpy()
    return table, ranks, [0, *(np.flatnonzero(np.diff(ranks)) + 1).tolist(), len(ranks)]


def proposals(ordered: DataFrame, kind: T.DataType, tree: PivotTree) -> DataFrame:
    """(segment, rank, cnt, lo, hi, mid): ends and zero-based middle of each segment of each rank, by place."""
    pivots, reverse, flat = _ready(tree, kind)
    schema = T.StructType([T.StructField(SEGMENT, T.IntegerType()), T.StructField(RANK, T.IntegerType()), T.StructField("cnt", T.LongType()), *(T.StructField(c, kind) for c in ("lo", "hi", "mid"))])

    def propose(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = _each_rank(batches)
        if found is None:
            return
        table, ranks, cuts = found
        values, probed = table["value"].chunk(0), table[_PROBED].chunk(0)
        for a, b in zip(cuts, cuts[1:]):
            bounds = a + search(probed.slice(a, b - a), pivots, reverse, flat)
            full = np.flatnonzero(np.diff(bounds))
            start, stop = bounds[full], bounds[full + 1]
            first, last, half = start, stop - 1, (stop - start) // 2
            places = (last, first, last - half) if reverse else (first, last, start + half)
            columns = [pa.array(full, pa.int32()), pa.array(np.full(len(full), ranks[a]), pa.int32()), pa.array(stop - start, pa.int64()), *(values.take(pa.array(x)) for x in places)]
            yield pa.RecordBatch.from_arrays(columns, [SEGMENT, RANK, "cnt", "lo", "hi", "mid"])

    return ordered.mapInArrow(propose, schema)


def _ready(tree: PivotTree, kind: T.DataType) -> tuple[list, bool, bool]:
    order = tree.in_order()
    return ([] if None in order else [_pivot(x, kind) for x in order]), tree.reverse, isinstance(kind, _FLAT)


def bounds(local: DataFrame, spec: KeySpec, tree: PivotTree, ties: str = "left") -> DataFrame:
    """(rank, segment, start, stop): where each segment with rows lies in its rank's sorted rows that have a key."""
    ordered, kind = ranks_in_order(local, spec, ties)
    pivots, reverse, flat = _ready(tree, kind)

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = _each_rank(batches)
        if found is None:
            return
        table, ranks, cuts = found
        probed = table[_PROBED].chunk(0)
        for a, b in zip(cuts, cuts[1:]):
            edges = search(probed.slice(a, b - a), pivots, reverse, flat)
            full = np.flatnonzero(np.diff(edges))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(full), ranks[a]), pa.int32()), pa.array(full, pa.int32()), pa.array(edges[full]), pa.array(edges[full + 1])], ["rank", "segment", "start", "stop"])

    return ordered.select(RANK, _PROBED).mapInArrow(split, "rank int, segment int, start long, stop long")
