"""Pivot trees: which segment a key belongs to.

Pivots are kept in heap order, the root at 1 and the children of slot h at 2h and 2h + 1, so level i
fills the slots 2^i to 2^(i+1) - 1, one for each segment that exists before it.  A tree may stop short
of the last level; its leaves are then the segments so far.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from typing import Any

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..placement import levels_of

SEGMENT = "__segment"
#: Up to so many segments the walk is nested conditions, which are compiled; then one fold over pivots in the
#: plan; then over one constant, or for flat numbers a binary search in Arrow.  All give the same segments.
NESTED, FOLDED = 64, 1024
_FLAT = (T.IntegralType, T.DoubleType, T.FloatType)
#: JSON that keeps instants to the microsecond.
_EXACT = {"timestampFormat": "yyyy-MM-dd HH:mm:ss.SSSSSSXXX", "timestampNTZFormat": "yyyy-MM-dd HH:mm:ss.SSSSSS"}


def literal(value: Any, kind: T.DataType) -> Column:
    """A pivot as a constant of the key's type."""
    if isinstance(kind, T.StructType):
        return F.struct(*(literal(value[i] if value is not None else None, f.dataType).alias(f.name) for i, f in enumerate(kind)))
    if isinstance(kind, T.ArrayType):
        return F.array(*(literal(v, kind.elementType) for v in value)) if value is not None else F.lit(None).cast(kind)
    return F.lit(value).cast(kind)


@dataclass(frozen=True)
class PivotTree:
    """Pivots in heap order (slot 1 first), of keys of one type; ``reverse`` for an order that runs downwards."""

    pivots: tuple = ()
    kind: T.DataType | None = None
    reverse: bool = False

    @property
    def levels(self) -> int:
        return (len(self.pivots) + 1).bit_length() - 1

    @property
    def segments(self) -> int:
        return len(self.pivots) + 1

    def extend(self, by_segment: dict[int, Any], kind: T.DataType) -> PivotTree:
        """One more level.  A segment without a pivot, empty on every rank, takes its parent's, which keeps the order."""
        first = self.segments
        added = [by_segment[s] if by_segment.get(s) is not None else (self.pivots[(first + s) // 2 - 1] if first > 1 else None) for s in range(first)]
        if added[0] is None and first == 1:
            added = [by_segment.get(0)]
        return PivotTree(self.pivots + tuple(added), kind, self.reverse)

    @staticmethod
    def from_sorted(splitters: list, kind: T.DataType, reverse: bool = False) -> PivotTree:
        """The tree whose leaves the sorted splitters bound: in-order slot i holds splitter i."""
        p = len(splitters) + 1
        heap = [None] * (p - 1)
        for level in range(levels_of(p)):
            for s in range(1 << level):
                heap[(1 << level) + s - 1] = splitters[inorder_slot(level, s, p) - 1]
        return PivotTree(tuple(heap), kind, reverse)

    def in_order(self) -> list:
        """The pivots from the smallest up."""
        p, out = self.segments, [None] * len(self.pivots)
        for level in range(self.levels):
            for s in range(1 << level):
                out[inorder_slot(level, s, p) - 1] = self.pivots[(1 << level) + s - 1]
        return out

    def _right(self, key: Column, pivot: Column) -> Column:
        return key < pivot if self.reverse else key > pivot

    def segment(self, key: Column, nulls_first: bool = True) -> Column:
        """The segment of a key: equal to a pivot goes left; a null to the first or the last segment."""
        last = self.segments - 1
        if not self.pivots or all(x is None for x in self.pivots):
            inner = F.lit(0)
        elif self.segments <= NESTED:
            inner = self._nested(key, 1)
        elif self.segments > FOLDED and isinstance(self.kind, _FLAT):
            inner = self._searched(key)
        else:
            tree = F.array(*(literal(x, self.kind) for x in self.pivots)) if self.segments <= FOLDED else self._constant()
            step = lambda slot, _: slot * 2 + F.when(self._right(key, F.get(tree, slot - 1)), 1).otherwise(0)
            inner = F.aggregate(F.sequence(F.lit(1), F.lit(self.levels)), F.lit(1), step) - self.segments
        return F.when(key.isNull(), F.lit(0 if nulls_first else last)).otherwise(inner).cast("int")

    def _nested(self, key: Column, slot: int) -> Column:
        if slot > len(self.pivots):
            return F.lit(slot - self.segments)
        if self.pivots[slot - 1] is None:
            return self._nested(key, 2 * slot)
        return F.when(self._right(key, literal(self.pivots[slot - 1], self.kind)), self._nested(key, 2 * slot + 1)).otherwise(self._nested(key, 2 * slot))

    def _constant(self) -> Column:
        """All pivots as one constant, through JSON: the plan does not hold an expression for each."""
        kind = T.ArrayType(self.kind)
        table = SparkSession.active().createDataFrame([(list(self.pivots),)], T.StructType([T.StructField("pivots", kind)]))
        return F.from_json(F.lit(table.select(F.to_json("pivots", _EXACT)).first()[0]), kind, _EXACT)

    def _searched(self, key: Column) -> Column:
        """A binary search over the pivots, which are sent to the workers once; NaN is beyond all numbers."""
        import numpy as np

        kind = np.float64 if isinstance(self.kind, (T.DoubleType, T.FloatType)) else np.int64
        upwards = np.array(self.in_order()[::-1] if self.reverse else self.in_order(), kind)
        sent, reverse = SparkSession.active().sparkContext.broadcast(upwards), self.reverse

        def search(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
            for keys in batches:
                values = keys.to_numpy(zero_copy_only=False)
                if reverse:  # pivots beyond the key, of which NaN has none
                    found = len(sent.value) - np.searchsorted(sent.value, values, "right")
                else:
                    found = np.searchsorted(sent.value, values, "left")
                yield pa.array(found.astype(np.int32))

        return F.arrow_udf(search, "int")(F.coalesce(key, F.lit(0).cast(self.kind)))

    def overlapping(self, low: Any, high: Any) -> tuple[int, int]:
        """First and last segment that can hold keys from low to high (None: unbounded)."""
        order = self.in_order()
        if self.reverse:
            low, high = high, low
        beyond = (lambda k, x: k < x) if self.reverse else (lambda k, x: k > x)
        return (0 if low is None else sum(beyond(low, x) for x in order)), (len(order) if high is None else sum(beyond(high, x) for x in order))

    def table(self, spark: SparkSession) -> DataFrame:
        """(level, segment, heap_slot, inorder_slot, pivot)."""
        rows = [Row(level=level, segment=s, heap_slot=(1 << level) + s, inorder_slot=inorder_slot(level, s, self.segments), pivot=self.pivots[(1 << level) + s - 1]) for level in range(self.levels) for s in range(1 << level)]
        fields = [T.StructField(n, T.IntegerType()) for n in ("level", "segment", "heap_slot", "inorder_slot")]
        return spark.createDataFrame(rows, T.StructType([*fields, T.StructField("pivot", self.kind or T.DoubleType())]))


def inorder_slot(level: int, segment: int, p: int) -> int:
    """Where a level's pivot stands among all p - 1 in ascending order."""
    return (2 * segment + 1) * p >> (level + 1)


def slots(spark: SparkSession, p: int) -> DataFrame:
    """(level, segment, heap_slot, inorder_slot) of a full tree."""
    heap = spark.range(1, p).select(F.col("id").cast("int").alias("heap_slot"))
    with_level = heap.withColumn("level", F.length(F.bin("heap_slot")) - 1).withColumn("segment", F.col("heap_slot") - F.call_function("shiftleft", F.lit(1), F.col("level")))
    inorder = F.call_function("shiftright", (F.col("segment") * 2 + 1) * p, F.col("level") + 1)
    return with_level.select("level", "segment", "heap_slot", inorder.cast("int").alias("inorder_slot"))
