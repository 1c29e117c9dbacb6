"""Keys: what rows are ordered by, and the arithmetic that pivots need."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

NUMERIC = (T.NumericType,)
_ORDERED = (T.NumericType, T.StringType, T.BinaryType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType, T.DayTimeIntervalType, T.StructType, T.ArrayType)


@dataclass(frozen=True)
class KeySpec:
    """An order: key columns, then columns that break ties between equal keys.

    descending: key columns that run downwards; in a composite key these must be numbers, because the
    pivots compare one structure.  nulls_first: where rows with a null in a one-column key go.
    """

    key: tuple[str, ...]
    tiebreak: tuple[str, ...] = ()
    descending: tuple[str, ...] = ()
    nulls_first: bool = True

    def __post_init__(self):
        if isinstance(self.key, str):
            object.__setattr__(self, "key", (self.key,))
        if not self.key or not set(self.descending) <= set(self.key):
            raise ValueError("a key has one column or more, and only its own columns can run downwards")

    @property
    def reversed(self) -> bool:
        """A single key that runs downwards: pivots compare the other way round."""
        return len(self.key) == 1 and bool(self.descending)

    def check(self, df: DataFrame) -> None:
        """Refuse keys that have no order."""
        for name in self.key:
            kind = df.schema[name].dataType
            if not isinstance(kind, _ORDERED):
                raise TypeError(f"the key column {name} of type {kind.simpleString()} has no order")
            if len(self.key) > 1 and name in self.descending and not isinstance(kind, NUMERIC):
                raise TypeError(f"in a composite key only numbers can run downwards, and {name} is {kind.simpleString()}")

    def value(self) -> Column:
        """What pivots compare."""
        if len(self.key) == 1:
            return F.col(self.key[0])
        return F.struct(*((-F.col(c) if c in self.descending else F.col(c)).alias(f"k{i}") for i, c in enumerate(self.key)))

    def total(self) -> Column:
        """Key and ties as one structure, for pivots in a total order."""
        return F.struct(self.value().alias("key"), *(F.col(c).alias(f"t{i}") for i, c in enumerate(self.tiebreak)))

    def orders(self) -> list[Column]:
        """Sort orders of key and ties."""
        out = []
        for name in self.key:
            column = F.col(name)
            down = name in self.descending
            if len(self.key) > 1:
                out.append(column.desc() if down else column.asc())
            elif self.nulls_first:
                out.append(column.desc_nulls_first() if down else column.asc_nulls_first())
            else:
                out.append(column.desc_nulls_last() if down else column.asc_nulls_last())
        return out + [F.col(c).asc() for c in self.tiebreak]

    def columns(self) -> list[str]:
        return list(dict.fromkeys((*self.key, *self.tiebreak)))


def comparable(value: Column, kind: T.DataType) -> Column:
    """The value where it may be a pivot: NaN is not, as a midpoint with it is NaN."""
    return F.when(~F.isnan(value), value) if isinstance(kind, (T.DoubleType, T.FloatType)) else value


def midpoint(low: Column, high: Column, kind: T.DataType) -> Column:
    """Half way from low to high in the key's own type, rounded down, without overflow."""
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        total = low + high
        half = F.when(F.abs(total) == float("inf"), low / 2 + high / 2).otherwise(total / 2)
        return half.cast(kind)
    if isinstance(kind, T.IntegralType):
        wide = F.floor((low.cast("decimal(38,0)") + high.cast("decimal(38,0)")) / 2)
        return wide.cast(kind)
    if isinstance(kind, T.DecimalType):
        return ((low + high) / 2).cast(kind)
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.timestamp_micros(midpoint(F.unix_micros(low.cast("timestamp")), F.unix_micros(high.cast("timestamp")), T.LongType())).cast(kind)
    if isinstance(kind, T.DateType):
        return F.date_from_unix_date(midpoint(F.unix_date(low), F.unix_date(high), T.IntegerType()))
    if isinstance(kind, T.DayTimeIntervalType):
        return low + (high - low) / 2
    if isinstance(kind, T.BooleanType):
        return low & high
    raise TypeError(f"a midpoint needs arithmetic, which {kind.simpleString()} has not; use a pivot that is an element")
