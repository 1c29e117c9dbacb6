"""Choosing pivots: what each rank proposes for a segment, and how the ranks agree.

A chooser gets rows (rank, segment, value) and returns one row a segment, (segment, pivot,
n_contributors).  Ranks with nothing in a segment propose nothing.  Two ways to that are kept, which
give the same pivots: leaving them out of the reduction, or letting them enter the neutral element.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..keys import comparable, midpoint
from ..placement import RANK
from .pivot_tree import SEGMENT

VALUE = "__value"
_TIE = "__tie"


# --- what a rank proposes ---


@dataclass(frozen=True)
class Extremes:
    """The ends of the rank's part of the segment."""

    def propose(self, rows: DataFrame) -> DataFrame:
        return rows.groupBy(SEGMENT, RANK).agg(F.count("*").alias("cnt"), F.min(VALUE).alias("lo"), F.max(VALUE).alias("hi"))


@dataclass(frozen=True)
class SampleExtremes:
    """The ends of a seeded sample of ``s`` rows of the rank's part; without a seed the rows of least tie number."""

    s: int = 20
    seed: int | None = 5

    def propose(self, rows: DataFrame) -> DataFrame:
        return Extremes().propose(_sample(rows, self.s, self.seed))


@dataclass(frozen=True)
class MiddleElement:
    """The middle of the rank's part in order: zero-based place half its length, rounded down."""

    def propose(self, rows: DataFrame) -> DataFrame:
        part = Window.partitionBy(SEGMENT, RANK)
        ranked = rows.where(F.col(VALUE).isNotNull()).withColumns({"__n": F.count("*").over(part), "__k": F.row_number().over(part.orderBy(VALUE))})
        middle = ranked.where(F.col("__k") == F.floor(F.col("__n") / 2) + 1)
        return middle.select(SEGMENT, RANK, F.col("__n").alias("cnt"), F.col(VALUE).alias("mid"))


@dataclass(frozen=True)
class ApproximateMiddle:
    """The middle of the rank's part within 1 / accuracy of its rows: one pass, no sort; numbers only."""

    accuracy: int = 1000

    def propose(self, rows: DataFrame) -> DataFrame:
        return rows.groupBy(SEGMENT, RANK).agg(F.count("*").alias("cnt"), F.percentile_approx(VALUE, 0.5, self.accuracy).alias("mid")).where("mid is not null")


@dataclass(frozen=True)
class RandomElement:
    """Some element: the one whose seeded hash is least."""

    seed: int = 5

    def propose(self, rows: DataFrame) -> DataFrame:
        hashed = F.struct(F.xxhash64(F.lit(self.seed), VALUE, _TIE), VALUE)
        return rows.where(F.col(VALUE).isNotNull()).groupBy(SEGMENT, RANK).agg(F.count("*").alias("cnt"), F.min(hashed)[VALUE].alias("mid"))


@dataclass(frozen=True)
class FirstElement:
    """The element that comes first by the ties' order."""

    def propose(self, rows: DataFrame) -> DataFrame:
        return rows.where(F.col(VALUE).isNotNull()).groupBy(SEGMENT, RANK).agg(F.count("*").alias("cnt"), F.min_by(VALUE, F.struct(_TIE, VALUE)).alias("mid"))


@dataclass(frozen=True)
class SamplePool:
    """A seeded sample of ``s`` rows, every one a candidate."""

    s: int = 20
    seed: int = 5

    def propose(self, rows: DataFrame) -> DataFrame:
        return _sample(rows, self.s, self.seed).select(SEGMENT, RANK, F.lit(1).alias("cnt"), F.col(VALUE).alias("mid"))


def _sample(rows: DataFrame, s: int, seed: int | None) -> DataFrame:
    """At most s rows of each (segment, rank), those of least seeded hash; bounded state by two-step ranking."""
    order = [F.col(_TIE) if seed is None else F.xxhash64(F.lit(seed), VALUE, _TIE), F.col(VALUE)]
    part = Window.partitionBy(SEGMENT, RANK).orderBy(*order)
    return rows.where(F.col(VALUE).isNotNull()).withColumn("__k", F.row_number().over(part)).where(F.col("__k") <= s)


# --- how the ranks agree ---


@dataclass(frozen=True)
class Midpoint:
    """Half way between the least and the greatest proposal; the least travels as the greatest of the negated.

    empty: ``skip`` leaves ranks without a proposal out, ``neutral`` enters the operator's neutral element for them.
    """

    empty: str = "skip"

    def agree(self, proposed: DataFrame, kind: T.DataType, p: int) -> DataFrame:
        low, high = F.col("lo"), F.col("hi")
        if self.empty == "neutral":
            if not isinstance(kind, (T.DoubleType, T.FloatType)):
                raise TypeError("the neutral element is an infinity, so the key is a floating-point number")
            every = proposed.select(SEGMENT).distinct().withColumn(RANK, F.explode(F.sequence(F.lit(0), F.lit(p - 1))))
            proposed = every.join(proposed, [SEGMENT, RANK], "left")
            low, high = F.coalesce(low, F.lit(float("inf"))), F.coalesce(high, F.lit(float("-inf")))
        ends = proposed.groupBy(SEGMENT).agg(F.min(low).alias("lo"), F.max(high).alias("hi"), F.count("cnt").alias("n_contributors"))
        return ends.where("lo <= hi").select(SEGMENT, midpoint(F.col("lo"), F.col("hi"), kind).alias("pivot"), "n_contributors")


@dataclass(frozen=True)
class Designated:
    """The proposal of one rank, or of the next that has one."""

    rank: int = 0

    def agree(self, proposed: DataFrame, kind: T.DataType, p: int) -> DataFrame:
        turn = F.pmod(F.col(RANK) - self.rank, F.lit(p))
        return proposed.groupBy(SEGMENT).agg(F.min_by("mid", turn).alias("pivot"), F.count("*").alias("n_contributors"))


@dataclass(frozen=True)
class MedianOfCandidates:
    """The lower middle of all proposals; there are at most p a segment, or p * s of pools."""

    def agree(self, proposed: DataFrame, kind: T.DataType, p: int) -> DataFrame:
        sorted_all = F.sort_array(F.collect_list("mid"))
        found = proposed.groupBy(SEGMENT).agg(sorted_all.alias("all"))
        return found.select(SEGMENT, F.get("all", (F.floor((F.size("all") + 1) / 2) - 1).cast("int")).alias("pivot"), F.size("all").cast("long").alias("n_contributors"))


@dataclass(frozen=True)
class MeanOfCandidates:
    """The mean of all proposals, in the key's type."""

    def agree(self, proposed: DataFrame, kind: T.DataType, p: int) -> DataFrame:
        return proposed.groupBy(SEGMENT).agg(F.avg("mid").cast(kind).alias("pivot"), F.count("*").alias("n_contributors"))


# --- both together ---


@dataclass(frozen=True)
class Chooser:
    """A local and a global choice.  ``tie``: a column that tells equal keys apart for the seeded hashes."""

    local: object = Extremes()
    agreed: object = Midpoint()

    def choose(self, rows: DataFrame, kind: T.DataType, p: int) -> DataFrame:
        if isinstance(self.local, Extremes) and isinstance(self.agreed, Midpoint) and self.agreed.empty == "skip":
            # one aggregate: the ends of all ranks are the ends of the segment
            ends = rows.groupBy(SEGMENT).agg(F.min(VALUE).alias("lo"), F.max(VALUE).alias("hi"), F.lit(None).cast("long").alias("n_contributors"))
            return ends.where("lo is not null").select(SEGMENT, midpoint(F.col("lo"), F.col("hi"), kind).alias("pivot"), "n_contributors")
        return self.agreed.agree(self.local.propose(rows), kind, p)


@dataclass(frozen=True)
class ExactMedian:
    """The lower middle of the whole segment: ideal pivots.

    For numbers a sketch brackets the middle to within ``2 / accuracy`` of the segment's rows, equal keys
    are counted together, and only the bracket's distinct keys are ordered.  Keys of other types are
    ordered whole, segment by segment, which is for moderate sizes.
    """

    accuracy: int = 10_000

    def choose(self, rows: DataFrame, kind: T.DataType, p: int) -> DataFrame:
        known = rows.where(F.col(VALUE).isNotNull())
        counted, below = known.groupBy(SEGMENT, VALUE).agg(F.count("*").alias("c")), F.lit(0)
        sizes = known.groupBy(SEGMENT).agg(F.count("*").alias("n"))
        if isinstance(kind, T.NumericType):
            margin = 2.0 / self.accuracy
            ends = F.percentile_approx(VALUE, [max(0.0, 0.5 - margin), min(1.0, 0.5 + margin)], self.accuracy)
            sizes = known.groupBy(SEGMENT).agg(F.count("*").alias("n"), ends.alias("ends"))
            marked = known.join(F.broadcast(sizes.drop("n")), SEGMENT)  # a row a segment
            under = marked.groupBy(SEGMENT).agg(F.count_if(F.col(VALUE) < F.col("ends")[0]).alias("under"))
            inside = marked.where((F.col(VALUE) >= F.col("ends")[0]) & (F.col(VALUE) <= F.col("ends")[1]))
            counted = inside.groupBy(SEGMENT, VALUE).agg(F.count("*").alias("c"))
            sizes, below = sizes.drop("ends").join(under, SEGMENT), F.col("under")
        upto = F.sum("c").over(Window.partitionBy(SEGMENT).orderBy(VALUE).rowsBetween(Window.unboundedPreceding, 0))
        placed = counted.join(F.broadcast(sizes), SEGMENT).withColumn("upto", upto + below)
        middle = F.floor((F.col("n") + 1) / 2)
        return placed.where((F.col("upto") >= middle) & (F.col("upto") - F.col("c") < middle)).select(SEGMENT, F.col(VALUE).alias("pivot"), F.col("n").alias("n_contributors"))


@dataclass(frozen=True)
class Sketch:
    """The middle of the whole segment by a mergeable quantile sketch: one pass, numbers only.

    kind: ``gk`` bounds the rank error by 1 / accuracy; ``kll`` is smaller, with a likely error of about 1 / k.
    """

    accuracy: int = 10_000
    kind: str = "gk"

    def choose(self, rows: DataFrame, kind: T.DataType, p: int) -> DataFrame:
        if self.kind == "kll":
            sketch = F.kll_sketch_agg_double(F.col(VALUE).cast("double"), min(self.accuracy, 65_535))
            middle = F.kll_sketch_get_quantile_double(sketch, F.lit(0.5)).cast(kind)
        elif self.kind == "gk":
            middle = F.percentile_approx(VALUE, 0.5, self.accuracy)
        else:
            raise ValueError(f"no sketch is called {self.kind}")
        return rows.groupBy(SEGMENT).agg(middle.alias("pivot"), F.count("*").alias("n_contributors")).where("pivot is not null")


MIDPOINT = Chooser(Extremes(), Midpoint())
SAMPLED = Chooser(SampleExtremes(20), Midpoint())
SAMPLED_BY_TIE = Chooser(SampleExtremes(20, None), Midpoint())
MIDDLE = Chooser(MiddleElement(), MedianOfCandidates())


def round_rows(df: DataFrame, value: Column, kind: T.DataType, segment: Column, tie: Column) -> DataFrame:
    """What a round reads: rank, segment, value and a number for ties; the payload stays in the files."""
    return df.select(RANK, segment.alias(SEGMENT), comparable(value, kind).alias(VALUE), tie.alias(_TIE))
