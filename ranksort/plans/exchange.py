"""The exchange variants: at every level partner ranks swap rows, one shuffle each."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..keys import KeySpec
from ..placement import RANK, levels_of
from ..shared import keep
from .pivot_tree import SEGMENT, PivotTree
from .pivots import MIDPOINT
from .redistribute import merge_runs
from .rounds import agree, compared


TRACE = "__trace"


def exchange_levels(df: DataFrame, spec: KeySpec, p: int, levels: int, chooser=MIDPOINT, *, ties: str = "left", order: str | None = None, tie: Column | None = None) -> tuple[DataFrame, PivotTree]:
    """The first ``levels`` levels: agree on a pivot a group, swap by one bit of the rank, go on in both halves.

    A group is a segment: before level i the leading i bits of a row's rank say which, so a round looks
    at the ranks of the group alone.  Each level's shuffle is checkpointed, or Catalyst would run all
    levels before it again for the next pivots, and join the shuffles into one.
    order: None, or how ranks keep their rows in order after a swap, ``sort`` or ``merge``.  A column
    ``TRACE`` (array of int), if the rows have it, gets each row's rank after every exchange.
    """
    value, kind = compared(df, spec, ties)
    tree, depth = PivotTree((), kind, spec.reversed), levels_of(p)
    if order:
        df = keep(df.repartitionById(p, F.col(RANK)).sortWithinPartitions(*spec.orders()))
    for level in range(levels):
        tree = agree(df, spec, p, chooser, tree=tree, levels=level + 1, ties=ties, in_order=order is not None, tie=tie)
        bit = 1 << (depth - 1 - level)
        right = (tree.segment(value, spec.nulls_first) % 2).cast("int")
        swapped = df.withColumn(RANK, F.col(RANK).bitwiseAND(F.lit(~bit)) + right * bit)
        if TRACE in df.columns:
            swapped = swapped.withColumn(TRACE, F.array_append(TRACE, F.col(RANK)))
        sent = swapped.repartitionById(p, F.col(RANK))
        if order == "sort":
            sent = sent.sortWithinPartitions(*spec.orders())
        elif order == "merge":
            sent = merge_runs(sent, spec)
        df = keep(sent)
    return df, tree


def as_segments(df: DataFrame) -> DataFrame:
    """After all levels a row's rank is its segment."""
    return df.withColumn(SEGMENT, F.col(RANK))
