"""Rounds of pivot agreement in which no row moves."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..keys import KeySpec, comparable
from ..placement import RANK, levels_of
from ..shared import keep
from . import ordered
from .pivot_tree import PivotTree
from .pivots import MIDPOINT, round_rows

def compared(df: DataFrame, spec: KeySpec, ties: str) -> tuple[Column, T.DataType]:
    """What pivots compare under a rule for ties, and its type."""
    if ties == "total_order" and (spec.reversed or not spec.nulls_first):
        raise ValueError("a total order runs upwards, nulls first")
    value = spec.total() if ties == "total_order" else spec.value()
    return value, df.select(value.alias("v")).schema["v"].dataType


def agree(df: DataFrame, spec: KeySpec, p: int, chooser=MIDPOINT, *, tree: PivotTree | None = None, levels: int | None = None, ties: str = "left", in_order: bool = False, tie: Column | None = None) -> PivotTree:
    """Pivots of all levels (or of the first ``levels``), level by level, from the rows where they lie.

    In each round every rank takes part for every segment; the driver sees one row a segment.  in_order:
    each rank is one partition, sorted; ends and middles are then read by place, which moves no key.
    tie: a whole number that tells rows apart, for seeded samples; by default a hash of the ties.
    """
    spec.check(df)
    value, kind = compared(df, spec, ties)
    tree = tree or PivotTree((), kind, spec.reversed)
    if tie is None:
        tie = F.xxhash64(*spec.tiebreak) if spec.tiebreak else F.lit(0).cast("long")
    while tree.levels < (levels_of(p) if levels is None else levels):
        if in_order and ordered.readable(chooser):
            found = chooser.agreed.agree(ordered.proposals(ordered.ranks_in_order(df, spec, ties)[0], kind, tree), kind, p)
        else:
            rows = round_rows(df, value, kind, tree.segment(value, spec.nulls_first), tie)
            found = chooser.choose(rows.where(F.col("__value").isNotNull()), kind, p)
        tree = tree.extend({r["__segment"]: r["pivot"] for r in found.collect()}, kind)  # a row a segment
    return tree


#: So many sampled keys are ordered in one task; more are ordered by ranges.
_IN_ONE_TASK = 1_000_000


def agree_on_sample(df: DataFrame, spec: KeySpec, p: int, *, per_rank: int = 400, seed: int = 5, ties: str = "left", n: int | None = None) -> PivotTree:
    """Pivots of all levels from one scan: a sample of the keys by seeded hash, then exact middles of the sample.

    The sample has about p * per_rank keys, of which a rank's share scatters by about 1 / sqrt(per_rank).
    n: the number of rows, which is counted if it is not given.
    """
    spec.check(df)
    value, kind = compared(df, spec, ties)
    tie = F.xxhash64(*spec.tiebreak) if spec.tiebreak else F.lit(0).cast("long")
    share = p * per_rank / max(1, df.count() if n is None else n)
    keys = df.select(comparable(value, kind).alias("v"), F.xxhash64(F.lit(seed), value, tie, F.col(RANK)).alias("h")).where("v is not null")
    sample = keys if share >= 1 else keys.where(F.shiftrightunsigned("h", 1) < int(share * (1 << 63)))
    return splitters_of(sample.select("v"), p, kind, spec.reversed, expected=p * per_rank)


def splitters_of(keys: DataFrame, p: int, kind: T.DataType, reverse: bool = False, expected: int | None = None) -> PivotTree:
    """The tree of p - 1 evenly spaced keys of a relation with one column ``v``; only these reach the driver.

    The i-th is at place n * i / p, counted from 1.  expected: about how many keys there are; up to a
    million are ordered in one task, more by ranges whose counts give the places.
    """
    if p == 1:
        return PivotTree((), kind, reverse)
    if expected is not None and expected <= _IN_ONE_TASK:
        every = F.sort_array(F.collect_list("v"), not reverse)
        place = lambda i: F.greatest(F.floor(F.size("a").cast("long") * i / p).cast("int") - 1, F.lit(0))
        found = keys.agg(every.alias("a")).select(F.transform(F.sequence(F.lit(1), F.lit(p - 1)), lambda i: F.get("a", place(i))).alias("s"), F.size("a").alias("n")).first()
        splitters, n = found["s"], found["n"]
        least = [i for i in range(1, p) if n * i // p]
        splitters = [splitters[max(i, least[0] if least else 1) - 1] for i in range(1, p)]
        return PivotTree.from_sorted(splitters, kind, reverse)
    order = F.col("v").desc() if reverse else F.col("v").asc()
    ranged = keep(keys.repartitionByRange(order).sortWithinPartitions(order).select("v", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("place")))
    sizes = {r["part"]: r["n"] for r in ranged.groupBy("part").agg(F.count("*").alias("n")).collect()}  # a row a partition
    before, n = {}, 0
    for part in sorted(sizes):
        before[part], n = n, n + sizes[part]
    if not n:
        return PivotTree((None,) * (p - 1), kind, reverse)
    starts = F.create_map(*(F.lit(x) for pair in before.items() for x in pair))
    at = F.element_at(starts, F.col("part")) + F.col("place") + 1
    first = F.ceil(at * p / F.lit(n)).cast("long")  # the first splitter whose place is here or later
    rows = ranged.withColumn("at", at).withColumn("i", first).where((F.floor(F.lit(n).cast("long") * F.col("i") / p) == F.col("at")) & (F.col("i") < p)).select("at", "v").collect()  # at most p - 1
    found = {r["at"]: r["v"] for r in rows}
    known = next((found[n * i // p] for i in range(1, p) if n * i // p), None)
    return PivotTree.from_sorted([found.get(n * i // p, known) for i in range(1, p)], kind, reverse)


def sketch_splitters(df: DataFrame, spec: KeySpec, p: int, accuracy: int | None = None) -> PivotTree:
    """All pivots from one mergeable sketch: one pass, numbers only; its error must be far below 1 / p."""
    spec.check(df)
    value, kind = compared(df, spec, "left")
    if not isinstance(kind, T.NumericType):
        raise TypeError("a quantile sketch needs numbers")
    shares = [i / p for i in range(1, p)]
    if p == 1:
        return PivotTree((), kind, spec.reversed)
    found = df.agg(F.percentile_approx(comparable(value, kind), shares, accuracy or max(10_000, 16 * p)).alias("q")).first()["q"] or [None] * (p - 1)
    return PivotTree.from_sorted(found[::-1] if spec.reversed else found, kind, spec.reversed)


def agree_fused(df: DataFrame, spec: KeySpec, p: int, *, levels_a_pass: int = 3, accuracy: int | None = None) -> PivotTree:
    """Pivots of several levels from each pass: the evenly spaced quantiles of every segment, by one sketch a segment.

    log2 p / levels_a_pass passes over the keys instead of log2 p; numbers only.
    """
    spec.check(df)
    value, kind = compared(df, spec, "left")
    if not isinstance(kind, T.NumericType):
        raise TypeError("a quantile sketch needs numbers")
    tree = PivotTree((), kind, spec.reversed)
    while tree.levels < levels_of(p):
        step = min(levels_a_pass, levels_of(p) - tree.levels)
        parts = 1 << step
        shares = [i / parts for i in range(1, parts)]
        rows = round_rows(df, value, kind, tree.segment(value, spec.nulls_first), F.lit(0).cast("long")).where("__value is not null")
        found = rows.groupBy("__segment").agg(F.percentile_approx("__value", shares, accuracy or max(10_000, 16 * parts)).alias("q")).collect()  # a row a segment
        by_segment = {r["__segment"]: (r["q"][::-1] if spec.reversed else r["q"]) for r in found}
        first = tree.levels
        for level in range(step):
            width = parts >> (level + 1)
            added = {}
            for s in range(1 << (first + level)):
                above, within = divmod(s, 1 << level)
                if above in by_segment:
                    added[s] = by_segment[above][(2 * within + 1) * width - 1]
            tree = tree.extend(added, kind)
    return tree
