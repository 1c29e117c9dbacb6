"""Ranks: how many there are, where rows start, and who exchanges with whom."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

RANK = "__rank"


def levels_of(p: int) -> int:
    """log2 of a number of ranks, which must be a power of two."""
    if p < 1 or p & (p - 1):
        raise ValueError(f"the number of ranks is a power of two, not {p}")
    return p.bit_length() - 1


def place(df: DataFrame, p: int, by: Column | str = "hash", seed: int = 17) -> DataFrame:
    """Adds the starting rank.

    by: an expression (any whole number, taken modulo p), ``hash`` of all columns, or ``random``, a hash
    that the seed shuffles: both give a repeated task the same rows, as an unseeded draw would not.
    """
    levels_of(p)
    if isinstance(by, str):
        columns = [F.to_json(F.struct(c)) if t.startswith("map") else F.col(c) for c, t in df.dtypes]
        if by not in ("hash", "random"):
            raise ValueError(f"no placement is called {by}")
        by = F.xxhash64(F.lit(seed if by == "random" else 0), *columns)
    return df.withColumn(RANK, F.pmod(by.cast("long"), F.lit(p)).cast("int"))


def blocked(order: Column, n: int, p: int) -> Column:
    """An expression that keeps runs of neighbours on one rank: position ``order`` of n."""
    return F.floor(order * p / max(n, 1))


def partner(rank: Column, level: int, p: int) -> Column:
    """Whom a rank exchanges with at a level: the rank that differs in this level's bit."""
    return rank.bitwiseXOR(F.lit(p >> (level + 1)))


def group(rank: Column, level: int, p: int) -> Column:
    """The group a rank belongs to before a level: its leading bits."""
    return F.shiftright(rank, levels_of(p) - level)


def schedule(spark: SparkSession, p: int) -> DataFrame:
    """(level, rank, partner, grp) of all exchanges."""
    ranks = spark.range(p).select(F.explode(F.sequence(F.lit(0), F.lit(levels_of(p) - 1))).alias("level") if p > 1 else F.explode(F.expr("cast(array() as array<int>)")).alias("level"), F.col("id").cast("int").alias("rank"))
    half = F.lit(p).cast("int")
    return ranks.select("level", "rank", F.col("rank").bitwiseXOR(F.call_function("shiftright", half, F.col("level") + 1)).alias("partner"), F.call_function("shiftright", F.col("rank"), F.lit(levels_of(p)) - F.col("level")).alias("grp"))
