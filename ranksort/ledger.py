"""Counted costs: rows moved, pivots, rounds, balance, and what the models predict."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .placement import RANK, levels_of
from .plans.exchange import TRACE
from .plans.pivot_tree import SEGMENT


def _differs(segmented_rank: Column, segment: Column) -> Column:
    return segmented_rank.bitwiseXOR(segment)


def moves(p: int, exchange_levels: int) -> Column:
    """How often a row moves: once for each leading bit of its rank that is wrong, and once more for all the rest."""
    depth = levels_of(p)
    wrong = _differs(F.col(RANK), F.col(SEGMENT))
    rest = depth - exchange_levels
    leading = F.bit_count(F.shiftright(wrong, rest))
    return leading + (wrong.bitwiseAND(F.lit((1 << rest) - 1)) != 0).cast("int")


def rows_moved(segmented: DataFrame, p: int, exchange_levels: int) -> DataFrame:
    """One row: rows_moved in all, for a variant with so many exchange levels (0: exchange-free, log2 p: all)."""
    return segmented.agg(F.coalesce(F.sum(moves(p, exchange_levels)), F.lit(0)).cast("long").alias("rows_moved"))


def moves_made() -> Column:
    """How often a row has moved by its trace: from its first rank through those after each exchange to its segment."""
    way = F.concat(F.col(TRACE), F.array(F.col(SEGMENT).cast("int")))
    return F.size(F.filter(F.sequence(F.lit(1), F.size(way) - 1), lambda i: F.get(way, i) != F.get(way, i - 1)))


def rows_scanned(segmented: DataFrame, p: int) -> DataFrame:
    """One row: scanned, what a scan of every segment of every rank looks at over all levels, and probes, what binary searches do.

    A search for the place after the equal keys in m sorted rows takes ceil(log2(m + 1)) probes.
    """
    depth = levels_of(p)
    parts = segmented.groupBy(RANK, SEGMENT).agg(F.count("*").alias("n"))
    levels = F.explode(F.sequence(F.lit(0), F.lit(depth - 1))).alias("level")
    sized = parts.select(RANK, SEGMENT, "n", levels).groupBy(RANK, "level", F.expr(f"shiftright({SEGMENT}, {depth} - level)").alias("s")).agg(F.sum("n").alias("n"))
    return sized.agg(F.sum("n").alias("scanned"), F.sum(F.length(F.bin("n"))).cast("long").alias("probes"))


def rows_moved_by_level(segmented: DataFrame, p: int) -> DataFrame:
    """(level, rows_moved) of the exchange variants."""
    depth = levels_of(p)
    wrong = _differs(F.col(RANK), F.col(SEGMENT))
    each = F.array(*(F.struct(F.lit(i).alias("level"), F.shiftright(wrong, depth - 1 - i).bitwiseAND(F.lit(1)).alias("bit")) for i in range(depth)))
    return segmented.select(F.explode(each).alias("x")).groupBy("x.level").agg(F.sum("x.bit").cast("long").alias("rows_moved"))


def rows_moved_by_rank(segmented: DataFrame) -> DataFrame:
    """(rank, sent, received) of the exchange-free variants."""
    away = segmented.where(F.col(RANK) != F.col(SEGMENT))
    both = away.select(F.explode(F.array(F.struct(F.col(RANK).alias("rank"), F.lit(1).alias("s"), F.lit(0).alias("r")), F.struct(F.col(SEGMENT).alias("rank"), F.lit(0).alias("s"), F.lit(1).alias("r")))).alias("x"))
    return both.groupBy("x.rank").agg(F.sum("x.s").alias("sent"), F.sum("x.r").alias("received"))


def imbalance(segmented: DataFrame, p: int) -> DataFrame:
    """One row: max_rows, min_rows (of ranks with rows), empty_ranks."""
    sizes = segmented.groupBy(SEGMENT).agg(F.count("*").alias("n"))
    return sizes.agg(F.max("n").alias("max_rows"), F.min("n").alias("min_rows"), (F.lit(p) - F.count("*")).cast("long").alias("empty_ranks"))


def imbalance_per_rank(segmented: DataFrame, p: int) -> DataFrame:
    """(rank, rows_in, rows_out, abs_diff) of every rank."""
    ranks = segmented.sparkSession.range(p).select(F.col("id").cast("int").alias("rank"))
    came = segmented.groupBy(F.col(RANK).alias("rank")).agg(F.count("*").alias("rows_in"))
    left = segmented.groupBy(F.col(SEGMENT).alias("rank")).agg(F.count("*").alias("rows_out"))
    both = ranks.join(came, "rank", "left").join(left, "rank", "left").fillna(0, ["rows_in", "rows_out"])
    return both.withColumn("abs_diff", F.abs(F.col("rows_out") - F.col("rows_in")))


def balance(segmented: DataFrame, p: int) -> float:
    """Largest over mean rank; 2 and more calls for better pivots before delivery."""
    sizes = [r["n"] for r in segmented.groupBy(SEGMENT).agg(F.count("*").alias("n")).collect()]  # p rows
    return max(sizes) * p / sum(sizes) if sizes else 1.0


def pivot_quality(segmented: DataFrame, p: int) -> DataFrame:
    """(level, segment, left_rows, right_rows): how each pivot divides its segment."""
    depth = levels_of(p)
    leaf = segmented.groupBy(SEGMENT).agg(F.count("*").alias("n"))
    each = F.array(*(F.struct(F.lit(i).alias("level"), F.shiftright(F.col(SEGMENT), depth - i).alias("segment"), F.shiftright(F.col(SEGMENT), depth - 1 - i).bitwiseAND(F.lit(1)).alias("right")) for i in range(depth)))
    rows = leaf.select("n", F.explode(each).alias("x"))
    return rows.groupBy("x.level", "x.segment").agg(F.sum(F.when(F.col("x.right") == 0, F.col("n")).otherwise(0)).alias("left_rows"), F.sum(F.when(F.col("x.right") == 1, F.col("n")).otherwise(0)).alias("right_rows"))


def with_ranks(sized: DataFrame, a_rank: int) -> DataFrame:
    """Adds p, the least number of ranks that hold the n rows at ``a_rank`` each."""
    depth = F.when(F.col("n") > a_rank, F.length(F.bin(F.ceil(F.col("n") / a_rank) - 1))).otherwise(0)
    return sized.withColumn("p", F.call_function("shiftleft", F.lit(1), depth))


_VARIANTS = ("exchange_quicksort", "exchange_sort_first", "exchange_free_quicksort", "exchange_free_sort_first")


def _of_variants(df: DataFrame) -> DataFrame:
    """A row a variant, with free, whether it exchanges no rows between levels, and depth, log2 p."""
    each = df.withColumn("variant", F.explode(F.array(*map(F.lit, _VARIANTS))))
    return each.withColumns({"free": F.col("variant").contains("free"), "depth": F.length(F.bin("p")) - 1})


def communication(ranked: DataFrame) -> DataFrame:
    """Adds (variant, pivots_agreed, pivots_per_rank, rounds, group_splits) to rows with p: what is agreed on, whatever the rows."""
    free, depth, pivots = F.col("free"), F.col("depth"), F.col("p") - 1
    counted = {"pivots_agreed": pivots, "pivots_per_rank": F.when(free, pivots).otherwise(depth), "rounds": F.when(free, depth + 2).otherwise(2 * depth), "group_splits": F.when(free, 0).otherwise(depth)}
    return _of_variants(ranked).withColumns(counted).drop("free", "depth")


def scanned(n: int, p: int, ordered: bool) -> float:
    """Rows looked at while splitting: all of them at each level, or the probes of binary searches."""
    return p * math.log2(max(2.0, n / p)) * p if ordered else n * levels_of(p)


def predict(variant: str, n: float, p: int, s: float = 20.0, alpha: float = 1.0, beta: float = 1.0) -> dict[str, float]:
    """Terms of the linear cost model, a rank's: local work, row exchange, pivot agreement, start-ups."""
    log_n, log_p, each = math.log2(n), math.log2(p), n / p
    terms = {"local_work": each * log_n, "row_exchange": beta * each * log_p, "pivots": alpha * log_p * (log_p + s), "start_ups": 0.0}
    if "free" in variant:
        terms |= {"row_exchange": beta * each, "pivots": alpha * (log_p * log_p + p), "start_ups": alpha * p}
        if "sort_first" in variant:
            terms["local_work"] = each * math.log2(max(2.0, each)) + p * math.log2(max(2.0, each)) + each * log_p
    elif "sort_first" in variant:
        terms["pivots"] = alpha * log_p * log_p
    return terms


def terms(sized: DataFrame) -> DataFrame:
    """Adds variant and the terms of ``predict`` at unit costs, rounded to thousandths, to rows with n and p."""
    sort_first, free, depth = F.col("variant").contains("sort_first"), F.col("free"), F.col("depth").cast("double")
    each, log_n = F.col("n").cast("double") / F.col("p"), F.log2(F.greatest("n", F.lit(1)).cast("double"))
    probes = F.log2(F.greatest(F.lit(2.0), each))
    found = {
        "local_work": F.when(free & sort_first, each * probes + F.col("p") * probes + each * depth).otherwise(each * log_n),
        "row_exchange": F.when(free, each).otherwise(each * depth),
        "pivots": F.when(free, depth * depth + F.col("p")).when(sort_first, depth * depth).otherwise(depth * (depth + 20)),
        "start_ups": F.when(free, F.col("p").cast("double")).otherwise(0.0),
    }
    return _of_variants(sized).withColumns({k: F.floor(x * 1000 + 0.5) / 1000 for k, x in found.items()}).drop("free", "depth")


def predicted_time(variant: str, n: float, p: int, **costs: float) -> float:
    return sum(predict(variant, n, p, **costs).values())


def switch_table(sized: DataFrame, ranks: list[int], constants: list[float]) -> DataFrame:
    """Adds (p, c, exchange_levels, group_size) to rows with n: ``variants.switch_level`` of every p and c."""
    every = sized.withColumn("p", F.explode(F.array(*map(F.lit, ranks)))).withColumn("c", F.explode(F.array(*(F.lit(float(c)) for c in constants))))
    left = lambda level: F.call_function("shiftright", F.col("p"), level)
    log_n = F.log2(F.greatest("n", F.lit(2)).cast("double"))
    ends = lambda level: (left(level) == 1) | (F.col("n") < 2) | (F.col("n").cast("double") / F.col("p") > F.col("c") * left(level) / log_n)
    level = F.get(F.filter(F.sequence(F.lit(0), F.length(F.bin("p")) - 1), ends), F.lit(0))
    return every.withColumn("exchange_levels", level).withColumn("group_size", left(F.col("exchange_levels")))


# --- times ---


@dataclass(frozen=True)
class Timing:
    """The best of some repetitions after warm-ups."""

    best: float
    runs: tuple[float, ...]


def best_of(run: Callable[[], object], repetitions: int = 43, warm_ups: int = 5) -> Timing:
    """The protocol of the experiments: warm-ups that do not count, then the best; a job waits for its slowest task."""
    for _ in range(warm_ups):
        run()
    runs = []
    for _ in range(repetitions):
        began = time.perf_counter()
        run()
        runs.append(time.perf_counter() - began)
    return Timing(min(runs), tuple(runs))


def execute(df: DataFrame) -> None:
    """Run a plan to its end and keep nothing."""
    df.write.format("noop").mode("overwrite").save()


def shuffle_metrics(spark: SparkSession, run: Callable[[], object]) -> dict[str, int]:
    """Bytes written to shuffles, bytes spilled to disk and tasks of the stages that ``run`` starts."""

    def stages() -> dict[int, tuple[int, int, int]]:
        context = spark.sparkContext
        context._jsc.sc().listenerBus().waitUntilEmpty()
        found = context._jsc.sc().statusStore().stageList(None, False, False, context._gateway.new_array(spark._jvm.double, 0), None)
        all_stages = (found.apply(i) for i in range(found.size()))
        return {s.stageId(): (s.shuffleWriteBytes(), s.diskBytesSpilled(), s.numCompleteTasks()) for s in all_stages}

    before = max(stages(), default=-1)  # old stages leave the store, new ones have higher numbers
    run()
    new = [counts for stage, counts in stages().items() if stage > before]
    return dict(zip(("shuffle_bytes", "spilled_bytes", "tasks"), map(sum, zip(*new)) if new else (0, 0, 0)))


def speedup(sequential: float, parallel: float) -> float:
    return sequential / parallel


def efficiency(sequential: float, parallel: float, p: int) -> float:
    return speedup(sequential, parallel) / p


def relative_factor(exchange: float, exchange_free: float) -> float:
    """Over 1 where the exchange-free variant is faster."""
    return exchange / exchange_free


def crossover(sweep: list[tuple[float, float, float]]) -> float | None:
    """The least rows a rank, of (rows a rank, exchange, exchange-free), from which on the exchange-free variant is faster."""
    found = None
    for rows, exchange, free in sorted(sweep, reverse=True):
        if relative_factor(exchange, free) <= 1:
            break
        found = rows
    return found
