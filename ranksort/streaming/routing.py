"""Streams on frozen pivots: routing, sorted runs, load monitors, drift."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..keys import KeySpec
from ..plans.pivot_tree import SEGMENT, PivotTree


def route_stream(stream: DataFrame, spec: KeySpec, tree: PivotTree) -> DataFrame:
    """Adds the segment to each row: no state, so any sink and mode."""
    return stream.withColumn(SEGMENT, tree.segment(spec.value(), spec.nulls_first))


def run_sink(stream: DataFrame, spec: KeySpec, tree: PivotTree, path: str, checkpoint: str) -> StreamingQuery:
    """Each micro-batch as sorted runs under ``path``/batch=<id>/rank=<segment>; a repeated batch replaces its own."""

    def write(batch: DataFrame, number: int) -> None:
        routed = route_stream(batch, spec, tree).repartitionById(tree.segments, F.col(SEGMENT)).sortWithinPartitions(SEGMENT, *spec.orders())
        routed.withColumnRenamed(SEGMENT, "rank").write.mode("overwrite").partitionBy("rank").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def compact_runs(spark: SparkSession, path: str, spec: KeySpec, tree: PivotTree) -> DataFrame:
    """All runs as one sorted relation, rank by rank."""
    runs = spark.read.parquet(path).withColumnRenamed("rank", SEGMENT).drop("batch")
    return runs.repartitionById(tree.segments, F.col(SEGMENT)).sortWithinPartitions(SEGMENT, *spec.orders())


def segment_load(routed: DataFrame, time: str, *, width: str = "1 hour", slide: str | None = None, gap: str | None = None, late: str = "10 minutes") -> DataFrame:
    """(window, segment, n): rows a segment in tumbling or sliding windows, or in sessions with ``gap``; later rows than ``late`` are dropped."""
    window = F.session_window(time, gap) if gap else F.window(time, width, slide)
    marked = routed.withWatermark(time, late) if routed.isStreaming else routed
    return marked.groupBy(window.alias("window"), F.col(SEGMENT).alias("segment")).agg(F.count("*").alias("n"))


def drift(routed: DataFrame, p: int, threshold: float = 2.0) -> DataFrame:
    """(rows, worst, repivot): per micro-batch, how far the fullest segment is beyond the mean so far.

    State is one count a segment, kept under one key: p numbers, whatever the stream's length.  Each batch
    is first counted by segment, so that key's task gets at most p rows a task before it.
    """

    def watch(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        counts = list(state.get[0]) if state.exists else [0] * p
        for batch in batches:
            for segment, n in zip(batch["segment"], batch["n"]):
                counts[int(segment)] += int(n)
        state.update((counts,))
        total = sum(counts)
        worst = max(counts) * p / total if total else 1.0
        yield pd.DataFrame({"rows": [total], "worst": [worst], "repivot": [worst > threshold]})

    ones = routed.select(F.lit(0).alias("all"), F.col(SEGMENT).alias("segment"), F.lit(1).cast("long").alias("n"))
    return ones.groupBy("all").applyInPandasWithState(watch, "rows long, worst double, repivot boolean", "counts array<long>", "append", "NoTimeout")


def deduplicate(stream: DataFrame, keys: list[str], time: str, late: str = "10 minutes") -> DataFrame:
    """The first of rows with equal keys that arrive within the lateness of one another."""
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark(keys)


def enrich(stream: DataFrame, static: DataFrame, on) -> DataFrame:
    """A stream joined with a table."""
    return stream.join(static, on, "left")


def pair_within(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, within: str, late: str = "10 minutes") -> DataFrame:
    """Rows of two streams with equal keys, the right one at most ``within`` after the left."""
    a, b = left.withWatermark(left_time, late).alias("a"), right.withWatermark(right_time, late).alias("b")
    near = F.expr(f"a.{key} = b.{key} and b.{right_time} >= a.{left_time} and b.{right_time} <= a.{left_time} + interval {within}")
    return a.join(b, near)


def run_to_end(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run a stream over what has arrived and read the result back.

    In append mode rows go to Parquet files beside the checkpoint, whatever their number; in the other modes,
    which return a row a group, to a table in the driver's memory.
    """
    writer = stream.writeStream.queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    if mode != "append":
        writer.format("memory").start().awaitTermination()
        return stream.sparkSession.table(name)
    path = f"{checkpoint}-rows"
    writer.format("parquet").start(path).awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)
