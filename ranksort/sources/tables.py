"""Sources and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..placement import RANK
from ..plans.pivot_tree import SEGMENT
from ..plans.variants import Sorted

READERS = ("parquet", "orc", "csv", "json", "avro")


def load(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """One Parquet table of a folder."""
    return spark.read.parquet(f"{folder}/{name}.parquet")


def load_all(spark: SparkSession, folder: str, names: list[str]) -> dict[str, DataFrame]:
    """Several tables, each also a temporary view."""
    tables = {n: load(spark, folder, n) for n in names}
    for name, table in tables.items():
        table.createOrReplaceTempView(name)
    return tables


def read_file(spark: SparkSession, path: str, fmt: str, schema: T.StructType | str, **options: str) -> DataFrame:
    """Files of a format with a schema that is given, never inferred."""
    if fmt not in READERS:
        raise ValueError(f"no reader for {fmt}")
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def read_stream(spark: SparkSession, path: str, schema: T.StructType | str, fmt: str = "parquet", files_per_batch: int = 1) -> DataFrame:
    """A stream of the files that arrive in a folder."""
    return spark.readStream.format(fmt).schema(schema).option("maxFilesPerTrigger", files_per_batch).load(path)


def uniform(spark: SparkSession, n: int, low: float = 0.0, high: float | None = None, seed: int = 42) -> DataFrame:
    """(id, key): n uniform doubles in [low, high], high by default n - 1, each from a hash of its id, so retries agree."""
    high = n - 1.0 if high is None else high
    share = F.shiftrightunsigned(F.xxhash64(F.lit(seed), "id"), 11).cast("double") / float(1 << 53)
    return spark.range(n).withColumn("key", low + share * (high - low))


def permutation(spark: SparkSession, n: int, seed: int = 42) -> DataFrame:
    """(id, key): 0 to n - 1 in an order that an affine map modulo n makes."""
    from math import gcd

    step = next(a for a in range(int(n * 0.618) | 1, 4 * n + 4) if gcd(a, n) == 1) if n > 1 else 1
    wide = (F.col("id").cast("decimal(38,0)") * step + seed) % n
    return spark.range(n).withColumn("key", wide.cast("long"))


def write_sorted(result: Sorted, path: str) -> None:
    """A folder a rank, named by it, so that a range of keys is a range of folders; rows lie in order in each."""
    result.rows.drop(RANK).withColumn("rank", F.col(SEGMENT)).drop(SEGMENT).write.partitionBy("rank").parquet(path)


def read_sorted(spark: SparkSession, path: str) -> DataFrame:
    """What write_sorted wrote, with ``rank`` as a partition column."""
    return spark.read.parquet(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, key: str) -> None:
    """A table bucketed and sorted by a key, for joins without a shuffle."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)
