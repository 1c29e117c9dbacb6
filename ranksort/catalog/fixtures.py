"""The inputs of the experiments: each a table, its order and its starting ranks, for Spark and for SQL."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..keys import KeySpec
from ..placement import place
from ..sources.tables import load

P = 8


@dataclass(frozen=True)
class Fixture:
    """columns are sorted and delivered; ``shown`` says how a query returns one of them, in Spark and in SQL.

    start, where a row starts, is a SQL expression that both know, with {p} ranks and {n} rows.  shuffled:
    another, a whole number that tells rows apart, by which samples are drawn.
    """

    table: str
    columns: tuple[str, ...]
    spec: KeySpec
    start: str
    whole: bool = False
    shown: tuple[tuple[str, str, str], ...] = ()
    shuffled: str = ""

    def rows(self, spark: SparkSession, folder: str, p: int = P) -> DataFrame:
        """The columns and the starting rank."""
        df = load(spark, folder, self.table)
        n = df.count() if "{n}" in self.start else 0
        needed = df.withColumn("__start", F.expr(self.start.format(p=p, n=n))).select(*self.columns, "__start")
        return place(needed, p, F.col("__start")).drop("__start")

    def base(self, p: int = P, key: str | None = None) -> str:
        """SQL of (k, r, t, columns)."""
        return f"SELECT {key or self.spec.key[0]} AS k, {self.start_of(p)} AS r, {self.shuffled or '0'} AS t, {', '.join(self.columns)} FROM {self.table}"

    def show(self, df: DataFrame) -> DataFrame:
        """The columns as a query returns them, and what else ``df`` has."""
        how = {c: spark for c, spark, _ in self.shown}
        named = [F.expr(how[c]).alias(f"{c}_shown") if c in how else F.col(c) for c in self.columns]
        return df.select(*named, *(c for c in df.columns if c not in self.columns))

    def returned(self) -> str:
        """The same in SQL."""
        how = {c: sql for c, _, sql in self.shown}
        return ", ".join(f"{how[c]} AS {c}_shown" if c in how else c for c in self.columns)

    def order(self) -> str:
        down = self.spec.descending
        return ", ".join([*(f"{c} DESC" if c in down else c for c in self.spec.key), *self.spec.tiebreak])

    def start_of(self, p: int) -> str:
        return f"({self.start.format(p=p, n=f'(SELECT count(*) FROM {self.table})')}) % {p}"


_LINE = ("l_orderkey", "l_linenumber", "l_extendedprice")
_START = "l_orderkey * 7 + l_linenumber"
_SHUFFLED = "(l_orderkey * 7919 + l_linenumber * 104729 + CAST(floor(l_extendedprice * 100) AS BIGINT) * 31) % 1000003"
UNIFORM = Fixture("lineitem", _LINE, KeySpec("l_extendedprice", ("l_orderkey", "l_linenumber")), _START, shuffled=_SHUFFLED)
PERMUTATION = Fixture("orders", ("o_orderkey", "o_custkey"), KeySpec("o_orderkey"), "o_custkey", whole=True, shuffled="(o_orderkey * 7919 + o_custkey * 31) % 1000003")
INTEGERS = Fixture("lineitem", ("l_partkey", *_LINE), KeySpec("l_partkey", _LINE), _START, whole=True, shuffled=_SHUFFLED)
SKEWED = Fixture("events", ("event_id", "value"), KeySpec("value", ("event_id",)), "event_id")
DUPLICATES = Fixture("lineitem", ("l_discount", *_LINE), KeySpec("l_discount", _LINE), _START)
ORDERED_START = Fixture("events", ("event_id", "ts"), KeySpec("ts", ("event_id",)), "CAST(floor(event_id * {p} / {n}) AS BIGINT)")
NEGATIVE = Fixture("customer", ("c_custkey", "c_acctbal"), KeySpec("c_acctbal", ("c_custkey",)), "c_custkey")
COMPOSITE = Fixture("lineitem", ("l_returnflag", *_LINE), KeySpec(("l_returnflag", "l_extendedprice"), ("l_orderkey", "l_linenumber"), ("l_extendedprice",)), _START)
LARGE_ROWS = Fixture("documents", ("doc_id", "n_chars", "text"), KeySpec("n_chars", ("doc_id",)), "doc_id", whole=True, shown=(("text", "sha2(text, 256)", "sha256(text)"),))
PAGES = Fixture("pages", ("page_id", "url", "html"), KeySpec("url", ("page_id",)), "page_id", shown=(("html", "sha2(html, 256)", "sha256(html)"),))
STRINGS = Fixture("part", ("p_partkey", "p_name"), KeySpec("p_name", ("p_partkey",)), "p_partkey")
DATES = Fixture("orders", ("o_orderkey", "o_orderdate"), KeySpec("o_orderdate", ("o_orderkey",)), "o_custkey")
VECTORS = Fixture("embeddings", ("vec_id", "embedding"), KeySpec("embedding", ("vec_id",)), "vec_id", shown=(("embedding", "CAST(array_max(embedding) AS DOUBLE)", "CAST(list_max(embedding) AS DOUBLE)"),))
