"""URL verdicts: prefix rules, then exact membership in a list by a cascade of Bloom filters.

Level 1 of the cascade encodes the listed keys that occur; level 2 the other keys of the universe
that level 1 takes for listed; level 3 the listed keys that level 2 takes for the others; and so on
until no key is mistaken.  A key's depth, the number of levels it passes in a row, is odd exactly if
it is listed, for every key of the universe, which is the complete set of the corpus's keys.  Rows
are judged by expressions over the filters' bits: no join, no shuffle of rows, no Python.  The keys
are hosts; a host is listed if the list names it or a parent domain.

The filters hold about 1.44 log2(others / listed) + 6 bits a listed key.  They are sent with the
plan while that is within ``max_filter_bytes`` (checked, from the counts); beyond, ``judge`` joins
the hosts with the list instead, which gives the same verdicts.

Defined results: a url that is null or lacks ``://`` has an empty host and path, fits no rule and is
not listed; keys of an empty list: nothing is listed; repeated rows give repeated rows; extra
columns pass through, but for those with a result's name, which are replaced.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import materialize, unused

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_WORD = 64


def host_and_path(url: Column) -> tuple[Column, Column]:
    """After the first ``://``: the host up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; the path up to ``?``, ``#`` or the end."""
    whole = F.coalesce(url, F.lit(""))
    mark = F.instr(whole, "://")
    rest = F.when(mark > 0, F.substring(whole, mark + 3, F.length(whole))).otherwise("")
    return F.translate(F.regexp_extract(rest, "^[^/?#]*+", 0), _UPPER, _LOWER), F.regexp_extract(rest, "^[^/?#]*+([^?#]*+)", 1)


@dataclass(frozen=True)
class Rule:
    """``rule`` is host and path prefix, as in ``net/de/``."""

    verdict: str
    rule: str

    @property
    def host(self) -> str:
        return self.rule.partition("/")[0]

    @property
    def path(self) -> str:
        return "/" + self.rule.partition("/")[2] if "/" in self.rule else ""


#: Rules beyond this many are joined by host suffix instead of standing in the plan.
RULES_IN_PLAN = 500


def _by_rules(df: DataFrame, rules: list[Rule], host: str, path: str, hit: str) -> DataFrame:
    """Adds ``hit``, the verdict and the rule that is the longest that fits (ties: the smaller string)."""
    spark = df.sparkSession
    if len(rules) <= RULES_IN_PLAN:
        chosen = F.lit(None).cast("struct<verdict:string,rule:string>")
        for r in sorted(rules, key=lambda r: (len(r.rule), [-ord(c) for c in r.rule])):
            fits = ((F.col(host) == r.host) | F.endswith(F.col(host), F.lit("." + r.host))) & F.startswith(F.col(path), F.lit(r.path))
            chosen = F.when(fits, F.struct(F.lit(r.verdict).alias("verdict"), F.lit(r.rule).alias("rule"))).otherwise(chosen)
        return df.withColumn(hit, chosen)
    table = spark.createDataFrame([(r.host, r.path, r.rule, r.verdict, len(r.rule)) for r in rules], "__s string, __p string, __r string, __v string, __n int")
    places = df.select(host, path).distinct()
    hits = places.withColumn("__s", F.explode(suffixes(F.col(host)))).join(table, "__s").where(F.startswith(F.col(path), F.col("__p")))
    best = hits.groupBy(host, path).agg(F.min(F.struct((-F.col("__n")).alias("n"), "__r", "__v")).alias("b"))
    return df.join(best.select(host, path, F.struct(F.col("b.__v").alias("verdict"), F.col("b.__r").alias("rule")).alias(hit)), [host, path], "left")


def suffixes(host: Column) -> Column:
    """The host and its parent domains; none for an empty host."""
    labels = F.split(host, r"\.")
    tails = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    return F.when(host != "", tails).otherwise(F.expr("cast(array() as array<string>)"))


@dataclass(frozen=True)
class Level:
    """One Bloom filter: its bits as 64-bit words, in a table (word, bits)."""

    words: DataFrame
    n_bits: int
    n_hashes: int
    seed: int


def _probes(key: Column, n_bits: int, n_hashes: int, seed: int) -> list[Column]:
    """Bit places by double hashing."""
    size = F.lit(n_bits).cast("long")
    first, second = F.pmod(F.xxhash64(F.lit(seed), key), size), F.pmod(F.xxhash64(F.lit(~seed), key), size)
    return [(first + second * F.lit(i)) % size for i in range(n_hashes)]


def _fill(keys: DataFrame, n_bits: int, n_hashes: int, seed: int) -> DataFrame:
    place = keys.select(F.explode(F.array(*_probes(F.col("key"), n_bits, n_hashes, seed))).alias("place"))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("place") % _WORD).cast("int"))
    return place.groupBy(F.floor(F.col("place") / _WORD).cast("int").alias("word")).agg(F.bit_or(bit).alias("bits"))


class Cascade:
    """Exact membership of a universe's keys in a list."""

    def __init__(self, levels: list[DataFrame], sizes: list[tuple[int, int, int]]):
        self._levels, self.sizes = levels, sizes

    @property
    def n_bits(self) -> int:
        return sum(n for n, _, _ in self.sizes)

    def has(self, key: Column) -> Column:
        """Whether the key is listed: exact for keys of the universe."""
        passes = []
        for words, (n_bits, n_hashes, seed) in zip(self._levels, self.sizes):
            held, bits = F.lit(True), words.scalar()
            for place in _probes(key, n_bits, n_hashes, seed):
                word = F.get(bits, F.floor(place / _WORD).cast("int"))
                held = held & (_bit(word, place) == 1)
            passes.append(held)
        listed: Column = F.lit(False)
        for level in range(len(passes), 0, -1):  # fails level n first: depth n - 1, listed if that is odd
            listed = F.when(passes[level - 1], listed if level < len(passes) else F.lit(level % 2 == 1)).otherwise(F.lit(level % 2 == 0))
        return listed


def _bit(word: Column, place: Column) -> Column:
    return F.getbit(word, (place % _WORD).cast("int"))


def mark_listed(hosts: DataFrame, listed: DataFrame, *, broadcast_keys: int = 200_000) -> DataFrame:
    """(key, listed): every distinct host, and whether it or a parent domain is in the list.

    The list is broadcast while it has at most ``broadcast_keys`` keys (counted), else shuffled.
    """
    known = listed.select(F.translate(F.col(listed.columns[0]), _UPPER, _LOWER).alias("__key")).where("__key is not null and __key <> ''").distinct()
    if known.limit(broadcast_keys + 1).count() <= broadcast_keys:
        known = F.broadcast(known)
    tails = hosts.select("key", F.explode(suffixes(F.col("key"))).alias("__key"))
    hit = tails.join(known, "__key", "left_semi").select("key").distinct().withColumn("listed", F.lit(True))
    return hosts.join(hit, "key", "left").select("key", F.coalesce("listed", F.lit(False)).alias("listed"))


def build_cascade(marked: DataFrame, *, max_filter_bytes: int = 32 << 20, seed: int = 7) -> Cascade:
    """Fit a cascade to (key, listed), one row for each key of the universe.

    The first level's error rate is listed / (others * sqrt 2), each further one's a half, which is
    near the smallest total.  Raises OverflowError if the bits would exceed the bound.
    """
    spark = marked.sparkSession
    n_listed, n_others = marked.agg(F.count_if("listed"), F.count_if(~F.col("listed"))).first()
    if expected_bits(n_listed, n_others) / 8 > max_filter_bytes:
        raise OverflowError(f"a cascade over {n_listed} listed of {n_listed + n_others} keys exceeds {max_filter_bytes} bytes")
    levels, sizes = [], []
    encode, against, side, other = marked.where("listed"), marked.where("not listed"), n_listed, n_others
    while side:
        rate = 0.5 if levels else min(0.5, max(1e-9, side / (max(other, 1) * math.sqrt(2))))
        n_hashes = max(1, round(-math.log2(rate)))
        n_bits = max(_WORD, _WORD * math.ceil(side * n_hashes / math.log(2) / _WORD))
        sizes.append((n_bits, n_hashes, seed + len(levels)))
        every = spark.range(n_bits // _WORD).join(_fill(encode, *sizes[-1]), F.col("id") == F.col("word"), "left")
        cells = F.sort_array(F.collect_list(F.struct("id", F.coalesce("bits", F.lit(0).cast("long")).alias("bits"))))
        levels.append(materialize(every.agg(F.transform(cells, lambda c: c["bits"]).alias("bits")), "url-bits"))  # within the checked bound
        mistaken = materialize(against.where(Cascade(levels[-1:], sizes[-1:]).has(F.col("key"))), "url-level")
        encode, against, other = mistaken, encode, side
        side = mistaken.count()
    return Cascade(levels, sizes)


def expected_bits(n_listed: int, n_others: int) -> float:
    """About what a cascade needs."""
    return n_listed * (1.44 * max(1.0, math.log2(max(1, n_others) / max(1, n_listed) * math.sqrt(2))) + 6)


def judge(df: DataFrame, rules: list[Rule], listed: DataFrame, *, url: str = "url", max_filter_bytes: int = 32 << 20) -> DataFrame:
    """Adds host, path, rule and verdict: the longest fitting rule's, else ``block`` if the host or a parent domain is listed, else ``allow``."""
    host, path = host_and_path(F.col(url))
    placed = df.withColumns({"host": host, "path": path})
    marked = materialize(mark_listed(placed.select(F.col("host").alias("key")).where("key <> ''").distinct(), listed), "url-keys")
    hit, in_list = unused(placed.columns, "hit"), unused(placed.columns, "in_list")
    ruled = _by_rules(placed, rules, "host", "path", hit)
    try:
        by_list = build_cascade(marked, max_filter_bytes=max_filter_bytes).has(F.col("host"))
    except OverflowError:
        ruled = ruled.join(marked.select(F.col("key").alias("host"), F.col("listed").alias(in_list)), "host", "left")
        by_list = F.coalesce(in_list, F.lit(False))
    verdict = F.coalesce(F.col(f"{hit}.verdict"), F.when((F.col("host") != "") & by_list, "block").otherwise("allow"))
    kept = [c for c in placed.columns if c not in ("rule", "verdict")]
    return ruled.select(*kept, F.col(f"{hit}.rule").alias("rule"), verdict.alias("verdict"))
