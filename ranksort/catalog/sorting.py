"""Queries of the sorting methods, their pivots and their counted costs, with SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import ledger, verify
from ..placement import schedule
from ..plans.exchange import TRACE
from ..plans import ordered
from ..plans import pivots as pv
from ..plans.pivot_tree import SEGMENT, slots
from ..plans.redistribute import POSITION, count_matrix, run_bounds, split_evenly, with_segments
from ..plans.rounds import agree, agree_on_sample, sketch_splitters
from ..plans import variants as v
from ..operators.order import histogram
from ..sources.tables import load
from . import fixtures as fx
from . import sql

P = fx.P
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    """Register a query, and its SQL twin where there is one."""

    def add(function):
        QUERIES[name] = function
        if oracle is not None:
            ORACLES[name] = oracle
        return function

    return add


# --- the methods, by position ---


def _positions(result: v.Sorted, fixture: fx.Fixture) -> DataFrame:
    return fixture.show(result.with_positions().select(*fixture.columns, F.col(POSITION).alias("pos")))


METHODS: dict[str, Callable[[DataFrame, object], v.Sorted]] = {
    "sort_m1": lambda df, spec: v.local_sort(df, spec),
    "sort_m2": lambda df, spec: v.exchange_quicksort(df, spec, P),
    "sort_m3": lambda df, spec: v.exchange_sort_first(df, spec, P, order="merge"),
    "sort_m4": lambda df, spec: v.exchange_free_quicksort(df, spec, P),
    "sort_m5": lambda df, spec: v.exchange_free_sort_first(df, spec, P, merge="heap"),
    "sort_m6": lambda df, spec: v.combined_quicksort(df, spec, 4 * P),
    "sort_m7": lambda df, spec: v.combined_sort_first(df, spec, 4 * P),
    "sort_m8": lambda df, spec: v.sample_sort(df, spec, P),
    "sort_m8_regular": lambda df, spec: v.sample_sort(df, spec, P, method="regular"),
    "sort_m4_sample": lambda df, spec: v.exchange_free_quicksort(df, spec, P, plan="sample"),
    "sort_m4_sketch": lambda df, spec: v.exchange_free_quicksort(df, spec, P, plan="sketch"),
    "sort_m4_fused": lambda df, spec: v.exchange_free_quicksort(df, spec, P, plan="fused"),
    "sort_m6_fused": lambda df, spec: v.combined_quicksort(df, spec, 4 * P, fused=True),
}


def _method(name: str, fixture: fx.Fixture, run, p: int = P) -> None:
    def own(spark: SparkSession, folder: str) -> DataFrame:
        return _positions(run(fixture.rows(spark, folder, p), fixture.spec), fixture)

    query(name, sql.by_position(fixture.table, fixture.returned(), fixture.order()))(own)


for _name, _run in METHODS.items():
    _method(_name, fx.UNIFORM, _run, 4 * P if _name.startswith(("sort_m6", "sort_m7")) else P)

_method("sort_integers", fx.INTEGERS, METHODS["sort_m4"])
_method("sort_permutation", fx.PERMUTATION, METHODS["sort_m4"])
_method("sort_skewed", fx.SKEWED, lambda df, spec: v.exchange_free_quicksort(df, spec, P, pv.MIDDLE))
_method("sort_duplicates", fx.DUPLICATES, lambda df, spec: v.exchange_free_quicksort(df, spec, P, pv.MIDDLE, ties="total_order"))
_method("sort_ordered_start", fx.ORDERED_START, METHODS["sort_m4"])
_method("sort_negative", fx.NEGATIVE, METHODS["sort_m4"])
_method("sort_composite", fx.COMPOSITE, lambda df, spec: v.exchange_free_quicksort(df, spec, P, pv.MIDDLE))
_method("sort_large_rows", fx.LARGE_ROWS, lambda df, spec: v.exchange_free_quicksort(df, spec, P, pv.MIDDLE))
_method("sort_pages", fx.PAGES, lambda df, spec: v.exchange_free_quicksort(df, spec, P, pv.MIDDLE))
_method("sort_strings", fx.STRINGS, lambda df, spec: v.exchange_free_quicksort(df, spec, P, pv.MIDDLE))
_method("sort_dates", fx.DATES, METHODS["sort_m4"])


_method("sort_vectors", fx.VECTORS, lambda df, spec: v.exchange_free_quicksort(df, spec, P, pv.MIDDLE))


@query("sort_native", ORACLES["sort_m1"])
def sort_native(spark, folder):
    """Spark's own global sort."""
    done = v.native_positions(fx.UNIFORM.rows(spark, folder), fx.UNIFORM.spec, P)
    return done.select(*fx.UNIFORM.columns, F.col(POSITION).alias("pos"))


@query("sort_rdd", ORACLES["sort_m1"])
def sort_rdd(spark, folder):
    """Delivery and sort in one row-at-a-time shuffle."""
    rows = fx.UNIFORM.rows(spark, folder)
    return v.rdd_sort(rows, fx.UNIFORM.spec, P, agree(rows, fx.UNIFORM.spec, P)).select(*fx.UNIFORM.columns, F.col(POSITION).alias("pos"))


# --- pivots ---


def _pivots(name: str, fixture: fx.Fixture, chooser, rule: str | None, p: int = P, drop: tuple = ()) -> None:
    def own(spark: SparkSession, folder: str) -> DataFrame:
        tie = F.expr(fixture.shuffled) if rule == "sampled" else None
        tree = agree(fixture.rows(spark, folder, p), fixture.spec, p, chooser, tie=tie)
        pivot = F.round("pivot", 6).alias("pivot") if rule == "mean" else "pivot"  # sums in another order differ in the last place
        return tree.table(spark).select("level", "segment", "inorder_slot", pivot)

    twin = sql.pivots(fixture.base(p), p, rule, whole=fixture.whole) if rule else None
    query(name, f"SELECT level, segment, inorder_slot, round(\"pivot\", 6) AS pivot FROM ({twin})" if rule == "mean" else twin)(own)


_pivots("pivots_midpoint", fx.UNIFORM, pv.MIDPOINT, "midpoint")
_pivots("pivots_midpoint_integers", fx.INTEGERS, pv.MIDPOINT, "midpoint")
_pivots("pivots_middle", fx.UNIFORM, pv.MIDDLE, "middle")
_pivots("pivots_median_of_candidates", fx.UNIFORM, pv.MIDDLE, "middle", 16)
_pivots("pivots_designated", fx.UNIFORM, pv.Chooser(pv.MiddleElement(), pv.Designated()), "designated")
_pivots("pivots_exact_median", fx.UNIFORM, pv.ExactMedian(), "exact")
_pivots("pivots_sample", fx.UNIFORM, pv.SAMPLED, None)
_pivots("pivots_pool", fx.UNIFORM, pv.Chooser(pv.SamplePool(20), pv.MedianOfCandidates()), None)
_pivots("pivots_mean", fx.UNIFORM, pv.Chooser(pv.MiddleElement(), pv.MeanOfCandidates()), "mean")
_pivots("pivots_sampled_ends", fx.UNIFORM, pv.SAMPLED_BY_TIE, "sampled")
_pivots("pivots_random_element", fx.UNIFORM, pv.Chooser(pv.RandomElement(), pv.MedianOfCandidates()), None)
_pivots("pivots_first_element", fx.UNIFORM, pv.Chooser(pv.FirstElement(), pv.Designated()), None)
_pivots("pivots_approximate_middle", fx.UNIFORM, pv.Chooser(pv.ApproximateMiddle(), pv.MedianOfCandidates()), None)
_pivots("pivots_sketch_rounds", fx.UNIFORM, pv.Sketch(), None)
_pivots("pivots_kll_rounds", fx.UNIFORM, pv.Sketch(2048, "kll"), None)
_pivots("empty_skip", fx.SKEWED, pv.Chooser(pv.Extremes(), pv.Midpoint("skip")), "midpoint", 32)
_pivots("empty_neutral", fx.SKEWED, pv.Chooser(pv.Extremes(), pv.Midpoint("neutral")), "midpoint", 32)


@query("pivots_sketch")
def pivots_sketch(spark, folder):
    """All pivots of one sketch."""
    return sketch_splitters(fx.UNIFORM.rows(spark, folder), fx.UNIFORM.spec, P).table(spark).select("level", "segment", "inorder_slot", "pivot")


@query("pivots_on_sample")
def pivots_on_sample(spark, folder):
    """All pivots of one sample."""
    return agree_on_sample(fx.UNIFORM.rows(spark, folder), fx.UNIFORM.spec, P).table(spark).select("level", "segment", "inorder_slot", "pivot")


_LEVELS = P.bit_length() - 1
_CHAIN = sql.chain(fx.UNIFORM.base(), P)
_ALL_CANDIDATES = " UNION ALL ".join(f"SELECT {i} AS level, CAST(s AS INTEGER) AS segment, CAST(r AS INTEGER) AS rank, count(*) AS cnt, min(k) AS lo, max(k) AS hi FROM s{i} GROUP BY s, r" for i in range(_LEVELS))


@query("local_candidates", f"{_CHAIN} {_ALL_CANDIDATES}")
def local_candidates(spark, folder):
    """What each rank proposes in each round."""
    rows, spec, out = fx.UNIFORM.rows(spark, folder), fx.UNIFORM.spec, None
    tree = agree(rows, spec, P)
    for level in range(_LEVELS):
        upper = type(tree)(tree.pivots[: (1 << level) - 1], tree.kind)
        seen = pv.round_rows(rows, spec.value(), tree.kind or rows.schema[spec.key[0]].dataType, upper.segment(spec.value()), F.lit(0).cast("long"))
        part = pv.Extremes().propose(seen).select(F.lit(level).alias("level"), F.col(SEGMENT).alias("segment"), F.col("__rank").alias("rank"), "cnt", "lo", "hi")
        out = part if out is None else out.unionByName(part)
    return out


# --- segments, balance, ledgers ---


def _segmented(spark: SparkSession, folder: str, fixture: fx.Fixture = fx.UNIFORM, p: int = P, chooser=pv.MIDPOINT, ties: str = "left") -> DataFrame:
    rows = fixture.rows(spark, folder, p)
    return with_segments(rows, fixture.spec, agree(rows, fixture.spec, p, chooser, ties=ties), ties)


_END = sql.last(P)


@query("segments", f"{_CHAIN} SELECT l_orderkey, l_linenumber, l_extendedprice, CAST(s AS INTEGER) AS segment FROM {_END}")
def segments(spark, folder):
    return _segmented(spark, folder).select(*fx.UNIFORM.columns, F.col(SEGMENT).alias("segment"))


@query("count_matrix", f"{_CHAIN} SELECT CAST(r AS INTEGER) AS src_rank, CAST(s AS INTEGER) AS dst_rank, count(*) AS n FROM {_END} GROUP BY r, s")
def matrix(spark, folder):
    return count_matrix(_segmented(spark, folder))


_BOUNDS = f"{_CHAIN}, z AS (SELECT r, s, count(*) AS n FROM {_END} GROUP BY r, s), w AS (SELECT r, s, n, sum(n) OVER (PARTITION BY r ORDER BY s) AS t FROM z) SELECT CAST(r AS INTEGER) AS rank, CAST(s AS INTEGER) AS segment, CAST(t - n AS BIGINT) AS start, CAST(t AS BIGINT) AS stop FROM w"


@query("run_bounds", _BOUNDS)
def bounds(spark, folder):
    """Where each segment lies in its rank's order, from the counts."""
    return run_bounds(_segmented(spark, folder))


@query("run_bounds_searched", _BOUNDS)
def bounds_searched(spark, folder):
    """The same by binary search in sorted ranks."""
    rows = fx.UNIFORM.rows(spark, folder)
    local = rows.repartitionById(P, F.col("__rank")).sortWithinPartitions(*fx.UNIFORM.spec.orders())
    return ordered.bounds(local, fx.UNIFORM.spec, agree(rows, fx.UNIFORM.spec, P))


@query("rank_histogram", f"{_CHAIN} SELECT CAST(s AS INTEGER) AS rank, count(*) AS n, min(k) AS lo, max(k) AS hi FROM {_END} GROUP BY s")
def rank_histogram(spark, folder):
    return histogram(_segmented(spark, folder), fx.UNIFORM.spec)


@query("imbalance", f"{_CHAIN}, z AS (SELECT s, count(*) AS n FROM {_END} GROUP BY s) SELECT max(n) AS max_rows, min(n) AS min_rows, {P} - count(*) AS empty_ranks FROM z")
def imbalance(spark, folder):
    return ledger.imbalance(_segmented(spark, folder), P)


@query(
    "imbalance_per_rank",
    f"{_CHAIN}, i AS (SELECT r, count(*) AS n FROM base GROUP BY r), o AS (SELECT s, count(*) AS n FROM {_END} GROUP BY s) "
    f"SELECT CAST(g.range AS INTEGER) AS rank, coalesce(i.n, 0) AS rows_in, coalesce(o.n, 0) AS rows_out, abs(coalesce(o.n, 0) - coalesce(i.n, 0)) AS abs_diff FROM range({P}) g LEFT JOIN i ON i.r = g.range LEFT JOIN o ON o.s = g.range",
)
def imbalance_per_rank(spark, folder):
    return ledger.imbalance_per_rank(_segmented(spark, folder), P)


@query(
    "ledger_exchange",
    f"{_CHAIN} " + " UNION ALL ".join(f"SELECT {i} AS level, CAST(sum((xor(CAST(r AS BIGINT), CAST(s AS BIGINT)) >> {_LEVELS - 1 - i}) & 1) AS BIGINT) AS rows_moved FROM {_END}" for i in range(_LEVELS)),
)
def ledger_exchange(spark, folder):
    return ledger.rows_moved_by_level(_segmented(spark, folder), P)


@query(
    "ledger_by_rank",
    f"{_CHAIN}, x AS (SELECT r AS rank, 1 AS a, 0 AS b FROM {_END} WHERE r <> s UNION ALL SELECT s, 0, 1 FROM {_END} WHERE r <> s) SELECT CAST(rank AS INTEGER) AS rank, CAST(sum(a) AS BIGINT) AS sent, CAST(sum(b) AS BIGINT) AS received FROM x GROUP BY rank",
)
def ledger_by_rank(spark, folder):
    return ledger.rows_moved_by_rank(_segmented(spark, folder))


def _ledgers(spark: SparkSession, folder: str, ranks: list[int], levels: Callable[[int, int], int], fixture: fx.Fixture = fx.UNIFORM) -> DataFrame:
    out, n = None, fixture.rows(spark, folder, 2).count()
    for p in ranks:
        one = ledger.rows_moved(_segmented(spark, folder, fixture, p), p, levels(p, n)).select(F.lit(p).alias("p"), "rows_moved")
        out = one if out is None else out.unionByName(one)
    return out


def _moved_sql(p: int, levels: int, fixture: fx.Fixture = fx.UNIFORM) -> str:
    return f"{sql.chain(fixture.base(p), p)} SELECT {p} AS p, CAST(sum({sql.moved(p, levels)}) AS BIGINT) AS rows_moved FROM {sql.last(p)}"


def _union(parts: list[str]) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({x})" for x in parts)


_RANKS = [2, 4, 8, 16, 32]


@query("ledger_exchange_free", _union([_moved_sql(p, 0) for p in _RANKS]))
def ledger_exchange_free(spark, folder):
    return _ledgers(spark, folder, _RANKS, lambda p, n: 0)


@query("ledger_combined", _union([_moved_sql(p, 1) for p in _RANKS]))
def ledger_combined(spark, folder):
    return _ledgers(spark, folder, _RANKS, lambda p, n: 1)


@query("ledger_by_p", f"SELECT a.p, a.rows_moved AS exchange, b.rows_moved AS exchange_free FROM ({_union([_moved_sql(p, p.bit_length() - 1) for p in _RANKS])}) a JOIN ({_union([_moved_sql(p, 0) for p in _RANKS])}) b ON a.p = b.p")
def ledger_by_p(spark, folder):
    """Rows moved by both kinds: the same at two ranks, and ever further apart."""
    every = _ledgers(spark, folder, _RANKS, lambda p, n: p.bit_length() - 1).withColumnRenamed("rows_moved", "exchange")
    return every.join(_ledgers(spark, folder, _RANKS, lambda p, n: 0).withColumnRenamed("rows_moved", "exchange_free"), "p")


#: The line items by how often two divides their order's key, parts of which each is about half of the one before, and the
#: ranks that hold at most 500 rows each.
_A_RANK = 500
_PARTS_SQL = "SELECT CAST(length(bin(l_orderkey & -l_orderkey)) - 1 AS INTEGER) AS part, count(l_extendedprice) AS n FROM lineitem GROUP BY 1"
RANKED_SQL = f"SELECT part, n, d, CAST(1 << d AS INTEGER) AS p FROM (SELECT part, n, CAST(CASE WHEN n > {_A_RANK} THEN length(bin((n + {_A_RANK - 1}) // {_A_RANK} - 1)) ELSE 0 END AS INTEGER) AS d FROM ({_PARTS_SQL}))"


def _sized_parts(spark: SparkSession, folder: str) -> DataFrame:
    """(part, n)."""
    part = F.length(F.bin(F.col("l_orderkey").bitwiseAND(-F.col("l_orderkey")))) - 1
    return load(spark, folder, "lineitem").groupBy(part.alias("part")).agg(F.count("l_extendedprice").alias("n"))


def ranked_parts(spark: SparkSession, folder: str) -> DataFrame:
    """(part, n, p)."""
    return ledger.with_ranks(_sized_parts(spark, folder), _A_RANK)


_VARIANT_SQL = "(VALUES ('exchange_quicksort', 0), ('exchange_sort_first', 0), ('exchange_free_quicksort', 1), ('exchange_free_sort_first', 1)) AS v(variant, free)"


@query("pivot_ledger", f"SELECT part, n, variant, p, p - 1 AS pivots_agreed, CASE WHEN free = 1 THEN p - 1 ELSE d END AS pivots_per_rank FROM {_VARIANT_SQL}, ({RANKED_SQL})")
def pivot_ledger(spark, folder):
    return ledger.communication(ranked_parts(spark, folder)).select("part", "n", "variant", "p", "pivots_agreed", "pivots_per_rank")


@query("round_ledger", f"SELECT part, n, variant, p, CASE WHEN free = 1 THEN d + 2 ELSE 2 * d END AS rounds, CASE WHEN free = 1 THEN 0 ELSE d END AS group_splits FROM {_VARIANT_SQL}, ({RANKED_SQL})")
def round_ledger(spark, folder):
    return ledger.communication(ranked_parts(spark, folder)).select("part", "n", "variant", "p", "rounds", "group_splits")


_SCHEDULED = 16


@query(
    "rank_schedule",
    f"""WITH z AS (SELECT {fx.UNIFORM.start_of(_SCHEDULED)} AS r, count(*) AS n FROM lineitem GROUP BY 1), e AS (SELECT CAST(l.range AS INTEGER) AS level, CAST(r.range AS INTEGER) AS rank,
        CAST(xor(r.range, {_SCHEDULED} >> (l.range + 1)::INTEGER) AS INTEGER) AS partner, CAST(r.range >> (4 - l.range)::INTEGER AS INTEGER) AS grp FROM range(4) l, range({_SCHEDULED}) r)
    SELECT level, rank, partner, grp, coalesce(a.n, 0) AS n, coalesce(b.n, 0) AS partner_n FROM e LEFT JOIN z a ON a.r = rank LEFT JOIN z b ON b.r = partner""",
)
def rank_schedule(spark, folder):
    """Who exchanges with whom, and the line items that both start with."""
    held = fx.UNIFORM.rows(spark, folder, _SCHEDULED).groupBy(F.col("__rank").alias("rank")).agg(F.count("*").alias("n"))
    other = held.select(F.col("rank").alias("partner"), F.col("n").alias("partner_n"))
    both = schedule(spark, _SCHEDULED).join(held, "rank", "left").join(other, "partner", "left")
    return both.fillna(0, ["n", "partner_n"]).select("level", "rank", "partner", "grp", "n", "partner_n")


_REACHED = " UNION ALL ".join(f"SELECT {i} AS level, s >> {4 - i} AS s, count(*) AS n FROM {sql.last(_SCHEDULED)} GROUP BY ALL" for i in range(4))
_SLOTS = " UNION ALL ".join(f"SELECT {i} AS level, CAST(range AS INTEGER) AS segment, CAST({1 << i} + range AS INTEGER) AS heap_slot, CAST((2 * range + 1) * {_SCHEDULED >> (i + 1)} AS INTEGER) AS inorder_slot FROM range({1 << i})" for i in range(4))


@query("pivot_slots", f"{sql.chain(fx.UNIFORM.base(_SCHEDULED), _SCHEDULED)}, z AS ({_REACHED}) SELECT a.level, a.segment, a.heap_slot, a.inorder_slot, coalesce(z.n, 0) AS n FROM ({_SLOTS}) a LEFT JOIN z ON z.level = a.level AND z.s = a.segment")
def pivot_slots(spark, folder):
    """Where each pivot stands, and the line items that it divides."""
    levels = F.explode(F.sequence(F.lit(0), F.lit(_SCHEDULED.bit_length() - 2))).alias("level")
    leaves = _segmented(spark, folder, p=_SCHEDULED).groupBy(SEGMENT).agg(F.count("*").alias("n"))
    reached = leaves.select(levels, SEGMENT, "n").groupBy("level", F.expr(f"shiftright({SEGMENT}, {_SCHEDULED.bit_length() - 1} - level)").alias("segment")).agg(F.sum("n").alias("n"))
    return slots(spark, _SCHEDULED).join(reached, ["level", "segment"], "left").fillna(0, ["n"]).select("level", "segment", "heap_slot", "inorder_slot", "n")


_SWITCH_P, _CONSTANTS = [8, 16, 32, 64, 128, 256, 1024, 2048, 4096, 8192], [0.0, 150.0, 500.0, 1500.0, 5000.0, float("inf")]
_C_SQL = ", ".join(f"('{c}'::DOUBLE)" for c in _CONSTANTS)


@query(
    "switch_sweep",
    f"""WITH n AS ({_PARTS_SQL}), p(p, d) AS (VALUES {', '.join(f'({p}, {p.bit_length() - 1})' for p in _SWITCH_P)}), c(c) AS (VALUES {_C_SQL}),
    l AS (SELECT part, n, p, d, c, range AS level FROM n, p, c, range(14) WHERE range <= d),
    f AS (SELECT part, n, p, d, c, min(level) AS level FROM l WHERE level = d OR n < 2 OR n::DOUBLE / p > c * (p >> level::INTEGER) / log2(greatest(n, 2)) GROUP BY part, n, p, d, c)
    SELECT part, n, p, c, CAST(level AS INTEGER) AS exchange_levels, CAST(p >> level::INTEGER AS INTEGER) AS group_size FROM f""",
)
def switch_sweep(spark, folder):
    """Where the combined methods switch, for parts of the line items that halve."""
    return ledger.switch_table(_sized_parts(spark, folder), _SWITCH_P, _CONSTANTS).select("part", "n", "p", "c", "exchange_levels", "group_size")


_MODEL = [16, 256, 1024, 4096, 8192]
_MODEL_SQL = "(VALUES " + ", ".join(f"({p}, {p.bit_length() - 1})" for p in _MODEL) + ") AS p(p, lp)"


@query(
    "cost_model",
    f"""WITH x AS (SELECT variant, free, part, n, p, n::DOUBLE / p AS e, log2(greatest(n, 1)::DOUBLE) AS ln, log2(greatest(2.0, n::DOUBLE / p)::DOUBLE) AS le, lp, contains(variant, 'sort_first') AS sf FROM {_VARIANT_SQL}, ({_PARTS_SQL}), {_MODEL_SQL})
    SELECT part, variant, n, p, floor((CASE WHEN free = 1 AND sf THEN e * le + p * le + e * lp ELSE e * ln END) * 1000 + 0.5) / 1000 AS local_work,
        floor((CASE WHEN free = 1 THEN e ELSE e * lp END) * 1000 + 0.5) / 1000 AS row_exchange, (CASE WHEN free = 1 THEN lp * lp + p WHEN sf THEN lp * lp ELSE lp * (lp + 20) END)::DOUBLE AS pivots,
        CASE WHEN free = 1 THEN p ELSE 0 END::DOUBLE AS start_ups FROM x""",
)
def cost_model(spark, folder):
    """The linear cost model's terms, at unit costs, for parts of the line items that halve."""
    sized = _sized_parts(spark, folder).withColumn("p", F.explode(F.array(*map(F.lit, _MODEL))))
    return ledger.terms(sized).select("part", "variant", "n", "p", "local_work", "row_exchange", "pivots", "start_ups")


@query("pivot_quality", f"{_CHAIN} " + " UNION ALL ".join(f"SELECT {i} AS level, CAST(s >> {_LEVELS - i} AS INTEGER) AS segment, count(*) FILTER (((s >> {_LEVELS - 1 - i}) & 1) = 0) AS left_rows, count(*) FILTER (((s >> {_LEVELS - 1 - i}) & 1) = 1) AS right_rows FROM {_END} GROUP BY s >> {_LEVELS - i}" for i in range(_LEVELS)))
def pivot_quality(spark, folder):
    return ledger.pivot_quality(_segmented(spark, folder), P)


@query("is_sorted", f"SELECT CAST({P - 1} AS BIGINT) AS rank_pairs, CAST(0 AS BIGINT) AS violations")
def is_sorted(spark, folder):
    return verify.check_sorted(v.exchange_free_quicksort(fx.UNIFORM.rows(spark, folder), fx.UNIFORM.spec, P).rows, fx.UNIFORM.spec)


# --- ties ---


def _sizes(segmented: DataFrame) -> DataFrame:
    return segmented.groupBy(F.col(SEGMENT).alias("segment")).agg(F.count("*").alias("n"))


_TIED = sql.chain(fx.DUPLICATES.base(), P)


@query("ties_left", f"{_TIED} SELECT CAST(s AS INTEGER) AS segment, count(*) AS n FROM {_END} GROUP BY s")
def ties_left(spark, folder):
    return _sizes(_segmented(spark, folder, fx.DUPLICATES))


_EVEN = ["e0 AS (SELECT k, l_discount, l_orderkey, l_linenumber, l_extendedprice, 0 AS s FROM base)"]
for _i in range(_LEVELS):
    _EVEN.append(f"t{_i} AS (SELECT e.*, b.piv, row_number() OVER (PARTITION BY e.s, e.k = b.piv ORDER BY e.l_discount, e.l_orderkey, e.l_linenumber, e.l_extendedprice) AS turn FROM e{_i} e JOIN pv{_i} b ON e.s = b.s)")
    _EVEN.append(f"e{_i + 1} AS (SELECT k, l_discount, l_orderkey, l_linenumber, l_extendedprice, 2 * s + CASE WHEN k > piv OR (k = piv AND turn % 2 = 0) THEN 1 ELSE 0 END AS s FROM t{_i})")


@query("ties_even", f"{_TIED}, {', '.join(_EVEN)} SELECT CAST(s AS INTEGER) AS segment, count(*) AS n FROM e{_LEVELS} GROUP BY s")
def ties_even(spark, folder):
    """Rows equal to a pivot halved exactly."""
    rows = fx.DUPLICATES.rows(spark, folder)
    return _sizes(split_evenly(rows, fx.DUPLICATES.spec, agree(rows, fx.DUPLICATES.spec, P)))


@query("ties_even_hashed")
def ties_even_hashed(spark, folder):
    """Rows equal to a pivot halved by a bit of a hash, without a window."""
    return _sizes(_segmented(spark, folder, fx.DUPLICATES, ties="even"))


_ALL_PIVOTS = " UNION ALL ".join(f"SELECT piv FROM pv{i}" for i in range(_LEVELS))


@query(
    "ties_three_way",
    f"{_TIED}, a AS ({_ALL_PIVOTS}), q AS (SELECT b.*, (SELECT count(*) FROM a WHERE a.piv = b.k) AS equal FROM {_END} b) SELECT CAST(s + (l_orderkey + l_linenumber) % (equal + 1) AS INTEGER) AS segment, count(*) AS n FROM q GROUP BY 1",
)
def ties_three_way(spark, folder):
    """Keys that equal pivots dealt over all the segments they may lie in."""
    rows, spec = fx.DUPLICATES.rows(spark, folder), fx.DUPLICATES.spec
    return _sizes(with_segments(rows, spec, agree(rows, spec, P), "three_way", F.col("l_orderkey") + F.col("l_linenumber")))


_TOTAL = f"SELECT row_number() OVER (ORDER BY {fx.DUPLICATES.order()}) AS k, {fx.DUPLICATES.start_of(P)} AS r FROM lineitem"


@query("ties_total_order", f"{sql.chain(_TOTAL, P, 'middle')} SELECT CAST(s AS INTEGER) AS segment, count(*) AS n FROM {_END} GROUP BY s")
def ties_total_order(spark, folder):
    """Ties compared as part of the key: balance whatever repeats."""
    return _sizes(_segmented(spark, folder, fx.DUPLICATES, chooser=pv.MIDDLE, ties="total_order"))


# --- experiments, by counts ---


@query("skew_midpoint", f"{sql.chain(fx.SKEWED.base(), P)} SELECT CAST(s AS INTEGER) AS rank, count(*) AS n FROM {_END} GROUP BY s")
def skew_midpoint(spark, folder):
    return _sizes(_segmented(spark, folder, fx.SKEWED)).withColumnRenamed("segment", "rank")


@query("skew_middle", f"{sql.chain(fx.SKEWED.base(), P, 'middle')} SELECT CAST(s AS INTEGER) AS rank, count(*) AS n FROM {_END} GROUP BY s")
def skew_middle(spark, folder):
    return _sizes(_segmented(spark, folder, fx.SKEWED, chooser=pv.MIDDLE)).withColumnRenamed("segment", "rank")


_PLACEMENTS = {"dealt": "event_id", "blocked": f"event_id * {P} // (SELECT count(*) FROM events)"}


@query("placement_effect", _union([f"{sql.chain(f'SELECT epoch_us(ts) AS k, ({e}) % {P} AS r FROM events', P, whole=True)} SELECT '{n}' AS placement, CAST(sum({sql.moved(P, 0)}) AS BIGINT) AS rows_moved FROM {_END}" for n, e in _PLACEMENTS.items()]))
def placement_effect(spark, folder):
    """An input that lies in order already moves few rows; one that is dealt moves nearly all."""
    from ..placement import blocked, place

    rows, out = fx.ORDERED_START.rows(spark, folder), None
    n = rows.count()
    for name, by in {"dealt": F.col("event_id"), "blocked": blocked(F.col("event_id"), n, P)}.items():
        placed = place(rows.drop("__rank"), P, by)
        one = ledger.rows_moved(with_segments(placed, fx.ORDERED_START.spec, agree(placed, fx.ORDERED_START.spec, P)), P, 0)
        one = one.select(F.lit(name).alias("placement"), "rows_moved")
        out = one if out is None else out.unionByName(one)
    return out


# The experiments at their published settings: quicksort takes the ends of 20 sampled rows a rank, sort-first those of its
# sorted ranks; both take the midpoint.  Rows carry their way, so that moves are counted from what the variants did.

_PAIRS = {"quicksort": ("exchange_quicksort", "combined_quicksort", "exchange_free_quicksort"), "sort_first": ("exchange_sort_first", "combined_sort_first", "exchange_free_sort_first")}


def _run(name: str, rows: DataFrame, fixture: fx.Fixture, p: int, n: int) -> DataFrame:
    """(variant, p, exchange_levels, rows_moved, max_rows) of one run."""
    traced, spec = rows.withColumn(TRACE, F.array("__rank")), fixture.spec
    levels = {"exchange": p.bit_length() - 1, "combined": v.switch_level(n, p), "exchange_free": 0}[name.rsplit("_quicksort")[0].rsplit("_sort_first")[0]]
    if name.endswith("quicksort"):
        options = {"n": n} if name.startswith("combined") else {}
        done = getattr(v, name)(traced, spec, p, chooser=pv.SAMPLED_BY_TIE, tie=F.expr(fixture.shuffled), **options)
    else:
        options = {"n": n} if name.startswith("combined") else {}
        done = getattr(v, name)(traced, spec, p, chooser=pv.MIDPOINT, **options)
    by_rank = done.segmented.groupBy(SEGMENT).agg(F.count("*").alias("n"), F.sum(ledger.moves_made()).alias("moved"))
    return by_rank.agg(F.sum("moved").cast("long").alias("rows_moved"), F.max("n").alias("max_rows")).select(F.lit(name).alias("variant"), F.lit(p).alias("p"), F.lit(levels).alias("exchange_levels"), "rows_moved", "max_rows")


def _runs(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for one in parts[1:]:
        out = out.unionByName(one)
    return out


def _run_sql(name: str, fixture: fx.Fixture, p: int, base: str | None = None) -> str:
    """The same by the closed form of a row's moves, from segments that the levels' pivots give."""
    d, wrong, kind = p.bit_length() - 1, "xor(CAST(r AS BIGINT), CAST(s AS BIGINT))", name.rsplit("_quicksort")[0].rsplit("_sort_first")[0]
    rest = {"exchange": "0", "exchange_free": str(d), "combined": f"(SELECT CAST({d} - min(g.range) AS INTEGER) FROM range({d + 1}) g, (SELECT count(*) AS n FROM base) b WHERE g.range = {d} OR b.n::DOUBLE / {p} > 1500 * ({p} >> g.range::INTEGER) / log2(b.n))"}[kind]
    rule = "midpoint" if name.endswith("sort_first") else {"exchange": "sampled_exchange", "exchange_free": "sampled", "combined": "sampled_combined"}[kind]
    return (
        f"{sql.chain(base or fixture.base(p), p, rule, whole=fixture.whole)}, lv AS (SELECT {rest} AS rest), z AS (SELECT max(n) AS m FROM (SELECT count(*) AS n FROM {sql.last(p)} GROUP BY s)) "
        f"SELECT '{name}' AS variant, {p} AS p, CAST({d} - max(lv.rest) AS INTEGER) AS exchange_levels, CAST(sum(bit_count({wrong} >> lv.rest) + CASE WHEN ({wrong} & ((1 << lv.rest) - 1)) <> 0 THEN 1 ELSE 0 END) AS BIGINT) AS rows_moved, (SELECT m FROM z) AS max_rows FROM {sql.last(p)}, lv"
    )


def _experiment(label: str, names: tuple[str, ...], ranks: list[int], fixture: fx.Fixture, about: str) -> None:
    def own(spark: SparkSession, folder: str) -> DataFrame:
        n = fixture.rows(spark, folder, 2).count()
        return _runs([_run(name, fixture.rows(spark, folder, p), fixture, p, n) for p in ranks for name in names])

    own.__doc__ = about
    query(label, _union([_run_sql(name, fixture, p) for p in ranks for name in names]))(own)


_STRONG, _SWITCHING = [2, 4, 8, 16, 32], [16, 32]
for _pair, _names in _PAIRS.items():
    _experiment(f"strong_{_pair}", (_names[0], _names[2]), _STRONG, fx.UNIFORM, "Fixed rows, more ranks: rows that a pair of variants moved.")
    _experiment(f"strong_combined_{_pair}", _names, _SWITCHING, fx.UNIFORM, "Fixed rows, more ranks: the combined variant, whose switch depends on the rows, between the pure ones.")
    _experiment(f"strong_integers_{_pair}", (_names[0], _names[2]), [8, 32], fx.INTEGERS, "The same with whole numbers.")
    _experiment(f"strong_permutation_{_pair}", (_names[0], _names[2]), [8, 32], fx.PERMUTATION, "The same with a permutation.")


_PARTS, _WEAK_P = [8, 4, 2, 1], 16


def _weak(pair: str) -> None:
    names = (_PAIRS[pair][0], _PAIRS[pair][2])

    def own(spark: SparkSession, folder: str) -> DataFrame:
        parts = []
        for m in _PARTS:
            rows = fx.UNIFORM.rows(spark, folder, _WEAK_P).where(F.pmod("l_orderkey", F.lit(m)) == 0)
            parts += [_run(name, rows, fx.UNIFORM, _WEAK_P, 0).withColumn("size", F.lit(_WEAK_P * 8 // m)) for name in names]
        return _runs(parts)

    own.__doc__ = "Fixed ranks, more rows a rank: an experiment on shares of the table, which doubles from one size to the next."
    shares = [f"SELECT *, {_WEAK_P * 8 // m} AS size FROM ({_run_sql(name, fx.UNIFORM, _WEAK_P, f'{fx.UNIFORM.base(_WEAK_P)} WHERE l_orderkey % {m} = 0')})" for m in _PARTS for name in names]
    query(f"weak_{pair}", _union(shares))(own)


for _pair in _PAIRS:
    _weak(_pair)


_SCANNED = " UNION ALL ".join(f"SELECT r, {i} AS level, s >> {_LEVELS - i} AS s, count(*) AS n FROM {_END} GROUP BY ALL" for i in range(_LEVELS))


@query("ledger_scanned", f"{_CHAIN} SELECT CAST(sum(n) AS BIGINT) AS scanned, CAST(sum(length(bin(n))) AS BIGINT) AS probes FROM ({_SCANNED})")
def ledger_scanned(spark, folder):
    """Rows looked at while splitting: by scans, and by binary searches in sorted ranks."""
    return ledger.rows_scanned(_segmented(spark, folder), P)


@query("sample_size_sweep")
def sample_size_sweep(spark, folder):
    """(s, table, max_over_mean): balance by the size of the pivot sample."""
    rows = []
    for name, fixture in {"uniform": fx.UNIFORM, "skewed": fx.SKEWED}.items():
        for s in (1, 5, 20, 100):
            for kind, chooser in {"ends": pv.Chooser(pv.SampleExtremes(s), pv.Midpoint()), "pool": pv.Chooser(pv.SamplePool(s), pv.MedianOfCandidates())}.items():
                rows.append((name, kind, s, ledger.balance(_segmented(spark, folder, fixture, P, chooser), P)))
    return spark.createDataFrame(rows, "input string, sample string, s int, max_over_mean double")


@query("participation")
def participation(spark, folder):
    """(variant, level, worst): how far from a half the pivots of sampled ends divide, with all ranks or the group's alone taking part."""
    rows, spec, out = fx.UNIFORM.rows(spark, folder), fx.UNIFORM.spec, None
    for name, segmented in {"exchange": v.exchange_quicksort(rows, spec, P, pv.SAMPLED).segmented, "exchange_free": _segmented(spark, folder, chooser=pv.SAMPLED)}.items():
        share = F.abs(F.col("left_rows") / (F.col("left_rows") + F.col("right_rows")) - 0.5)
        one = ledger.pivot_quality(segmented, P).groupBy("level").agg(F.max(share).alias("worst")).select(F.lit(name).alias("variant"), "level", "worst")
        out = one if out is None else out.unionByName(one)
    return out
