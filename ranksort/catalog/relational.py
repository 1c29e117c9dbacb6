"""Queries of the operators around the sorts, of functions and of streams, with SQL twins."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import surface
from ..keys import KeySpec
from ..operators import joins, order
from ..placement import place
from ..plans import variants as v
from ..plans.pivot_tree import SEGMENT, PivotTree
from ..plans.pivots import MIDDLE
from ..plans.redistribute import POSITION, positions, with_segments
from ..plans.rounds import agree
from ..shared import scratch
from ..sources import tables
from ..sources.tables import load
from ..streaming import routing
from . import fixtures as fx
from . import sorting, sql

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


def _uniform(spark: SparkSession, folder: str) -> v.Sorted:
    return v.exchange_free_quicksort(fx.UNIFORM.rows(spark, folder), fx.UNIFORM.spec, P)


# --- questions that an order answers ---


@query("range_filter", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem WHERE l_extendedprice BETWEEN 30000 AND 40000")
def range_filter(spark, folder):
    """A range of keys: the pivots rule out all other segments."""
    done = _uniform(spark, folder)
    return order.range_scan(done.segmented, done.spec, done.tree, 30_000.0, 40_000.0).select(*fx.UNIFORM.columns)


@query(
    "predicates",
    """SELECT p_partkey, p_size, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS class FROM part
    WHERE (p_brand IN ('Brand#11', 'Brand#23') OR p_type LIKE '%STEEL%') AND p_name IS NOT NULL AND p_retailprice BETWEEN 900 AND 1500""",
)
def predicates(spark, folder):
    part = load(spark, folder, "part")
    chosen = part.where((F.col("p_brand").isin("Brand#11", "Brand#23") | F.col("p_type").like("%STEEL%")) & F.col("p_name").isNotNull() & F.col("p_retailprice").between(900, 1500))
    return chosen.select("p_partkey", "p_size", F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large").alias("class"))


@query("top_k", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice, l_orderkey, l_linenumber LIMIT 100")
def top_k(spark, folder):
    """The first hundred rows, from the leading segments alone."""
    rows = fx.UNIFORM.rows(spark, folder)
    return order.top_k(rows, fx.UNIFORM.spec, agree(rows, fx.UNIFORM.spec, P), 100).select(*fx.UNIFORM.columns)


@query("bottom_k", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber LIMIT 100")
def bottom_k(spark, folder):
    """The last hundred rows: the leading segments of the downward order."""
    rows, spec = fx.UNIFORM.rows(spark, folder), KeySpec("l_extendedprice", ("l_orderkey", "l_linenumber"), ("l_extendedprice",))
    return order.top_k(rows, spec, agree(rows, spec, P), 100).select(*fx.UNIFORM.columns)


@query("top_k_group", "SELECT c_mktsegment, c_custkey, c_acctbal, place FROM (SELECT *, CAST(row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) AS INTEGER) AS place FROM customer) WHERE place <= 5")
def top_k_group(spark, folder):
    spec = KeySpec("c_acctbal", ("c_custkey",), ("c_acctbal",))
    return order.top_k_group(load(spark, folder, "customer"), spec, ["c_mktsegment"], 5).select("c_mktsegment", "c_custkey", "c_acctbal", "place")


@query("page", "SELECT l_orderkey, l_linenumber, l_extendedprice, pos FROM (SELECT *, row_number() OVER (ORDER BY l_extendedprice, l_orderkey, l_linenumber) - 1 AS pos FROM lineitem) WHERE pos >= 1000 AND pos < 1100")
def page(spark, folder):
    return order.page(_uniform(spark, folder), 1000, 100).select(*fx.UNIFORM.columns, F.col(POSITION).alias("pos"))


@query("kth_element", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM (SELECT *, row_number() OVER (ORDER BY l_extendedprice, l_orderkey, l_linenumber) - 1 AS pos FROM lineitem) WHERE pos = 1234")
def kth_element(spark, folder):
    return order.select_kth(_uniform(spark, folder), 1234).select(*fx.UNIFORM.columns)


_SHARES = [0.0, 0.01, 0.25, 0.5, 0.75, 0.99, 1.0]


@query(
    "exact_quantiles",
    f"""WITH q(share) AS (VALUES {', '.join(f'({s}::DOUBLE)' for s in _SHARES)}), o AS (SELECT l_extendedprice, row_number() OVER (ORDER BY l_extendedprice) - 1 AS pos, count(*) OVER () AS n FROM lineitem)
    SELECT share, l_extendedprice AS value FROM q JOIN o ON pos = greatest(0, CAST(ceil(share * n) AS BIGINT) - 1)""",
)
def exact_quantiles(spark, folder):
    return order.quantiles(_uniform(spark, folder), _SHARES)


@query("global_row_number", sql.by_position("customer", "c_custkey, c_acctbal", "c_acctbal DESC, c_custkey"))
def global_row_number(spark, folder):
    """Row numbers of a downward order, without a window over everything."""
    spec = KeySpec("c_acctbal", ("c_custkey",), ("c_acctbal",))
    done = v.exchange_free_quicksort(fx.NEGATIVE.rows(spark, folder), spec, P)
    return done.with_positions().select("c_custkey", "c_acctbal", F.col(POSITION).alias("pos"))


@query(
    "global_rank",
    "SELECT l_orderkey, l_linenumber, l_extendedprice, l_discount, rank() OVER (ORDER BY l_discount) AS rank, dense_rank() OVER (ORDER BY l_discount) AS dense_rank, percent_rank() OVER (ORDER BY l_discount) AS percent_rank FROM lineitem",
)
def global_rank(spark, folder):
    rows = fx.DUPLICATES.rows(spark, folder)
    done = order.global_ranks(v.exchange_free_quicksort(rows, fx.DUPLICATES.spec, P))
    return done.select("l_orderkey", "l_linenumber", "l_extendedprice", "l_discount", "rank", "dense_rank", "percent_rank")


@query("dedup_sorted", "SELECT min(doc_id) AS doc_id, sha256(text) AS text_sha256 FROM documents GROUP BY text")
def dedup_sorted(spark, folder):
    """One row of each text, by comparing neighbours; ordered by digest, so that texts do not travel."""
    docs = load(spark, folder, "documents").select("doc_id", F.sha2("text", 256).alias("text_sha256"))
    spec = KeySpec("text_sha256", ("doc_id",))
    even = PivotTree.from_sorted([f"{256 * i // P:02x}" for i in range(1, P)], T.StringType())  # digests are uniform: no rounds
    return order.dedup_sorted(with_segments(docs, spec, even), spec).select("doc_id", "text_sha256")


@query("merge_sorted", "SELECT key, src, row_number() OVER (ORDER BY key, src, id) - 1 AS pos FROM (SELECT c_acctbal AS key, 'c' AS src, c_custkey AS id FROM customer UNION ALL SELECT s_acctbal, 's', s_suppkey FROM supplier)")
def merge_sorted(spark, folder):
    a = load(spark, folder, "customer").select(F.col("c_acctbal").alias("key"), F.lit("c").alias("src"), F.col("c_custkey").alias("id"))
    b = load(spark, folder, "supplier").select(F.col("s_acctbal").alias("key"), F.lit("s").alias("src"), F.col("s_suppkey").alias("id"))
    return order.merge_sorted(a, b, KeySpec("key", ("src", "id")), P).with_positions().select("key", "src", F.col(POSITION).alias("pos"))


# --- joins ---


def _orders_lines(spark, folder):
    return load(spark, folder, "orders").select("o_orderkey", "o_totalprice"), load(spark, folder, "lineitem").select("l_orderkey", "l_linenumber", "l_extendedprice")


_EQUI = "SELECT o_orderkey, l_linenumber, l_extendedprice, o_totalprice FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
_EQUI_COLUMNS = ("o_orderkey", "l_linenumber", "l_extendedprice", "o_totalprice")


@query("join_sort_merge", _EQUI)
def join_sort_merge(spark, folder):
    orders, lines = _orders_lines(spark, folder)
    return joins.join(lines, orders, F.col("o_orderkey") == F.col("l_orderkey"), strategy="merge").select(*_EQUI_COLUMNS)


@query("join_hash", _EQUI)
def join_hash(spark, folder):
    orders, lines = _orders_lines(spark, folder)
    return joins.join(lines, orders, F.col("o_orderkey") == F.col("l_orderkey"), strategy="hash").select(*_EQUI_COLUMNS)


@query("join_coranked", _EQUI)
def join_coranked(spark, folder):
    """Both sides dealt by one pivot tree; equal keys meet without an exchange of the join's own."""
    orders, lines = _orders_lines(spark, folder)
    placed = place(orders, P, F.col("o_orderkey"))
    tree = agree(placed, KeySpec("o_orderkey"), P)
    return joins.merge_join(orders, lines, "o_orderkey", "l_orderkey", tree, P).select(*_EQUI_COLUMNS)


@query("join_broadcast", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(spark, folder):
    customers, nations, regions = (load(spark, folder, t) for t in ("customer", "nation", "region"))
    places = joins.join(nations, regions, F.col("n_regionkey") == F.col("r_regionkey"), strategy="broadcast")
    return joins.join(customers, places, F.col("c_nationkey") == F.col("n_nationkey"), strategy="broadcast").select("c_custkey", "n_name", "r_name")


@query("join_theta", "SELECT n_nationkey, r_regionkey FROM nation JOIN region ON n_regionkey < r_regionkey")
def join_theta(spark, folder):
    """An inequality between two small tables of fixed size."""
    nations, regions = load(spark, folder, "nation"), load(spark, folder, "region")
    return joins.join(nations, regions, F.col("n_regionkey") < F.col("r_regionkey"), strategy="broadcast").select("n_nationkey", "r_regionkey")


_BANDS = [(f"b{i}", 800.0 + 90 * i, 800.0 + 90 * i + 150) for i in range(20)]


@query("join_range", f"SELECT p_partkey, band FROM part JOIN (VALUES {', '.join(f'({chr(39)}{n}{chr(39)}, {a}::DOUBLE, {b}::DOUBLE)' for n, a, b in _BANDS)}) AS bands(band, low, high) ON p_retailprice >= low AND p_retailprice < high")
def join_range(spark, folder):
    """Points in overlapping bands, met by segment."""
    parts = load(spark, folder, "part").select("p_partkey", "p_retailprice")
    bands = spark.createDataFrame(_BANDS, "band string, low double, high double")
    tree = agree(place(parts, P, F.col("p_partkey")), KeySpec("p_retailprice"), P)
    return joins.range_join(parts, bands, "p_retailprice", "low", "high", tree).select("p_partkey", "band")


@query(
    "join_asof",
    "SELECT c.event_id, (SELECT max(w.event_id) FROM events w WHERE w.event_type = 'view' AND w.user_id = c.user_id AND w.ts = m.last) AS view_id FROM events c "
    "LEFT JOIN (SELECT a.event_id, max(b.ts) AS last FROM events a JOIN events b ON b.user_id = a.user_id AND b.event_type = 'view' AND b.ts < a.ts WHERE a.event_type = 'click' GROUP BY a.event_id) m ON m.event_id = c.event_id WHERE c.event_type = 'click'",
)
def join_asof(spark, folder):
    """Each click with the user's last view before it."""
    events = load(spark, folder, "events").select("event_id", "ts", "user_id", "event_type")
    clicks, views = events.where("event_type = 'click'").drop("event_type"), events.where("event_type = 'view'").withColumnRenamed("event_id", "view_id")
    return joins.asof_join(clicks, views, "ts", "user_id", "view_id").select("event_id", "view_id")


@query("join_asof_parts", ORACLES["join_asof"])
def join_asof_parts(spark, folder):
    """The same with each user's time cut into parts."""
    events = load(spark, folder, "events").select("event_id", "ts", "user_id", "event_type")
    clicks, views = events.where("event_type = 'click'").drop("event_type"), events.where("event_type = 'view'").withColumnRenamed("event_id", "view_id")
    tree = agree(place(views, P, F.col("view_id")), KeySpec("ts", ("view_id",)), P)
    return joins.asof_join(clicks, views, "ts", "user_id", "view_id", parts=tree).select("event_id", "view_id")


@query("join_semi", "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def join_semi(spark, folder):
    orders, lines = _orders_lines(spark, folder)
    return joins.join(orders, lines, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey")


@query("join_anti", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def join_anti(spark, folder):
    orders, lines = _orders_lines(spark, folder)
    return joins.join(orders, lines, F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@query("join_left", "SELECT o_orderkey, l_linenumber FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey")
def join_left(spark, folder):
    orders, lines = _orders_lines(spark, folder)
    return joins.join(orders, lines, F.col("o_orderkey") == F.col("l_orderkey"), "left").select("o_orderkey", "l_linenumber")


@query("join_right", "SELECT c_custkey, s_suppkey FROM customer RIGHT JOIN supplier ON c_custkey = s_suppkey * 3 AND c_acctbal > 0")
def join_right(spark, folder):
    customers, suppliers = load(spark, folder, "customer"), load(spark, folder, "supplier")
    return joins.join(customers, suppliers, (F.col("c_custkey") == F.col("s_suppkey") * 3) & (F.col("c_acctbal") > 0), "right").select("c_custkey", "s_suppkey")


@query("join_full", "SELECT c_custkey, s_suppkey FROM customer FULL JOIN supplier ON c_custkey = s_suppkey * 3")
def join_full(spark, folder):
    return joins.join(load(spark, folder, "customer"), load(spark, folder, "supplier"), F.col("c_custkey") == F.col("s_suppkey") * 3, "full").select("c_custkey", "s_suppkey")


# --- aggregates ---


@query("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, min(l_extendedprice) AS lo, max(l_extendedprice) AS hi, CAST(sum(CAST(l_extendedprice AS DECIMAL(12, 2))) AS DOUBLE) AS total FROM lineitem GROUP BY ALL")
def agg_basic(spark, folder):
    total = F.sum(F.col("l_extendedprice").cast("decimal(12,2)")).cast("double")
    return load(spark, folder, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"), total.alias("total"))


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT (l_partkey, l_suppkey)) AS pairs FROM lineitem GROUP BY l_returnflag")
def agg_distinct(spark, folder):
    return load(spark, folder, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct(F.struct("l_partkey", "l_suppkey")).alias("pairs"))


@query("agg_approximate")
def agg_approximate(spark, folder):
    """Sketches: distinct counts and medians within their errors."""
    return load(spark, folder, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("median"))


_PRIORITY = "CASE WHEN o_totalprice > 250000 THEN 'high' ELSE 'low' END"


@query("agg_rollup", f"SELECT o_orderstatus, {_PRIORITY} AS worth, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, {_PRIORITY})")
def agg_rollup(spark, folder):
    return load(spark, folder, "orders").withColumn("worth", F.expr(_PRIORITY)).rollup("o_orderstatus", "worth").agg(F.count("*").alias("n"))


@query("agg_cube", f"SELECT o_orderstatus, {_PRIORITY} AS worth, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, {_PRIORITY})")
def agg_cube(spark, folder):
    return load(spark, folder, "orders").withColumn("worth", F.expr(_PRIORITY)).cube("o_orderstatus", "worth").agg(F.count("*").alias("n"))


@query("agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def agg_grouping_sets(spark, folder):
    sets = [[F.col("o_orderstatus")], [F.col("o_orderpriority")], []]
    return load(spark, folder, "orders").groupingSets(sets, "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")).select("o_orderstatus", "o_orderpriority", "n")


@query("agg_positional", "SELECT c_mktsegment, min_by(c_custkey, c_acctbal) AS poorest, max_by(c_custkey, c_acctbal) AS richest, CAST(len(list(c_custkey)) AS INTEGER) AS n FROM customer GROUP BY c_mktsegment")
def agg_positional(spark, folder):
    """Ends by another column.  Of rows that tie the least key counts, as where SQL meets rows in the order of keys; rows without a key or a balance are no end."""
    known = F.col("c_custkey").isNotNull() & F.col("c_acctbal").isNotNull()
    least, most = F.struct("c_acctbal", "c_custkey"), F.struct(F.col("c_acctbal"), F.bitwise_not("c_custkey"))
    ends = [F.min_by("c_custkey", F.when(known, least)).alias("poorest"), F.max_by("c_custkey", F.when(known, most)).alias("richest")]
    return load(spark, folder, "customer").groupBy("c_mktsegment").agg(*ends, F.count("*").cast("int").alias("n"))


@query(
    "agg_first_last",
    """SELECT user_id, first(event_id ORDER BY ts, event_id) AS first_event, last(event_id ORDER BY ts, event_id) AS last_event, array_to_string(list(event_id ORDER BY ts, event_id), ',') AS events, m.event_type AS usual
    FROM events JOIN (SELECT user_id AS u, event_type FROM (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY count(*) DESC, event_type) AS k FROM events GROUP BY user_id, event_type) WHERE k = 1) m ON m.u = user_id GROUP BY user_id, m.event_type""",
)
def agg_first_last(spark, folder):
    """First, last and all of a group in order, and its most frequent value (ties: the smallest)."""
    at, events = F.struct("ts", "event_id"), load(spark, folder, "events")
    every = F.array_join(F.transform(F.sort_array(F.collect_list(at)), lambda x: x["event_id"].cast("string")), ",")
    return events.groupBy("user_id").agg(F.min_by("event_id", at).alias("first_event"), F.max_by("event_id", at).alias("last_event"), every.alias("events"), F.mode("event_type", True).alias("usual"))


@query("agg_extremes_sample")
def agg_extremes_sample(spark, folder):
    """The mergeable aggregate of ends and a bounded sample."""
    return load(spark, folder, "lineitem").groupBy("l_returnflag").agg(surface.extremes_sample(F.col("l_extendedprice"), F.col("l_orderkey")).alias("x")).select("l_returnflag", "x.lo", "x.hi", F.size("x.sample").alias("sampled"))


# --- windows ---

_SUPPLIERS = "PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey"


@query("win_ranking", f"SELECT s_suppkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd, CAST(ntile(4) OVER w AS INTEGER) AS nt FROM supplier WINDOW w AS ({_SUPPLIERS})")
def win_ranking(spark, folder):
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")
    return load(spark, folder, "supplier").select("s_suppkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"), F.ntile(4).over(w).alias("nt"))


@query("win_analytic", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS later, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_analytic(spark, folder):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, folder, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("later"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(w).alias("second"))


@query(
    "win_frames",
    "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS last_four, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS best_before, "
    "count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS last_day FROM events",
)
def win_frames(spark, folder):
    by = Window.partitionBy("user_id")
    rows, day = by.orderBy("ts", "event_id"), by.orderBy(F.unix_micros(F.col("ts").cast("timestamp")))
    return load(spark, folder, "events").select(
        "event_id", F.count("*").over(rows.rowsBetween(-3, 0)).alias("last_four"), F.max("value").over(rows.rowsBetween(Window.unboundedPreceding, -1)).alias("best_before"),
        F.count("*").over(day.rangeBetween(-86_400_000_000, 0)).alias("last_day"),
    )


# --- sets ---


@query("set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def set_union(spark, folder):
    return load(spark, folder, "customer").select(F.col("c_nationkey").alias("k")).union(load(spark, folder, "supplier").select("s_nationkey")).distinct()


@query("set_union_all", "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")
def set_union_all(spark, folder):
    return load(spark, folder, "customer").select(F.col("c_nationkey").alias("k")).union(load(spark, folder, "supplier").select("s_nationkey"))


@query("set_intersect", "SELECT l_partkey AS k FROM lineitem INTERSECT SELECT p_partkey FROM part")
def set_intersect(spark, folder):
    return load(spark, folder, "lineitem").select(F.col("l_partkey").alias("k")).intersect(load(spark, folder, "part").select("p_partkey"))


@query("set_intersect_all", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
def set_intersect_all(spark, folder):
    return load(spark, folder, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(load(spark, folder, "supplier").select("s_nationkey"))


@query("set_except", "SELECT o_orderkey AS k FROM orders EXCEPT SELECT l_orderkey FROM lineitem")
def set_except(spark, folder):
    return load(spark, folder, "orders").select(F.col("o_orderkey").alias("k")).subtract(load(spark, folder, "lineitem").select("l_orderkey"))


@query("set_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def set_except_all(spark, folder):
    return load(spark, folder, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(load(spark, folder, "supplier").select("s_nationkey"))


# --- scalar functions ---


@query("fn_string", "SELECT p_partkey, upper(p_name) AS u, substring(p_name, 2, 3) AS s, length(p_type) AS n, regexp_extract(p_brand, '([0-9]+)', 1) AS d, concat_ws('-', p_brand, p_type) AS c, split_part(p_name, ' ', 1) AS f FROM part")
def fn_string(spark, folder):
    return load(spark, folder, "part").select(
        "p_partkey", F.upper("p_name").alias("u"), F.substring("p_name", 2, 3).alias("s"), F.length("p_type").cast("long").alias("n"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("d"),
        F.concat_ws("-", "p_brand", "p_type").alias("c"), F.split_part("p_name", F.lit(" "), F.lit(1)).alias("f"),
    )


@query("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS t, datediff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS d, CAST(o_orderdate AS DATE) + 30 AS later FROM orders")
def fn_date(spark, folder):
    day = F.col("o_orderdate").cast("date")
    return load(spark, folder, "orders").select(
        "o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.trunc(day, "month").alias("t"), F.datediff(day, F.lit("1992-01-01").cast("date")).cast("long").alias("d"), F.date_add(day, 30).alias("later")
    )


@query("fn_math", "SELECT l_orderkey, l_linenumber, l_extendedprice, (l_orderkey * 7 + l_linenumber) % 8 AS r, CAST(bit_count(xor(l_orderkey, l_partkey)) AS INTEGER) AS b, l_orderkey >> 3 AS h, CAST(floor(l_extendedprice / 100) AS BIGINT) AS f, abs(l_quantity - 25) AS a FROM lineitem")
def fn_math(spark, folder):
    return load(spark, folder, "lineitem").select(
        "l_orderkey", "l_linenumber", "l_extendedprice", F.pmod(F.col("l_orderkey") * 7 + F.col("l_linenumber"), F.lit(8)).alias("r"), F.bit_count(F.col("l_orderkey").bitwiseXOR(F.col("l_partkey"))).alias("b"),
        F.shiftright("l_orderkey", 3).alias("h"), F.floor(F.col("l_extendedprice") / 100).alias("f"), F.abs(F.col("l_quantity") - 25).alias("a"),
    )


@query("fn_array", "SELECT vec_id, len(embedding) AS n, list_max(embedding)::DOUBLE AS hi, list_min(embedding)::DOUBLE AS lo, list_sort(embedding)[1]::DOUBLE AS first, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def fn_array(spark, folder):
    return load(spark, folder, "embeddings").select(
        "vec_id", F.size("embedding").cast("long").alias("n"), F.array_max("embedding").cast("double").alias("hi"), F.array_min("embedding").cast("double").alias("lo"), F.sort_array("embedding")[0].cast("double").alias("first"),
        F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"),
    )


@query("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events")
def fn_json(spark, folder):
    return load(spark, folder, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("fn_map", "SELECT event_id, 'k' AS name, CAST(json_extract_string(props, '$.k') AS BIGINT) AS number FROM events")
def fn_map(spark, folder):
    entries = F.explode(F.from_json("props", "map<string,long>")).alias("name", "number")
    return load(spark, folder, "events").select("event_id", entries)


@query("fn_conditional", "SELECT c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS s, CASE WHEN c_acctbal < 0 THEN 0 ELSE c_acctbal END AS b, greatest(c_custkey, 100) AS g FROM customer")
def fn_conditional(spark, folder):
    return load(spark, folder, "customer").select("c_custkey", F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("none")).alias("s"), F.when(F.col("c_acctbal") < 0, 0.0).otherwise(F.col("c_acctbal")).alias("b"), F.greatest("c_custkey", F.lit(100)).alias("g"))


@query("fn_hash", "SELECT o_orderkey, md5(CAST(o_orderkey AS VARCHAR)) AS m, sha256(o_orderpriority) AS s FROM orders")
def fn_hash(spark, folder):
    """Digests."""
    return load(spark, folder, "orders").select("o_orderkey", F.md5(F.col("o_orderkey").cast("string").cast("binary")).alias("m"), F.sha2("o_orderpriority", 256).alias("s"))


@query("fn_xxhash")
def fn_xxhash(spark, folder):
    """The hash that placement and ties use."""
    return load(spark, folder, "orders").select("o_orderkey", F.xxhash64("o_orderkey").alias("x"))


# --- sources, sinks, SQL surface ---


@query("source_round_trip", "SELECT f.fmt, r_regionkey, r_name FROM region, (VALUES ('csv'), ('json'), ('orc'), ('parquet')) AS f(fmt)")
def source_round_trip(spark, folder):
    """A table written in each format and read back with its schema."""
    regions, out = load(spark, folder, "region").select("r_regionkey", "r_name"), None
    for fmt in ("csv", "json", "orc", "parquet"):
        path = scratch(spark, f"region-{fmt}")
        regions.write.format(fmt).save(path)
        one = tables.read_file(spark, path, fmt, regions.schema).select(F.lit(fmt).alias("fmt"), "r_regionkey", "r_name")
        out = one if out is None else out.unionByName(one)
    return out


@query("sink_by_rank", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem WHERE l_extendedprice < 20000")
def sink_by_rank(spark, folder):
    """Rows written by rank; a range of keys reads only the folders that its pivots name."""
    done, path = _uniform(spark, folder), scratch(spark, "by-rank")
    tables.write_sorted(done, path)
    first, last = done.tree.overlapping(None, 20_000.0)
    return tables.read_sorted(spark, path).where(F.col("rank").between(first, last) & (F.col("l_extendedprice") < 20_000)).select(*fx.UNIFORM.columns)


@query("sql_segment_of", f"{sql.chain(fx.UNIFORM.base(), P)} SELECT CAST(s AS INTEGER) AS segment, count(*) AS n FROM {sql.last(P)} GROUP BY s")
def sql_segment_of(spark, folder):
    """The registered function, in SQL."""
    rows = fx.UNIFORM.rows(spark, folder)
    surface.register_segment_of(spark, agree(rows, fx.UNIFORM.spec, P), "segment_of_lines")
    rows.createOrReplaceTempView("ranked_lines")
    return surface.sql(spark, "SELECT segment_of_lines(l_extendedprice) AS segment, count(*) AS n FROM ranked_lines GROUP BY 1")


@query(
    "sql_table_functions",
    f"SELECT p, CAST(level AS INTEGER) AS level, count(*) AS ranks, CAST(max(xor(rank, p >> (level + 1)::INTEGER)) AS INTEGER) AS last FROM (SELECT DISTINCT p, d FROM ({sorting.RANKED_SQL})) q, unnest(range(d)) l(level), unnest(range(p)) r(rank) GROUP BY p, level",
)
def sql_table_functions(spark, folder):
    """The schedules of as many ranks as the parts of the line items need."""
    surface.register_table_functions(spark)
    sorting.ranked_parts(spark, folder).createOrReplaceTempView("ranked_parts")
    return surface.sql(spark, "SELECT q.p, s.level, count(*) AS ranks, max(s.partner) AS last FROM (SELECT DISTINCT p FROM ranked_parts) q, LATERAL rank_schedule(q.p) s GROUP BY q.p, s.level")


# --- streams ---


def _event_stream(spark: SparkSession, folder: str, days: bool = False) -> tuple[DataFrame, PivotTree]:
    """The events as files that arrive in order of time, and pivots of their values."""
    rows = fx.SKEWED.rows(spark, folder)
    tree = agree(rows, fx.SKEWED.spec, P)
    path = scratch(spark, "events")
    events = load(spark, folder, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "value")
    events.repartitionByRange(6, "ts").sortWithinPartitions("ts").write.parquet(path)
    return tables.read_stream(spark, path, events.schema, files_per_batch=6), tree


_STREAMED = sql.chain("SELECT value AS k, event_id % 8 AS r, ts FROM events", P)


@query("stream_route", f"{_STREAMED} SELECT CAST(s AS INTEGER) AS segment, count(*) AS n FROM {sql.last(P)} GROUP BY s")
def stream_route(spark, folder):
    """A stream on frozen pivots; what it routed, counted."""
    stream, tree = _event_stream(spark, folder)
    routed = routing.route_stream(stream, fx.SKEWED.spec, tree)
    done = routing.run_to_end(routed.select(F.col(SEGMENT).alias("segment")), f"routed_{uuid.uuid4().hex}", scratch(spark, "routed"))
    return done.groupBy("segment").agg(F.count("*").alias("n"))


@query("stream_windows", f"{_STREAMED} SELECT CAST(epoch_us(date_trunc('hour', ts)) // 1000000 AS BIGINT) AS opens, CAST(s AS INTEGER) AS segment, count(*) AS n FROM {sql.last(P)} GROUP BY ALL")
def stream_windows(spark, folder):
    """Rows a segment and hour, from a stream run to its end."""
    stream, tree = _event_stream(spark, folder)
    load_of = routing.segment_load(routing.route_stream(stream, fx.SKEWED.spec, tree), "ts", late="40 days")
    flat = load_of.select(F.unix_seconds("window.start").alias("opens"), "segment", "n")
    return routing.run_to_end(flat, f"windows_{uuid.uuid4().hex}", scratch(spark, "windows"), "complete")


@query("stream_runs", sql.by_position("events", "event_id, value", "value, event_id"))
def stream_runs(spark, folder):
    """Sorted runs of micro-batches, compacted into one order."""
    stream, tree = _event_stream(spark, folder)
    path = scratch(spark, "runs")
    routing.run_sink(stream, fx.SKEWED.spec, tree, path, scratch(spark, "runs-state")).awaitTermination()
    merged = routing.compact_runs(spark, path, fx.SKEWED.spec, tree)
    return positions(merged, merged, fx.SKEWED.spec).select("event_id", "value", F.col(POSITION).alias("pos"))


def _micros(column: str) -> str:
    return f"epoch_us({column})"


@query(
    "stream_sliding",
    f"""{_STREAMED}, w AS (SELECT unnest([epoch_us(ts) // 1800000000 * 1800, epoch_us(ts) // 1800000000 * 1800 - 1800]) AS opens, s FROM {sql.last(P)})
    SELECT CAST(opens AS BIGINT) AS opens, CAST(s AS INTEGER) AS segment, count(*) AS n FROM w GROUP BY ALL""",
)
def stream_sliding(spark, folder):
    """Rows a segment in windows of an hour that open every half hour."""
    stream, tree = _event_stream(spark, folder)
    load_of = routing.segment_load(routing.route_stream(stream, fx.SKEWED.spec, tree), "ts", width="1 hour", slide="30 minutes", late="40 days")
    flat = load_of.select(F.unix_seconds("window.start").alias("opens"), "segment", "n")
    return routing.run_to_end(flat, f"sliding_{uuid.uuid4().hex}", scratch(spark, "sliding"), "complete")


@query(
    "stream_sessions",
    f"""{_STREAMED}, o AS (SELECT s, {_micros('ts')} AS t, CASE WHEN {_micros('ts')} - lag({_micros('ts')}) OVER w < 600000000 THEN 0 ELSE 1 END AS fresh FROM {sql.last(P)} WINDOW w AS (PARTITION BY s ORDER BY ts)),
    g AS (SELECT s, t, sum(fresh) OVER (PARTITION BY s ORDER BY t ROWS UNBOUNDED PRECEDING) AS k FROM o) SELECT CAST(s AS INTEGER) AS segment, CAST(min(t) AS BIGINT) AS opens, count(*) AS n FROM g GROUP BY s, k""",
)
def stream_sessions(spark, folder):
    """Rows a segment in sessions that end after ten minutes without any."""
    stream, tree = _event_stream(spark, folder)
    load_of = routing.segment_load(routing.route_stream(stream, fx.SKEWED.spec, tree), "ts", gap="10 minutes", late="40 days")
    flat = load_of.select("segment", F.unix_micros("window.start").alias("opens"), "n")
    return routing.run_to_end(flat, f"sessions_{uuid.uuid4().hex}", scratch(spark, "sessions"), "complete")


_BATCHES = "SELECT event_id, user_id, value, ts, CASE event_id % 10 WHEN 0 THEN 2 WHEN 9 THEN 1 ELSE 0 END AS batch FROM events"


def _late_stream(spark: SparkSession, folder: str) -> DataFrame:
    """The events in three batches: most, then every tenth, and then another tenth, which is late by then.

    A batch's late rows are told by the watermark that stood before the batch before it.
    """
    path, events = scratch(spark, "late"), load(spark, folder, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "value")
    for some in ("event_id % 10 between 1 and 8", "event_id % 10 = 9", "event_id % 10 = 0"):
        events.where(some).coalesce(1).write.mode("append").parquet(path)
    return tables.read_stream(spark, path, events.schema)


@query(
    "stream_late_rows",
    f"""WITH b AS ({_BATCHES}), m AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM b WHERE batch = 0)
    SELECT CAST(epoch_us(date_trunc('day', ts)) // 1000000 AS BIGINT) AS opens, count(*) AS n FROM b, m WHERE batch < 2 OR date_trunc('day', ts) + INTERVAL 1 DAY > mark GROUP BY ALL""",
)
def stream_late_rows(spark, folder):
    """Rows a day, where those of days that the watermark has closed are dropped."""
    daily = _late_stream(spark, folder).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("window")).agg(F.count("*").alias("n"))
    done = routing.run_to_end(daily.select(F.unix_seconds("window.start").alias("opens"), "n"), f"late_{uuid.uuid4().hex}", scratch(spark, "late-state"), "update")
    return done.groupBy("opens").agg(F.max("n").alias("n"))


@query("stream_dedup", "SELECT user_id, min(event_id) AS event_id FROM events GROUP BY user_id")
def stream_dedup(spark, folder):
    """One row of each user, where all lie within the lateness; rows carry the user's least event."""
    events = load(spark, folder, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id")
    path = scratch(spark, "dedup")
    first = events.withColumn("event_id", F.min("event_id").over(Window.partitionBy("user_id")))
    first.write.parquet(path)
    stream = tables.read_stream(spark, path, first.schema, files_per_batch=2)
    return routing.run_to_end(routing.deduplicate(stream, ["user_id"], "ts", "400 days").select("user_id", "event_id"), f"dedup_{uuid.uuid4().hex}", scratch(spark, "dedup-state"))


@query("stream_drift", f"{_STREAMED}, z AS (SELECT s, count(*) AS n FROM {sql.last(P)} GROUP BY s) SELECT CAST(sum(n) AS BIGINT) AS rows, max(n) * {P}::DOUBLE / sum(n) AS worst, max(n) * {P}::DOUBLE / sum(n) > 2 AS repivot FROM z")
def stream_drift(spark, folder):
    """How far the fullest segment is beyond the mean when all has arrived."""
    stream, tree = _event_stream(spark, folder)
    watched = routing.drift(routing.route_stream(stream, fx.SKEWED.spec, tree), P)
    done = routing.run_to_end(watched, f"drift_{uuid.uuid4().hex}", scratch(spark, "drift"))
    return done.orderBy(F.desc("rows")).limit(1)
