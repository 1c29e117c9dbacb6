"""Times the headline queries and prints one JSON line.

BENCH_SF_DIR names the tables' folder, BENCH_CPUS the local threads.  Each query runs once to warm up and
then BENCH_REPS times (3 by default); the best time counts, as in the published protocol.
"""

from __future__ import annotations

import json
import os
import sys
import tempfile

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = os.pathsep.join(x for x in (ROOT, os.environ.get("PYTHONPATH")) if x)

FOLDER = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
REPETITIONS = int(os.environ.get("BENCH_REPS", "3"))
MANY = 128


def main() -> None:
    from pyspark.sql import SparkSession

    from ranksort import catalog, ledger
    from ranksort.catalog import fixtures as fx
    from ranksort.plans import variants as v

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench")
        .config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g")).config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="bench-")).getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    rows = fx.UNIFORM.rows(spark, FOLDER).cache()
    n = rows.count()
    p = int(os.environ.get("BENCH_RANKS", "8"))

    sorts = {
        "local_sort": lambda: v.local_sort(rows, fx.UNIFORM.spec).rows,
        "native_sort": lambda: v.native_sort(rows, fx.UNIFORM.spec, p),
        "exchange_quicksort": lambda: v.exchange_quicksort(rows, fx.UNIFORM.spec, p).rows,
        "exchange_sort_first": lambda: v.exchange_sort_first(rows, fx.UNIFORM.spec, p).rows,
        "exchange_free_quicksort": lambda: v.exchange_free_quicksort(rows, fx.UNIFORM.spec, p).rows,
        "exchange_free_on_sample": lambda: v.exchange_free_quicksort(rows, fx.UNIFORM.spec, p, plan="sample", n=n).rows,
        "exchange_free_sketch": lambda: v.exchange_free_quicksort(rows, fx.UNIFORM.spec, p, plan="sketch").rows,
        "exchange_free_sort_first": lambda: v.exchange_free_sort_first(rows, fx.UNIFORM.spec, p).rows,
        "combined_quicksort": lambda: v.combined_quicksort(rows, fx.UNIFORM.spec, p, n=n).rows,
        "combined_sort_first": lambda: v.combined_sort_first(rows, fx.UNIFORM.spec, p, n=n).rows,
        "sample_sort": lambda: v.sample_sort(rows, fx.UNIFORM.spec, p, n=n).rows,
    }
    # so many ranks that the combined variants exchange first: two levels at 600 000 rows
    many = fx.UNIFORM.rows(spark, FOLDER, MANY).cache()
    many.count()
    sorts |= {
        f"exchange_quicksort_{MANY}": lambda: v.exchange_quicksort(many, fx.UNIFORM.spec, MANY).rows,
        f"exchange_free_quicksort_{MANY}": lambda: v.exchange_free_quicksort(many, fx.UNIFORM.spec, MANY).rows,
        f"combined_quicksort_{MANY}": lambda: v.combined_quicksort(many, fx.UNIFORM.spec, MANY, n=n).rows,
        f"combined_fused_{MANY}": lambda: v.combined_quicksort(many, fx.UNIFORM.spec, MANY, n=n, fused=True).rows,
    }
    found: dict[str, float] = {}
    for name, make in sorts.items():
        found[name] = round(ledger.best_of(lambda make=make: ledger.execute(make()), REPETITIONS, 1).best, 4)
    for name in ("sort_m4", "rank_histogram", "count_matrix", "top_k", "exact_quantiles", "join_coranked", "join_range", "join_asof", "agg_basic", "dedup_sorted", "stream_route"):
        found[name] = round(ledger.best_of(lambda name=name: ledger.execute(catalog.QUERIES[name](spark, FOLDER)), REPETITIONS, 1).best, 4)
    ratios = {
        "exchange_over_exchange_free": ledger.relative_factor(found["exchange_quicksort"], found["exchange_free_quicksort"]),
        "exchange_over_exchange_free_sort_first": ledger.relative_factor(found["exchange_sort_first"], found["exchange_free_sort_first"]),
        "sort_first_over_quicksort": ledger.relative_factor(found["exchange_free_sort_first"], found["exchange_free_quicksort"]),
        "combined_over_better_pure": found[f"combined_quicksort_{MANY}"] / min(found[f"exchange_quicksort_{MANY}"], found[f"exchange_free_quicksort_{MANY}"]),
        "sample_sort_over_native": found["sample_sort"] / found["native_sort"],
        "native_over_exchange_free": found["native_sort"] / found["exchange_free_quicksort"],
        "speedup_exchange_free": ledger.speedup(found["local_sort"], found["exchange_free_quicksort"]),
        "efficiency_exchange_free": ledger.efficiency(found["local_sort"], found["exchange_free_quicksort"], int(CPUS)),
    }
    print(json.dumps({
        "metric": "total of the best times", "value": round(sum(found.values()), 3), "unit": "sec", "queries": found, "sf": FOLDER.rstrip("/").rpartition("sf")[2],
        "rows": n, "ranks": p, "levels_of_combined": v.switch_level(n, MANY), "rows_per_second_exchange_free": round(n / found["exchange_free_quicksort"]), "ratios": {k: round(x, 3) for k, x in ratios.items()},
    }))
    spark.stop()


if __name__ == "__main__":
    main()
