"""Headline queries on $BENCH_SF_DIR with local[$BENCH_CPUS]: one JSON line.

One warm-up run that doesn't count, then the median of $BENCH_REPEATS runs of each query; the value is the mean of the medians
of the ten-query suite.  ``python bench.py --paths`` also prints the execution paths (SQL and the engine on both sources, a cached
always-on table) over the four window lengths, with costs from what the runs scanned and used, and the stages of the winner query
under coupled and independent plans.
"""

from __future__ import annotations

import json
import os
import sys

from pyspark.sql import SparkSession

from chronofold.plans.measures import MIB, break_even, consume, cost_scan, cost_serverless, frontier, measure, observe, suite_mean

FOLDER = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
REPEATS = int(os.environ.get("BENCH_REPEATS", "5"))
#: Q6's count at sf0.1, and what path costs are reckoned with: parameters, as prices vary.
THRESHOLD = 80
WORKER_GB = 5.0
PRICES = {"gb_second": 1.7e-5, "read": 4e-7, "write": 5e-6, "queue": 4e-7, "commit": 1.25e-6}


def session() -> SparkSession:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def asked(spark: SparkSession, window: str) -> dict:
    """Q1 to Q10 of the deep history and its stored layout."""
    from chronofold.workloads.histories import HISTORIES
    from chronofold.workloads.stored import asked as queries
    from chronofold.workloads.stored import stored

    made = queries("part", spark, FOLDER, HISTORIES["part"].windows[window], THRESHOLD)
    return {f"q{i}": make() for i, make in made.items()}, stored(spark, FOLDER, "part", bucket_groups=1)


def suite_seconds(spark: SparkSession) -> dict[str, float]:
    """Q1 to Q10 through a stored layout."""
    from chronofold.plans.runner import run_fanout

    queries, layout = asked(spark, "w12")
    return {n: round(measure(lambda q=q: consume(run_fanout(q, layout, spark)), 1, REPEATS), 4) for n, q in queries.items()}


def path_points(spark: SparkSession) -> list[dict]:
    """Mean seconds and cost of the ten queries by path and window, with the bytes that the runs scanned."""
    from chronofold.baselines import paths
    from chronofold.plans.runner import run_fanout, run_mono
    from chronofold.sources.folders import scratch
    from chronofold.sources.layout import write_scd2
    from chronofold.workloads import studies
    from chronofold.workloads.histories import HISTORIES

    d = HISTORIES["part"]
    source = scratch(spark)
    write_scd2(d.build(spark, FOLDER), source)
    held = spark.read.parquet(source).drop("from_month").persist()
    held.count()
    points = {}
    for name in ("w1", "w3", "w6", "w12"):
        w = d.windows[name]
        queries, layout = asked(spark, name)
        views = studies.views(spark, FOLDER, source, layout)
        ways = {f"SQL, {tag}": {f"q{i}": lambda run=run, v=v: run(v) for i, run in studies.sql_runs(spark, FOLDER, w).items()} for tag, v in views.items()}
        ways["engine, unclipped"] = {n: lambda q=q: paths.engine_on_scd2(spark, source, q, d.grid) for n, q in queries.items()}
        ways["engine, clipped"] = {n: lambda q=q: run_fanout(q, layout, spark) for n, q in queries.items()}
        ways["always on"] = {n: lambda q=q: run_mono(q, held) for n, q in queries.items()}
        for way, runs in ways.items():
            seconds, usd = [], []
            for run in runs.values():
                seen = observe(spark, lambda run=run: consume(run()))
                seconds.append(measure(lambda run=run: consume(run()), 0, REPEATS))
                usd.append(0.0 if way == "always on" else cost_scan(seen.scanned_bytes, least=0) if way.startswith("SQL") else cost_serverless(seen.usage(WORKER_GB), PRICES))
            points[way, name] = (round(suite_mean(seconds), 4), suite_mean(usd))
    held.unpersist()
    return frontier(points)


def stage_points(spark: SparkSession) -> list[dict]:
    """Where the time of the winner query goes, and what it exchanges: coupled plans against independent pieces."""
    from chronofold.workloads.queries import QUERIES

    return [{"plan": n, "shuffle_mb": round(x.shuffle_bytes / MIB, 3), "shuffle_rows": x.shuffle_rows, "seconds": round(x.seconds, 3)} | x.split for n in ("coupled_winner", "exchanged_winner", "independent_winner") for x in [observe(spark, lambda n=n: consume(QUERIES[n](spark, FOLDER)))]]


def main() -> None:
    spark = session()
    seconds = suite_seconds(spark)
    out = {"metric": "mean of the medians of the ten-query suite, 12-month window, clipped layout", "value": round(suite_mean(list(seconds.values())), 4), "unit": "sec", "queries": seconds, "sf": os.path.basename(FOLDER.rstrip("/")).removeprefix("sf")}
    if "--paths" in sys.argv:
        points = path_points(spark)
        for p in points + stage_points(spark):
            print(json.dumps(p), file=sys.stderr)
        engine = next(p["usd"] for p in points if (p["path"], p["window"]) == ("engine, clipped", "w12"))
        print(json.dumps({"break_even_queries_per_hour": break_even(201.0, engine)}), file=sys.stderr)
    print(json.dumps(out))


if __name__ == "__main__":
    main()
