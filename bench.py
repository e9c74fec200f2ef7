"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line.

Beside seconds it gives what the published experiments count: rounds, samples
a part, imbalance, rows that move, and the shares of searching and sorting, for
narrowing and for what it is compared with.
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .appName("rangecut-bench")
        .config("spark.sql.shuffle.partitions", str(2 * int(CPUS)))
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from rangecut import workloads
    from rangecut.operators import quantiles, windows
    from rangecut.plans import baselines, exchange, search
    from rangecut.plans.keys import lineitem
    from rangecut.sources.tables import load

    df = load(spark, SF_DIR, "lineitem").repartition(2 * int(CPUS)).persist()
    n, parts, eps = df.count(), 32, 0.02
    spec = lineitem()
    seconds: dict[str, float] = {}
    facts: dict[str, float] = {"rows": n, "parts": parts, "eps": eps}

    def timed(name: str, f):
        began = time.time()
        out = f()
        seconds[name] = round(time.time() - began, 3)
        print(name, seconds[name], file=sys.stderr, flush=True)
        return out

    noop = lambda d: d.write.format("noop").mode("overwrite").save()
    search.budget_rounds(df, spec, 8, 0.1, portable=False)  # starts workers and compiles
    ours = timed("search_narrowing", lambda: search.budget_rounds(df, spec, parts, eps, 5, portable=False))
    rival = timed("search_per_interval", lambda: search.per_interval_rounds(df, spec, parts, eps, 5, portable=False))
    scan = timed("search_greedy_scan", lambda: baselines.greedy_scan(df, spec, parts, eps))
    one = timed("search_one_round", lambda: search.one_round(df, spec, 8, 0.1, portable=False))
    facts |= {
        "narrowing_rounds": ours.rounds, "narrowing_samples_per_part": ours.sample / parts, "per_interval_rounds": rival.rounds, "per_interval_samples_per_part": rival.sample / parts,
        "scan_samples_per_part": scan[1] / parts, "one_round_samples_per_part_8_parts": one.sample / 8,
        "narrowing_rows_counted_share": sum(t[3] for t in ours.trace) / n,
        "narrowing_rank_error_share": max(ours.state.error(i) or 0 for i in range(parts - 1)) / n,
    }
    facts["imbalance"] = exchange.imbalance(exchange.assign_bucket(df, spec, ours.keys), parts)
    timed("exchange_and_sort", lambda: noop(exchange.range_sort(df, spec, parts, eps, ours.keys)))
    timed("platform_sort", lambda: noop(df.orderBy(spec.column(df))))
    staged = timed("two_stage_search", lambda: workloads.two_stage(spark, SF_DIR, 64, 8, 0.02))
    rival_staged = timed("two_stage_per_interval", lambda: workloads.two_stage(spark, SF_DIR, 64, 8, 0.02, "per_interval"))
    facts |= {"two_stage_rounds": sum(staged[1]), "two_stage_rounds_per_interval": sum(rival_staged[1])}
    curve, along = workloads.curve_keys(spark, SF_DIR, "lineitem")
    curve = curve.repartition(2 * int(CPUS)).persist()
    curve.count()
    curved = timed("curve_narrowing", lambda: search.budget_rounds(curve, along, 80, 0.05, 5, portable=False))
    _, halved = timed("curve_value_bisection", lambda: baselines.domain_bisect(curve, "code", 80, 0.05, 0, workloads.CURVE_END - 1))
    facts |= {"curve_narrowing_rounds": curved.rounds, "curve_bisection_rounds": len(halved), "curve_gain_over_bisection": 1 - seconds["curve_narrowing"] / seconds["curve_value_bisection"]}
    curve.unpersist()
    phases = {m: workloads.timed_sort(df, spec, parts, eps, m) for m in ("narrowing", "per interval")}
    for m, found in phases.items():
        facts |= {f"{m.replace(' ', '_')}_{phase}_seconds": found[phase] for phase in ("local_sort", "search", "exchange", "merge", "total")}
    facts["sort_gain_over_per_interval"] = workloads.gain(phases["narrowing"], phases["per interval"])
    facts["warm_start_rounds"] = timed("warm_start", lambda: search.warm_start(df, spec, ours.keys, parts, eps)).rounds
    timed("exact_quantiles", lambda: quantiles.exact_quantiles(df, spec, [0.01, 0.5, 0.99]))
    timed("global_row_number", lambda: noop(windows.row_number(df, spec, 16)))
    facts["top_k_rows"] = timed("top_k", lambda: quantiles.top_k(df, spec, 10_000).agg(F.count("*")).first()[0])
    print(json.dumps({"metric": "splitter search, exchange and operators on them", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": SF_DIR, "facts": {k: round(float(v), 4) for k, v in facts.items()}}))
    spark.stop()


if __name__ == "__main__":
    main()
