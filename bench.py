"""Headline queries on $BENCH_SF_DIR with local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import statistics
import sys
import time

from pyspark.sql import SparkSession

HEADLINE = [
    "linreg_state", "linreg_state_by_flag", "embedding_gram", "gnb_state", "gnb_predict_accuracy", "mnb_predict_lang", "combine_overlap_auto", "month_drill_week",
    "logit_chunk_three_steps", "logit_sgd_chunks", "logit_sgd_scratch", "group_descriptors_chains", "best_plan_cost", "execute_plan_linreg", "execute_plan_gnb",
    "workload_gain_by_coverage", "range_scan", "multi_range_signed_scan", "sliding_week_state", "range_join_points", "tumbling_states",
]


def requests_bench(spark, sf_dir: str) -> dict:
    """Seconds of a request with kept models over 90 % of the points against building from points,
    for each kind, at the published request size (50,000 points) and at that size scaled to the
    table; seconds of a set of requests in one job; and the work done."""
    from spanfold import workloads as W
    from spanfold.registry.planning import _logit, _written
    from spanfold.registry.state import size_of
    from spanfold.sources.layout import lineitem_source
    from spanfold.sources.points import GNB_LINES, LINREG

    n = size_of(lineitem_source(spark, sf_dir))
    out: dict = {}
    for kind, spec in (("linreg", LINREG), ("gnb", GNB_LINES), ("logit", _logit(5_000_000, 10_000))):
        source = _written(spark, sf_dir, spec)
        cost = W.calibrated(source, spec)
        for c in (0, 90):
            engine = W.Engine(spark, cost=cost)
            if spec.kind == "logit":
                W.keep_chunks(engine, source, spec, W.place_models(n, c, W.Sizes("fixed", spec.chunk), 1, unit=1.0, grid=True))
            else:
                W.keep_exact(engine, source, spec, W.place_models(n, c, W.NORMAL, seed=1, unit=1.0))
            got = W.timed(engine, source, spec, W.requests(n, 21, W.NORMAL, seed=2, unit=1.0))
            out |= {f"{kind}_{k}_{c}": got[k] for k in ("speedup",)} | {f"{kind}_{k[2:]}_ms_{c}": 1000 * got[k] for k in ("t_plan", "t_io", "t_merge", "t_total", "t_base")}
            out[f"{kind}_points_share_{c}"] = got["points_read"] / got["base_points"]
    source = _written(spark, sf_dir, LINREG)
    engine = W.engine_at(spark, source, LINREG, n, 90, seed=1)
    out["small_speedup_90"] = W.timed(engine, source, LINREG, W.requests(n, 21, W.NORMAL, seed=2))["speedup"]
    out |= W.timed_many(engine, source, LINREG, W.requests(n, 1000, W.NORMAL, seed=3))
    plans = W.planned(n, [m.range for m in engine.store.models(LINREG)], W.requests(n, 200, W.NORMAL, seed=3))
    r = engine.store.models(LINREG)[0].range
    began = time.perf_counter()
    for _ in range(20):
        engine.fit(source, LINREG, *r)
    return out | {"cost_share_90": plans["best"], "cost_share_90_add_only": plans["add_only"], "covered_request_ms": 50 * (time.perf_counter() - began)}


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "8g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from spanfold.queries import queries

    known, seconds = queries(), {}
    for name in HEADLINE:
        runs = []
        for _ in range(3):
            began = time.perf_counter()
            known[name](spark, sf_dir).collect()  # built anew each time, so nothing finished is used again
            runs.append(time.perf_counter() - began)
        seconds[name] = round(statistics.median(runs[1:]), 4)
        print(name, seconds[name], file=sys.stderr)
    reuse = requests_bench(spark, sf_dir)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf_dir).removeprefix("sf"), "reuse": {k: round(v, 4) for k, v in reuse.items()}}))


if __name__ == "__main__":
    main()
