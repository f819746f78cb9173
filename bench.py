"""Headline runs of the miner on the stand-ins of the paper's four sequences. Prints one line of JSON.

A cell is one run of a compared method for one k at a duration of 2, with the published strategies only (`full_ours` adds our raise by whole windows). A run that takes longer than BENCH_LIMIT_S is cancelled and has no result,
as in the paper; so have the method's larger k on that sequence. Cells that the whole budget, BENCH_BUDGET_S, does not reach are listed as not run. Besides seconds each cell carries candidates, thresholds, peak heap and
shuffled and spilled bytes; candidates and thresholds compare with the published ones in direction, not in value.
The numbers of candidates come from groups of roots of a fixed size, so they do not depend on the machine."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

LIMIT_S, BUDGET_S = float(os.environ.get("BENCH_LIMIT_S", "90")), float(os.environ.get("BENCH_BUDGET_S", "480"))
METHODS = ("full", "no_event_raise", "raw_bound", "prior_top_k")
SPARSE, FEW, MANY = (5, 10, 15, 20, 25, 30), (1, 3, 5, 7, 9, 11), (500, 1000, 1500, 2000, 2500, 3000)


def session(cpus: int):  # noqa: ANN201
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.driver.memory", "12g")
        .config("spark.sql.shuffle.partitions", str(cpus))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.checkpoint.dir", f"file://{tempfile.mkdtemp(prefix='bench-')}")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    began, sf = time.perf_counter(), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = session(int(os.environ.get("BENCH_CPUS", "8")))
    from chronolode.plans import metrics
    from chronolode.plans.baselines import variant
    from chronolode.plans.miner import mine_threshold
    from chronolode.plans.storage import written
    from chronolode.sources import ces

    makers = {"orders": (lambda s, d: ces.first_n(ces.order_parts(s, d), 4141), MANY), "retail": (ces.retail, SPARSE), "suppliers": (ces.dense_suppliers, SPARSE), "chain": (ces.chain, FEW)}  # orders: as many transactions as the smallest published set
    made, queries, details, ended = {}, {}, {}, {}

    def sequence(name: str):  # noqa: ANN202
        if name not in made:
            at = time.perf_counter()
            made[name] = written(makers[name][0](spark, sf))
            queries[f"build_{name}"] = round(time.perf_counter() - at, 3)
        return made[name]

    def cell(key: str, group: str, name: str, method: str, mtd: int, k: int, **more) -> None:  # noqa: ANN003
        if (mtd, k) >= ended.get(group, (mtd + 1,)):
            details[key] = {"result": f"no result: a smaller setting took over {LIMIT_S:.0f} s"}
            return
        if time.perf_counter() - began > BUDGET_S:
            details[key] = {"result": "not run: the budget of the bench was used up"}
            return
        rows, stage = sequence(name), metrics.stage_costs(spark)["last"]
        metrics.reset_memory(spark)
        took, r = metrics.timed(lambda: variant(method, rows, mtd, k, prepared=True, **more), LIMIT_S)
        costs, peak = metrics.stage_costs(spark, stage), metrics.memory(spark)
        queries[key] = round(took, 3)
        spent = {"jvm_peak_mb": peak["jvm_peak_mb"], "shuffle_mb": costs["shuffle_bytes"] >> 20, "spill_mb": costs["spill_bytes"] >> 20, "cpu_s": costs["cpu_ms"] // 1000}
        if r is None:
            ended[group] = min(ended.get(group, (mtd, k)), (mtd, k))
            details[key] = {"result": f"no result within {LIMIT_S:.0f} s", **spent}
        else:
            details[key] = {**r.candidates, "initial": r.initial_min_util, "end": r.end_min_util, "waves": r.waves, "levels": r.levels, "complete": r.complete, **spent}
        print(key, queries[key], details[key], file=sys.stderr, flush=True)

    variant("full", ces.example(spark), 2, 4)  # starts the workers
    order = [0, 5, 2, 1, 3, 4]  # the ends of each row of k first
    for name, method in [("orders", m) for m in METHODS]:
        for i in (0, 5):
            cell(f"{name}_{method}_k{MANY[i]}", f"{name} {method}", name, method, 2, MANY[i])
    cell("orders_full_ours_k500", "ours", "orders", "full", 2, 500, window_raise=True)
    cell("orders_full_levelwise_k500", "levels", "orders", "full", 2, 500, strategy="levelwise")
    for first in "IS":
        cell(f"orders_full_{first}_first_single_k500", f"single {first}", "orders", "full", 2, 500, strategy="dfs_single", first=first)
    for mtd in (2, 3, 4, 5, 6):
        for method in ("full", "prior_top_k"):
            cell(f"orders_{method}_k1000_mtd{mtd}", f"mtd {method}", "orders", method, mtd, 1000)
    for place in order:
        for name in ("retail", "suppliers", "chain", "orders"):
            for method in METHODS:
                if f"{name}_{method}_k{makers[name][1][place]}" not in details:
                    k = makers[name][1][place]
                    cell(f"{name}_{method}_k{k}", f"{name} {method}", name, method, 2, k)
    hours = written(ces.event_hours(spark, sf))
    for percent in (10, 25, 45):
        for bound in ("remaining", "raw"):
            at, key = time.perf_counter(), f"hours_threshold_{bound}_{percent}pct"
            details[key] = {"episodes": mine_threshold(hours, 1, min_util_ratio=percent / 100, bound=bound).count()}
            queries[key] = round(time.perf_counter() - at, 3)
    print(json.dumps({"metric": "seconds of all mining runs", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": sf, "details": details}))


if __name__ == "__main__":
    main()
