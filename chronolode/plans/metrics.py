"""Cost and accuracy measures of runs."""

from __future__ import annotations

import resource
import time
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from contextvars import copy_context

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode.plans.baselines import variant
from chronolode.plans.miner import Result, Shared, few_windows, limited


def candidates(r: Result) -> dict[str, int]:
    """generated: utility and bound computed; promising: bound at the threshold at least; buffered: entered the best k."""
    return dict(r.candidates)


def thresholds(r: Result) -> tuple[int, int]:
    return r.initial_min_util, r.end_min_util


def raise_gain(r: Result) -> float:
    """Initial over end threshold: 1 where the first scan found it."""
    return r.initial_min_util / r.end_min_util if r.end_min_util else 1.0


def timed(run: Callable[[], Result], limit_s: float = 10_000) -> tuple[float, Result | None]:
    """Seconds, and the result, None where there is none: the run's jobs are cancelled at the limit, or memory ran out."""
    began, out = time.perf_counter(), None
    spark = SparkSession.getActiveSession()
    try:
        with limited(spark, limit_s if spark else None) as limit:
            out = run()
    except MemoryError:
        out = None
    took = time.perf_counter() - began
    return took, None if limit["stopped"] or took > limit_s else out


def _pools(spark: SparkSession) -> list:
    return [x for x in spark.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans() if x.getType().toString() == "Heap memory"]


def reset_memory(spark: SparkSession) -> None:
    """Peaks of this JVM's heap count from now on. With a local master that is the executor's heap too."""
    for pool in _pools(spark):
        pool.resetPeakUsage()


def memory(spark: SparkSession) -> dict[str, int]:
    """Peaks in MB: of this process, of this JVM's heap since `reset_memory`, and the largest heap that an executor has reported; and the JVM's heap in use."""
    runtime = spark.sparkContext._jvm.java.lang.Runtime.getRuntime()
    peaks = [x.peakMemoryMetrics().get().getMetricValue("JVMHeapMemory") for x in _items(spark.sparkContext._jsc.sc().statusStore().executorList(False)) if x.peakMemoryMetrics().isDefined()]
    return {
        "driver_peak_mb": resource.getrusage(resource.RUSAGE_SELF).ru_maxrss // 1024,
        "jvm_used_mb": (runtime.totalMemory() - runtime.freeMemory()) >> 20,
        "jvm_peak_mb": sum(x.getPeakUsage().getUsed() for x in _pools(spark)) >> 20,
        "executor_peak_mb": max(peaks, default=0) >> 20,
    }


def _items(seq) -> list:  # noqa: ANN001
    return [seq.apply(i) for i in range(seq.size())]


def stage_costs(spark: SparkSession, after: int = -1) -> dict[str, int]:
    """Sums over finished stages with a number above `after`: shuffled and spilled bytes, CPU milliseconds of tasks; and the last stage's number."""
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway
    stages = _items(spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList()))
    new = [x for x in stages if x.stageId() > after]
    return {
        "stages": len(new),
        "shuffle_bytes": sum(x.shuffleWriteBytes() for x in new),
        "spill_bytes": sum(x.diskBytesSpilled() for x in new),
        "cpu_ms": sum(x.executorCpuTime() for x in new) // 1_000_000,
        "last": max((x.stageId() for x in stages), default=-1),
    }


def exactness(found: DataFrame, truth: DataFrame) -> dict[str, float]:
    """Recall of the truth's rows (episode, utility), and rows that should not be there."""
    a, b = (x.select("episode", "utility") for x in (found, truth))
    n, missing = b.count(), b.exceptAll(a).count()
    return {"recall": 1 - missing / n if n else 1.0, "wrong": a.exceptAll(b).count()}


def tightness(table: DataFrame, episodes: DataFrame) -> DataFrame:
    """(item, bound_x100): a root's bound over the best utility of its subtree, in hundredths."""
    best = episodes.select(F.regexp_extract("episode", r"^((?:\\.|[^+>\\])*)", 1).alias("item"), "utility").groupBy("item").agg(F.max("utility").alias("best"))
    return table.select("item", F.col("remaining").alias("bound")).join(best, "item").select("item", F.floor(F.col("bound") * 100 / F.col("best")).alias("bound_x100"))


def spark_costs(df: DataFrame) -> dict[str, int]:
    """Exchanges, broadcasts and Python steps of a plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {"exchanges": text.count("Exchange hashpartitioning") + text.count("Exchange rangepartitioning") + text.count("Exchange SinglePartition"), "broadcasts": text.count("BroadcastExchange"), "python": text.count("Python") + text.count("InPandas")}


def sweep(spark: SparkSession, ces: DataFrame, variants: Iterable[str], ks: Iterable[int], mtds: Iterable[int], at_once: int = 1, **more) -> DataFrame:  # noqa: ANN003
    """A row for each variant, k and duration: counters, thresholds, seconds (without the windows of few items and the first thresholds, which runs share). at_once: runs whose jobs share the cores; more than one changes seconds alone."""
    from chronolode.plans.storage import written

    ces, shared, mtds = written(ces), Shared(), list(mtds)

    def run(name: str, k: int, mtd: int) -> tuple:
        r = variant(name, ces, mtd, k, prepared=True, shared=shared, **more)
        return (name, k, mtd, r.initial_min_util, r.end_min_util, r.candidates["generated"], r.candidates["promising"], r.candidates["buffered"], r.peak_frontier_rows, r.complete, r.runtime_s)

    with ThreadPoolExecutor(at_once) as pool:
        results = lambda do, rows: [x.result() for x in [pool.submit(copy_context().run, do, *row) for row in rows]]
        if not more.keys() & {"order", "semantics", "span"} and more.get("strategy") != "levelwise":
            shared.windows = dict(zip(mtds, results(few_windows, [(ces, mtd) for mtd in mtds]), strict=True))
        rows = results(run, [(name, k, mtd) for name in variants for k in ks for mtd in mtds])
    return spark.createDataFrame(rows, "variant string, k int, mtd int, initial_min_util long, end_min_util long, generated long, promising long, buffered long, peak_frontier_rows long, complete boolean, seconds double")
