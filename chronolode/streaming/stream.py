"""Sequences as streams: windowed utilities with watermarks, sessions, deduplication, and a stateful matcher of a fixed episode."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from chronolode.functions.model import Episode
from chronolode.plans.miner import mine_top_k
from chronolode.plans.storage import folder
from chronolode.sources.ces import calendar_clock, cents, simultaneous

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def source(spark: SparkSession, path: str, delay: str = "1 hour", files_per_batch: int = 1000) -> DataFrame:
    """Events of a folder of Parquet files, or of one file given as a pattern, with a watermark on `at`."""
    rows = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return rows.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", delay)


def deduplicated(events: DataFrame) -> DataFrame:
    """First arrivals of each event id within the watermark."""
    return events.dropDuplicatesWithinWatermark(["event_id"])


def tumbling_utility(events: DataFrame, size: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(start, item, u): summed cents of each event type and window; rows behind the watermark are dropped."""
    w = F.window("at", size, slide) if slide else F.window("at", size)
    rows = events.withColumn("u", cents(F.col("value"))).filter("u > 0")
    return rows.groupBy(w.alias("w"), F.col("event_type").alias("item")).agg(F.sum("u").alias("u")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "item", "u")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, n, u) of each user's sessions."""
    rows = events.withColumn("u", cents(F.col("value")))
    return rows.groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum("u").alias("u")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n", "u")


def weighted(events: DataFrame, dim: DataFrame, key: str, external: str) -> DataFrame:
    """A stream with unit values from a static table."""
    return events.join(dim, key).withColumn("u", cents(F.col("value") * F.col(external)))


STATE = T.StructType([T.StructField("t", T.ArrayType(T.LongType())), T.StructField("item", T.ArrayType(T.StringType())), T.StructField("u", T.ArrayType(T.LongType())), T.StructField("last_start", T.LongType())])
OCCURRENCE = T.StructType([T.StructField("user_id", T.LongType()), T.StructField("ts", T.LongType()), T.StructField("te", T.LongType()), T.StructField("u", T.LongType())])


def latest_fit(sets: dict[int, dict[str, int]], episode: Episode, end: int, width: int) -> tuple[int, int] | None:
    """(ts, u) of the latest start of an occurrence that ends at `end`; u of the earliest fit from that start."""
    if not all(x in sets[end] for x in episode[-1]):
        return None
    at, times = end, sorted(t for t in sets if end - width <= t < end)
    for wanted in reversed(episode[:-1]):
        while times and not all(x in sets[times[-1]] for x in wanted):
            times.pop()
        if not times:
            return None
        at = times.pop()
    u, i, order = 0, 0, sorted(t for t in sets if at <= t <= end)
    for n, wanted in enumerate(episode):
        while not all(x in sets[order[i]] for x in wanted):
            i += 1
        t = end if n == len(episode) - 1 else order[i]
        u += sum(sets[t][x] for x in wanted)
        i += 1
    return at, u


def matcher(episode: Episode, width: int) -> Callable:
    """A stateful function over (user_id, t, item, u): minimal occurrences, as soon as their last time is in. A batch holds whole times of a user, later than those before it."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:  # noqa: ANN001
        old_t, old_i, old_u, last = state.get if state.exists else ([], [], [], -1)
        rows = pd.concat([pd.DataFrame({"t": list(old_t), "item": list(old_i), "u": list(old_u)}), *[b[["t", "item", "u"]] for b in batches]])
        known, sets, out = set(old_t), {}, []
        for t, item, u in rows.sort_values("t").itertuples(index=False):
            at = sets.setdefault(int(t), {})
            at[item] = at.get(item, 0) + int(u)
        for t in [x for x in sorted(sets) if x not in known]:
            found = latest_fit(sets, episode, t, width)
            if found and found[0] > last:
                last = found[0]
                out.append((key[0], found[0], t, found[1]))
        newest = max(sets)
        kept = [(t, i, u) for t, s in sets.items() if t >= newest - width for i, u in s.items()]
        state.update(([x[0] for x in kept], [x[1] for x in kept], [x[2] for x in kept], last))
        yield pd.DataFrame(out, columns=["user_id", "ts", "te", "u"])

    return step


def matches(events: DataFrame, episode: Episode, width: int, unit: str = "minute") -> DataFrame:
    """(user_id, ts, te, u) of an episode's minimal occurrences in each user's events."""
    rows = events.select("user_id", calendar_clock(F.col("ts"), unit).alias("t"), F.col("event_type").alias("item"), cents(F.col("value")).alias("u")).filter("u > 0")
    return rows.groupBy("user_id").applyInPandasWithState(matcher(episode, width), OCCURRENCE, STATE, "append", "NoTimeout")


def mine_batches(events: DataFrame, mine: Callable[[DataFrame, int], None], trigger: dict | None = None):  # noqa: ANN201
    """Runs a miner on each micro-batch; thresholds are not carried over, as utilities of a moved window may fall."""
    return events.writeStream.foreachBatch(mine).trigger(**(trigger or {"availableNow": True})).start()


def drained(df: DataFrame, mode: str, progress: list | None = None) -> DataFrame:
    """Runs a finite stream to its end into files of the shared folder, and gives their rows: of all batches, or of the last one in complete mode. A batch that is run again replaces its own files.

    progress: takes the stream's progress reports."""
    spark, path, done = df.sparkSession, folder(df.sparkSession), []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        done.append(f"{path}/{number}")

    q = df.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    if progress is not None:
        progress.extend(q.recentProgress)
    if not done:
        return spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(*(done[-1:] if mode == "complete" else dict.fromkeys(done)))


def late_rows(progress: list) -> int:
    """Rows that stateful steps dropped as they came behind the watermark."""
    return sum(step["numRowsDroppedByWatermark"] for report in progress for step in report["stateOperators"])


def remined(events: DataFrame, mtd: int, k: int, unit: str = "hour") -> DataFrame:
    """(batch, episode, utility, frequency, rank): the best of every micro-batch, mined anew."""
    spark, path, done = events.sparkSession, folder(events.sparkSession), []

    def mine(batch: DataFrame, number: int) -> None:
        rows = batch.select(calendar_clock(F.col("ts"), unit).alias("t"), F.col("event_type").alias("item"), cents(F.col("value")).alias("u"))
        best = mine_top_k(simultaneous(rows), mtd, k).df.select(F.lit(number).cast("long").alias("batch"), "episode", "utility", "frequency", "rank")
        best.write.mode("overwrite").parquet(f"{path}/{number}")
        done.append(f"{path}/{number}")

    mine_batches(events, mine).awaitTermination()
    if not done:
        return spark.createDataFrame([], "batch long, episode string, utility long, frequency long, rank int")
    return spark.read.parquet(*dict.fromkeys(done))
