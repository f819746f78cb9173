"""Occurrences of a given episode, its minimal occurrences, utility and frequency."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronolode.functions.model import Episode
from chronolode.operators.windows import build, gap


def set_utility(ces: DataFrame, items: tuple[str, ...]) -> DataFrame:
    """(t, u): times whose set holds all the items, with their summed utility there."""
    return ces.filter(F.col("item").isin(*items)).groupBy("t").agg(F.sum("u").alias("u"), F.count("*").alias("n")).filter(F.col("n") == len(set(items))).select("t", "u")


def occ_set(ces: DataFrame, episode: Episode, mtd: int, span: str = "gap") -> DataFrame:
    """(ts, te, u): every interval, no longer than the duration, that starts with the first set and ends with the last; u of the earliest fit of the sets before the last.

    One equality join a set: times are sent to every start within the duration before them."""
    width = gap(mtd, span)
    now = set_utility(ces, episode[0]).select(F.col("t").alias("ts"), F.col("t").alias("te"), "u")
    for items in episode[1:]:
        # Only the earliest end so far leads on.
        now = now.groupBy("ts").agg(F.min(F.struct("te", "u")).alias("x")).select("ts", F.col("x.te").alias("before"), F.col("x.u").alias("u0"))
        there = set_utility(ces, items).select(F.col("t").alias("te"), "u", F.explode(F.sequence(F.col("t") - width, F.col("t"))).alias("ts"))
        now = now.join(there, "ts").filter(F.col("te") > F.col("before")).select("ts", "te", (F.col("u0") + F.col("u")).alias("u"))
    return now


def minimal(occurrences: DataFrame, minimality: str = "contained", chunk: int = 1 << 16) -> DataFrame:
    """Those intervals that hold no other: by start the earliest end, kept if the next start ends later. A later start never ends earlier, so its neighbour decides.

    Starts are compared inside stretches of `chunk` times; the last of a stretch meets the first of the next one through a table of one row a stretch.
    'both_strict' keeps an interval unless another lies strictly inside at both ends (for study on small data)."""
    first = occurrences.groupBy("ts").agg(F.min(F.struct("te", "u")).alias("x")).select("ts", "x.te", "x.u")
    if minimality == "contained":
        first = first.withColumn("chunk", F.floor(F.col("ts") / chunk))
        heads = first.groupBy("chunk").agg(F.min(F.struct("ts", "te")).alias("head"))
        after = heads.select("chunk", F.lead("head.te").over(W.orderBy("chunk")).alias("after"))  # of stretches, not of starts
        rows = first.join(after, "chunk").withColumn("next", F.coalesce(F.lead("te").over(W.partitionBy("chunk").orderBy("ts")), F.col("after")))
        return rows.filter("next IS NULL OR next > te").select("ts", "te", "u")
    if minimality != "both_strict":
        raise ValueError(f"minimality: {minimality}")
    inner = occurrences.select(F.col("ts").alias("s2"), F.col("te").alias("e2"))
    return occurrences.join(inner, (F.col("s2") > F.col("ts")) & (F.col("e2") < F.col("te")), "left_anti")


def within(occurrences: DataFrame, mtd: int, span: str = "gap") -> DataFrame:
    return occurrences.filter(F.col("te") - F.col("ts") <= gap(mtd, span))


def episode_utility(occurrences: DataFrame, key: str, minimality: str = "contained") -> DataFrame:
    """(episode, utility, frequency)"""
    return minimal(occurrences, minimality).agg(F.coalesce(F.sum("u"), F.lit(0)).cast("long").alias("utility"), F.count("*").alias("frequency")).select(F.lit(key).alias("episode"), "utility", "frequency")


def pair_utilities(ces: DataFrame, mtd: int, kind: str, span: str = "gap") -> DataFrame:
    """(episode, utility, frequency) of all episodes of two events: of one time ('simultaneous'), or of two ('serial')."""
    width = gap(mtd, span)
    from chronolode.functions.model import escaped_column

    name = lambda a, sep, b: F.concat(escaped_column(F.col(a)), F.lit(sep), escaped_column(F.col(b)))
    if kind == "simultaneous":
        other = ces.select("t", F.col("item").alias("item2"), F.col("u").alias("u2"))
        pairs = ces.join(other, "t").filter("item < item2").select(name("item", "+", "item2").alias("episode"), (F.col("u") + F.col("u2")).alias("u"))
        return pairs.groupBy("episode").agg(F.sum("u").cast("long").alias("utility"), F.count("*").alias("frequency"))
    w = build(ces, width).filter("own OR true")
    left = w.filter("t = ts").select("chunk", "own", "ts", F.col("item").alias("a"), F.col("u").alias("u1"))
    right = w.filter("t > ts").select("chunk", "ts", "t", F.col("item").alias("b"), F.col("u").alias("u2"))
    pairs = left.join(right, ["chunk", "ts"]).groupBy("chunk", "own", "a", "b", "ts").agg(F.min(F.struct("t", F.col("u1") + F.col("u2"))).alias("x"))
    nxt = F.lead("x.t").over(W.partitionBy("chunk", "a", "b").orderBy("ts"))
    kept = pairs.withColumn("next", nxt).filter("own AND (next IS NULL OR next > x.t)")
    return kept.groupBy(name("a", ">", "b").alias("episode")).agg(F.sum("x.col2").cast("long").alias("utility"), F.count("*").alias("frequency"))


def parallel(ces: DataFrame, items: tuple[str, ...], mtd: int, span: str = "gap", chunk: int = 1 << 12) -> DataFrame:
    """(ts, te, u): minimal intervals, no longer than the duration, that hold all the items in whatever order; u sums each item's last event up to the end.

    An interval that ends at te starts at the earliest of the items' last times; it is minimal if no earlier end has the same start. Times are cut into stretches with a halo of one duration before them."""
    width = gap(mtd, span)
    rows = ces.filter(F.col("item").isin(*items)).withColumn("chunk", F.explode(F.sequence(F.floor(F.col("t") / chunk), F.floor((F.col("t") + width) / chunk))))
    last = {x: F.max(F.when(F.col("item") == x, F.struct("t", "u"))).over(W.partitionBy("chunk").orderBy("t").rangeBetween(-width, 0)) for x in items}
    rows = rows.select("chunk", "t", *(c.alias(f"last{i}") for i, c in enumerate(last.values()))).distinct()
    every = [F.col(f"last{i}") for i in range(len(items))]
    start = F.least(*(x["t"] for x in every)) if len(items) > 1 else every[0]["t"]
    u = sum((x["u"] for x in every[1:]), every[0]["u"])
    rows = rows.filter(" AND ".join(f"last{i} IS NOT NULL" for i in range(len(items)))).select("chunk", start.alias("ts"), F.col("t").alias("te"), u.alias("u"))
    first = rows.groupBy("chunk", "ts").agg(F.min(F.struct("te", "u")).alias("x")).select("chunk", "ts", "x.te", "x.u")
    return first.filter(F.floor(F.col("te") / chunk) == F.col("chunk")).select("ts", "te", "u")


def gaps(ces: DataFrame, chunk: int = 1 << 16) -> DataFrame:
    """(item, t, gap): times since the item's event before, null for its first. Inside stretches of times by lag; across them through a table of one row for each item and stretch."""
    rows = ces.select("item", "t", F.floor(F.col("t") / chunk).alias("chunk"))
    ends = rows.groupBy("item", "chunk").agg(F.max("t").alias("end"))
    before = ends.select("item", "chunk", F.lag("end").over(W.partitionBy("item").orderBy("chunk")).alias("before"))
    inside = F.lag("t").over(W.partitionBy("item", "chunk").orderBy("t"))
    return rows.join(before, ["item", "chunk"]).select("item", "t", (F.col("t") - F.coalesce(inside, F.col("before"))).alias("gap"))
