"""Level-wise growth: all episodes of one more event in one plan, pruned by one threshold.

The frontier has a row for each episode and start: (chunk, own, ep, width, ts, ends), ends sorted by time, each with te, pos, u and what the bound needs. A level is one equality join with the window index,
one grouping by chunk and episode that also decides minimality, and partial sums by episode: only sums leave a chunk. The index and the frontiers are tables bucketed by chunk (`by_chunk`), so that neither the join
nor the grouping moves a row.
"""

from __future__ import annotations

import threading
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronolode.functions.model import escaped_column
from chronolode.operators.bounds import per_occurrence
from chronolode.plans.storage import folder

KEYS = ["chunk", "ts"]


def _end(windows: DataFrame, te: str, pos: str, u, last):  # noqa: ANN001, ANN202
    fields = [F.col(te).alias("te"), F.col(pos).alias("pos"), u.alias("u"), last.alias("last"), F.col("rest").alias("rest")]
    return F.struct(*fields, *([F.col("from_t").alias("from_t")] if "from_t" in windows.columns else []))


#: Lets a join on chunk and time use tables that are bucketed by chunk alone.
CO_PARTITION = "spark.sql.requireAllClusterKeysForCoPartition"


#: The session's setting before, once for each run that is in `by_chunk`: the last one to leave puts it back.
_BEFORE: list[str] = []
_LOCK = threading.Lock()


@contextmanager
def by_chunk(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """A function that stores rows bucketed by chunk in the shared folder and reads them back. The tables leave the catalog at the end; their files stay for readers of results."""
    names, n = [], int(spark.conf.get("spark.sql.shuffle.partitions"))

    def store(df: DataFrame) -> DataFrame:
        name = f"by_chunk_{uuid.uuid4().hex}"
        df.write.bucketBy(n, "chunk").sortBy("chunk", "ts").option("path", folder(spark)).saveAsTable(name)
        names.append(name)
        return spark.table(name)

    with _LOCK:
        if not _BEFORE:
            before = spark.conf.get(CO_PARTITION)
            spark.conf.set(CO_PARTITION, "false")
        _BEFORE.append(_BEFORE[0] if _BEFORE else before)
    try:
        yield store
    finally:
        with _LOCK:
            before = _BEFORE.pop()
            if not _BEFORE:
                spark.conf.set(CO_PARTITION, before)
        for name in names:
            spark.sql(f"DROP TABLE IF EXISTS {name}")


def set_count(ep: str) -> Column:
    """The number of sets of an episode's key."""
    return F.size(F.split(F.regexp_replace(ep, r"\\.", "x"), ">"))


def is_complex(ep: str) -> Column:
    """Whether an episode has several sets, one of them of several events."""
    plain = F.regexp_replace(ep, r"\\.", "x")
    return plain.contains(">") & plain.contains("+")


def roots(windows: DataFrame, only: DataFrame | None = None) -> DataFrame:
    """The frontier of episodes of one event, of all items or those of `only`."""
    rows = windows.filter("t = ts")
    rows = rows if only is None else rows.join(only, "item", "left_semi")
    return rows.select("chunk", "own", escaped_column(F.col("item")).alias("ep"), F.lit(1).alias("width"), "ts", F.array(_end(windows, "t", "pos", F.col("u"), F.col("u"))).alias("ends"))


def extend(frontier: DataFrame, windows: DataFrame, kinds: str = "all", max_size: int | None = None, semantics: str = "definition") -> DataFrame:
    """The frontier of all extensions by one event, with minimal starts only."""
    ends = frontier.select("chunk", "own", "ep", "width", "ts", F.posexplode("ends").alias("i", "e"))
    later = windows.select("chunk", "ts", F.col("pos").alias("pos2"), F.col("t").alias("t2"), "item", F.col("u").alias("u2"), "rest", *(["from_t"] if "from_t" in windows.columns else []))
    same = F.col("t2") == F.col("e.te")
    allowed = (F.col("pos2") > F.col("e.pos")) & (same | (F.col("i") == 0))
    if kinds == "serial":
        allowed = allowed & ~same
    if kinds == "simultaneous":
        allowed = allowed & same
    if max_size is not None:
        allowed = allowed & (~same | (F.col("width") < max_size))
    rows = ends.join(later, KEYS).filter(allowed)
    u = F.col("e.u") + F.col("u2")
    last = F.when(same, F.col("e.last") + F.col("u2")).otherwise(F.col("u2"))
    child = rows.select(
        "chunk", "own", F.concat("ep", F.when(same, "+").otherwise(">"), escaped_column(F.col("item"))).alias("ep"),
        F.when(same, F.col("width") + 1).otherwise(1).alias("width"), "ts", _end(windows, "t2", "pos2", u, last).alias("e"),
    )
    child = child.groupBy("chunk", "own", "ep", "width", "ts").agg(F.array_sort(F.collect_list("e")).alias("ends"))  # at most a duration's ends
    first = F.col("ends")[0]["te"]
    child = child.withColumn("next", F.lead(first).over(W.partitionBy("chunk", "ep").orderBy("ts")))
    kept = child.filter(F.col("next").isNull() | (F.col("next") > first)).drop("next")
    return kept if semantics == "definition" else kept.withColumn("ends", F.slice("ends", 1, 1))


def stats(frontier: DataFrame, bound: str) -> DataFrame:
    """(ep, utility, frequency, bound) over own starts."""
    e = F.col("ends")[0]
    from_t = e["from_t"] if bound in ("raw", "no_overlap") else F.lit(0)
    value = per_occurrence(bound, e["u"], e["rest"], from_t, e["last"])
    return frontier.filter("own").groupBy("ep").agg(F.sum(e["u"]).cast("long").alias("utility"), F.count("*").alias("frequency"), F.sum(value).cast("long").alias("bound"))
