"""Raising the threshold before and while episodes grow: by events, by transactions, and by the best candidates.

'distinct' is safe: equal sets are one episode and are summed, sets of one event are left to the list of events, and no value is used unless there are k of them.
The printed forms can overshoot: they take each transaction as an episode of its own, and the smallest value of a list shorter than k.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronolode.functions.model import escaped_column

MODES = ("distinct", "printed_sequential", "printed_merged")


def event_list(ces: DataFrame) -> DataFrame:
    """(item, utility, frequency): the utilities of episodes of one event."""
    return ces.groupBy("item").agg(F.sum("u").cast("long").alias("utility"), F.count("*").alias("frequency"))


def transaction_list(ces: DataFrame, mode: str = "distinct", max_len: int | None = None, max_size: int | None = None) -> DataFrame:
    """(set_key, utility, n): in the printed form a row for each time, else one for each different set of two events or more."""
    if mode != "distinct":
        return ces.groupBy(F.col("t").cast("string").alias("set_key")).agg(F.sum("u").cast("long").alias("utility"), F.lit(1).cast("long").alias("n"))
    by_t = ces.groupBy("t").agg(F.array_join(F.array_sort(F.collect_list(escaped_column(F.col("item")))), "+").alias("set_key"), F.sum("u").alias("tu"), F.count("*").alias("events"))
    by_t = by_t.filter(F.col("events") > 1)
    limit = min([x for x in (max_len, max_size) if x is not None], default=None)
    if limit is not None:
        by_t = by_t.filter(F.col("events") <= limit)
    return by_t.groupBy("set_key").agg(F.sum("tu").cast("long").alias("utility"), F.count("*").alias("n"))


def kth(values: DataFrame, k: int, short: str = "zero") -> int:
    """The kth largest of a column utility; of a shorter list 0, or its last value in the printed form."""
    top = [r[0] for r in values.select("utility").orderBy(F.desc("utility")).limit(k).collect()]
    return top[-1] if top and (len(top) == k or short == "last") else 0


def by_event(ces: DataFrame, k: int, short: str = "zero") -> int:
    return kth(event_list(ces), k, short)


def by_transaction(ces: DataFrame, k: int, mode: str = "distinct", short: str = "zero") -> int:
    return kth(transaction_list(ces, mode), k, short)


def initial(ces: DataFrame, k: int, raise_: tuple[str, ...], mode: str = "distinct", max_len: int | None = None, max_size: int | None = None, sets_allowed: bool = True) -> int:
    """The threshold after the first scan."""
    if mode not in MODES:
        raise ValueError(f"raise_mode: {mode}")
    lists = []
    if "event" in raise_:
        lists.append(event_list(ces).select("utility"))
    if "transaction" in raise_ and sets_allowed:
        lists.append(transaction_list(ces, mode, max_len, max_size).select("utility"))
    if not lists:
        return 0
    if mode == "printed_sequential":
        return max(kth(x, k, "last") for x in lists)
    merged = lists[0] if len(lists) == 1 else lists[0].union(lists[1])
    return kth(merged, k, "zero" if mode == "distinct" else "last")


def by_window(index: DataFrame, k: int) -> int:
    """A safe threshold from whole windows (arrays of the window index): all events of a window, with at most one left out, are an episode whose one occurrence there is minimal,
    since it needs every time of the window. Equal episodes of several windows count once, with the largest value; 0 unless there are k. Ours; not among the printed strategies."""
    alone = ~(F.coalesce(F.get("t", F.col("p") - 2) == F.get("t", F.col("p") - 1), F.lit(False)) | F.coalesce(F.get("t", F.col("p")) == F.get("t", F.col("p") - 1), F.lit(False)))
    rows = index.select("ts", "t", "u", (F.col("u")[0] + F.col("rest")[0]).alias("total"), F.explode(F.sequence(F.lit(0), F.size("t"))).alias("p"))
    rows = rows.filter((F.col("p") == 0) | ~alone).select("ts", "p", (F.col("total") - F.coalesce(F.get("u", F.col("p") - 1), F.lit(0))).alias("value"))
    best = rows.orderBy(F.desc("value"), "ts", "p").limit(4 * k)
    name = F.array_join(F.transform(F.filter(F.sequence(F.lit(1), F.size("t")), lambda x: x != F.col("p")), lambda x: F.concat(F.element_at("items", x), F.lit("@"), F.size(F.array_distinct(F.filter("t", lambda y: y <= F.element_at("t", x)))).cast("string"))), "+")
    named = best.join(index.select("ts", "t", "items"), "ts").groupBy(name.alias("name")).agg(F.max("value").alias("utility"))
    return kth(named, k)


def by_candidate(best: dict[str, tuple], k: int, min_util: int, distinct: bool = True) -> int:
    """The threshold after new episodes entered the best ones so far (key to a row whose first field is the utility)."""
    if len(best) < k:
        return min_util
    return max(min_util, sorted((row[0] for row in best.values()), reverse=True)[k - 1])
