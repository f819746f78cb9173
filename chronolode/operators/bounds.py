"""Upper bounds of the utility of every episode that extends a prefix, and the pruning test.

For one occurrence [ts, te] of utility u, with rest the utilities after its last event and all those from te on:
remaining = u + rest (the tightest); no_overlap = u - u(last set) + all from te, which still counts events beside the last one; raw = u + all from te, which counts the last set twice.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronolode.operators.windows import one_episode_table  # noqa: F401  part of this surface

BOUNDS = ("remaining", "no_overlap", "raw", "none")


def per_occurrence(bound: str, u: Column, rest: Column, from_te: Column, last_set: Column) -> Column:
    """The bound of one occurrence."""
    return {"remaining": u + rest, "no_overlap": u - last_set + from_te, "raw": u + from_te, "none": F.lit((1 << 62) // (1 << 20))}[bound]


def promising(bound: Column, min_util: int) -> Column:
    """Whether some extension may still reach the threshold. Only prefixes are pruned: an event of low bound can end a good episode."""
    return bound >= min_util


def remaining(ces: DataFrame) -> DataFrame:
    """(t, item, ru): utilities of the events after this one in its own set."""
    after = W.partitionBy("t").orderBy("item").rowsBetween(1, W.unboundedFollowing)
    return ces.select("t", "item", F.coalesce(F.sum("u").over(after), F.lit(0)).cast("long").alias("ru"))


def gap_of_bounds(table: DataFrame) -> DataFrame:
    """(item, raw_minus_remaining): how much tighter the optimized bound is."""
    return table.select("item", (F.col("raw") - F.col("remaining")).alias("raw_minus_remaining"))
