"""The compared methods as settings of the one miner, and the counters of each."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronolode.plans.miner import ALL, Result, mine_threshold, mine_top_k

#: The prior baseline's internals are not described; it is rebuilt as raw bound with transaction and candidate raising.
VARIANTS = {
    "full": {},
    "no_event_raise": {"raise_": ("transaction", "candidate")},
    "raw_bound": {"bound": "raw"},
    "prior_top_k": {"bound": "raw", "raise_": ("transaction", "candidate")},
}
RAISES = {"none": (), "event": ("event",), "transaction": ("transaction",), "event_transaction": ("event", "transaction"), "all": ALL}


def variant(name: str, ces: DataFrame, mtd: int, k: int, **more) -> Result:  # noqa: ANN003
    """A compared method, with the printed raising strategies only unless window_raise is given."""
    return mine_top_k(ces, mtd, k, **{"window_raise": False, **VARIANTS[name], **more})


def exhaustive(ces: DataFrame, mtd: int, max_len: int | None = None, span: str = "gap") -> DataFrame:
    """Every episode within the duration, with utility and frequency. For checks on small sequences."""
    return mine_threshold(ces, mtd, min_util=0, bound="none", max_len=max_len, span=span)


def top_k_frequent(ces: DataFrame, mtd: int, k: int, **more) -> Result:  # noqa: ANN003
    """The k most frequent episodes; frequency never grows with an episode, so it is its own bound."""
    return mine_top_k(ces, mtd, k, rank_by="frequency", raise_=("candidate",), **more)


def compare_support_utility(ces: DataFrame, mtd: int, max_len: int | None = None) -> DataFrame:
    """(episode, utility, frequency, utility_rank, frequency_rank) of all episodes."""
    from pyspark.sql import Window as W

    rows = exhaustive(ces, mtd, max_len).select("episode", "utility", "frequency")
    place = lambda c: F.row_number().over(W.orderBy(F.desc(c), "episode"))  # noqa: E731  of results, not of the sequence
    return rows.withColumns({"utility_rank": place("utility"), "frequency_rank": place("frequency")})


def closed(rows: DataFrame) -> DataFrame:
    """Episodes of a result without a super-episode of the same frequency in it."""
    from chronolode.functions.udf import is_subepisode_udf

    other = rows.select(F.col("episode").alias("super"), F.col("frequency").alias("f"))
    dominated = rows.join(other, (F.col("frequency") == F.col("f")) & (F.col("episode") != F.col("super"))).filter(is_subepisode_udf()("episode", "super"))
    return rows.join(dominated.select("episode").distinct(), "episode", "left_anti")


def mine_sequences(ces: DataFrame, mtd: int, k: int, length: int | None = None, **more) -> Result:  # noqa: ANN003
    """Several sequences (seq_id, t, item, u) at once: each gets a stretch of times of its own, further apart than the duration. length: of a stretch, no shorter than the longest sequence; that by default."""
    from chronolode.sources.ces import ordinal_clock

    begins = ces.groupBy("seq_id").agg(F.min("t").alias("begin"), F.max("t").alias("end"))
    longest = begins.agg(F.coalesce(F.max(F.col("end") - F.col("begin")), F.lit(0))).first()[0] + 1
    if length is not None and length < longest:
        raise ValueError(f"length: {length}, but a sequence spans {longest} times")
    numbered = ordinal_clock(begins.select("seq_id"), "seq_id").select("seq_id", F.col("t").alias("n")).join(begins, "seq_id")
    stretch = (longest if length is None else length) + mtd + 1
    rows = ces.join(numbered, "seq_id").select((F.col("n") * stretch + F.col("t") - F.col("begin")).alias("t"), "item", "u")
    return mine_top_k(rows, mtd, k, **more)
