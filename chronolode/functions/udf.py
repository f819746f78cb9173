"""Functions of Python for users of results: predicates on keys, and table functions. Each is made when called, since a session must exist."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from chronolode.functions.model import Episode, i_extend, is_subepisode, key, kind, length, parse, s_extend


def is_subepisode_udf():  # noqa: ANN201
    @F.pandas_udf("boolean")
    def test(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([None if x is None or y is None else is_subepisode(parse(x), parse(y)) for x, y in zip(a, b, strict=True)], dtype=object)

    return test


def kind_udf():  # noqa: ANN201
    @F.pandas_udf("string")
    def of(a: pd.Series) -> pd.Series:
        return a.map(lambda x: None if x is None else kind(parse(x)))

    return of


def episode_length_udf():  # noqa: ANN201
    @F.pandas_udf("int")
    def of(a: pd.Series) -> pd.Series:
        return a.map(lambda x: None if x is None else length(parse(x)))

    return of


def kth_largest_udf(k: int):  # noqa: ANN201
    """The kth largest of a group's values, 0 where there are fewer. For small groups; raising.kth() serves large ones."""

    @F.pandas_udf("long")
    def kth(u: pd.Series) -> int:
        return int(u.nlargest(k).iloc[-1]) if len(u) >= k else 0

    return kth


def matches(times: list[int], items: list[list[str]], utilities: list[list[int]], episode: Episode, start: int, width: int) -> tuple[int, int] | None:
    """(te, u) of the earliest end of an episode that starts at one time; times are in order."""
    u, i = 0, times.index(start)
    for n, wanted in enumerate(episode):
        while i < len(times) and times[i] <= start + width:
            at = dict(zip(items[i], utilities[i], strict=True))
            if all(x in at for x in wanted):
                break
            if n == 0:
                return None
            i += 1
        else:
            return None
        u += sum(at[x] for x in wanted)
        te = times[i]
        i += 1
    return te, u


class MatchEpisode:
    """Table function: one window (ts, t[], item[], u[]) and an episode's key; gives (ts, te, u) of the earliest end, if there is one."""

    def eval(self, ts: int, t: list[int], item: list[str], u: list[int], episode: str) -> Iterator[tuple[int, int, int]]:
        by_time: dict[int, tuple[list, list]] = {}
        for a, b, c in zip(t, item, u, strict=True):
            names, values = by_time.setdefault(a, ([], []))
            names.append(b)
            values.append(c)
        times = sorted(by_time)
        found = matches(times, [by_time[x][0] for x in times], [by_time[x][1] for x in times], parse(episode), ts, times[-1] - ts)
        if found:
            yield ts, found[0], found[1]


class Extend:
    """Table function: an episode's key and the items that follow in a window; gives each extension's key."""

    def eval(self, episode: str, same: list[str], later: list[str]) -> Iterator[tuple[str]]:
        e = parse(episode)
        for x in same or []:
            if x > max(e[-1]):
                yield (key(i_extend(e, x)),)
        for x in sorted(set(later or [])):
            yield (key(s_extend(e, x)),)


def register(spark: SparkSession) -> None:
    """The functions under SQL names."""
    spark.udf.register("is_subepisode", is_subepisode_udf())
    spark.udf.register("episode_kind", kind_udf())
    spark.udf.register("episode_length", episode_length_udf())
    spark.udtf.register("match_episode", F.udtf(MatchEpisode, returnType="ts long, te long, u long"))
    spark.udtf.register("extend_episode", F.udtf(Extend, returnType="episode string"))
