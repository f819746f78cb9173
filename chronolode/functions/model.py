"""Episode algebra. An episode is a tuple of sets (tuples of items in order); its key joins items by + and sets by >, with both and the backslash escaped."""

from __future__ import annotations

import re

from pyspark.sql import Column
from pyspark.sql import functions as F

Episode = tuple[tuple[str, ...], ...]
_SPECIAL = re.compile(r"([+>\\])")


def escape(item: str) -> str:
    return _SPECIAL.sub(r"\\\1", item)


def key(episode: Episode) -> str:
    return ">".join("+".join(map(escape, sorted(s))) for s in episode)


def parse(text: str) -> Episode:
    sets, items, item, i = [], [], "", 0
    while i < len(text):
        c = text[i]
        if c == "\\":
            i += 1
            item += text[i]
        elif c in "+>":
            items.append(item)
            item = ""
            if c == ">":
                sets.append(tuple(items))
                items = []
        else:
            item += c
        i += 1
    return (*sets, (*items, item))


def i_extend(episode: Episode, item: str) -> Episode:
    """Adds an item to the last set."""
    return (*episode[:-1], tuple(sorted({*episode[-1], item})))


def s_extend(episode: Episode, item: str) -> Episode:
    """Adds a set of one item after the last."""
    return (*episode, (item,))


def length(episode: Episode) -> int:
    return sum(map(len, episode))


def size(episode: Episode) -> int:
    return len(episode)


def kind(episode: Episode) -> str:
    if length(episode) == 1:
        return "simple"
    if len(episode) == 1:
        return "simultaneous"
    return "serial" if length(episode) == len(episode) else "complex"


def is_subepisode(a: Episode, b: Episode) -> bool:
    """Whether the sets of a are contained, in order, in sets of b. The earliest fit is as good as any."""
    at = 0
    for s in a:
        while at < len(b) and not set(s) <= set(b[at]):
            at += 1
        if at == len(b):
            return False
        at += 1
    return True


# The same as built-in expressions, over arrays of arrays.
def i_extend_column(episode: Column, item: Column) -> Column:
    last = F.element_at(episode, -1)
    return F.concat(F.slice(episode, 1, F.size(episode) - 1), F.array(F.array_sort(F.array_append(last, item))))


def s_extend_column(episode: Column, item: Column) -> Column:
    return F.array_append(episode, F.array(item))


def length_column(episode: Column) -> Column:
    return F.aggregate(episode, F.lit(0), lambda n, s: n + F.size(s))


def escaped_column(item: Column) -> Column:
    return F.regexp_replace(item, r"([+>\\])", r"\\$1")
