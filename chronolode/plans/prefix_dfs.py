"""Depth-first growth of one root's subtree inside a task, and waves of roots over tasks.

A group holds the windows of some roots (or a part of the children of one, where a root is hot), each from the root's event on. The miner grows episodes by same-time and later events, prunes by the bound,
and raises its threshold by the best k it has. A group returns its episodes that reach the threshold and one row of counters.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Callable
from dataclasses import dataclass
from itertools import groupby

import numpy as np
import pandas as pd
import pyarrow as pa

from chronolode.functions.model import key
from chronolode.operators.windows import events
from chronolode.plans import dense_dfs

#: Episodes of so many events and sets that a probe extends.
PROBE = 16
OUT = "kind string, episode string, events int, sets int, utility long, frequency long, n long"
ARROW = pa.schema([("kind", pa.string()), ("episode", pa.string()), ("events", pa.int32()), ("sets", pa.int32()), ("utility", pa.int64()), ("frequency", pa.int64()), ("n", pa.int64())])


@dataclass(frozen=True)
class Rules:
    """Everything that decides results, as one value that goes to the tasks."""

    k: int
    bound: str = "remaining"
    candidate_raise: bool = True
    semantics: str = "definition"
    kinds: str = "all"
    first: str = "I"
    max_len: int | None = None
    max_size: int | None = None
    keep_all: bool = False
    rank_by: str = "utility"
    fixed: bool = False
    #: Also report the best k below the threshold, for runs that may end early.
    spare: bool = False
    #: Where a root is cut into parts: episodes of more events belong to one part each, those of at most so many are seen by every part and counted by the first.
    split: int = 1
    #: Only look for candidates that raise the threshold (`Miner.probe`).
    probe: bool = False
    #: Windows of few items and times, merged: groups are Arrow tables (`dense_subtrees`).
    dense: bool = False
    #: Episodes that a task of merged windows generates before it hands back what it has not extended (`Miner.open`); None for all of them.
    most: int | None = None


class Window:
    """One start's events from the root's event on, in (t, rank) order."""

    __slots__ = ("items", "rest", "t", "u", "upto")

    def __init__(self, t: list[int], items: list[str], u: list[int], rest: list[int]) -> None:
        self.t, self.items, self.u, self.rest = t, items, u, rest


class Miner:
    def __init__(self, rules: Rules, min_util: int) -> None:
        self.rules, self.min_util = rules, min_util
        self.windows: list[Window] = []
        self.sums: list[dict[int, int]] = []
        self.part = (0, 1)
        self.found: dict[str, tuple] = {}
        self.heap: list[int] = []
        self.below: list[tuple] = []
        #: Episodes (sets, events, what they reach, part, parts) that are counted and offered, but left for another task to extend.
        self.open: list[tuple] = []
        self.generated = self.promising = self.buffered = 0

    def offer(self, sets: tuple, events: int, utility: int, frequency: int) -> None:
        counts = int(self.part[0] == 0 or events > self.rules.split)
        value = utility if self.rules.rank_by == "utility" else frequency
        if self.rules.kinds == "complex" and (len(sets) == 1 or events == len(sets)):
            return
        if value < self.min_util:
            if self.rules.spare and counts:
                push = heapq.heappush if len(self.below) < self.rules.k else heapq.heappushpop
                push(self.below, (value, sets, events, utility, frequency))
            return
        self.buffered += counts
        if counts:  # the first part reports what all see: it leaves out only what k others of its own exceed
            self.found[key(sets)] = (value, events, len(sets), utility, frequency)
        if not self.rules.candidate_raise or self.rules.fixed:
            return
        heapq.heappush(self.heap, value)
        if len(self.heap) > self.rules.k:
            heapq.heappop(self.heap)
        if len(self.heap) == self.rules.k and self.heap[0] > self.min_util:
            self.min_util = self.heap[0]
            if len(self.found) > 4 * self.rules.k + 1000:
                self.found = {e: x for e, x in self.found.items() if x[0] >= self.min_util}

    def score(self, occ: list, size_of_last: int) -> tuple[list, int, int, int]:
        """Keeps minimal starts; gives them with utility, frequency and bound. occ: [start, [(te, u, pos, u of the last set)...]] by start."""
        kept, utility, bound, windows, kind = [], 0, 0, self.windows, self.rules.bound
        by_definition = self.rules.semantics == "definition"
        for i, (s, ends) in enumerate(occ):
            te, u, pos, last = ends[0]
            # occ is in the order of start times; the next start decides.
            if i + 1 < len(occ) and occ[i + 1][1][0][0] <= te:
                continue
            kept.append((s, ends if by_definition else ends[:1]))
            utility += u
            if kind == "remaining":
                bound += u + windows[s].rest[pos]
            elif kind != "none":
                bound += u + self.sums[s][te] - (last if kind == "no_overlap" else 0)
        return kept, utility, len(kept), (bound if kind != "none" else 1 << 62)

    def grow(self, sets: tuple, events: int, occ: list) -> None:
        """Extends an episode whose minimal starts are occ."""
        r = self.rules
        if r.max_len is not None and events >= r.max_len:
            return
        same, later = {}, {}
        windows = self.windows
        want_same = r.kinds != "serial" and (r.max_size is None or len(sets[-1]) < r.max_size)
        want_later = r.kinds != "simultaneous"
        for s, ends in occ:
            w = windows[s]
            t, items, us = w.t, w.items, w.u
            if want_same:
                for te, u, pos, last in ends:
                    i = pos + 1
                    while i < len(t) and t[i] == te:
                        row = same.setdefault(items[i], [])
                        if row and row[-1][0] == s:
                            row[-1][1].append((te, u + us[i], i, last + us[i]))
                        else:
                            row.append((s, [(te, u + us[i], i, last + us[i])]))
                        i += 1
            if want_later:
                te, u, pos, last = ends[0]
                i, n = pos + 1, len(t)
                while i < n and t[i] == te:
                    i += 1
                while i < n:
                    row = later.setdefault(items[i], [])
                    if row and row[-1][0] == s:
                        row[-1][1].append((t[i], u + us[i], i, us[i]))
                    else:
                        row.append((s, [(t[i], u + us[i], i, us[i])]))
                    i += 1
        steps = [(same, lambda i: (*sets[:-1], (*sets[-1], i))), (later, lambda i: (*sets, (i,)))]
        for children, name in steps if r.first == "I" else steps[::-1]:
            for item in sorted(children):
                if self.elsewhere(name(item), events + 1):
                    continue
                self.visit(name(item), events + 1, children.pop(item))

    def visit(self, sets: tuple, events: int, occ: list) -> None:
        kept, utility, frequency, bound = self.score(occ, len(sets[-1]))
        if self.enters(sets, events, utility, frequency, bound):
            self.grow(sets, events, kept)

    def enters(self, sets: tuple, events: int, utility: int, frequency: int, bound: int) -> bool:
        """Counts and offers an episode; whether it is worth extending."""
        counts = int(self.part[0] == 0 or events > self.rules.split)
        self.generated, self.last = self.generated + counts, bound
        reach = bound if self.rules.rank_by == "utility" else frequency
        if reach < self.min_util:
            if self.rules.spare:
                self.offer(sets, events, utility, frequency)
            return False
        self.promising += counts
        self.offer(sets, events, utility, frequency)
        return True

    def elsewhere(self, sets: tuple, events: int) -> bool:
        """Whether an episode belongs to another part of its root."""
        return self.part[1] > 1 and events == self.rules.split + 1 and part_of(sets[-1][-1] if events == 2 else key(sets), self.part[1]) != self.part[0]

    def extended(self, block: dense_dfs.Block, only: Callable[[tuple], bool] | None = None) -> dense_dfs.Children:
        """All extensions of a block's episodes; only: which of them may be extended further."""
        r, events = self.rules, sum(map(len, block.sets[0]))
        order = [same for same in ((True, False) if r.first == "I" else (False, True)) if r.kinds != ("serial" if same else "simultaneous")]
        wanted = (lambda sets: not self.elsewhere(sets, events + 1)) if self.part[1] > 1 and events == r.split else None
        if only:
            here = wanted
            wanted = lambda sets: only(sets) and (here is None or here(sets))
        by_frequency = r.rank_by == "frequency"  # its own bound: no other is summed
        return dense_dfs.Children(block, order, r.max_size, "none" if by_frequency else r.bound, by_frequency, self.min_util, wanted, r.max_len is None or events + 1 < r.max_len)

    def grow_rows(self, children: dense_dfs.Children, i: int, events: int) -> None:
        """`grow` over merged windows: visits the extensions of a block's i-th episode, of so many events."""
        r = self.rules
        counts = int(self.part[0] == 0 or events + 1 > r.split)
        grows = r.max_len is None or events + 1 < r.max_len
        for step, (there, utility, frequency, bound) in enumerate(zip(children.there[i], children.utility[i], children.frequency[i], children.bound[i], strict=True)):
            if not there or (events == r.split and self.elsewhere(children.sets(i, step), events + 1)):
                continue
            if not r.spare and (bound if r.rank_by == "utility" else frequency) < self.min_util:
                self.generated, self.last = self.generated + counts, bound
            elif self.enters(children.sets(i, step), events + 1, utility, frequency, bound) and frequency and grows:
                if r.most is not None and self.generated >= r.most:
                    self.open.append((children.sets(i, step), events + 1, bound if r.rank_by == "utility" else frequency, *self.part))
                else:
                    self.grow_rows(*children.block(i, step, self.min_util, self.extended), events + 1)

    def resume(self, block: dense_dfs.Block, left: dict[tuple, int]) -> None:
        """Extends episodes that tasks handed back (with what they reach), below one root and of one part. What leads to them has been visited, and is only gone through again."""
        r, ahead = self.rules, {sets for e in left for sets in _steps_to(e)}
        only = lambda sets: sets in ahead or any(e in left for e in _steps_to(sets))  # noqa: E731  blocks hold episodes of both kinds
        extend = lambda b: self.extended(b, only)

        def walk(children: dense_dfs.Children, i: int, events: int) -> None:
            for step, (there, frequency, bound) in enumerate(zip(children.there[i], children.frequency[i], children.bound[i], strict=True)):
                if not there or (sets := children.sets(i, step)) not in ahead or (bound if r.rank_by == "utility" else frequency) < self.min_util:
                    continue
                if sets in left and r.most is not None and self.generated >= r.most:
                    self.open.append((sets, events + 1, left[sets], *self.part))
                else:
                    (self.grow_rows if sets in left else walk)(*children.block(i, step, self.min_util, extend), events + 1)

        walk(extend(block), 0, 1)

    def probe(self, children: dense_dfs.Children) -> None:
        """Candidates without the whole search: of each number of events and of sets, extends the PROBE episodes of largest utility (frequency) whose bound reaches the threshold. Whatever it finds is a candidate like any other.

        Numbers of sets are kept apart, since episodes of few large sets start with less than others of as many events, and end with more where times are full."""
        r, events, value = self.rules, 1, children.utility if self.rules.rank_by == "utility" else children.frequency
        while True:
            open_: dict[int, list[tuple]] = {}
            for i, there in enumerate(children.there):
                for step in range(len(there)):
                    if there[step] and children.frequency[i][step] and self.enters(children.sets(i, step), events + 1, children.utility[i][step], children.frequency[i][step], children.bound[i][step]):
                        open_.setdefault(len(children.sets(i, step)), []).append((-value[i][step], i, step))
            events += 1
            if not open_ or (r.max_len is not None and events >= r.max_len):
                return
            children = self.extended(children.some([(i, step) for some in open_.values() for _, i, step in sorted(some)[:PROBE]]))
            value = children.utility if r.rank_by == "utility" else children.frequency


def _steps_to(sets: tuple) -> list[tuple]:
    """The episodes of two events or more from which an episode grew, and itself."""
    return [(*sets[:i], sets[i][: j + 1]) for i in range(len(sets)) for j in range(len(sets[i])) if i or j]


def _root(miner: Miner, rows: list[tuple], part: int, parts: int, root: str) -> None:
    """Mines one root: rows (ts, t[], items[], u[], rest[], beside, n or nothing) in the order of ts; n equal windows, 1 by default, may be one row where `dense_dfs.fits`."""
    miner.part = (part, parts)
    rows = [r if len(r) > 6 else (*r, 1) for r in rows]
    names, times = dense_dfs.fits(rows) if miner.rules.semantics == "definition" else ([], 0)
    if times:
        _from_block(miner, lambda: dense_dfs.root_block(rows, names, times, root, miner.rules.bound in ("raw", "no_overlap")))
        return
    if miner.rules.probe:
        return
    windows, sums = [], []
    for _, t, items, u, rest, beside, _ in rows:
        t, u, rest = np.asarray(t).tolist(), np.asarray(u).tolist(), np.asarray(rest).tolist()
        windows.append(Window(t, list(items), u, rest))
        if miner.rules.bound in ("raw", "no_overlap"):
            full = {a: b + c for a, b, c in zip(reversed(t), reversed(rest), reversed(u), strict=True)}  # the last seen of a time is its first event
            full[t[0]] += int(beside)
            sums.append(full)
    miner.windows, miner.sums = windows, sums
    kept, *_ = miner.score([(s, [(w.t[0], w.u[0], 0, w.u[0])]) for s, w in enumerate(windows)], 1)
    miner.grow(((root,),), 1, kept)


def _from_block(miner: Miner, block: Callable[[], dense_dfs.Block]) -> None:
    """Mines the root of a block."""
    if miner.rules.max_len is None or miner.rules.max_len > 1:
        children = miner.extended(block())
        miner.probe(children) if miner.rules.probe else miner.grow_rows(children, 0, 1)


def _report(miner: Miner) -> pd.DataFrame:
    rows = [("episode", e, x[1], x[2], x[3], x[4], 0) for e, x in miner.found.items() if x[0] >= miner.min_util]
    rows += [("episode", key(sets), events, len(sets), utility, frequency, 0) for _, sets, events, utility, frequency in miner.below]
    rows += [("open", key(sets), events, part, reach, parts, 0) for sets, events, reach, part, parts in miner.open]
    rows += [(name, None, 0, 0, 0, 0, n) for name, n in (("generated", miner.generated), ("promising", miner.promising), ("buffered", miner.buffered))]
    return pd.DataFrame(rows, columns=["kind", "episode", "events", "sets", "utility", "frequency", "n"])


COLUMNS = ["ts", "t", "items", "u", "rest", "beside", "n"]


def subtrees(rules: Rules, min_util: int) -> Callable[[pd.DataFrame], pd.DataFrame]:
    """A function for applyInPandas over (root, bound, part, parts, ts, t[], items[], u[], rest[], beside, n): the windows of some roots, each from the root's event on.

    Roots are mined in falling order of bound with one threshold for all, as a single process would with all roots."""

    if rules.dense:
        return dense_subtrees(rules, min_util)

    def mine(pdf: pd.DataFrame) -> pd.DataFrame:
        miner = Miner(rules, min_util)
        pdf = pdf.sort_values(["bound", "root", "part", "ts"], ascending=[False, True, True, True])
        rows = pdf[["bound", "root", "part", "parts", *COLUMNS]].itertuples(index=False, name=None)
        for (bound, root, part, parts), some in groupby(rows, key=lambda r: r[:4]):
            if bound < miner.min_util:
                break
            _root(miner, [r[4:] for r in some], part, parts, root)
        return _report(miner)

    return mine


def dense_subtrees(rules: Rules, min_util: int) -> Callable[[pa.Table], pa.Table]:
    """`subtrees` for applyInArrow over (root, bound, part, parts, ts, t[], items[], u[], n): merged windows of few items and times, whole."""

    def mine(table: pa.Table) -> pa.Table:
        miner = Miner(rules, min_util)
        root, bound, part = table["root"].to_pylist(), table["bound"].to_numpy(), table["part"].to_numpy()
        groups: dict[tuple, list[int]] = {}
        for i, group in enumerate(zip((-bound).tolist(), root, part.tolist(), table["parts"].to_pylist(), strict=True)):
            groups.setdefault(group, []).append(i)
        for (less, name, miner_part, parts), rows in sorted(groups.items()):
            if -less < miner.min_util:
                break
            miner.part = (miner_part, parts)
            _from_block(miner, lambda name=name, rows=rows: _block(table.take(pa.array(rows)), name, rules.bound in ("raw", "no_overlap")))
        return pa.Table.from_pandas(_report(miner), ARROW, preserve_index=False)

    return mine


def resumed(rules: Rules, min_util: int, left: dict[int, dict[tuple, int]]) -> Callable[[pa.Table], pa.Table]:
    """A function for applyInArrow over what `dense_subtrees` takes, one root and part a slot: extends the episodes of each slot that tasks handed back."""

    def mine(table: pa.Table) -> pa.Table:
        miner = Miner(rules, min_util)
        miner.part = (table["part"][0].as_py(), table["parts"][0].as_py())
        miner.resume(_block(table, table["root"][0].as_py(), rules.bound in ("raw", "no_overlap")), left[table["slot"][0].as_py()])
        return pa.Table.from_pandas(_report(miner), ARROW, preserve_index=False)

    return mine


def _block(table: pa.Table, root: str, from_t: bool) -> dense_dfs.Block:
    """A root's block, from whole windows at whose start it is."""
    offsets, t = events(table["t"])
    t, u, items = t.to_numpy(), events(table["u"])[1].to_numpy(), events(table["items"])[1].dictionary_encode()
    names = sorted(items.dictionary.to_pylist())
    item = np.array([names.index(x) for x in items.dictionary.to_pylist()])[items.indices.to_numpy()]
    row = np.repeat(np.arange(table.num_rows), np.diff(offsets))
    begin = np.flatnonzero((item == names.index(root)) & (t == table["ts"].to_numpy()[row]))  # one event a window
    kept = np.arange(len(t)) >= begin[row]
    until = np.r_[0, u.cumsum()]
    sizes, times = offsets[1:] - begin, 1 + int(np.max(t - t[begin][row]))
    return dense_dfs.block_of(names, times, root, sizes, t[kept], item[kept], u[kept], table["n"].to_numpy(), until[begin] - until[offsets[:-1]] if from_t else None)


def part_of(item: str, parts: int) -> int:
    """Which part of a hot root's children an item belongs to."""
    return zlib.crc32(item.encode()) % parts
