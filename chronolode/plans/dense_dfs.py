"""Depth-first growth where a root's windows hold few items and times: the same search as `prefix_dfs.Miner`, over arrays of windows.

Whether an occurrence from a window's start is minimal shows inside that window: it is not if the episode also occurs from a later time of it on, and ends no later. So windows that hold the same items at the same places
are one row, with their summed utilities and their number; utilities, frequencies and bounds are sums over windows and stay what they were. For each row a bit mask over its times says where an item is; an episode's
state is, for the rows where its occurrence is minimal, the times at which its last set can end, from the start on and from a later time on, both by the earliest fit.

Of a row, only what comes after the earliest end can matter to longer episodes. So the rows of an episode are moved to begin at that end, and those that look the same from there on are merged again: the longer an
episode, the fewer its rows. Episodes of one length that follow each other in the search are extended together, in blocks of some rows; the miner then visits them one by one, in its own order.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import cache

import numpy as np
import pandas as pd

#: Times of a window (bits of a mask), and cells (items x times) of a row. Beyond these, windows stay lists.
MAX_TIMES, MAX_CELLS = 16, 512
#: Rows that are extended together; an episode of more rows is a block of its own.
BLOCK_ROWS = 8192
#: Rows that are alike from an end on are merged where so many of them, or fewer, are different.
MERGED_FROM = 0.8


@cache
def _tables() -> tuple[np.ndarray, np.ndarray]:
    """The lowest time of each mask (MAX_TIMES: none), and for each such time the mask of later ones."""
    low = np.full(1 << MAX_TIMES, MAX_TIMES, np.uint8)
    for t in reversed(range(MAX_TIMES)):
        low[1 << t :: 1 << (t + 1)] = t
    after = np.array([((1 << MAX_TIMES) - 1) & ~((1 << (t + 1)) - 1) for t in range(MAX_TIMES)] + [0], np.uint16)
    return low, after


def _beside(row: np.ndarray, slot: np.ndarray, item: np.ndarray, d: int, n: int) -> list[tuple[int, int]]:
    """The pairs of items that stand d places apart at one time of a row."""
    p = np.flatnonzero((row[d:] == row[:-d]) & (slot[d:] == slot[:-d]))
    return [divmod(int(x), n) for x in np.unique(item[p] * n + item[p + d])]


def fits(windows: list[tuple]) -> tuple[list[str], int]:
    """The items of some windows, and the times of the longest, or 0 if they do not fit this form."""
    names: set[str] = set()
    for w in windows:
        names.update(w[2])
        if 2 * len(names) > MAX_CELLS:
            return [], 0
    times = max((1 + int(np.count_nonzero(np.diff(w[1]))) for w in windows), default=0)
    return sorted(names), times if times <= MAX_TIMES and len(names) * (times + 1) <= MAX_CELLS else 0


class Block:
    """Episodes of one length with their rows, one after the other: `begin` says where each one's rows begin.

    By item and row `has` (masks), by item, time and row `u`, by time and row `from_t` and `set_u` (utility of the last set, if it is at that time); by row `n`, `ends`, `inner` and `before` (utility before the
    last set). Time 0 is the earliest end of the last set; after the last time stands one without events."""

    __slots__ = ("after", "before", "begin", "ends", "from_t", "has", "inner", "items", "last", "n", "order", "set_u", "sets", "u")


def root_block(windows: list[tuple], names: list[str], times: int, root: str, from_t: bool = False) -> Block:
    """The one episode of a root. windows: (ts, t[], items[], u[], rest[], beside, n), as `prefix_dfs._root` has them."""
    t, u = (np.concatenate([np.asarray(w[i]) for w in windows]).astype(np.int64) for i in (1, 3))
    item = pd.Categorical(np.concatenate([np.asarray(w[2]) for w in windows]), categories=names).codes.astype(np.int64)
    sizes, number, beside = (np.fromiter(x, np.int64, len(windows)) for x in ((len(w[1]) for w in windows), (w[6] for w in windows), (w[5] for w in windows)))
    return block_of(names, times, root, sizes, t, item, u, number, beside if from_t else None)


def block_of(names: list[str], times: int, root: str, sizes: np.ndarray, t: np.ndarray, item: np.ndarray, u: np.ndarray, number: np.ndarray, beside: np.ndarray | None) -> Block:
    """`root_block` from the events of all windows, one window after the other: sizes of windows, (t, place of the item in names, u) of events. beside: what stands beside the root at its start, where from_t is wanted."""
    b, n = Block(), len(sizes)
    row, begin = np.repeat(np.arange(n), sizes), np.r_[0, sizes.cumsum()[:-1]]
    new = np.r_[False, (t[1:] != t[:-1]) & (row[1:] == row[:-1])]
    fresh = new.astype(np.int64).cumsum()
    slot = fresh - fresh[begin][row]
    has = np.zeros((n, len(names)), np.uint16)
    np.bitwise_or.at(has, (row, item), (1 << slot).astype(np.uint16))
    _, first, same = np.unique(has.view(np.dtype((np.void, has.dtype.itemsize * len(names)))).ravel(), return_index=True, return_inverse=True)
    same, width, size = same.ravel(), times + 1, len(first)
    b.items, b.has, b.n = names, np.ascontiguousarray(has[first].T), np.zeros(size, np.int64)
    np.add.at(b.n, same, number)
    b.u = np.zeros((len(names), width, size), np.int64)
    np.add.at(b.u, (item, slot, same[row]), u)
    # The one order of items, as far as it matters: which stand after which at one time.
    b.after = np.zeros((len(names), len(names)), bool)
    for d in range(1, len(names)):
        for x, y in _beside(row, slot, item, d, len(names)):
            b.after[x, y] = True
    b.order = _in_order(b.after)
    b.from_t = None
    if beside is not None:  # of a time's first event here: its own and all after it; at the start also those before the root
        b.from_t = b.u.sum(0)[::-1].cumsum(0)[::-1]
        np.add.at(b.from_t[0], same, beside)
    i = names.index(root)
    b.ends, b.inner = b.has[i] & np.uint16(1), b.has[i] & np.uint16((1 << MAX_TIMES) - 2)
    b.before, b.set_u = np.zeros(size, np.int64), b.u[i]
    b.begin, b.sets, b.last = np.array([0, size]), [((root,),)], np.array([i])
    return b


def _in_order(after: np.ndarray) -> list[int]:
    """All items in an order in which those that stand after others at one time come after them."""
    left, out = list(range(len(after))), []
    while left:
        x = next(x for x in left if not after[left, x].any())
        out.append(x)
        left.remove(x)
    return out


def _rest(b: Block) -> np.ndarray:
    """By item, time and row the utility of what comes after the item there, in the order of times and items."""
    out, total = np.empty_like(b.u), np.zeros(b.u.shape[2], np.int64)
    for t in reversed(range(b.u.shape[1])):
        for x in reversed(b.order):
            out[x, t] = total
            total += b.u[x, t]
    return out


class Children:
    """All extensions by one event of the episodes of a block.

    `steps` are (in the last set, item), in the order in which the miner visits them; by step and episode `there`, `utility`, `frequency`, `bound`. `block(i, step)` gives the block and the place in it of a child that
    reached `least` when its siblings were extended."""

    def __init__(self, b: Block, order: tuple[bool, ...], wide: int | None, bound: str, by_frequency: bool, least: int, wanted: Callable[[tuple], bool] | None, grow: bool) -> None:
        """order: True for extensions of the last set; wide: the most events of a set; wanted: which children are grown at all; grow: whether any is."""
        low, after = _tables()
        self.parent, n = b, len(b.sets)
        node = np.repeat(np.arange(n), np.diff(b.begin))
        room = np.ones(n, bool) if wide is None else np.array([len(s[-1]) < wide for s in b.sets], bool)
        rest = _rest(b) if bound == "remaining" else None
        self.steps, got, rows = [], [], []
        for same in order:
            outer, inner = (b.ends, b.inner) if same else (after[0], after[low[b.inner]])
            base = b.before if same else b.before + b.set_u[0]
            for x in range(len(b.items)):
                mask = b.has[x] & outer
                if same:
                    mask = np.where((b.after[b.last, x] & room)[node], mask, np.uint16(0))
                end = low[mask]
                k = np.flatnonzero(end < low[b.has[x] & inner])
                some = np.zeros(n, bool)
                some[node[mask != 0]] = True
                if not some.any():
                    continue
                end, cut = end[k].astype(np.int64), np.searchsorted(k, b.begin)
                last = b.u[x, end, k]
                if same:
                    last += b.set_u[end, k]
                utility, frequency = _sums(base[k] + last, cut), _sums(b.n[k], cut)
                if bound == "none":
                    limit = np.full(n, 1 << 62)
                elif bound == "remaining":
                    limit = utility + _sums(rest[x, end, k], cut)
                else:
                    limit = utility + _sums(b.from_t[end, k] - (last if bound == "no_overlap" else 0), cut)
                self.steps.append((same, b.items[x]))
                got.append((some, utility, frequency, limit))
                rows.append((k, end))
        self.there, self.utility, self.frequency, self.bound = (np.array([g[i] for g in got]).reshape(len(got), n).T.tolist() for i in range(4))
        self.groups: list = []
        if not grow or not got:
            return
        good = np.array([g[0] & (g[2] > 0) & (g[2 if by_frequency else 3] >= least) for g in got]).T  # without rows there is nothing to grow
        if wanted:
            for i, s in zip(*np.nonzero(good), strict=True):
                good[i, s] = wanted(self.sets(i, s))
        number = good.ravel().cumsum().reshape(good.shape) - 1
        self.number, self.members = number, np.argwhere(good)
        self.reach = np.array([g[2 if by_frequency else 3] for g in got]).T[good]
        part = [np.flatnonzero(good[node[k], s]) for s, (k, _) in enumerate(rows)]
        self.row = np.concatenate([k[p] for (k, _), p in zip(rows, part, strict=True)])
        self.end = np.concatenate([e[p] for (_, e), p in zip(rows, part, strict=True)])
        self.child = np.concatenate([number[node[k[p]], s] for s, ((k, _), p) in enumerate(zip(rows, part, strict=True))])
        by = np.argsort(self.child, kind="stable")
        self.row, self.end, self.child = self.row[by], self.end[by], self.child[by]
        # Blocks of following children, each of BLOCK_ROWS rows at most or of one child.
        groups, total, at = [], 0, -1
        for size in np.bincount(self.child, minlength=len(self.members)).tolist():
            if at < 0 or total + size > BLOCK_ROWS:
                at, total = at + 1, 0
            total += size
            groups.append(at)
        self.group_of, self.groups = np.array(groups, np.int64), [None] * (at + 1)

    def sets(self, i: int, step: int) -> tuple:
        """The child's episode."""
        before, (same, item) = self.parent.sets[i], self.steps[step]
        return (*before[:-1], (*before[-1], item)) if same else (*before, (item,))

    def block(self, i: int, step: int, least: int, extend: Callable[[Block], Children]) -> tuple[Children, int]:
        """The extensions of a child and of those that follow it and still reach `least`, and its place among them."""
        child = int(self.number[i, step])
        g = self.group_of[child]
        if self.groups[g] is None:
            first, end = np.searchsorted(self.group_of, [g, g + 1])
            chosen = np.flatnonzero(self.reach[first:end] >= least) + first
            place = np.full(end - first, -1)
            place[chosen - first] = np.arange(len(chosen))
            self.groups = [None] * len(self.groups)  # those before are done
            self.groups[g] = extend(self._moved(chosen)), int(first), place.tolist()
        children, first, place = self.groups[g]
        return children, place[child - first]

    def some(self, steps: list[tuple[int, int]]) -> Block:
        """The block of some children (episode, step) that reached `least`, in the order of the search."""
        return self._moved(np.array(sorted(int(self.number[x]) for x in steps)))

    def _moved(self, chosen: np.ndarray) -> Block:
        """The block of some children, in their order: rows begin at the earliest end of the last set, and those of a child that are alike from there on are one."""
        low, after = _tables()
        b, new = self.parent, Block()
        new.items, new.after, new.order = b.items, b.after, b.order
        members = self.members[chosen]
        step_same = np.array([s for s, _ in self.steps])
        step_item = np.array([b.items.index(x) for _, x in self.steps])
        first, last = np.searchsorted(self.child, [chosen[0], chosen[-1] + 1])
        place = np.full(chosen[-1] - chosen[0] + 1, -1)
        place[chosen - chosen[0]] = np.arange(len(chosen))
        at = place[self.child[first:last] - chosen[0]]
        k, end = self.row[first:last][at >= 0], self.end[first:last][at >= 0]
        at = at[at >= 0]
        new.last = step_item[members[:, 1]]
        same, item = step_same[members[:, 1]][at], new.last[at]
        shift = end.astype(np.uint16)
        mine = b.has[item, k]
        inner = b.inner[k]
        ends = (mine & np.where(same, b.ends[k], after[0])) >> shift
        inner = (mine & np.where(same, inner, after[low[inner]])) >> shift
        has = b.has[:, k] >> shift
        # At time 0 only items that may still join the last set matter.
        has &= np.where(b.after[item].T, np.uint16((1 << MAX_TIMES) - 1), np.uint16((1 << MAX_TIMES) - 2))
        # Rows after whose end nothing comes have no part in longer episodes.
        more = np.flatnonzero(np.bitwise_or.reduce(has, axis=0))
        if len(more) < len(k):
            k, end, same, item, at, ends, inner, has = k[more], end[more], same[more], item[more], at[more], ends[more], inner[more], has[:, more]
        times = max(1, int(np.bitwise_or.reduce(has | ends, axis=None)).bit_length())
        bits = (len(b.items) + 2) * times
        starts = None
        if len(k) and bits + len(chosen).bit_length() < 63:
            code = at << bits
            for j, x in enumerate((ends, inner, *has)):
                code |= x.astype(np.int64) << (j * times)
            by = np.argsort(code)
            code = code[by]
            starts = np.flatnonzero(np.r_[True, code[1:] != code[:-1]])
            if len(starts) > MERGED_FROM * len(k):  # not worth the sums: longer episodes have fewer different rows
                starts = None
        if starts is not None:
            k, end, same, item, at = k[by], end[by], same[by], item[by], at[by]
            one = by[starts]
            ends, inner, has = ends[one], inner[one], has[:, one]
        new.has, new.ends, new.inner = has, ends, inner
        merge = (lambda x: np.add.reduceat(x, starts)) if starts is not None and len(starts) < len(k) else lambda x: x
        last_slot, size = b.u.shape[1] - 1, b.u.shape[2]
        new.u, new.set_u = np.empty((len(b.items), times + 1, has.shape[1]), np.int64), np.empty((times + 1, has.shape[1]), np.int64)
        new.from_t = None if b.from_t is None else np.empty_like(new.set_u)
        before_u, set_u = b.u.reshape(len(b.items), -1), b.set_u.reshape(-1)
        for j in range(times + 1):
            cell = np.minimum(end + j, last_slot) * size + k
            for x in range(len(b.items)):
                new.u[x, j] = merge(before_u[x].take(cell))
            new.set_u[j] = merge(before_u.reshape(-1).take(item * before_u.shape[1] + cell) + np.where(same, set_u.take(cell), 0))
            if b.from_t is not None:
                new.from_t[j] = merge(b.from_t.reshape(-1).take(cell))
        new.before = merge(b.before[k] + np.where(same, 0, b.set_u[0, k]))
        new.n = merge(b.n[k])
        at = at if starts is None else at[starts]
        new.begin = np.searchsorted(at, np.arange(len(chosen) + 1))
        new.sets = [self.sets(i, s) for i, s in members.tolist()]
        return new


def _sums(x: np.ndarray, cut: np.ndarray) -> np.ndarray:
    """Sums of the stretches between cuts."""
    total = np.zeros(len(x) + 1, np.int64)
    np.cumsum(x, out=total[1:])
    return np.diff(total[cut])
