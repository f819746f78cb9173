"""Plain enumeration of episodes, independent of the engine."""

from __future__ import annotations

import random
from collections import defaultdict
from itertools import combinations


def occurrences(ces, width):
    """{episode: {start: {end: (time vector, utility)}}}, the smallest time vector for each end; sets grow from every earlier prefix."""
    sets = defaultdict(dict)
    for t, i, u in ces:
        sets[t][i] = u
    times = sorted(sets)
    subsets = {t: [c for n in range(1, len(s) + 1) for c in combinations(sorted(s), n)] for t, s in sets.items()}
    found = defaultdict(lambda: defaultdict(dict))
    stack = [((c,), (t,), sum(sets[t][i] for i in c)) for t in times for c in subsets[t]]
    while stack:
        episode, vector, u = stack.pop()
        old = found[episode][vector[0]].get(vector[-1])
        if old is None or vector < old[0]:
            found[episode][vector[0]][vector[-1]] = (vector, u)
        for t in times:
            if vector[-1] < t <= vector[0] + width:
                stack += [((*episode, c), (*vector, t), u + sum(sets[t][i] for i in c)) for c in subsets[t]]
    return found


def utilities(ces, width):
    """{key: (utility, frequency)} over minimal occurrences."""
    out = {}
    for episode, starts in occurrences(ces, width).items():
        spans = [(s, min(ends), ends[min(ends)][1]) for s, ends in starts.items()]
        kept = [x for x in spans if not any(y[0] >= x[0] and y[1] <= x[1] and (y[0], y[1]) != (x[0], x[1]) for y in spans)]
        out[">".join("+".join(s) for s in episode)] = (sum(x[2] for x in kept), len(kept))
    return out


def top(ces, width, k):
    rows = sorted(((u, f, e) for e, (u, f) in utilities(ces, width).items()), key=lambda r: (-r[0], r[2]))
    return [(e, u, f) for u, f, e in rows[:k]]


def random_ces(seed, items="ABCD"):
    r = random.Random(seed)
    times = sorted(r.sample(range(1, 10), r.randrange(3, 8)))
    return [(t, i, r.randrange(1, 10)) for t in times for i in r.sample(items, r.randrange(1, 4))]
