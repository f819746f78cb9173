"""Long searches over merged windows: tasks hand back what they have not extended, and a probe keeps numbers of sets apart."""

import random

import brute
import pytest

from chronolode.plans import miner, prefix_dfs
from chronolode.sources import ces

EVENTS = [(t, i, (7 * t + 3 * ord(i)) % 29 + 1) for t in range(1, 60) for i in "ABC" if (t * t + 5 * ord(i)) % 7 > 2]


def _watched(monkeypatch, most, split_rows):
    """Sets the limits; the number of episodes of each wave that is dealt out again."""
    dealt, resumed = [], prefix_dfs.resumed
    monkeypatch.setattr(miner, "MOST", most)
    monkeypatch.setattr(miner, "WHOLE_CELLS", 4)
    monkeypatch.setattr(miner, "SPLIT_ROWS", split_rows)
    monkeypatch.setattr(prefix_dfs, "resumed", lambda rules, least, left: dealt.append(sum(map(len, left.values()))) or resumed(rules, least, left))
    return dealt


@pytest.mark.parametrize("split_rows", [0, 6000], ids=["whole", "parts"])
@pytest.mark.parametrize("more", [{}, {"bound": "raw"}, {"rank_by": "frequency"}, {"ties": "keep"}, {"first": "S"}, {"bound": "none", "max_len": 3}], ids=str)
def test_handed_back_episodes_are_all_extended(spark, monkeypatch, more, split_rows):
    """F1 to F3: a task that has generated enough hands back the rest; the best are those of enumeration."""
    dealt = _watched(monkeypatch, 12, split_rows)
    found = miner.mine_top_k(ces.from_rows(spark, EVENTS), 2, 10, window_raise=False, raise_=("event", "transaction"), **more) if more.get("bound") == "none" else miner.mine_top_k(ces.from_rows(spark, EVENTS), 2, 10, window_raise=False, **more)
    assert dealt and found.complete and found.waves == 1 + len(dealt)
    by = more.get("rank_by", "utility")
    every = [((u, f)[by == "frequency"], e) for e, (u, f) in brute.utilities(EVENTS, 2).items() if e.count("+") + e.count(">") < more.get("max_len", 99)]
    best = sorted(every, key=lambda x: (-x[0], x[1]))
    want = best[:10] if more.get("ties") != "keep" else [x for x in best if x[0] >= best[9][0]]
    assert sorted((-r[by], r.episode) for r in found.df.collect()) == sorted((-v, e) for v, e in want)


@pytest.mark.parametrize("split_rows", [0, 6000], ids=["whole", "parts"])
def test_handing_back_changes_no_counter(spark, monkeypatch, split_rows):
    """F1 to F3: without raises by candidates the threshold is fixed, and each episode is generated once however often tasks stop."""
    seq, out = ces.from_rows(spark, EVENTS), []
    for most in (100_000, 12):
        dealt = _watched(monkeypatch, most, split_rows)
        found = miner.mine_top_k(seq, 2, 10, window_raise=False, raise_=("event",))
        out.append((found.candidates["generated"], found.candidates["promising"], found.end_min_util))
    assert dealt and out[0] == out[1]


def test_probe_finds_large_sets(spark, monkeypatch):
    """F1 to F3: full minutes, whose best episodes are few large sets; the probe's threshold comes near the last one."""
    draw, starts, subtrees = random.Random(4), [], prefix_dfs.subtrees
    events = [(t, i, draw.randint(20, 30)) for t in range(1, 400) for i in "ABCDE" if draw.random() < 0.94]
    monkeypatch.setattr(prefix_dfs, "subtrees", lambda rules, least: starts.append(least) or subtrees(rules, least))
    found = miner.mine_top_k(ces.from_rows(spark, events), 4, 10, window_raise=False)
    assert found.end_min_util >= starts[1] > 0.9 * found.end_min_util


def test_runs_at_once_change_no_row(spark, monkeypatch):
    """durations share the cores, more than one at a time, and give the rows of runs one by one."""
    from chronolode.plans import metrics

    inside, most, real = [0], [0], metrics.variant

    def variant(*args, **more):
        inside[0] += 1
        most[0] = max(most[0], inside[0])
        try:
            return real(*args, **more)
        finally:
            inside[0] -= 1

    monkeypatch.setattr(metrics, "variant", variant)
    seq = ces.from_rows(spark, EVENTS)
    got = [metrics.sweep(spark, seq, ("full", "prior_top_k"), (10,), (1, 2, 3), at_once=n).drop("seconds").collect() for n in (1, 3)]
    assert got[0] == got[1] and len(got[0]) == 6 and most[0] > 1


def test_levels_at_once_leave_the_session_as_it_was(spark):
    """runs that grow by levels overlap; the setting they share comes back when the last one ends."""
    from chronolode.plans.levelwise import CO_PARTITION, by_chunk

    before = spark.conf.get(CO_PARTITION)
    a, b = by_chunk(spark), by_chunk(spark)
    a.__enter__()
    b.__enter__()
    a.__exit__(None, None, None)
    inside = spark.conf.get(CO_PARTITION)
    b.__exit__(None, None, None)
    assert inside == "false" and spark.conf.get(CO_PARTITION) == before


@pytest.mark.parametrize("name", ["mtd_sweep_minutes", "mtd_sweep_thresholds"])
def test_sweeps_run_at_once(spark, tmp_path, monkeypatch, name):
    """the queries ask for it."""
    import datetime as dt

    import __spark_entry__ as entry

    from chronolode.plans import metrics

    asked, real = [], metrics.sweep
    monkeypatch.setattr(metrics, "sweep", lambda *args, **more: asked.append(more.get("at_once", 1)) or real(*args, **more))
    rows = [(dt.datetime(2024, 1, 1) + dt.timedelta(minutes=t), k, 1.0, 1) for t in range(20) for k in ("click", "view")]
    spark.createDataFrame(rows, "ts timestamp, event_type string, value double, user_id long").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    assert entry.queries()[name](spark, str(tmp_path)).count() == (5 if name.endswith("minutes") else 10) and asked[0] > 1
