"""Windows of few items are cut and merged over Arrow columns, and go to the tasks whole."""

import datetime as dt
import random

import __spark_entry__ as entry
import brute
import pyarrow as pa
import pytest
from compare import differences, duck

from chronolode.operators import windows
from chronolode.plans import baselines, dense_dfs, metrics, miner, prefix_dfs
from chronolode.sources import ces


def _events(n, items="ABC", seed=6, share=0.6):
    draw = random.Random(seed)
    return [(t, i, draw.randint(1, 30)) for t in range(1, n) for i in items if draw.random() < share]


def _minutes(spark, folder):
    draw = random.Random(2)
    rows = [(dt.datetime(2024, 1, 1) + dt.timedelta(minutes=t), k, float(draw.randint(1, 9)), 1) for t in range(60) for k in ("click", "view") if draw.random() < 0.6]
    spark.createDataFrame(rows, "ts timestamp, event_type string, value double, user_id long").coalesce(1).write.parquet(f"{folder}/events.parquet")


@pytest.mark.parametrize("width", [0, 3])
def test_windows_are_those_of_one_row_an_event_and_start(spark, width):
    """Chunks of a few times, and gaps wider than a window; merged windows are equal too."""
    rows = [(t, i, u) for t, i, u in _events(80) if t % 20 < 12]
    seq = ces.from_rows(spark, rows)
    want, got = windows.arrays(windows.build(seq, width)), windows.arrays_by_set(seq, width, 5)
    assert got.schema.simpleString() == want.schema.simpleString()
    assert want.exceptAll(got).isEmpty() and got.exceptAll(want).isEmpty()
    assert windows.merged(got).exceptAll(windows.merged(want)).isEmpty()


def test_merging_in_steps_changes_nothing(spark):
    """F8, F9: what a task has merged is merged again with what comes later."""
    index = windows.arrays_by_set(ces.from_rows(spark, _events(200, "AB")), 1).toArrow().combine_chunks()
    half = index.num_rows // 2
    steps = windows._alike(pa.concat_tables([pa.Table.from_batches([windows._alike(index.slice(0, half))]), index.slice(half)]))
    by_ts = lambda batch: sorted(batch.to_pylist(), key=lambda r: r["ts"])
    once = windows._alike(index)
    assert by_ts(steps) == by_ts(once) and once.num_rows < half and sum(once["n"].to_pylist()) == index.num_rows


@pytest.mark.parametrize("name", ["support_vs_utility_all_lengths", "topk_frequent_minutes", "mtd_sweep_thresholds"])
def test_no_window_is_cut_at_each_root(spark, tmp_path, monkeypatch, name):
    """F8, F9, F4: tasks get whole windows and cut them themselves; results are those of SQL where there is any."""
    _minutes(spark, tmp_path)

    def refused(*_, **__):
        raise AssertionError("a row a root, cut")

    monkeypatch.setattr(miner, "root_windows", refused)
    df, sql = entry.queries()[name](spark, str(tmp_path)), entry.oracle_sql().get(name)
    if sql:
        a, b, _ = differences(df, sql, duck(str(tmp_path)))
        assert not a and not b
    assert df.count()


@pytest.mark.parametrize("more", [{"order": "utility"}, {"order": "bound", "bound": "raw"}, {"bound": "no_overlap"}, {"rank_by": "frequency"}], ids=str)
def test_whole_windows_give_what_enumeration_gives(spark, more):
    rows = _events(60)
    found = miner.mine_top_k(ces.from_rows(spark, rows), 2, 15, **more).df.collect()
    by = more.get("rank_by", "utility")
    every = sorted((-(u, f)[by == "frequency"], e) for e, (u, f) in brute.utilities(rows, 2).items())
    assert sorted((-r[by], r.episode) for r in found) == every[:15]


@pytest.mark.parametrize("bound", ["remaining", "raw", "no_overlap"])
def test_merging_of_rows_changes_nothing(monkeypatch, bound):
    """Rows alike from an end on: never merged, always merged, or where it is worth it."""
    seen, out = {}, []
    for t, i, u in _events(120, "ABCD"):
        seen.setdefault(t, []).append((i, u))
    for share in (0, 0.8, 1):
        monkeypatch.setattr(dense_dfs, "MERGED_FROM", share)
        m = prefix_dfs.Miner(prefix_dfs.Rules(15, bound=bound), 40)
        for root in "ABCD":
            rows = []
            for ts in sorted(seen):
                events = [(t, i, u) for t in range(ts, ts + 4) for i, u in seen.get(t, ())]
                for p in (p for p, x in enumerate(events) if x[:2] == (ts, root)):
                    u = [x[2] for x in events]
                    rows.append((ts, [x[0] for x in events[p:]], [x[1] for x in events[p:]], u[p:], [sum(u[q + 1 :]) for q in range(p, len(u))], sum(u[:p])))
            prefix_dfs._root(m, rows, 0, 1, root)
        out.append((m.found, m.min_util, m.generated, m.promising))
    assert out[0] == out[1] == out[2] and out[0][2] > 20


def test_frequency_needs_no_other_bound(monkeypatch):
    """what follows an event is not summed up where episodes are ranked by frequency."""

    def refused(_):
        raise AssertionError("a bound that nothing reads")

    monkeypatch.setattr(dense_dfs, "_rest", refused)
    rows = [(t, [t, t + 1], ["A", "B"], [t, 1], [1, 0], 0, 1) for t in range(1, 30, 3)]
    m = prefix_dfs.Miner(prefix_dfs.Rules(3, rank_by="frequency"), 0)
    prefix_dfs._root(m, rows, 0, 1, "A")
    assert m.found["A>B"][-1] == 10


def test_runs_of_a_sweep_share_windows_and_first_thresholds(spark, monkeypatch):
    """windows are stored once a duration and lists made once a variant; rows are those of runs on their own."""
    stored, lists, store, initial = [], [], miner.written, miner.raising.initial
    seq = ces.from_rows(spark, _events(60))
    alone = [(v, mtd, r.initial_min_util, r.end_min_util, r.candidates) for v in ("full", "prior_top_k") for mtd in (1, 2) for r in [baselines.variant(v, seq, mtd, 10)]]
    monkeypatch.setattr(miner, "written", lambda df: stored.append(df.columns) or store(df))
    monkeypatch.setattr(miner.raising, "initial", lambda *a: lists.append(a) or initial(*a))
    got = metrics.sweep(spark, seq, ("full", "prior_top_k"), (10,), (1, 2)).collect()
    assert [(r.variant, r.mtd, r.initial_min_util, r.end_min_util, {c: r[c] for c in ("generated", "promising", "buffered")}) for r in got] == alone
    assert sum("head" in c for c in stored) == 2 == len(lists)
