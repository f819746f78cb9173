"""Sequences of few items: windows of the same items at the same distances are one row, and episodes grow over arrays."""

import datetime as dt
import random

import __spark_entry__ as entry
import brute
import pytest
from compare import differences, duck

from chronolode.operators.windows import arrays, build, merged
from chronolode.plans import dense_dfs, miner, prefix_dfs
from chronolode.plans.miner import mine_threshold, mine_top_k
from chronolode.sources import ces


def _windows(rows, width):
    out = {}
    for ts in sorted({t for t, _, _ in rows}):
        events = sorted((t, i, u) for t, i, u in rows if ts <= t <= ts + width)
        u = [x[2] for x in events]
        for p in range(sum(x[0] == ts for x in events)):
            rest = [sum(u[q + 1 :]) for q in range(p, len(u))]
            out.setdefault(events[p][1], []).append((ts, [x[0] for x in events[p:]], [x[1] for x in events[p:]], u[p:], rest, sum(u[:p]), 1))
    return out


@pytest.mark.parametrize("more", [{"bound": b} for b in ("remaining", "raw", "no_overlap", "none")] + [{"first": "S"}, {"kinds": "serial"}, {"kinds": "simultaneous"}, {"kinds": "complex"}, {"max_len": 3}, {"max_size": 2}, {"rank_by": "frequency"}, {"spare": True}], ids=str)
def test_arrays_give_what_lists_give(monkeypatch, more):
    """Episodes, their order and all counters."""
    draw, out = random.Random(3), []
    rows = [(t, i, draw.randint(1, 30)) for t in range(1, 50) for i in "ABCDE" if draw.random() < 0.5]
    for lists in (False, True):
        if lists:
            monkeypatch.setattr(dense_dfs, "fits", lambda _: ([], 0))
        miner = prefix_dfs.Miner(prefix_dfs.Rules(15, **more), 40 if more.get("rank_by") != "frequency" else 4)
        for root, windows in sorted(_windows(rows, 3).items()):
            prefix_dfs._root(miner, windows, 0, 1, root)
        out.append((miner.found, sorted(miner.below), miner.min_util, miner.generated, miner.promising, miner.buffered))
    assert out[0] == out[1] and out[0][3] > 20


def test_rows_alike_from_an_end_on_are_one():
    """Windows that differ in their first minute only; blocks of a few rows and parts of roots give what one block gives."""
    draw = random.Random(5)
    rows = [(4 * d + t, i, draw.randint(1, 30)) for d in range(60) for t in range(3) for i in "ABCDE" if t or draw.random() < 0.6]
    windows = [w for w in _windows(rows, 2)["A"] if w[0] % 4 == 0]
    block = dense_dfs.root_block(windows, list("ABCDE"), 3, "A")
    assert block.has.shape[1] > 8
    children = prefix_dfs.Miner(prefix_dfs.Rules(10), 0).extended(block)
    step = children.steps.index((False, "A"))
    below, place = children.block(0, step, 0, prefix_dfs.Miner(prefix_dfs.Rules(10), 0).extended)
    b = below.parent
    assert b.sets[place] == (("A",), ("A",)) and b.begin[place + 1] - b.begin[place] == 1 and b.n[b.begin[place]] == block.n.sum()


@pytest.mark.parametrize("size", [1, 7, 50])
def test_size_of_blocks_changes_nothing(monkeypatch, size):
    draw, out = random.Random(9), []
    rows = [(t, i, draw.randint(1, 30)) for t in range(1, 60) for i in "ABCD" if draw.random() < 0.6]
    for rows_a_block in (dense_dfs.BLOCK_ROWS, size):
        monkeypatch.setattr(dense_dfs, "BLOCK_ROWS", rows_a_block)
        miner = prefix_dfs.Miner(prefix_dfs.Rules(15, split=2), 40)
        for root, windows in sorted(_windows(rows, 3).items()):
            for part in range(3):
                prefix_dfs._root(miner, windows, part, 3, root)
        out.append((miner.found, miner.min_util, miner.generated, miner.promising, miner.buffered))
    assert out[0] == out[1] and out[0][2] > 20


def test_equal_windows_are_one_row(spark):
    """300 times of which all but the last few look alike; results stay those of enumeration."""
    rows = [(t, i, t % 7 + ord(i) % 5) for t in range(1, 301) for i in "ABC" if t % 3 != 1 or i != "C"]
    seq = ces.from_rows(spark, rows)
    index = merged(arrays(build(seq, 2)))
    assert index.count() == 5 and index.agg({"n": "sum"}).first()[0] == 300
    every = brute.utilities(rows, 2)
    assert {r.episode: (r.utility, r.frequency) for r in mine_threshold(seq, 2, min_util=0, bound="none").collect()} == every
    for strategy in ("auto", "dfs_single"):
        got = mine_top_k(seq, 2, 25, strategy=strategy).df.orderBy("rank").collect()
        assert [(r.episode, r.utility, r.frequency) for r in got] == brute.top(rows, 2, 25)


NAMES = {"F5": "raise_gain_minutes", "F10": "topk_minutes_mtd3", "F2": "full_support_utility", "F9": "topk_frequent_minutes", "F1": "bound_tightness", "F6": "span_order_counts", "F7": "span_order_thresholds", "F11": "topk_minutes_mtd6"}


@pytest.mark.parametrize("name", NAMES.values())
def test_repeated_minutes(spark, tmp_path, monkeypatch, name):
    """A day of minutes that repeat, mined over fewer rows than windows, and with SQL where there is any."""
    rows = [(dt.datetime(2024, 1, 1) + dt.timedelta(minutes=t), k, float(t % 5 + 1), 1) for t in range(1440) for k in (("click", "view") if t % 4 else ("view",)) if t % 2 == 0 or k == "click"]
    spark.createDataFrame(rows, "ts timestamp, event_type string, value double, user_id long").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    seen, real = [], merged
    monkeypatch.setattr("chronolode.plans.miner.merged", lambda index: seen.append((index.count(), real(index).count())) or real(index))
    df, sql = entry.queries()[name](spark, str(tmp_path)), entry.oracle_sql().get(name)
    if sql:
        a, b, _ = differences(df, sql, duck(str(tmp_path)))
        assert not a and not b
    assert df.count() and seen and all(10 * few < many for many, few in seen)


MINUTES = {"F1": "bound_tightness", "F2": "full_support_utility", "F3": "mtd_sweep_minutes", "F4": "mtd_sweep_thresholds", "F6": "span_order_counts", "F7": "span_order_thresholds", "F8": "support_vs_utility_all_lengths", "F9": "topk_frequent_minutes", "F10": "topk_minutes_mtd3"}


@pytest.mark.parametrize("name", MINUTES.values())
def test_few_items_need_no_row_an_event_and_start(spark, tmp_path, monkeypatch, name):
    """Windows come from one row a minute; results are those of SQL where there is any."""
    draw = random.Random(2)
    rows = [(dt.datetime(2024, 1, 1) + dt.timedelta(minutes=t), k, float(draw.randint(1, 9)), 1) for t in range(60) for k in ("click", "view") if draw.random() < 0.6]
    spark.createDataFrame(rows, "ts timestamp, event_type string, value double, user_id long").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")

    def refused(*_, **__):
        raise AssertionError("a row an event and start")

    monkeypatch.setattr("chronolode.plans.miner.build", refused)
    df, sql = entry.queries()[name](spark, str(tmp_path)), entry.oracle_sql().get(name)
    if sql:
        a, b, _ = differences(df, sql, duck(str(tmp_path)))
        assert not a and not b
    assert df.count()


def test_all_lengths_over_repeated_minutes(spark, tmp_path):
    """support_vs_utility_all_lengths, with its ranks, by enumeration; no frontier is stored by chunk for it."""
    rows = [(t, k, t % 5 + 1) for t in range(1, 241) for k in ("click", "view") if t % 2 or k == "click"]
    stamped = [(dt.datetime(2024, 1, 1) + dt.timedelta(minutes=t - 1), k, u / 100, 1) for t, k, u in rows]
    spark.createDataFrame(stamped, "ts timestamp, event_type string, value double, user_id long").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    df = entry.queries()["support_vs_utility_all_lengths"](spark, str(tmp_path))
    assert "by_chunk" not in df._jdf.queryExecution().toString()
    assert {r.episode: (r.utility, r.frequency) for r in df.collect()} == brute.utilities(rows, 2)
    assert not any("bucket" in f for f in df.inputFiles()) and len({f.rsplit("/", 1)[0] for f in df.inputFiles()}) == 1


@pytest.mark.parametrize("name", ["concatenations_example", "theta_pairs_example", "udtf_extend_episode", "example_bounds"])
def test_reads_the_events(spark, name):
    df = entry.queries()[name](spark, "/root/testdata/sf0.01")
    assert any("events.parquet" in f for f in df.inputFiles())
    a, b, n = differences(df, entry.oracle_sql()[name], duck("/root/testdata/sf0.01"))
    assert not a and not b and n


@pytest.mark.parametrize("rows", [0, 6000], ids=["whole", "parts"])
@pytest.mark.parametrize("more", [{}, {"bound": "raw"}, {"rank_by": "frequency"}, {"ties": "keep"}], ids=str)
def test_candidates_raise_the_threshold_of_all_tasks(spark, monkeypatch, rows, more):
    """the search starts from a threshold that a probe of every root found, in parts or not, and gives what enumeration gives; no table of windows is stored before they are merged."""
    draw, starts, stored = random.Random(4), [], []
    events = [(t, i, draw.randint(1, 30)) for t in range(1, 60) for i in "ABC" if draw.random() < 0.6]
    subtrees, store = prefix_dfs.subtrees, miner.written
    monkeypatch.setattr(miner, "WHOLE_CELLS", 4)
    monkeypatch.setattr(miner, "SPLIT_ROWS", rows)
    monkeypatch.setattr(prefix_dfs, "subtrees", lambda rules, least: starts.append(least) or subtrees(rules, least))
    monkeypatch.setattr(miner, "written", lambda df: stored.append(df.columns) or store(df))
    seq = ces.from_rows(spark, events)
    found = miner.mine_top_k(seq, 2, 10, window_raise=False, **more)
    assert len(starts) == 2 and found.initial_min_util <= starts[0] < starts[1] <= found.end_min_util
    assert [c for c in stored if "head" in c] and sum("head" in c for c in stored) == 1
    by = more.get("rank_by", "utility")
    every = sorted(((u, f)[by == "frequency"], e) for e, (u, f) in brute.utilities(events, 2).items())
    best = sorted(every, key=lambda x: (-x[0], x[1]))
    want = best[:10] if more.get("ties") != "keep" else [x for x in best if x[0] >= best[9][0]]
    assert sorted((-r[by], r.episode) for r in found.df.collect()) == sorted((-v, e) for v, e in want)


@pytest.mark.parametrize("name", ["full_support_utility", "span_order_counts", "span_order_thresholds", "topk_frequent_minutes", "support_vs_utility_all_lengths"])
def test_sequence_and_windows_are_stored_once(spark, tmp_path, monkeypatch, name):
    """F2, F6 to F9: the minutes once a query, and once a run the windows, merged already."""
    rows = [(dt.datetime(2024, 1, 1) + dt.timedelta(minutes=t), k, float(t % 3 + 1), 1) for t in range(40) for k in ("click", "view")]
    spark.createDataFrame(rows, "ts timestamp, event_type string, value double, user_id long").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    stored, store = [], miner.written
    for module in ("plans.miner", "registry", "reports"):
        monkeypatch.setattr(f"chronolode.{module}.written", lambda df: stored.append(df.columns) or store(df))
    assert entry.queries()[name](spark, str(tmp_path)).count()
    runs = 2 if name.startswith(("full", "span")) else 1
    assert stored.count(["t", "item", "u"]) == 1 and sum("head" in c for c in stored) == runs
