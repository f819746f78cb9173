"""A sample of the registry beside its SQL, on the smallest tables."""

import __spark_entry__ as entry
import brute
import pytest
from compare import differences, duck

SF = "/root/testdata/sf0.001"
NAMES = ["ces_order_parts", "ordinal_clock_orders", "dataset_characteristics", "kth_merged_k500", "window_suffix_minutes", "one_episode_table_orders", "minimal_click_view", "pair_serial_orders_mtd2", "topk_minutes_mtd3", "topk_ties_keep", "rollup_item_month", "asof_next_purchase", "udtf_match_episode", "stream_tumbling_utility", "stream_matcher"]
NAMES += sorted(set(__import__("chronolode.reports", fromlist=["ORACLES"]).ORACLES) - {"mtd_sweep_thresholds", "stream_dedup_events"})


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, name):
    a, b, _ = differences(entry.queries()[name](spark, SF), entry.oracle_sql()[name], duck(SF))
    assert not a and not b


def test_entry_and_names(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_set_ops_cover_the_whole_clock(spark, tmp_path):
    """A type of the last day only, and one that leaves after the first half."""
    import datetime as dt

    rows = [(dt.datetime(2024, 1, day, hour), kind, 1.0, 1) for kind, days in (("both", (1, 2, 29)), ("early", (1, 2)), ("late", (30,))) for day in days for hour in (1, 13)]
    path = f"{tmp_path}/events.parquet"
    spark.createDataFrame(rows, "ts timestamp, event_type string, value double, user_id long").coalesce(1).write.parquet(path)
    query, sql = (f()["set_ops_items_all_hours"] for f in (entry.queries, entry.oracle_sql))
    found = {(r.item, r.side) for r in query(spark, str(tmp_path)).collect()}
    assert found == {("both", "both"), ("early", "more"), ("both", "more"), ("late", "second")}
    for d in (str(tmp_path), "/root/testdata/sf0.01"):
        a, b, _ = differences(query(spark, d), sql, duck(d))
        assert not a and not b


@pytest.mark.parametrize("name, unit", [("topk_hours_mtd2_all_lengths", "hours"), ("support_vs_utility_all_lengths", "minutes")])
def test_all_lengths_equal_enumeration(spark, tmp_path, name, unit):
    """Windows of more than four events, ranked by plain enumeration."""
    import datetime as dt

    rows = [(t, i, 3 * t + ord(i) % 7) for t in (1, 2, 3, 5, 6) for i in ("ABC" if t % 2 else "AC")]
    stamped = [(dt.datetime(2024, 1, 1) + dt.timedelta(**{unit: t - 1}), i, u / 100, 1) for t, i, u in rows]
    spark.createDataFrame(stamped, "ts timestamp, event_type string, value double, user_id long").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    got = entry.queries()[name](spark, str(tmp_path)).collect()
    every = brute.utilities(rows, 2)
    length = lambda e: e.count("+") + e.count(">") + 1
    if unit == "hours":
        assert [(r.episode, r.utility, r.frequency) for r in sorted(got, key=lambda r: r["rank"])] == brute.top(rows, 2, 20)
    else:
        by = {c: [e for e in sorted(every, key=lambda e: (-every[e][c], e))] for c in (0, 1)}
        assert {r.episode: (r.utility, r.frequency) for r in got} == every
        assert [r.episode for r in sorted(got, key=lambda r: r.utility_rank)] == by[0] and [r.episode for r in sorted(got, key=lambda r: r.frequency_rank)] == by[1]
    assert max(length(r.episode) for r in got) > 4


def test_first_orders_are_ten_thousand(spark):
    query, sql = (f()["first_n_orders_10000"] for f in (entry.queries, entry.oracle_sql))
    a, b, _ = differences(query(spark, "/root/testdata/sf0.01"), sql, duck("/root/testdata/sf0.01"))
    assert not a and not b and query(spark, "/root/testdata/sf0.01").agg({"t": "max"}).first()[0] == 10_000
