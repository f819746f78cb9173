"""Queries over the given tables, with the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronolode import oracle as sql
from chronolode.functions import udf
from chronolode.operators import bounds, occurrence, raising
from chronolode.operators.windows import arrays_by_set, build, episodes_at_starts, one_episode_table
from chronolode.plans import baselines, metrics
from chronolode.plans.miner import mine_threshold, mine_top_k
from chronolode.plans.storage import written
from chronolode.sources import ces
from chronolode.streaming import stream

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
CLICK_VIEW = (("click",), ("view",))


def add(name: str, query: Query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def with_rank(df: DataFrame) -> DataFrame:
    return df.select("episode", "events", "sets", "utility", "frequency", "rank")


SEQUENCES = {"order_parts": (ces.order_parts, "orders"), "event_hours": (ces.event_hours, "hours"), "event_minutes": (ces.event_minutes, "minutes"), "brand_days": (ces.brand_days, "brands")}
for _name, (_make, _key) in SEQUENCES.items():
    add(f"ces_{_name}", _make, sql.CES[_key])
add("props_weighted_events", ces.props_weighted, sql.CES["props"])
add("ordinal_clock_orders", lambda s, d: ces.ordinal_clock(ces.load(s, d, "orders"), "o_orderdate", "o_orderkey").select("o_orderkey", "t"), "SELECT o_orderkey, row_number() OVER (ORDER BY o_orderdate, o_orderkey) AS t FROM orders")


def _first_orders(s: SparkSession, d: str, n: int = 1000) -> DataFrame:
    numbers = ces.ordinal_clock(ces.load(s, d, "orders"), "o_orderdate", "o_orderkey").select((F.col("o_orderkey") + 1).alias("old"), F.col("t").alias("n"))
    rows = ces.order_parts(s, d).join(numbers, F.col("t") == F.col("old")).select(F.col("n").alias("t"), "item", "u")
    return ces.first_n(rows, n)


add("first_n_orders", _first_orders, f"WITH c AS ({sql.CES['orders']}), n AS (SELECT o_orderkey + 1 AS old, row_number() OVER (ORDER BY o_orderdate, o_orderkey) AS t FROM orders) SELECT n.t, item, u FROM c JOIN n ON c.t = n.old WHERE n.t <= 1000")
add("first_n_orders_10000", lambda s, d: _first_orders(s, d, 10_000), f"WITH c AS ({sql.CES['orders']}), n AS (SELECT o_orderkey + 1 AS old, row_number() OVER (ORDER BY o_orderdate, o_orderkey) AS t FROM orders) SELECT n.t, item, u FROM c JOIN n ON c.t = n.old WHERE n.t <= 10000")


def _characteristics(s: SparkSession, d: str) -> DataFrame:
    out = None
    for name, (make, _) in SEQUENCES.items():
        row = ces.characteristics(make(s, d)).withColumn("name", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out.select("name", "transactions", "avg_len_x100", "items")


add("dataset_characteristics", _characteristics, " UNION ALL ".join(f"SELECT '{n}' AS name, count(DISTINCT t)::BIGINT AS transactions, floor(count(*) * 100 / count(DISTINCT t))::BIGINT AS avg_len_x100, count(DISTINCT item)::BIGINT AS items FROM ({sql.CES[k]})" for n, (_, k) in SEQUENCES.items()))
add("simulated_utilities", lambda s, d: ces.simulate(ces.order_parts(s, d).select("t", "item")).select("t", "item", "q", "p"))
add("validate_orders", lambda s, d: ces.validate(ces.order_parts(s, d)), f"SELECT 'none' AS problem, 0::BIGINT AS n FROM ({sql.CES['orders']}) WHERE u < 1")
add("transaction_utility_hours", lambda s, d: ces.transaction_utility(ces.event_hours(s, d)), f"SELECT t, sum(u)::BIGINT AS tu FROM ({sql.CES['hours']}) GROUP BY t")
add("total_utility", lambda s, d: ces.total_utility(ces.event_hours(s, d)), f"SELECT sum(u)::BIGINT AS tu_total FROM ({sql.CES['hours']})")
for _name, _key, _make in (("hours", "hours", ces.event_hours), ("parts", "orders", ces.order_parts)):
    add(f"event_utility_{_name}", lambda s, d, m=_make: raising.event_list(m(s, d)), f"SELECT item, sum(u)::BIGINT AS utility, count(*)::BIGINT AS frequency FROM ({sql.CES[_key]}) GROUP BY item")
add("distinct_set_utility", lambda s, d: raising.transaction_list(ces.event_hours(s, d)), sql.sets(sql.CES["hours"]) + "SELECT * FROM d")


def _kth(k: int, value: Callable[[DataFrame], int]) -> Query:
    return lambda s, d: s.createDataFrame([(k, value(ces.order_parts(s, d)))], "k int, min_util long")


_EVENT = f"SELECT sum(u) AS utility FROM ({sql.CES['orders']}) GROUP BY item"
_PRINTED = f"SELECT sum(u) AS utility FROM ({sql.CES['orders']}) GROUP BY t"
_DISTINCT = sql.sets(sql.CES["orders"]) + "SELECT utility FROM d"
for _k in (10, 500, 3000):
    add(f"kth_event_k{_k}", _kth(_k, lambda c, k=_k: raising.by_event(c, k)), sql.kth(_EVENT, _k))
    add(f"kth_transaction_printed_k{_k}", _kth(_k, lambda c, k=_k: raising.by_transaction(c, k, "printed_sequential", "last")), sql.kth(_PRINTED, _k, "last"))
    add(f"kth_transaction_distinct_k{_k}", _kth(_k, lambda c, k=_k: raising.by_transaction(c, k)), sql.kth(_DISTINCT, _k))
    add(f"kth_merged_k{_k}", _kth(_k, lambda c, k=_k: raising.initial(c, k, ("event", "transaction"))), sql.kth(f"SELECT * FROM ({_EVENT}) UNION ALL SELECT * FROM ({_DISTINCT})", _k))

add("remaining_utility_hours", lambda s, d: bounds.remaining(ces.event_hours(s, d)), f"SELECT t, item, coalesce(sum(u) OVER (PARTITION BY t ORDER BY item ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0)::BIGINT AS ru FROM ({sql.CES['hours']})")
add("window_suffix_minutes", lambda s, d: build(ces.event_minutes(s, d), 3).filter("own").select("ts", "t", "item", "rest"), sql.windows(sql.CES["minutes"], 3) + "SELECT ts, t, item, rest FROM w")
add("one_episode_table_hours", lambda s, d: one_episode_table(build(ces.event_hours(s, d), 2)), sql.one_episodes(sql.CES["hours"], 2))
add("one_episode_table_orders", lambda s, d: one_episode_table(build(ces.order_parts(s, d), 2)), sql.one_episodes(sql.CES["orders"], 2))
add("bound_gap", lambda s, d: bounds.gap_of_bounds(one_episode_table(build(ces.event_hours(s, d), 2))), f"SELECT item, raw - remaining AS raw_minus_remaining FROM ({sql.one_episodes(sql.CES['hours'], 2)})")
add("example_bounds", lambda s, d: one_episode_table(build(ces.event_minutes(s, d), 2)), sql.one_episodes(sql.CES["minutes"], 2))

_CV = sql.pair_occurrences(sql.CES["minutes"], 3, "click", "view")
add("occurrences_click_view", lambda s, d: occurrence.occ_set(ces.event_minutes(s, d), CLICK_VIEW, 3).select("ts", "te"), _CV + "SELECT ts, te FROM o")
add("minimal_click_view", lambda s, d: occurrence.minimal(occurrence.occ_set(ces.event_minutes(s, d), CLICK_VIEW, 3)), _CV + "SELECT ts, te, u FROM m")
add("episode_utility_click_view", lambda s, d: occurrence.episode_utility(occurrence.occ_set(ces.event_minutes(s, d), CLICK_VIEW, 3), "click>view"), _CV + "SELECT 'click>view' AS episode, sum(u)::BIGINT AS utility, count(*)::BIGINT AS frequency FROM m")
_LATE = [(1, "A", 1), (2, "B", 1), (3, "B", 1), (3, "C", 1)]
add("episode_utility_late_partner", lambda s, d: mine_threshold(ces.from_rows(s, _LATE), 2, min_util=0).filter("episode = 'A>B+C'").select("episode", "utility", "frequency"), sql.enumerated(sql.CES["late_partner"], 2) + "SELECT episode, utility, frequency FROM ep WHERE episode = 'A>B+C'")
_top = lambda df: df.orderBy(F.desc("utility"), "episode").limit(100)
add("pair_simultaneous_orders", lambda s, d: _top(occurrence.pair_utilities(ces.order_parts(s, d), 2, "simultaneous")), sql.pairs(sql.CES["orders"], 2, "simultaneous") + " ORDER BY utility DESC, episode LIMIT 100")
add("pair_serial_orders_mtd2", lambda s, d: _top(occurrence.pair_utilities(ces.order_parts(s, d), 2, "serial")), sql.pairs(sql.CES["orders"], 2, "serial") + " ORDER BY utility DESC, episode LIMIT 100")

for _gap, _k in ((1, 7), (2, 4), (3, 2)):
    add(f"example_topk_gap{_gap}", lambda s, d, g=_gap, k=_k: with_rank(mine_top_k(ces.example(s), g, k).df), sql.top_k(sql.CES["example"], _gap, _k))
add("example_topk_points2", lambda s, d: with_rank(mine_top_k(ces.example(s), 2, 7, span="points").df), sql.top_k(sql.CES["example"], 1, 7))


def _top_k(make: Query, mtd: int, k: int, **more) -> Query:  # noqa: ANN003
    return lambda s, d: with_rank(mine_top_k(make(s, d), mtd, k, **more).df)


HOURS1 = sql.top_k(sql.CES["hours"], 1, 20)
add("topk_hours_mtd1", _top_k(ces.event_hours, 1, 20), HOURS1)
add("topk_hours_mtd2_len4", _top_k(ces.event_hours, 2, 20, max_len=4), sql.top_k(sql.CES["hours"], 2, 20, 4))
add("topk_hours_mtd2_all_lengths", _top_k(ces.event_hours, 2, 20))  # no SQL: enumeration of windows of 15 events is too slow
add("topk_minutes_mtd3", _top_k(ces.event_minutes, 3, 50), sql.top_k(sql.CES["minutes"], 3, 50))
add("topk_minutes_mtd6", _top_k(ces.event_minutes, 6, 50), sql.top_k(sql.CES["minutes"], 6, 50))
ORDERS1 = f"WITH c AS ({sql.CES['orders']}), s AS (SELECT * FROM (SELECT item AS episode, 1 AS events, 1 AS sets, sum(u)::BIGINT AS utility, count(*)::BIGINT AS frequency FROM c GROUP BY item) UNION ALL SELECT episode, 2, 1, utility, frequency FROM ({sql.pairs('SELECT * FROM c', 1, 'simultaneous')}) UNION ALL SELECT episode, 2, 2, utility, frequency FROM ({sql.pairs('SELECT * FROM c', 1, 'serial')})) SELECT episode, events::INTEGER AS events, sets::INTEGER AS sets, utility, frequency, rank::INTEGER AS rank FROM (SELECT *, row_number() OVER (ORDER BY utility DESC, episode) AS rank FROM s) WHERE rank <= 500"
add("topk_orders_mtd1_len2", _top_k(ces.order_parts, 1, 500, max_len=2), ORDERS1)
for _strategy in ("levelwise", "prefix_dfs", "dfs_single"):
    add(f"topk_hours_{_strategy}", _top_k(ces.event_hours, 1, 20, strategy=_strategy), HOURS1)
for _order in ("utility", "bound"):
    add(f"topk_hours_order_{_order}", _top_k(ces.event_hours, 1, 20, order=_order), HOURS1)
for _name, _settings in baselines.VARIANTS.items():
    if _settings:
        add(f"baseline_{_name}_hours", _top_k(ces.event_hours, 1, 20, **_settings, window_raise=False), HOURS1)
for _bound in ("no_overlap", "none"):
    add(f"topk_hours_bound_{_bound}", _top_k(ces.event_hours, 1, 20, bound=_bound, window_raise=False), HOURS1)
for _name, _raise in baselines.RAISES.items():
    if _name != "all":
        add(f"topk_hours_raise_{_name}", _top_k(ces.event_hours, 1, 20, raise_=_raise, window_raise=False), HOURS1)
add("exhaustive_hours_mtd1", lambda s, d: baselines.exhaustive(ces.event_hours(s, d), 1), sql.threshold(sql.CES["hours"], 1, "0"))
add("topk_first_s", _top_k(ces.event_hours, 1, 20, first="S", strategy="dfs_single"), HOURS1)
add("topk_serial_only", _top_k(ces.event_hours, 2, 20, kinds="serial"), sql.top_k(sql.CES["hours"], 2, 20, kinds="serial"))
add("topk_simultaneous_only", _top_k(ces.event_hours, 0, 20, kinds="simultaneous"), sql.top_k(sql.CES["hours"], 0, 20, kinds="simultaneous"))
add("topk_ties_keep", _top_k(lambda s, d: ces.event_hours(s, d).withColumn("u", F.lit(1).cast("long")), 1, 20, ties="keep"), sql.top_k(f"SELECT t, item, 1::BIGINT AS u FROM ({sql.CES['hours']})", 1, 20, ties="keep"))
add("hue_threshold_hours", lambda s, d: mine_threshold(ces.event_hours(s, d), 1, min_util=20_000_000), sql.threshold(sql.CES["hours"], 1, "20000000"))
add("hue_ratio_hours", lambda s, d: mine_threshold(ces.event_hours(s, d), 1, min_util_ratio=0.3, bound="raw"), sql.threshold(sql.CES["hours"], 1, "ceil(0.3 * (SELECT sum(u) FROM ces))"))
add("topk_frequent_minutes", lambda s, d: with_rank(baselines.top_k_frequent(ces.event_minutes(s, d), 3, 50).df), sql.top_k(sql.CES["minutes"], 3, 50, by="frequency"))
add("support_vs_utility", lambda s, d: baselines.compare_support_utility(ces.event_minutes(s, d), 2, 3), sql.enumerated(sql.CES["minutes"], 2, 3) + "SELECT episode, utility, frequency, (row_number() OVER (ORDER BY utility DESC, episode))::INTEGER AS utility_rank, (row_number() OVER (ORDER BY frequency DESC, episode))::INTEGER AS frequency_rank FROM ep")

add("support_vs_utility_all_lengths", lambda s, d: baselines.compare_support_utility(ces.event_minutes(s, d), 2))  # no SQL, as above


def _sweep(s: SparkSession, d: str) -> DataFrame:
    return metrics.sweep(s, ces.event_hours(s, d), baselines.VARIANTS, (5, 20), (1,), strategy="dfs_single")


add("candidates_by_variant", lambda s, d: _sweep(s, d).select("variant", "k", "generated", "promising", "buffered"))
add("thresholds_by_variant", lambda s, d: _sweep(s, d).select("variant", "k", "end_min_util"), " UNION ALL ".join(f"SELECT '{v}' AS variant, {k}::INTEGER AS k, (SELECT utility FROM ({sql.top_k(sql.CES['hours'], 1, k)}) WHERE rank = {k}) AS end_min_util" for v in baselines.VARIANTS for k in (5, 20)))
add("mtd_sweep_minutes", lambda s, d: metrics.sweep(s, ces.event_minutes(s, d), ("full",), (50,), (2, 3, 4, 5, 6), at_once=5).select("variant", "mtd", "end_min_util", "generated", "promising"))


def _tightness(s: SparkSession, d: str) -> DataFrame:
    c = written(ces.event_minutes(s, d))
    return metrics.tightness(episodes_at_starts(arrays_by_set(c, 2)), baselines.exhaustive(c, 2))


add("bound_tightness", _tightness, sql.enumerated(sql.CES["minutes"], 2) + f", b AS ({sql.one_episodes(sql.CES['minutes'], 2)}) SELECT b.item, floor(any_value(remaining) * 100 / max(ep.utility))::BIGINT AS bound_x100 FROM b JOIN ep ON regexp_extract(episode, '^[^+>]*') = b.item GROUP BY b.item")


def _per_length(s: SparkSession, d: str) -> DataFrame:
    rows = mine_threshold(ces.event_hours(s, d), 1, min_util=0)
    place = F.row_number().over(W.partitionBy("events").orderBy(F.desc("utility"), "episode"))
    return rows.withColumn("place", place).filter("place <= 3").select("events", "place", "episode", "utility")


add("top_per_length", _per_length, sql.enumerated(sql.CES["hours"], 1) + "SELECT events, place::INTEGER AS place, episode, utility FROM (SELECT *, row_number() OVER (PARTITION BY events ORDER BY utility DESC, episode) AS place FROM ep) WHERE place <= 3")
_MONTH = "make_date(2024, 1, 1) + (t - 1) div 24"


def _rollup(s: SparkSession, d: str) -> DataFrame:
    rows = ces.event_hours(s, d).withColumn("month", F.month(F.date_add(F.lit("2024-01-01").cast("date"), F.floor((F.col("t") - 1) / 24).cast("int"))))
    return rows.rollup("item", "month").agg(F.sum("u").cast("long").alias("utility"))


add("rollup_item_month", _rollup, f"SELECT item, month(DATE '2024-01-01' + ((t - 1) // 24)::INTEGER)::INTEGER AS month, sum(u)::BIGINT AS utility FROM ({sql.CES['hours']}) GROUP BY ROLLUP (1, 2)")
add("cube_kind_size", lambda s, d: mine_threshold(ces.event_hours(s, d), 1, min_util=0).withColumn("serial", F.col("events") == F.col("sets")).cube("serial", "events").agg(F.sum("utility").cast("long").alias("utility"), F.count("*").alias("n")), sql.enumerated(sql.CES["hours"], 1) + "SELECT events = sets AS serial, events, sum(utility)::BIGINT AS utility, count(*)::BIGINT AS n FROM ep GROUP BY CUBE (1, 2)")


def _asof(s: SparkSession, d: str) -> DataFrame:
    """The next purchase within three minutes of each click: an equality join on the minutes before a purchase."""
    c = ces.event_minutes(s, d)
    left = c.filter("item = 'click'").select("t")
    right = c.filter("item = 'purchase'").select(F.col("t").alias("next_t"), F.col("u").alias("next_u"), F.explode(F.sequence(F.col("t") - 3, F.col("t") - 1)).alias("t"))
    best = right.groupBy("t").agg(F.min(F.struct("next_t", "next_u")).alias("x"))
    return left.join(best, "t", "left").select("t", "x.next_t", "x.next_u")


add("asof_next_purchase", _asof, f"WITH c AS ({sql.CES['minutes']}) SELECT a.t, b.t AS next_t, b.u AS next_u FROM (SELECT t FROM c WHERE item = 'click') a ASOF LEFT JOIN (SELECT t, t - 1 AS k, u, t AS tt FROM c WHERE item = 'purchase') b ON a.t <= b.k WHERE b.t IS NULL OR b.t <= a.t + 3 UNION ALL SELECT a.t, NULL, NULL FROM (SELECT t FROM c WHERE item = 'click') a ASOF JOIN (SELECT t, t - 1 AS k FROM c WHERE item = 'purchase') b ON a.t <= b.k WHERE b.t > a.t + 3")


def _semi(s: SparkSession, d: str) -> DataFrame:
    c = ces.event_hours(s, d)
    table = one_episode_table(build(c, 1)).filter(bounds.promising(F.col("remaining"), 40_000_000)).select("item")
    return c.join(table, "item", "left_semi").select("t", "item", "u")


add("semi_promising", _semi, f"SELECT t, item, u FROM ({sql.CES['hours']}) WHERE item IN (SELECT item FROM ({sql.one_episodes(sql.CES['hours'], 1)}) WHERE remaining >= 40000000)")
add("anti_orders_without_items", lambda s, d: ces.load(s, d, "orders").select("o_orderkey").join(ces.load(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_anti"), "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")


def _full(s: SparkSession, d: str) -> DataFrame:
    c = written(ces.event_minutes(s, d))
    by = {x: (mine_top_k(c, 2, 20, prepared=True) if x == "u" else baselines.top_k_frequent(c, 2, 20, prepared=True)).df.select("episode", F.col("utility" if x == "u" else "frequency").alias(x)) for x in ("u", "f")}
    return by["u"].join(by["f"], "episode", "full")


add("full_support_utility", _full, f"SELECT coalesce(a.episode, b.episode) AS episode, a.utility AS u, b.frequency AS f FROM ({sql.top_k(sql.CES['minutes'], 2, 20)}) a FULL JOIN ({sql.top_k(sql.CES['minutes'], 2, 20, by='frequency')}) b ON a.episode = b.episode")


def _set_ops(s: SparkSession, d: str) -> DataFrame:
    """Event types of the first and second twelve hours of the first day, no others: in both, and in one only."""
    c = ces.event_hours(s, d)
    a, b = c.filter("t <= 12").select("item"), c.filter("t > 12 AND t <= 24").select("item")
    return a.intersect(b).withColumn("side", F.lit("both")).unionByName(a.exceptAll(b).withColumn("side", F.lit("more"))).unionByName(b.subtract(a).withColumn("side", F.lit("second")))


add("set_ops_items", _set_ops, f"WITH c AS ({sql.CES['hours']}), a AS (SELECT item FROM c WHERE t <= 12), b AS (SELECT item FROM c WHERE t > 12 AND t <= 24) SELECT item, 'both' AS side FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT item, 'more' FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b) UNION ALL SELECT item, 'second' FROM (SELECT * FROM b EXCEPT SELECT * FROM a)")


def _set_ops_all(s: SparkSession, d: str) -> DataFrame:
    """Event types of the first and second half of the whole clock, every row on one side: in both, and in one only."""
    c = ces.event_hours(s, d)
    c = c.join(c.agg(F.floor((F.min("t") + F.max("t")) / 2).alias("middle")))
    a, b = c.filter("t <= middle").select("item"), c.filter("t > middle").select("item")
    return a.intersect(b).withColumn("side", F.lit("both")).unionByName(a.exceptAll(b).withColumn("side", F.lit("more"))).unionByName(b.subtract(a).withColumn("side", F.lit("second")))


add("set_ops_items_all_hours", _set_ops_all, f"WITH c AS ({sql.CES['hours']}), h AS (SELECT (min(t) + max(t)) // 2 AS middle FROM c), a AS (SELECT item FROM c, h WHERE t <= middle), b AS (SELECT item FROM c, h WHERE t > middle) SELECT item, 'both' AS side FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT item, 'more' FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b) UNION ALL SELECT item, 'second' FROM (SELECT * FROM b EXCEPT SELECT * FROM a)")


def _match(s: SparkSession, d: str) -> DataFrame:
    """Earliest ends of click>view by the table function, over windows that start with a click."""
    from chronolode.functions.sql import register

    register(s, ces.event_minutes(s, d), 3, "match_")
    return s.sql("SELECT m.ts, m.te FROM match_window_arrays w, LATERAL match_episode(w.ts, w.t, w.items, w.u, 'click>view') m")


add("udtf_match_episode", _match, _CV + "SELECT ts, min(te) AS te FROM o GROUP BY ts")


def _subepisodes(s: SparkSession, d: str) -> DataFrame:
    rows = baselines.exhaustive(ces.example(s), 2).select("episode")
    return rows.filter(udf.is_subepisode_udf()(F.lit("B>A+C"), "episode")).select("episode", udf.kind_udf()("episode").alias("kind"))


add("udf_is_subepisode", _subepisodes, sql.enumerated(sql.CES["example"], 2) + r"SELECT episode, CASE WHEN events = 1 THEN 'simple' WHEN sets = 1 THEN 'simultaneous' WHEN events = sets THEN 'serial' ELSE 'complex' END AS kind FROM ep WHERE regexp_matches(episode, '(^|[+>])B([+][^>]*)?>(.*[+>])?A[+]C')")


def _events_path(d: str) -> str:
    return f"{d}/events.parquet*"


add("stream_tumbling_utility", lambda s, d: stream.drained(stream.tumbling_utility(stream.source(s, _events_path(d))), "complete"), f"SELECT date_trunc('hour', ts) AS start, event_type AS item, sum({sql.CENTS})::BIGINT AS u FROM events WHERE {sql.CENTS} > 0 GROUP BY 1, 2")
add("stream_session_users", lambda s, d: stream.drained(stream.sessions(stream.source(s, _events_path(d))), "complete"), f"WITH x AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), y AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS n_session FROM x) SELECT user_id, min(ts) AS start, count(*)::BIGINT AS n, sum({sql.CENTS})::BIGINT AS u FROM y GROUP BY user_id, n_session")
_USERS = f"WITH c AS ({sql.CES['users']}), o AS (SELECT a.seq_id, a.t AS ts, b.t AS te, a.u + b.u AS u FROM c a JOIN c b ON a.seq_id = b.seq_id AND b.t > a.t AND b.t <= a.t + 600 WHERE a.item = 'click' AND b.item = 'view'), e AS (SELECT seq_id, ts, min(te) AS te, arg_min(u, te) AS u FROM o GROUP BY seq_id, ts), m AS (SELECT *, lead(te) OVER (PARTITION BY seq_id ORDER BY ts) AS nxt FROM e)"
add("stream_matcher", lambda s, d: stream.drained(stream.matches(stream.source(s, _events_path(d)), CLICK_VIEW, 600), "append"), _USERS + " SELECT seq_id AS user_id, ts, te, u FROM m WHERE nxt IS NULL OR nxt > te")


def _users(s: SparkSession, d: str) -> DataFrame:
    rows = ces.event_rows(s, d, "minute").filter("u > 0").groupBy(F.col("user_id").alias("seq_id"), "t", "item").agg(F.sum("u").alias("u"))
    return with_rank(baselines.mine_sequences(rows, 120, 20, chunk_len=1 << 20).df)


add("multi_sequence_topk_users", _users, sql.top_k(sql.CES["users"], 120, 20, by_sequence=True))


from chronolode import reports  # noqa: E402  its queries use the ones above

QUERIES.update(reports.QUERIES)
ORACLES.update(reports.ORACLES)


def flagship(s: SparkSession, d: str) -> DataFrame:
    return QUERIES["topk_hours_mtd1"](s, d)
