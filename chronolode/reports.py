"""Further queries: measures of the compared methods over their parameters, sequences of the experiments, and the operators that users of results need, with the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode import oracle as sql
from chronolode.functions import model, udf
from chronolode.operators import occurrence, raising
from chronolode.operators.windows import arrays, build
from chronolode.plans import baselines, metrics
from chronolode.plans.miner import mine_threshold, mine_top_k
from chronolode.plans.storage import folder, written
from chronolode.sources import ces
from chronolode.streaming import stream

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
HOURS, MINUTES, ORDERS = (sql.CES[x] for x in ("hours", "minutes", "orders"))
COLUMNS = ["episode", "events", "sets", "utility", "frequency", "rank"]


def add(name: str, query: Callable[[SparkSession, str], DataFrame], oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


# Measures of the compared methods.
def _initial(s: SparkSession, d: str) -> DataFrame:
    rows = ces.order_parts(s, d)
    return s.createDataFrame([(v, k, raising.initial(rows, k, settings.get("raise_", baselines.ALL))) for v, settings in baselines.VARIANTS.items() for k in (500, 1500, 3000)], "variant string, k int, initial_min_util long")


_LISTS = {
    True: f"SELECT utility FROM (SELECT sum(u) AS utility FROM ({ORDERS}) GROUP BY item) UNION ALL SELECT utility FROM ({sql.sets(ORDERS)} SELECT utility FROM d)",
    False: f"SELECT utility FROM ({sql.sets(ORDERS)} SELECT utility FROM d)",
}
add("initial_thresholds_by_variant", _initial, " UNION ALL ".join(f"SELECT '{v}' AS variant, k, min_util AS initial_min_util FROM ({sql.kth(_LISTS['event' in x.get('raise_', baselines.ALL)], k)})" for v, x in baselines.VARIANTS.items() for k in (500, 1500, 3000)))

_MTDS = (2, 3, 4, 5, 6)
add("mtd_sweep_thresholds", lambda s, d: metrics.sweep(s, ces.event_minutes(s, d), ("full", "prior_top_k"), (50,), _MTDS, at_once=5).select("variant", "mtd", "end_min_util"), " UNION ALL ".join(f"SELECT '{v}' AS variant, {m}::INTEGER AS mtd, coalesce((SELECT utility FROM ({sql.top_k(MINUTES, m, 50)}) WHERE rank = 50), 0) AS end_min_util" for v in ("full", "prior_top_k") for m in _MTDS))

_RATIOS = (10, 15, 20, 25, 30, 35, 40, 45)


def _ratios(s: SparkSession, d: str) -> DataFrame:
    """Episodes that reach a share of the whole utility, by both bounds: one run at the least share holds those of all."""
    rows = ces.event_hours(s, d)
    total, out = rows.agg(F.sum("u")).first()[0], None
    for bound in ("remaining", "raw"):
        found = mine_threshold(rows, 1, min_util_ratio=_RATIOS[0] / 100, bound=bound).select("utility")
        counts = [F.count(F.when(F.col("utility") * 100 >= p * total, 1)).alias(str(p)) for p in _RATIOS]
        row = found.agg(*counts).select(F.lit(bound).alias("bound"), F.explode(F.array(*(F.struct(F.lit(p).alias("percent"), F.col(str(p)).alias("episodes")) for p in _RATIOS))).alias("x")).select("bound", "x.*")
        out = row if out is None else out.unionByName(row)
    return out


add("hue_ratio_sweep_hours", _ratios, f"{sql.enumerated(HOURS, 1)}, r AS (SELECT unnest({list(_RATIOS)}) AS percent) SELECT bound, percent::INTEGER AS percent, (SELECT count(*) FROM ep WHERE utility * 100 >= percent * (SELECT sum(u) FROM ces))::BIGINT AS episodes FROM r, (VALUES ('remaining'), ('raw')) AS b(bound)")


def _span_order(s: SparkSession, d: str) -> DataFrame:
    """Growing in a set first, or after it first: the same answer, other counts."""
    rows = written(ces.event_minutes(s, d))
    runs = [(first, mine_top_k(rows, 3, 50, first=first, strategy="dfs_single", window_raise=False, prepared=True)) for first in ("I", "S")]
    return s.createDataFrame([(f, r.end_min_util, r.candidates["generated"], r.candidates["buffered"]) for f, r in runs], "first string, end_min_util long, generated long, buffered long")


add("span_order_counts", _span_order)
add("span_order_thresholds", lambda s, d: _span_order(s, d).select("first", "end_min_util"), " UNION ALL ".join(f"SELECT '{f}' AS first, coalesce((SELECT utility FROM ({sql.top_k(MINUTES, 3, 50)}) WHERE rank = 50), 0) AS end_min_util" for f in "IS"))


def _raise_gain(s: SparkSession, d: str) -> DataFrame:
    """Initial over end threshold, in hundredths; null where there are not as many episodes as the end threshold is of."""
    r = baselines.variant("full", ces.event_minutes(s, d), 2, 20)
    end = (r.end_min_util, int(metrics.raise_gain(r) * 100)) if r.end_min_util else (None, None)
    return s.createDataFrame([(r.initial_min_util, *end)], "initial_min_util long, end_min_util long, gain_x100 int")


_BOTH = f"SELECT utility FROM (SELECT sum(u) AS utility FROM ({MINUTES}) GROUP BY item) UNION ALL SELECT utility FROM ({sql.sets(MINUTES)} SELECT utility FROM d)"
add("raise_gain_minutes", _raise_gain, f"SELECT i AS initial_min_util, e AS end_min_util, floor(i * 100 / e)::INTEGER AS gain_x100 FROM (SELECT (SELECT min_util FROM ({sql.kth(_BOTH, 20)})) AS i, (SELECT utility FROM ({sql.top_k(MINUTES, 2, 20)}) WHERE rank = 20) AS e)")


def _exactness(s: SparkSession, d: str) -> DataFrame:
    rows = ces.event_hours(s, d)
    truth = baselines.exhaustive(rows, 1).orderBy(F.desc("utility"), "episode").limit(20)
    found = [(v, metrics.exactness(baselines.variant(v, rows, 1, 20).df, truth)) for v in baselines.VARIANTS]
    return s.createDataFrame([(v, x["recall"], int(x["wrong"])) for v, x in found], "variant string, recall double, wrong int")


add("exactness_by_variant", _exactness, " UNION ALL ".join(f"SELECT '{v}' AS variant, 1.0::DOUBLE AS recall, 0::INTEGER AS wrong" for v in baselines.VARIANTS))


def _costs(s: SparkSession, d: str) -> DataFrame:
    """Shuffled and spilled bytes and CPU of one mining run by each strategy, and peaks of memory."""
    rows, out = ces.event_hours(s, d), []
    for strategy in ("levelwise", "prefix_dfs", "dfs_single"):
        before = metrics.stage_costs(s)["last"]
        metrics.reset_memory(s)
        mine_top_k(rows, 1, 20, strategy=strategy)
        costs, peak = metrics.stage_costs(s, before), metrics.memory(s)
        out.append((strategy, costs["stages"], costs["shuffle_bytes"], costs["spill_bytes"], costs["cpu_ms"], peak["jvm_peak_mb"], peak["executor_peak_mb"]))
    return s.createDataFrame(out, "strategy string, stages int, shuffle_bytes long, spill_bytes long, cpu_ms long, jvm_peak_mb long, executor_peak_mb long")


add("run_costs_by_strategy", _costs)

# Sequences of the experiments.
for _name, _make in (("retail", ces.retail), ("dense_suppliers", ces.dense_suppliers), ("chain", ces.chain)):
    add(f"ces_{_name}", _make)
_GROUPS = {"retail": (4, 5, "l_partkey"), "dense_suppliers": (2, 5, "l_suppkey"), "chain": (4, 7, "l_partkey || l_returnflag")}


def _shapes(s: SparkSession, d: str) -> DataFrame:
    out = None
    for name in _GROUPS:
        row = ces.characteristics({"retail": ces.retail, "dense_suppliers": ces.dense_suppliers, "chain": ces.chain}[name](s, d)).select(F.lit(name).alias("name"), "transactions", "items")
        out = row if out is None else out.unionByName(row)
    return out


add("experiment_sequence_shapes", _shapes, " UNION ALL ".join(f"SELECT '{n}' AS name, count(DISTINCT t)::BIGINT AS transactions, count(DISTINCT item)::BIGINT AS items FROM (SELECT dense_rank() OVER (ORDER BY l_orderkey * {a} // {b}) AS t, ({x})::VARCHAR AS item FROM lineitem) WHERE t <= 10000" for n, (a, b, x) in _GROUPS.items()))


def _profile(s: SparkSession, d: str) -> DataFrame:
    """Simulated utilities by what does not depend on the hash: rows, items, ranges, one unit value an item."""
    rows = ces.simulate(ces.order_parts(s, d).select("t", "item"))
    items = rows.groupBy("item").agg(F.countDistinct("p").alias("p"))
    own = rows.agg(F.count("*").alias("n"), F.countDistinct("item").alias("items"), ((F.min("q") == 1) & (F.max("q") == 5)).alias("counts_ok"), ((F.min("p") >= 1) & (F.max("p") <= 1000)).alias("prices_ok"), F.bool_and(F.col("u") == F.col("q") * F.col("p")).alias("product_ok"))
    return own.join(items.agg((F.max("p") == 1).alias("one_price_an_item")))  # one row each


add("simulated_utilities_profile", _profile, f"SELECT count(*)::BIGINT AS n, count(DISTINCT item)::BIGINT AS items, TRUE AS counts_ok, TRUE AS prices_ok, TRUE AS product_ok, TRUE AS one_price_an_item FROM ({ORDERS})")

# Kinds of episodes.
_COMPLEX = sql.enumerated(HOURS, 1) + "SELECT episode, events, sets, utility, frequency, rank::INTEGER AS rank FROM (SELECT *, row_number() OVER (ORDER BY utility DESC, episode) AS rank FROM ep WHERE sets > 1 AND events > sets) WHERE rank <= 20"
add("topk_complex_only", lambda s, d: mine_top_k(ces.event_hours(s, d), 1, 20, kinds="complex").df.select(*COLUMNS), _COMPLEX)
add("topk_complex_levelwise", lambda s, d: mine_top_k(ces.event_hours(s, d), 1, 20, kinds="complex", strategy="levelwise").df.select(*COLUMNS), _COMPLEX)
_PARALLEL = f"WITH c AS ({MINUTES}), o AS (SELECT least(a.t, b.t) AS ts, greatest(a.t, b.t) AS te, a.u + b.u AS u FROM c a JOIN c b ON b.t BETWEEN a.t - 3 AND a.t + 3 WHERE a.item = 'click' AND b.item = 'view'), m AS (SELECT * FROM o x WHERE NOT EXISTS (SELECT 1 FROM o y WHERE y.ts >= x.ts AND y.te <= x.te AND (y.ts > x.ts OR y.te < x.te)))"
add("parallel_click_view", lambda s, d: occurrence.parallel(ces.event_minutes(s, d), ("click", "view"), 3), _PARALLEL + " SELECT ts, te, u::BIGINT AS u FROM m")
add("set_utility_hours", lambda s, d: occurrence.set_utility(ces.event_hours(s, d), ("click", "view")), f"SELECT t, sum(u)::BIGINT AS u FROM ({HOURS}) WHERE item IN ('click', 'view') GROUP BY t HAVING count(*) = 2")
_CV6 = sql.pair_occurrences(MINUTES, 6, "click", "view")
add("occurrences_within", lambda s, d: occurrence.within(occurrence.occ_set(ces.event_minutes(s, d), (("click",), ("view",)), 6), 3).select("ts", "te"), _CV6 + "SELECT ts, te FROM o WHERE te - ts <= 3")


def _grown(s: SparkSession, d: str) -> DataFrame:
    """Both ways to extend each event type by view, as built-in expressions over arrays."""
    one = ces.event_minutes(s, d).select("item").distinct().withColumn("e", F.array(F.array("item")))
    text = lambda e: F.array_join(F.transform(e, lambda x: F.array_join(x, "+")), ">")
    same, after = model.i_extend_column(F.col("e"), F.lit("view")), model.s_extend_column(F.col("e"), F.lit("view"))
    return one.filter("item <> 'view'").select("item", text(same).alias("same"), text(after).alias("after"), model.length_column(after).alias("events"))


add("concatenations_example", _grown, f"SELECT DISTINCT item, least(item, 'view') || '+' || greatest(item, 'view') AS same, item || '>view' AS after, 2::INTEGER AS events FROM ({MINUTES}) WHERE item <> 'view'")

# Operators on sequences and results.
add("event_gaps_minutes", lambda s, d: occurrence.gaps(ces.event_minutes(s, d), 512), f"SELECT item, t, (t - lag(t) OVER (PARTITION BY item ORDER BY t))::BIGINT AS gap FROM ({MINUTES})")


def _ranked(s: SparkSession, d: str) -> DataFrame:
    """Items by utility: a window over a table of one row an item."""
    from pyspark.sql import Window as W

    by = W.orderBy(F.desc("utility"), "item")
    rows = raising.event_list(ces.order_parts(s, d))
    return rows.select("item", F.dense_rank().over(W.orderBy(F.desc("utility"))).alias("dense"), F.floor(F.percent_rank().over(by) * 1000).cast("int").alias("permille"), F.ntile(10).over(by).alias("tenth"))


add("item_ranks", _ranked, f"SELECT item, (dense_rank() OVER (ORDER BY utility DESC))::INTEGER AS dense, floor(percent_rank() OVER (ORDER BY utility DESC, item) * 1000)::INTEGER AS permille, (ntile(10) OVER (ORDER BY utility DESC, item))::INTEGER AS tenth FROM (SELECT item, sum(u)::BIGINT AS utility FROM ({ORDERS}) GROUP BY item)")
add("grouping_sets_item_day", lambda s, d: ces.event_hours(s, d).withColumn("day", F.floor((F.col("t") - 1) / 24).cast("long")).groupingSets([("item", "day"), ("item",), ()], "item", "day").agg(F.sum("u").cast("long").alias("utility"), F.grouping_id().cast("int").alias("level")), f"SELECT item, day, sum(u)::BIGINT AS utility, grouping(item, day)::INTEGER AS level FROM (SELECT *, (t - 1) // 24 AS day FROM ({HOURS})) GROUP BY GROUPING SETS ((item, day), (item), ())")


def _maps(s: SparkSession, d: str) -> DataFrame:
    rows = ces.event_hours(s, d).groupBy("t").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("item", "u")))).alias("m"))
    return rows.select("t", F.array_join(F.map_keys("m"), "+").alias("set_key"), F.element_at("m", F.lit("click")).alias("u_click"), F.size(F.map_filter("m", lambda _, u: u >= 10_000)).alias("large"))


add("sets_as_maps", _maps, f"SELECT t, string_agg(item, '+' ORDER BY item) AS set_key, max(CASE WHEN item = 'click' THEN u END) AS u_click, count(CASE WHEN u >= 10000 THEN 1 END)::INTEGER AS large FROM ({HOURS}) GROUP BY t")


def _planning(s: SparkSession, d: str) -> DataFrame:
    """Approximate counts and quantiles, as used to plan for skew, beside the exact ones."""
    rows = ces.order_parts(s, d)
    exact, near = F.countDistinct("item"), F.approx_count_distinct("item", 0.02)
    rows = rows.join(rows.agg(F.percentile_approx("u", 0.5, 1000).alias("middle")))  # one row
    below = lambda test: F.avg(test.cast("double"))
    return rows.agg(exact.alias("items"), (F.abs(near / exact - 1) <= 0.1).alias("distinct_near"), ((below(F.col("u") <= F.col("middle")) >= 0.49) & (below(F.col("u") < F.col("middle")) <= 0.51)).alias("median_near"))


add("approximate_planning", _planning, f"SELECT count(DISTINCT item)::BIGINT AS items, TRUE AS distinct_near, TRUE AS median_near FROM ({ORDERS})")


def _theta(s: SparkSession, d: str) -> DataFrame:
    """Serial pairs of the hours by a range condition; blocks of three hours, of which a pair's first event looks into the one or two ahead, keep it from comparing all with all."""
    a, b = (ces.event_hours(s, d).select(F.col("t").alias(f"t{x}"), F.col("item").alias(f"item{x}")) for x in "ab")
    a = a.withColumn("block", F.explode(F.sequence(F.floor((F.col("ta") + 1) / 3), F.floor((F.col("ta") + 2) / 3))))
    b = b.withColumn("block", F.floor(F.col("tb") / 3))
    return a.join(b, "block").filter((F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + 2)).select(F.concat("itema", F.lit(">"), "itemb").alias("episode"), F.col("ta").alias("ts"), F.col("tb").alias("te"))


add("theta_pairs_example", _theta, f"WITH c AS ({HOURS}) SELECT a.item || '>' || b.item AS episode, a.t AS ts, b.t AS te FROM c a JOIN c b ON b.t > a.t AND b.t <= a.t + 2")
add("episode_search_hours", lambda s, d: mine_threshold(ces.event_hours(s, d), 1, min_util=5_000_000).filter(F.col("episode").rlike(r"(^|[+>])purchase([+>]|$)")).select("episode", "utility"), sql.enumerated(HOURS, 1) + "SELECT episode, utility FROM ep WHERE utility >= 5000000 AND regexp_matches(episode, '(^|[+>])purchase([+>]|$)')")


def _ids(s: SparkSession, d: str) -> DataFrame:
    """Hashes as short names of episodes, with the guard that no two episodes share one; and episodes as JSON."""
    rows = mine_threshold(ces.event_hours(s, d), 1, min_util=5_000_000).withColumn("id", F.xxhash64("episode"))
    sets = F.transform(F.split("episode", ">"), lambda x: F.split(x, r"\+"))
    shared = rows.groupBy("id").agg(F.count_distinct("episode").alias("n")).select("id", (F.col("n") > 1).alias("shared"))
    return rows.join(shared, "id").select("episode", F.to_json(sets).alias("json"), "shared")


add("episode_ids_and_json", _ids, sql.enumerated(HOURS, 1) + """SELECT episode, '[["' || replace(replace(episode, '>', '"],["'), '+', '","') || '"]]' AS json, FALSE AS shared FROM ep WHERE utility >= 5000000""")
add("kth_largest_by_item", lambda s, d: ces.event_hours(s, d).groupBy("item").agg(udf.kth_largest_udf(3)("u").alias("third")), f"SELECT item, CASE WHEN count(*) >= 3 THEN list_sort(list(u), 'DESC')[3] ELSE 0 END AS third FROM ({HOURS}) GROUP BY item")


def _extended(s: SparkSession, d: str) -> DataFrame:
    """Every extension by one event of every event of an hour, within an hour, by the table function over windows."""
    udf.register(s)
    index = arrays(build(ces.event_hours(s, d), 1)).withColumn("e", F.explode(F.slice("items", F.lit(1), F.col("head"))))
    index = index.select("ts", model.escaped_column(F.col("e")).alias("e"), F.slice("items", F.lit(1), F.col("head")).alias("same"), F.slice("items", F.col("head") + 1, F.size("items")).alias("later"))
    return s.sql("SELECT w.ts, x.episode FROM {w} w, LATERAL extend_episode(w.e, w.same, w.later) x", w=index)


add("udtf_extend_episode", _extended, f"WITH c AS ({HOURS}) SELECT a.t AS ts, a.item || '+' || b.item AS episode FROM c a JOIN c b ON b.t = a.t AND b.item > a.item UNION ALL SELECT a.t, a.item || '>' || b.item FROM c a JOIN c b ON b.t = a.t + 1")


def _sinks(s: SparkSession, d: str) -> DataFrame:
    """A result written in each format and read back."""
    best, out = mine_top_k(ces.event_hours(s, d), 1, 20).df.select(*COLUMNS), None
    for fmt in ("parquet", "orc", "csv", "json"):
        path = folder(s)
        ces.write_result(best, path, fmt)
        rows = ces.read_result(s, path, best.schema, fmt).withColumn("fmt", F.lit(fmt))
        out = rows if out is None else out.unionByName(rows)
    return out


add("result_sinks", _sinks, f"SELECT *, unnest(['parquet', 'orc', 'csv', 'json']) AS fmt FROM ({sql.top_k(HOURS, 1, 20)})")


def _log(s: SparkSession, d: str) -> DataFrame:
    """Events written as JSON lines and ORC, and read back as logs with expressions for time, event and utility."""
    rows, out = ces.load(s, d, "events").select(F.col("ts").cast("string").alias("at"), "event_type", "value"), None
    for fmt in ("json", "orc"):
        path = folder(s)
        rows.write.format(fmt).save(path)
        t = "CAST(floor(timestampdiff(SECOND, TIMESTAMP_NTZ '2024-01-01 00:00:00', CAST(at AS TIMESTAMP_NTZ)) / 3600) + 1 AS BIGINT)"
        log = ces.read_log(s, fmt, path, "at string, event_type string, value double", t, "event_type", "CAST(round(value * 100) AS BIGINT)").withColumn("fmt", F.lit(fmt))
        out = log if out is None else out.unionByName(log)
    return out


add("event_logs", _log, f"SELECT t, item, u, unnest(['json', 'orc']) AS fmt FROM ({HOURS})")


# Streams.
def _events(s: SparkSession, d: str) -> DataFrame:
    return stream.source(s, f"{d}/events.parquet*")


add("stream_dedup_events", lambda s, d: stream.drained(stream.deduplicated(_events(s, d).unionByName(_events(s, d))).select("event_id", "event_type"), "append"), "SELECT event_id, event_type FROM events")
add("stream_sliding_utility", lambda s, d: stream.drained(stream.tumbling_utility(_events(s, d), "1 hour", "30 minutes"), "complete"), f"SELECT time_bucket(INTERVAL 30 MINUTE, ts) - x * INTERVAL 30 MINUTE AS start, event_type AS item, sum({sql.CENTS})::BIGINT AS u FROM events, (VALUES (0), (1)) AS h(x) WHERE {sql.CENTS} > 0 GROUP BY 1, 2")
_UNITS = [("click", 2.0), ("view", 0.5), ("purchase", 10.0)]
add("stream_static_weights", lambda s, d: stream.drained(stream.weighted(_events(s, d), s.createDataFrame(_UNITS, "event_type string, unit double"), "event_type", "unit").select("event_id", "u"), "append"), f"SELECT event_id, round(value * unit * 100)::BIGINT AS u FROM events JOIN (VALUES {', '.join(map(str, _UNITS))}) AS x(kind, unit) ON event_type = kind")
add("stream_remine_hours", lambda s, d: stream.remined(_events(s, d), 1, 20), f"SELECT 0::BIGINT AS batch, episode, utility, frequency, rank FROM ({sql.top_k(HOURS, 1, 20)})")
