"""Complex event sequences: rows (t, item, u), unique on (t, item), made from the given tables, files or literals.

u is in whole cents (a long), so that sums do not depend on their order. Two clocks give t: ordinal numbers of transactions, and calendar units from an origin.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

CES = T.StructType([T.StructField("t", T.LongType(), False), T.StructField("item", T.StringType(), False), T.StructField("u", T.LongType(), False)])
#: Start of the calendar clocks.
ORIGIN = "2024-01-01 00:00:00"
UNITS = {"minute": 60, "hour": 3600, "day": 86400}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def from_rows(spark: SparkSession, rows: Iterable[tuple[int, str, int]]) -> DataFrame:
    """A literal sequence."""
    return spark.createDataFrame([(int(t), str(i), int(u)) for t, i, u in rows], CES)


def cents(value: Column) -> Column:
    return F.round(value * 100).cast("long")


def weighted(fact: DataFrame, dim: DataFrame, key: str, internal: str, external: Column) -> DataFrame:
    """fact with u: internal count times external unit value. The dimension is broadcast only if Spark's own size estimate allows it."""
    return fact.join(dim, key).withColumn("u", (F.col(internal).cast("long") * external).cast("long"))


def simultaneous(rows: DataFrame) -> DataFrame:
    """Rows (t, item, u) with repeats of an item at one time summed; null and non-positive utilities are left out."""
    kept = rows.filter(F.col("t").isNotNull() & F.col("item").isNotNull() & (F.col("u") > 0))
    return kept.groupBy(F.col("t").cast("long").alias("t"), F.col("item").cast("string").alias("item")).agg(F.sum("u").cast("long").alias("u"))


def sets(ces: DataFrame) -> DataFrame:
    """(t, items): one sorted set a time."""
    return ces.groupBy("t").agg(F.array_sort(F.collect_list(F.struct("item", "u"))).alias("items"))


def ordinal_clock(keys: DataFrame, *order: str) -> DataFrame:
    """keys with t = 1..n in the order of the columns, which must be a key.

    Two passes, no window over all rows: keys are range-partitioned and counted in each of the ranges, then numbered inside them on top of the counts before."""
    ranged = keys.select(*order).distinct().repartitionByRange(*order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id())
    from chronolode.plans.storage import written

    ranged = written(ranged)
    counts = ranged.groupBy("part").agg(F.count("*").alias("n"))  # a row for each partition
    offsets = counts.withColumn("offset", F.coalesce(F.sum("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    numbered = ranged.join(F.broadcast(offsets), "part")
    return numbered.withColumn("t", F.row_number().over(W.partitionBy("part").orderBy(*order)) + F.col("offset")).select(*order, F.col("t").cast("long").alias("t"))


def calendar_clock(ts: Column, unit: str, origin: str = ORIGIN) -> Column:
    """Whole units since the origin, from 1."""
    seconds = F.timestamp_diff("SECOND", F.lit(origin).cast("timestamp_ntz"), ts)
    return (F.floor(seconds / UNITS[unit]) + 1).cast("long")


def first_n(ces: DataFrame, n: int) -> DataFrame:
    return ces.filter(F.col("t") <= n)


def absolute(rows: DataFrame) -> DataFrame:
    return rows.withColumn("u", F.abs("u"))


def _uniform(seed: int, *keys: str) -> Column:
    """A number in (0, 1) that depends on the keys and the seed only."""
    return (F.pmod(F.xxhash64(F.lit(seed), *keys), F.lit(1 << 40)) + 0.5) / float(1 << 40)


def simulate(rows: DataFrame, seed: int = 42) -> DataFrame:
    """(t, item, q, p, u): q uniform in 1..5 for each row, p log-normal between 1 and 1000 for each item (median 20)."""
    normal = F.sqrt(-2 * F.log(_uniform(seed, "item"))) * F.cos(6.283185307179586 * _uniform(seed + 1, "item"))
    p = F.round(F.least(F.greatest(F.exp(F.lit(3.0) + normal), F.lit(1.0)), F.lit(1000.0))).cast("long")
    q = (F.floor(_uniform(seed + 2, "t", "item") * 5) + 1).cast("long")
    return rows.select("t", "item", q.alias("q"), p.alias("p"), (q * p).alias("u"))


def validate(ces: DataFrame) -> DataFrame:
    """(problem, n) of rows that break the model: nulls, times below 1, utilities below 1, repeated (t, item). Empty if all is well."""
    flags = F.when(F.col("t").isNull() | F.col("item").isNull() | F.col("u").isNull(), "null").when(F.col("t") < 1, "time").when(F.col("u") < 1, "utility")
    single = ces.select(flags.alias("problem")).filter("problem IS NOT NULL").groupBy("problem").agg(F.count("*").alias("n"))
    repeats = ces.groupBy("t", "item").agg(F.count("*").alias("c")).filter("c > 1").agg(F.sum("c").alias("n")).filter("n > 0").select(F.lit("repeated").alias("problem"), "n")
    return single.union(repeats)


def characteristics(ces: DataFrame) -> DataFrame:
    """(transactions, avg_len_x100, items): distinct times, mean set size in hundredths, distinct items."""
    by_t = ces.groupBy("t").agg(F.count("*").alias("len")).agg(F.count("*").alias("transactions"), F.sum("len").alias("rows"))
    return by_t.crossJoin(ces.agg(F.countDistinct("item").alias("items"))).select("transactions", F.floor(F.col("rows") * 100 / F.col("transactions")).cast("long").alias("avg_len_x100"), "items")  # one row each


def read_transactions(spark: SparkSession, path: str) -> DataFrame:
    """Text of a transaction a line, `items:total:utilities` with blanks between entries; t is the line's number in the order of file and offset."""
    lines = spark.read.text(path).select("value", F.col("_metadata.file_path").alias("file"), F.monotonically_increasing_id().alias("at")).filter(F.length(F.trim("value")) > 0)
    lines = lines.join(ordinal_clock(lines, "file", "at"), ["file", "at"])
    parts = F.split("value", ":")
    pairs = lines.select("t", F.explode(F.arrays_zip(F.split(F.trim(parts[0]), " +").alias("item"), F.split(F.trim(parts[2]), " +").alias("u"))).alias("x"))
    return simultaneous(pairs.select("t", F.col("x.item").alias("item"), F.abs(F.col("x.u").cast("long")).alias("u")))


def read_log(spark: SparkSession, fmt: str, path: str, schema: str, t: str, item: str, u: str, **options: str) -> DataFrame:
    """Event logs in CSV, JSON, ORC or Parquet; t, item and u are SQL expressions over their columns."""
    rows = spark.read.format(fmt).schema(schema).options(**options).load(path)
    return simultaneous(rows.select(F.expr(t).alias("t"), F.expr(item).alias("item"), F.expr(u).alias("u")))


def write(ces: DataFrame, path: str, span: int = 1 << 16) -> None:
    """Parquet, partitioned by ranges of t, sorted by (t, item) inside: reads of a time range touch its files only."""
    ranged = ces.withColumn("t_range", F.floor(F.col("t") / span))
    ranged.repartition("t_range").sortWithinPartitions("t", "item").write.partitionBy("t_range").parquet(path)


def write_result(rows: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Result rows as Parquet, ORC, CSV with a header, or JSON lines; CSV and JSON in the order of rank if there is one."""
    if fmt not in ("parquet", "orc", "csv", "json"):
        raise ValueError(f"fmt: {fmt}")
    rows = rows.sortWithinPartitions("rank") if "rank" in rows.columns else rows
    rows.write.format(fmt).options(**({"header": "true"} if fmt == "csv" else {})).save(path)


def read_result(spark: SparkSession, path: str, schema: T.StructType, fmt: str = "parquet") -> DataFrame:
    return spark.read.format(fmt).schema(schema).options(**({"header": "true"} if fmt == "csv" else {})).load(path)


def event_rows(spark: SparkSession, sf_dir: str, unit: str) -> DataFrame:
    e = load(spark, sf_dir, "events").select("ts", "event_type", "value", "user_id")
    return e.select(calendar_clock(F.col("ts"), unit).alias("t"), F.col("event_type").alias("item"), cents(F.col("value")).alias("u"), "user_id")


def event_hours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simultaneous(event_rows(spark, sf_dir, "hour").drop("user_id"))


def event_minutes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simultaneous(event_rows(spark, sf_dir, "minute").drop("user_id"))


def props_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hours, with the number k in the events' properties as utility."""
    e = load(spark, sf_dir, "events").select("ts", "event_type", "props")
    return simultaneous(e.select(calendar_clock(F.col("ts"), "hour").alias("t"), F.col("event_type").alias("item"), F.get_json_object("props", "$.k").cast("long").alias("u")))


def order_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("p_partkey"), "l_quantity")
    part = load(spark, sf_dir, "part").select("p_partkey", "p_retailprice")
    rows = weighted(items, part, "p_partkey", "l_quantity", cents(F.col("p_retailprice")))
    return simultaneous(rows.select((F.col("l_orderkey") + 1).alias("t"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("item"), "u"))


def brand_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Days from the first order date, brands, revenue."""
    items = load(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), F.col("l_partkey").alias("p_partkey"), "l_extendedprice")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate")
    part = load(spark, sf_dir, "part").select("p_partkey", "p_brand")
    rows = items.join(orders, "o_orderkey").join(part, "p_partkey")
    return simultaneous(rows.select(calendar_clock(F.col("o_orderdate"), "day", "1995-01-01 00:00:00").alias("t"), F.col("p_brand").alias("item"), cents(F.col("l_extendedprice")).alias("u")))


def _regrouped(spark: SparkSession, sf_dir: str, up: int, down: int, n: int, columns: list[str]) -> DataFrame:
    """The first n transactions of lineitem with orders regrouped to another mean length."""
    items = load(spark, sf_dir, "lineitem").select(F.floor(F.col("l_orderkey") * up / down).cast("long").alias("g"), *columns)
    return items.join(ordinal_clock(items, "g").filter(F.col("t") <= n), "g")


def retail(spark: SparkSession, sf_dir: str, n: int = 10_000) -> DataFrame:
    rows = _regrouped(spark, sf_dir, 4, 5, n, ["l_partkey"]).select("t", F.lpad(F.col("l_partkey").cast("string"), 8, "0").alias("item")).distinct()
    return simulate(rows).select("t", "item", "u")


def dense_suppliers(spark: SparkSession, sf_dir: str, n: int = 10_000) -> DataFrame:
    rows = _regrouped(spark, sf_dir, 2, 5, n, ["l_suppkey", "l_extendedprice"])
    return simultaneous(absolute(rows.select("t", F.lpad(F.col("l_suppkey").cast("string"), 6, "0").alias("item"), cents(F.col("l_extendedprice")).alias("u"))))


def chain(spark: SparkSession, sf_dir: str, n: int = 10_000) -> DataFrame:
    rows = _regrouped(spark, sf_dir, 4, 7, n, ["l_partkey", "l_returnflag"])
    rows = rows.select("t", F.concat(F.lpad(F.col("l_partkey").cast("string"), 8, "0"), F.col("l_returnflag")).alias("item")).distinct()
    return simulate(rows).select("t", "item", "u")


#: The worked example: five times, four events.
EXAMPLE = [(1, "A", 2), (2, "B", 2), (2, "D", 2), (3, "B", 3), (3, "C", 3), (4, "A", 4), (4, "C", 3), (5, "D", 2)]


def example(spark: SparkSession, sf_dir: str = "") -> DataFrame:
    return from_rows(spark, EXAMPLE)


def transaction_utility(ces: DataFrame) -> DataFrame:
    return ces.groupBy("t").agg(F.sum("u").cast("long").alias("tu"))


def total_utility(ces: DataFrame) -> DataFrame:
    return ces.agg(F.coalesce(F.sum("u"), F.lit(0)).cast("long").alias("tu_total"))
