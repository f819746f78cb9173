"""Mixing sources to target weights by weighted fair queueing.

Every copy of a document gets a virtual finish time: the words of its source up to and with it, in shuffled order, divided by the source's target. Copies are range-sorted by that time, over all sources and tasks, and
the sorted list is cut where the total budget is reached. Weights and targets follow the sources in code point order.

All of this is done on narrow rows (source, key, size). As virtual time rises along a source's order, what the cut leaves of a source is a prefix of that order for each copy, so the whole decision is a table of one row a
source: the last key taken, by copy. Documents meet that table and are compared with their source's keys; no text is sorted or shuffled.

Prefix sums never need one task a source: a source's order is cut into buckets by the shuffle key's first digits, buckets are summed and placed on a running sum, and rows are numbered inside their bucket only. After the
global sort a sum for each partition tells in which of them the budget ends; running sums are made inside that partition alone.

Assumption: the table of sources (one row each) fits one task; it holds sums, not rows.

Defined results: a null text has size 0; documents of size 0 and sources of size 0 take nothing; null sources are one source, the last; null ids shuffle as an empty id; rows of one source with the same id and text are
interchangeable, and where the cut falls among them the right number of them is taken; an empty table gives an empty table; extra columns of any name are kept as they are, and texts are read whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronolode.llm.common import BLANK, read, written

#: Weights by the source's place, the budget as halves of all words, copies of a document at most.
WEIGHTS, HALVES, COPIES = (5, 2, 1), 3, 2
#: Rows a bucket of the shuffled order holds on average.
BUCKET_ROWS = 2048
#: The order inside a source: a hash of the id, then what tells rows apart. known is 0 for a null id.
KEY = ["mix_key", "known", "id", "size", "sig"]


def words(text: str = "text") -> Column:
    """Number of runs of anything but ASCII white space."""
    trimmed = F.btrim(F.coalesce(F.col(text), F.lit("")), F.lit(" \t\n\x0b\f\r"))
    return F.when(trimmed == "", 0).otherwise(F.size(F.split(trimmed, f"{BLANK}+"))).cast("long")


def keyed(docs: DataFrame, *payload: Column) -> DataFrame:
    """(source, *KEY, *payload) of every document row."""
    key = {
        "mix_key": F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")),
        "known": F.col("doc_id").isNotNull().cast("int"),
        "id": F.coalesce(F.col("doc_id").cast("long"), F.lit(0)),
        "size": words(),
        "sig": F.xxhash64(F.coalesce(F.col("text"), F.lit(""))),
    }
    return docs.select(F.col("source"), *(key[c].alias(c) for c in KEY), *payload)


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, halves: int = HALVES, copies: int = COPIES) -> DataFrame:
    """(source, n, source_size, target) from rows (source, size). Sources are filled in the order of their limit over their weight."""
    t = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n"))
    place = F.row_number().over(W.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*map(F.lit, weights)), (place % len(weights) + 1).cast("int"))
    big = lambda c: F.col(c).cast("decimal(38,0)")
    by_limit = W.orderBy((big("source_size") / F.col("w")).asc(), F.col("source").asc_nulls_last())
    t = t.withColumn("w", weight).withColumn("limit", F.col("source_size") * copies)
    before = F.coalesce(F.sum("limit").over(by_limit.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    t = t.withColumns({"total": F.sum("source_size").over(W.partitionBy()), "before": before, "left": F.sum("w").over(by_limit.rowsBetween(0, W.unboundedFollowing))})
    full = big("w") * (halves * big("total") - 2 * big("before")) >= 2 * big("limit") * big("left")
    t = t.withColumn("full", full)
    rest = F.sum(F.when(F.col("full"), 0).otherwise(F.col("w"))).over(W.partitionBy())
    filled = F.sum(F.when(F.col("full"), F.col("limit")).otherwise(0)).over(W.partitionBy())
    share = (F.col("w") * (halves * F.col("total") - 2 * filled)).cast("double") / (2 * rest).cast("double")
    return t.select("source", "n", "source_size", F.when(F.col("full"), F.col("limit").cast("double")).otherwise(share).alias("target"))


def finish_times(narrow: DataFrame, sources: DataFrame) -> DataFrame:
    """(source, *KEY, copy, vft): both copies of every document that has words."""
    n = sources.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    digits = next(k for k in range(1, 15) if n <= BUCKET_ROWS * 16**k)
    rows = narrow.withColumn("bucket", F.substring("mix_key", 1, digits))
    sums = rows.groupBy("source", "bucket").agg(F.sum("size").alias("sum"))
    before = F.coalesce(F.sum("sum").over(W.partitionBy("source").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))  # of sums, 16 ** digits a source at most
    at = sums.select(F.col("source").alias("s"), F.col("bucket").alias("b"), before.alias("before"))
    rows = rows.join(at, rows["source"].eqNullSafe(at["s"]) & (rows["bucket"] == at["b"])).drop("s", "b")
    t = sources.select(F.col("source").alias("s"), "source_size", "target")
    rows = rows.join(t, rows["source"].eqNullSafe(t["s"])).drop("s").filter("size > 0 AND target > 0")
    run = F.col("before") + F.sum("size").over(W.partitionBy("source", "bucket").orderBy(*KEY).rowsBetween(W.unboundedPreceding, 0))
    rows = rows.withColumn("run", run).withColumn("copy", F.explode(F.array(*map(F.lit, range(COPIES)))))
    return rows.select("source", *KEY, "copy", ((F.col("run") + F.col("copy") * F.col("source_size")).cast("double") / F.col("target")).alias("vft"))


def truncated(copies: DataFrame, total: int, halves: int = HALVES) -> DataFrame:
    """The copies that fit the budget, in the global order of virtual time."""
    order = [F.col("vft"), F.col("source").asc_nulls_last(), *map(F.col, KEY), F.col("copy")]
    ranged = written(copies.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id()))
    parts = ranged.groupBy("part").agg(F.sum("size").alias("sum"))  # a row for each partition
    parts = parts.withColumn("before", F.coalesce(F.sum("sum").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    over = parts.filter(2 * (F.col("before") + F.col("sum")) > halves * total).orderBy("part").first()
    if over is None:
        return ranged
    last = ranged.filter(F.col("part") == over.part).withColumn("run", F.sum("size").over(W.partitionBy("part").orderBy(*order).rowsBetween(W.unboundedPreceding, 0)) + F.lit(over.before))
    return ranged.filter(F.col("part") < over.part).unionByName(last.filter(2 * F.col("run") <= halves * total).drop("run"))


def boundaries(narrow: DataFrame, halves: int = HALVES) -> DataFrame:
    """(mix_source, source_size, target, last0, among0, split0, last1, among1, split1): by copy, the last key that the mix takes of each source, how many rows of that very key, and whether it leaves others of them."""
    sources = written(targets(narrow, halves=halves))
    total = sources.agg(F.coalesce(F.sum("source_size"), F.lit(0))).first()[0]
    taken = written(truncated(finish_times(narrow, sources), total, halves).select("source", "copy", F.struct(*KEY).alias("key")))
    last = written(taken.groupBy("source", "copy").agg(F.max("key").alias("last"))).select(F.col("source").alias("s"), F.col("copy").alias("c"), "last")
    each = range(COPIES)
    at_last = lambda rows, *more: rows.join(last, rows["source"].eqNullSafe(last["s"]) & (F.col("key") == F.col("last")) & F.lit(True if not more else more[0]))
    among = at_last(taken, F.col("copy") == F.col("c")).groupBy("source").agg(*(x for c in each for x in (F.max(F.when(F.col("c") == c, F.col("last"))).alias(f"last{c}"), F.count(F.when(F.col("c") == c, 1)).alias(f"among{c}"))))
    there = at_last(narrow.select("source", F.struct(*KEY).alias("key"))).groupBy("source").agg(*(F.count(F.when(F.col("c") == c, 1)).alias(f"there{c}") for c in each))
    out = sources.select(F.col("source").alias("mix_source"), "source_size", "target")
    for part, name in ((among, "s1"), (there, "s2")):
        part = part.withColumnRenamed("source", name)
        out = out.join(part, out["mix_source"].eqNullSafe(part[name]), "left").drop(name)
    splits = {f"split{c}": F.coalesce(F.col(f"among{c}") < F.col(f"there{c}"), F.lit(False)) for c in each}
    return written(out.withColumns(splits).drop(*(f"there{c}" for c in each)))


def decided(rows: DataFrame, bounds: DataFrame) -> DataFrame:
    """rows of `keyed` with source_size, target and copies. Only rows of a last key that the cut splits are numbered."""
    each = range(COPIES)
    rows = rows.join(bounds, rows["source"].eqNullSafe(bounds["mix_source"])).drop("mix_source").withColumn("key", F.struct(*KEY))
    count = lambda test: sum((F.when((F.col("size") > 0) & test(c), 1).otherwise(0) for c in each), F.lit(0))
    at = lambda c: F.col("key") == F.col(f"last{c}")
    inside = lambda c: (F.col("key") < F.col(f"last{c}")) | (at(c) & ~F.col(f"split{c}"))
    out = rows.withColumn("copies", count(inside))
    if not bounds.filter(" OR ".join(f"split{c}" for c in each)).isEmpty():
        split = sum((F.coalesce(at(c) & F.col(f"split{c}"), F.lit(False)).cast("int") for c in each), F.lit(0)) > 0
        number = F.row_number().over(W.partitionBy("source", "key").orderBy("sig"))
        among = lambda c: inside(c) | (at(c) & (F.col("number") <= F.col(f"among{c}")))
        out = out.filter(~split).unionByName(rows.filter(split).withColumn("number", number).withColumn("copies", count(among)).drop("number"))
    return out.drop("key", *(f"{x}{c}" for c in each for x in ("last", "among", "split")))


def mix(docs: DataFrame, halves: int = HALVES) -> DataFrame:
    """(doc_id, source, size, source_size, target, copies, taken) of every document row."""
    narrow = written(keyed(docs))
    out = decided(narrow, boundaries(narrow, halves))
    doc_id = F.when(F.col("known") == 1, F.col("id")).cast(docs.schema["doc_id"].dataType)
    return out.select(doc_id.alias("doc_id"), "source", "size", "source_size", "target", "copies", (F.col("size") * F.col("copies")).alias("taken"))


def mixed_documents(docs: DataFrame, halves: int = HALVES) -> DataFrame:
    """The mix itself: each document as often as it was taken, with all its columns."""
    bounds = boundaries(written(keyed(docs)), halves)
    whole = F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row")
    out = decided(keyed(docs, whole), bounds).filter("copies > 0").select("row", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy"))
    return out.select(*(F.col("row").getField(c).alias(c) for c in docs.columns))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "source", "text")
    return mix(docs).select("doc_id", "size", "source_size", "target", "taken")


ORACLE = r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size, md5(coalesce(doc_id::VARCHAR, '')) AS k FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size, (ARRAY[5, 2, 1])[1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3] AS w FROM d GROUP BY source),
o AS (SELECT *, 2 * source_size AS lim, sum(source_size) OVER ()::BIGINT AS total,
    coalesce(sum(2 * source_size) OVER (ORDER BY source_size * 10 // w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::HUGEINT AS before,
    sum(w) OVER (ORDER BY source_size * 10 // w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)::HUGEINT AS rest FROM s),
f AS (SELECT *, w * (3 * total::HUGEINT - 2 * before) >= 2 * lim::HUGEINT * rest AS full_up FROM o),
t AS (SELECT source, source_size, total, CASE WHEN full_up THEN lim::DOUBLE ELSE (w * (3 * total - 2 * sum(CASE WHEN full_up THEN lim ELSE 0 END) OVER ()))::DOUBLE / (2 * sum(CASE WHEN full_up THEN 0 ELSE w END) OVER ())::DOUBLE END AS target FROM f),
c AS (SELECT d.*, source_size, total, target, sum(size) OVER (PARTITION BY d.source ORDER BY k, doc_id NULLS FIRST, size ROWS UNBOUNDED PRECEDING)::BIGINT AS run FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
v AS (SELECT *, e, (run + e * source_size)::DOUBLE / target AS vft FROM c, (VALUES (0), (1)) AS x(e) WHERE size > 0),
q AS (SELECT doc_id, source, size, k, e, 2 * sum(size) OVER (ORDER BY vft, source NULLS LAST, k, doc_id NULLS FIRST, size, e)::BIGINT <= 3 * total AS taken FROM v),
n AS (SELECT doc_id, source, size, sum(CASE WHEN taken THEN size ELSE 0 END)::BIGINT AS taken FROM q GROUP BY ALL)
SELECT c.doc_id, c.size::BIGINT AS size, c.source_size, c.target, coalesce(n.taken, 0)::BIGINT AS taken
FROM c LEFT JOIN n ON c.doc_id IS NOT DISTINCT FROM n.doc_id AND c.source IS NOT DISTINCT FROM n.source AND c.size = n.size
"""
