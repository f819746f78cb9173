"""What the operators share: readers, the shared folder for written tables, and word rules."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode.plans.storage import folder, written  # noqa: F401  part of this surface

#: Fixed values of the word rule: everything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"
#: ASCII white space as Java and RE2 patterns read it.
BLANK = r"[\x20\x09-\x0D]"
DOCUMENT_COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """A new path in the folder that all executors see; what is written there goes when the process ends."""
    return folder(spark, "llm")


def per_batch(df: DataFrame, make: Callable[[pa.RecordBatch], pa.RecordBatch | None], schema: str) -> DataFrame:
    """mapInArrow with one function from batch to batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows and (out := make(batch)) is not None:
                yield out

    return df.mapInArrow(run, schema)


def id_and_text(docs: DataFrame) -> DataFrame:
    """Only the two columns an operator on texts reads; a null text counts as empty."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))


def first_of_groups(docs: DataFrame, groups: DataFrame) -> DataFrame:
    """Of rows (component_id) of `groups`, the documents that name one, once: of several rows with one id the one whose text has the least hash. Rows without an id cannot be named and stay. All columns of docs, whatever their names."""
    kept = groups.select(F.col("component_id").alias("kept_id")).filter(F.col("kept_id").isNotNull()).distinct()
    rows = docs.select(F.col("doc_id").cast("long").alias("id"), F.xxhash64(F.coalesce(F.col("text"), F.lit(""))).alias("sig"), F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"))
    one = rows.join(kept, F.col("id") == F.col("kept_id"), "left_semi").groupBy("id").agg(F.min_by("row", "sig").alias("row"))
    return one.select("row").union(rows.filter("id IS NULL").select("row")).select(*(F.col("row").getField(c).alias(c) for c in docs.columns))
