"""SQL surface: sequences and windows as views, functions under names."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from chronolode.functions import udf
from chronolode.operators.windows import arrays, build


def register(spark: SparkSession, ces: DataFrame, mtd: int, prefix: str = "") -> None:
    """Views {prefix}ces(t, item, u), {prefix}windows(ts, pos, t, item, u, rest) and {prefix}window_arrays(ts, head, t, items, u, rest), and the Python functions."""
    windows = build(ces, mtd).filter("own")
    ces.createOrReplaceTempView(f"{prefix}ces")
    windows.drop("chunk", "own").createOrReplaceTempView(f"{prefix}windows")
    arrays(build(ces, mtd)).createOrReplaceTempView(f"{prefix}window_arrays")
    udf.register(spark)
