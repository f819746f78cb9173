"""Connected components of a table of links, by large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronolode.llm.common import written


def _star(edges: DataFrame, both_ways: bool) -> DataFrame:
    """Ties every neighbour to the least node around a node: with both_ways the larger neighbours, else the node and its smaller ones."""
    if both_ways:
        around = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = around.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        out = around.join(least, "a").filter(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        least = down.groupBy("a").agg(F.min("b").alias("m"))
        kept = down.join(least, "a")
        out = kept.select(F.col("b").alias("a"), F.col("m").alias("b")).union(least.select("a", F.col("m").alias("b")))
    return out.filter(F.col("a") != F.col("b")).distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root): the least node reachable from each node that has a link. Links are longs in either order, repeats and loops allowed.

    Every round is written to the shared folder; only a count and a checksum come to the driver. Nodes with many links are summed before they are shuffled, and the join on them can be split."""
    now = written(edges.select(F.col(a).alias("a"), F.col(b).alias("b")).filter("a <> b").distinct())
    state = None
    while True:
        n, check = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if n == 0 or (n, check) == state:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
        state = (n, check)
        now = written(_star(written(_star(now, True)), False))
