"""SimHash near-dedup by multi-index hashing.

A 64-bit fingerprint is cut into segments with a radius each, chosen so that two fingerprints within the distance are within the radius in one segment at least. One side lists its
segments, the other the small Hamming ball around each of its segments; matches are fetched by an equality join and verified by the whole distance in the join itself.
Equal fingerprints are one node, so copies are never paired. Each table entry's fingerprints are first compared with the least of them; then only matches in different components so far become rows, which leaves the
components that all links would give, without the pairs inside a dense cluster.

Defined results: of several rows with one id deduplication keeps the one whose text has the least hash; a null or empty text, or one of white space only, has fingerprint zero and links like any other; a null id never names a component while another id does; repeated rows give repeated rows; an empty table gives an empty table; other columns are not read.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode.llm.common import first_of_groups, id_and_text, per_batch, read, written
from chronolode.llm.graph import components

SHINGLE, DISTANCE, SEED = 4, 4, 42
#: (bits, radius) of segments for corpora below and above so many fingerprints. Radii plus one sum to more than the distance.
FEW, NARROW_PLAN, WIDE_PLAN = 1 << 24, ((22, 1), (21, 1), (21, 0)), ((32, 2), (32, 1))
PART = 1 << 16


def fingerprint(text: str, shingle: int = SHINGLE) -> int:
    """Unsigned 64 bits: a bit is set if more than half of the shingles' hashes set it."""
    found = text.encode().lower().split()  # of bytes: A-Z, and ASCII white space
    if not found:
        return 0
    starts = max(1, len(found) - shingle + 1)
    ones = np.zeros(64, np.int64)
    for at in range(0, starts, PART):
        part = found[at : at + PART + shingle - 1] if starts > PART else found
        n = min(PART, starts - at)
        hashes = np.fromiter((xxhash.xxh64_intdigest(b" ".join(part[i : i + shingle]), SEED) for i in range(n)), np.uint64, n)
        ones += np.unpackbits(hashes.view(np.uint8).reshape(n, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > starts, bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed long."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        values = np.array([fingerprint(t) for t in batch["text"].to_pylist()], np.uint64).view(np.int64)
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(values)], ["doc_id", "fp"])

    return per_batch(id_and_text(docs), make, "doc_id long, fp long")


def _ball(bits: int, radius: int) -> list[int]:
    return [sum(1 << b for b in some) for r in range(radius + 1) for some in combinations(range(bits), r)]


def _entries(nodes: DataFrame, n: int, distance: int) -> tuple[DataFrame, DataFrame]:
    """The table (b, key) and the probes (a, key) of n nodes, a distinct column fp with other columns beside it."""
    plan = NARROW_PLAN if n < FEW else WIDE_PLAN
    assert sum(bits for bits, _ in plan) == 64 and sum(r + 1 for _, r in plan) > distance
    shifts = [sum(bits for bits, _ in plan[:i]) for i in range(len(plan))]

    def keyed(name: str, masks: list[list[int]]) -> DataFrame:
        """A row for each mask of each segment: the segment's bits with the mask's flipped, and the segment's number above them."""
        all_masks = F.array(*(F.struct(F.lit(shifts[i]).alias("shift"), F.lit((1 << plan[i][0]) - 1).cast("long").alias("bits"), F.lit(x).cast("long").alias("flip"), F.lit(i << 32).cast("long").alias("base")) for i, m in enumerate(masks) for x in m))
        named = [F.col(c).alias(name if c == "fp" else f"{c}_{name}") for c in nodes.columns]
        rows = nodes.select(*named, F.explode(all_masks).alias("m"))
        return rows.withColumn("key", F.expr(f"((shiftrightunsigned({name}, m.shift) & m.bits) ^ m.flip) + m.base")).drop("m")

    return keyed("b", [[0]] * len(plan)), keyed("a", [_ball(*p) for p in plan])


def _near(distance: int) -> Column:
    return F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= distance


def links(nodes: DataFrame, n: int, distance: int = DISTANCE) -> DataFrame:
    """(a, b): pairs of different fingerprints, a < b, within the distance; a pair once for each segment that finds it. nodes: distinct column fp, n of them."""
    table, probes = _entries(nodes.select("fp"), n, distance)
    return probes.join(table, (probes["key"] == table["key"]) & (F.col("a") < F.col("b")) & _near(distance)).select("a", "b")


def roots(nodes: DataFrame, n: int, distance: int = DISTANCE) -> DataFrame:
    """(node, root) of the components that `links` makes, of nodes that have a link: through the least fingerprint of each table entry first, without any ball, then through links between components."""
    table, _ = _entries(nodes.select("fp"), n, distance)
    least = table.groupBy("key").agg(F.min("b").alias("a"), F.count("*").alias("n")).filter("n > 1").select("key", "a")
    first = written(table.join(least, "key").filter((F.col("a") != F.col("b")) & _near(distance)).select("a", "b").distinct())
    found = components(first)
    placed = nodes.select("fp").join(found, F.col("fp") == F.col("node"), "left").select("fp", F.coalesce("root", "fp").alias("root"))
    table, probes = _entries(written(placed), n, distance)
    rest = probes.join(table, (probes["key"] == table["key"]) & (F.col("a") < F.col("b")) & _near(distance) & (F.col("root_a") != F.col("root_b")))
    rest = written(rest.select(F.col("root_a").alias("a"), F.col("root_b").alias("b")).distinct())
    return found if rest.isEmpty() else components(first.union(rest))


def groups(docs: DataFrame) -> DataFrame:
    """(doc_id, fp, component_id) of every row."""
    rows = written(fingerprints(docs))
    nodes = written(rows.groupBy("fp").agg(F.min("doc_id").alias("first")))
    found = roots(nodes, nodes.count())
    rooted = nodes.join(found, nodes["fp"] == found["node"], "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("first").alias("component_id"))
    named = rooted.join(least, "root").select(F.col("fp").alias("f"), "component_id")
    return rows.join(named, rows["fp"] == named["f"]).select("doc_id", "fp", "component_id")


def deduplicated(docs: DataFrame) -> DataFrame:
    """docs with one document of each group: the one with the smallest id, once. Rows without an id cannot be named and stay."""
    return first_of_groups(docs, groups(docs))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = groups(read(spark, sf_dir, "documents"))
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
