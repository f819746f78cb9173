"""Near-dedup by shared word shingles: two texts are near copies if the Jaccard similarity of their sets of shingles is SIMILAR or more.

Candidates come from min-hash bands and every one of them is verified on the whole sets, so that no pair below the threshold is linked; a pair at it is missed with a chance of (1 - SIMILAR ** ROWS) ** BANDS, 0.04 %, and a closer one less often.
Equal sets are one node, so copies are never paired. Each band's nodes are first compared with its least one. Then the nodes of a band that lie in different components so far are compared block by block inside
tasks, blocks of TILE nodes each, and only links that join components leave a task: this gives the components that all pairs would give, and pairs are never rows.

Defined results: of several rows with one id deduplication keeps the one whose text has the least hash; a null or empty text, or one of white space only, has the empty set, and these are copies of each other; a text shorter than a shingle is one shingle; a row without an id links nothing and names no component; repeated rows give repeated rows; an empty table gives an empty table; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronolode.llm.common import first_of_groups, id_and_text, per_batch, written
from chronolode.llm.graph import components

SHINGLE, SIMILAR, SEED = 5, 0.8, 42
BANDS, ROWS = 20, 5
#: Shingles hashed at a time; nodes in a block; shingles compared at a time.
PART, TILE, COLUMNS = 1 << 13, 128, 1 << 14
_ODD, _ADD = np.random.default_rng(SEED).integers(1, 1 << 63, (2, BANDS * ROWS, 1), np.uint64)
_ODD = _ODD * np.uint64(2) + np.uint64(1)
_MULTIPLY = np.uint64(0x9E3779B97F4A7C15)


def _mixed(x: np.ndarray) -> np.ndarray:
    for shift in (32, 29):
        x = (x ^ (x >> np.uint64(shift))) * _MULTIPLY
    return x ^ (x >> np.uint64(32))


def shingles(text: str, shingle: int = SHINGLE) -> np.ndarray:
    """The set of shingles, as sorted hashes of 64 bits."""
    found = text.encode().lower().split()  # of bytes: A-Z, and ASCII white space
    if not found:
        return np.zeros(0, np.uint64)
    each = np.fromiter((xxhash.xxh64_intdigest(w, SEED) for w in found), np.uint64, len(found))
    width = min(shingle, len(found))
    out = np.full(len(found) - width + 1, width, np.uint64)
    for i in range(width):
        out = _mixed(out + each[i : i + len(out)])
    return np.unique(out)


def bands(found: np.ndarray) -> np.ndarray:
    """A key for each band, from the least hashes of its rows; none for the empty set."""
    if not len(found):
        return np.zeros(0, np.int64)
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(found), PART):
        least = np.minimum(least, (found[at : at + PART] * _ODD + _ADD).min(1))
    keys = np.arange(BANDS, dtype=np.uint64)
    for row in least.reshape(BANDS, ROWS).T:
        keys = _mixed(keys + row)
    return keys.view(np.int64)


def _node(found: np.ndarray) -> int:
    return int(np.uint64(xxhash.xxh64_intdigest(found.tobytes(), SEED)).view(np.int64))


def _signed(docs: DataFrame, shingle: int) -> DataFrame:
    """(doc_id, node, keys): node stands for the set of shingles."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets = [shingles(t, shingle) for t in batch["text"].to_pylist()]
        keys = pa.array([bands(s) for s in sets], pa.list_(pa.int64()))
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array([_node(s) for s in sets], pa.int64()), keys], ["doc_id", "node", "keys"])

    return per_batch(id_and_text(docs), make, "doc_id long, node long, keys array<long>")


def _sets(docs: DataFrame, nodes: DataFrame, some: DataFrame, shingle: int) -> DataFrame:
    """(node, found): the sets of some nodes (node), made again from one text each."""
    ids = nodes.join(some, "node", "left_semi").select(F.col("first").alias("id"))

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets = [shingles(t, shingle) for t in batch["text"].to_pylist()]
        return pa.RecordBatch.from_arrays([pa.array([_node(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], ["node", "found"])

    texts = docs.join(ids, docs["doc_id"] == ids["id"], "left_semi")
    return written(per_batch(id_and_text(texts), make, "node long, found binary").dropDuplicates(["node"]))


def _verified(sets: DataFrame, pairs: DataFrame, similar: float) -> DataFrame:
    """The pairs (a, b) of nodes whose sets are similar."""
    one, two = (sets.select(F.col("node").alias(x), F.col("found").alias(f"found_{x}")) for x in "ab")

    def keep(batch: pa.RecordBatch) -> pa.RecordBatch:
        def near(x: bytes, y: bytes) -> bool:
            p, q = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
            if min(len(p), len(q)) < similar * max(len(p), len(q)):
                return False
            both = len(np.intersect1d(p, q, assume_unique=True))
            return both >= similar * (len(p) + len(q) - both)

        kept = pa.array([near(x.as_py(), y.as_py()) for x, y in zip(batch["found_a"], batch["found_b"], strict=True)], pa.bool_())
        return batch.select(["a", "b"]).filter(kept)

    return per_batch(pairs.join(one, "a").join(two, "b").select("a", "b", "found_a", "found_b"), keep, "a long, b long")


def shared(found: list[np.ndarray]) -> np.ndarray:
    """How many elements each two of the sets have in common."""
    owner = np.repeat(np.arange(len(found)), [len(x) for x in found])
    _, at, times = np.unique(np.concatenate(found), return_inverse=True, return_counts=True)
    again = times > 1  # others are in one set only
    column = np.cumsum(again) - 1
    owner, column = owner[again[at]], column[at[again[at]]]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    out = np.zeros((len(found), len(found)), np.float32)
    for start in range(0, int(again.sum()), COLUMNS):
        a, b = np.searchsorted(column, (start, start + COLUMNS))
        part = np.zeros((len(found), COLUMNS), np.float32)
        part[owner[a:b], column[a:b] - start] = 1
        out += part @ part.T
    return out.astype(np.int64)


def _between(members: DataFrame, sets: DataFrame, similar: float) -> DataFrame:
    """(a, b): similar nodes of one band and different roots, enough of them to join the components that all would join. members: (key, node, root, n), n the band's nodes."""
    tiles = F.ceil(F.col("n") / TILE)
    rows = members.withColumn("tile", F.pmod(F.xxhash64("node"), tiles)).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), tiles - 1)))
    rows = rows.select("key", "node", "root", "tile", F.least("tile", "other").alias("low"), F.greatest("tile", "other").alias("high")).join(sets, "node")

    def compare(table: pa.Table) -> pa.Table:
        node, root, tile = (table[c].to_numpy() for c in ("node", "root", "tile"))
        found = [np.frombuffer(x, np.uint64) for x in table["found"].to_pylist()]
        size, both = np.array([len(x) for x in found]), shared(found)
        alike = (both >= similar * (size[:, None] + size[None, :] - both)) & (root[:, None] != root[None, :])
        if len(set(tile.tolist())) > 1:
            alike &= tile[:, None] != tile[None, :]  # pairs of one block have a task of their own
        parent, links = {r: r for r in root.tolist()}, []

        def top(r: int) -> int:
            while parent[r] != r:
                parent[r] = r = parent[parent[r]]
            return r

        for i, j in zip(*(x.tolist() for x in np.nonzero(np.triu(alike, 1))), strict=True):
            r, q = top(root[i].item()), top(root[j].item())
            if r != q:
                parent[r] = q
                links.append((node[i].item(), node[j].item()))
        return pa.table({"a": pa.array([a for a, _ in links], pa.int64()), "b": pa.array([b for _, b in links], pa.int64())})

    return rows.groupBy("key", "low", "high").applyInArrow(compare, "a long, b long")


def groups(docs: DataFrame, shingle: int = SHINGLE, similar: float = SIMILAR) -> DataFrame:
    """(doc_id, node, component_id) of every row."""
    rows = written(_signed(docs, shingle))
    nodes = written(rows.groupBy("node").agg(F.min("doc_id").alias("first"), F.first("keys").alias("keys")))
    keyed = nodes.filter(F.col("first").isNotNull()).select("node", F.explode("keys").alias("key"))
    least = keyed.groupBy("key").agg(F.min("node").alias("least"), F.count("*").alias("n")).filter("n > 1").select("key", "least")
    keyed = written(keyed.join(least, "key"))  # of bands with two nodes or more
    pairs = written(keyed.filter("node <> least").select(F.col("least").alias("a"), F.col("node").alias("b")).distinct())
    sets = _sets(docs, nodes, keyed.select("node").distinct(), shingle)
    links = written(_verified(sets, pairs, similar))
    roots = components(links)
    placed = written(keyed.join(roots, "node", "left").select("key", "node", F.coalesce("root", "node").alias("root")))
    mixed = placed.groupBy("key").agg(F.count("*").alias("n"), F.min("root").alias("low"), F.max("root").alias("high")).filter("n > 2 AND low <> high").select("key", "n")
    roots = components(links.union(_between(placed.join(mixed, "key"), sets, similar)))
    rooted = nodes.join(roots, "node", "left").select("node", "first", F.coalesce("root", "node").alias("root"))
    named = rooted.join(rooted.groupBy("root").agg(F.min("first").alias("component_id")), "root").select(F.col("node").alias("m"), "component_id")
    return rows.join(named, rows["node"] == named["m"]).select("doc_id", "node", "component_id")


def deduplicated(docs: DataFrame, shingle: int = SHINGLE, similar: float = SIMILAR) -> DataFrame:
    """docs with one document of each group: the one with the smallest id, once. Rows without an id cannot be named and stay."""
    return first_of_groups(docs, groups(docs, shingle, similar))
