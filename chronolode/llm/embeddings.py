"""Embedding near-dedup by a subspace pigeonhole join.

Unit vectors are rotated by a fixed orthogonal matrix and cut into blocks. Two vectors within the squared distance of the threshold are, in one block at least, within the block's share of it
(in proportion to its dimensions). Each block is range-joined: rows go to strips of its first coordinate as wide as the block's radius, and meet those of the same and the neighbouring strips.
Pairs that pass a block are verified by the exact cosine in double precision. A pair belongs to the first block that passes it, so it counts once.

Equal vectors of one label are one node. Strips are cut into tiles of at most TILE rows on each side, however many rows a label has. A task gives, for each of its nodes, the sum of links,
and the links' spanning forest: as many rows as nodes, not as pairs.

The comparisons grow with the square of a label's different vectors: at this radius (0.37 of a unit vector) no strip of a random subspace excludes much. The README has figures.

Defined results: vectors that are null, of norm zero, or hold null or non-finite components, and rows without a label, link with nothing; so do vectors of different length; repeated rows count as linked rows; an empty table gives an empty table; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode.llm.common import read, written
from chronolode.llm.graph import components

COSINE, BLOCK_DIMS, TILE, SEED = 0.93, 8, 2048, 7
SLACK = 1e-9


def rotation(dims: int) -> np.ndarray:
    """A fixed random orthogonal matrix."""
    q, r = np.linalg.qr(np.random.default_rng(SEED).standard_normal((dims, dims)))
    return q * np.sign(np.diag(r))


def blocks_of(dims: int) -> list[slice]:
    n = max(1, dims // BLOCK_DIMS)
    cuts = [dims * i // n for i in range(n + 1)]
    return [slice(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]


def _matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    column = column.chunk(0) if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _strips(nodes: DataFrame, cosine: float) -> DataFrame:
    """(node, block, strip): where each node lies in each block."""
    budget = 2 - 2 * cosine

    def run(batches):  # noqa: ANN001, ANN202
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, sizes = batch["node"].to_numpy(), np.array([len(v) for v in batch["embedding"].to_pylist()])
            for dims in np.unique(sizes):
                at = np.flatnonzero(sizes == dims)
                x = _unit(_matrix(batch["embedding"].take(pa.array(at)))) @ rotation(int(dims))
                for b, part in enumerate(blocks_of(int(dims))):
                    radius = np.sqrt(budget * (part.stop - part.start) / dims) * (1 + SLACK) + SLACK
                    strip = np.floor(x[:, part.start] / radius).astype(np.int32)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[at]), pa.array(np.full(len(at), b, np.int32)), pa.array(strip)], ["node", "block", "strip"])

    return nodes.select("node", "embedding").mapInArrow(run, "node long, block int, strip int")


def _roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least member of each of n nodes' components."""
    root = np.arange(n)
    while True:
        new = root.copy()
        np.minimum.at(new, a, root[b])
        np.minimum.at(new, b, root[a])
        new = new[new]
        if (new == root).all():
            return root
        root = new


def _tile(cosine: float):  # noqa: ANN202
    budget = 2 - 2 * cosine

    def make(group: pa.Table) -> pa.Table:
        block = group["block"][0].as_py()
        side = group["probe"].to_numpy()
        node, weight = group["node"].to_numpy(), group["n"].to_numpy()
        x = _matrix(group["embedding"])
        dims, unit = x.shape[1], _unit(x)
        turned, parts = unit @ rotation(dims), blocks_of(dims)
        p, t = np.flatnonzero(side == 1), np.flatnonzero(side == 0)
        near = lambda i, j, s: ((turned[i, s] - turned[j, s]) ** 2).sum(-1) <= budget * (s.stop - s.start) / dims * (1 + SLACK) + SLACK
        s = parts[block]
        u, v = turned[p, s], turned[t, s]
        apart = (u * u).sum(1)[:, None] + (v * v).sum(1)[None, :] - 2 * u @ v.T
        i, j = np.nonzero(apart <= budget * (s.stop - s.start) / dims + 1e-7)
        i, j = p[i], t[j]
        ok = near(i, j, s) & (node[i] != node[j])
        for earlier in parts[:block]:
            ok &= ~near(i, j, earlier)
        i, j = i[ok], j[ok]
        norms = np.linalg.norm(x, axis=1)
        cos = np.concatenate([np.einsum("ij,ij->i", x[i[k : k + TILE]], x[j[k : k + TILE]]) for k in range(0, len(i), TILE)] or [np.zeros(0)]) / (norms[i] * norms[j])
        i, j = i[cos >= cosine], j[cos >= cosine]
        order, place = np.unique(node, return_inverse=True)  # a node may be on both sides
        sums = np.bincount(place[i], weight[j], len(order)).astype(np.int64)
        root = _roots(len(order), place[i], place[j])
        some = np.flatnonzero((sums > 0) | (root != np.arange(len(order))))
        return pa.table({"node": order[some], "links": sums[some], "root": order[root[some]]})

    return make


def links(nodes: DataFrame, cosine: float = COSINE) -> DataFrame:
    """(node, links, root): partial sums of linked rows, and links of a spanning forest. nodes: node, label, embedding, n rows that share it."""
    placed = written(_strips(nodes, cosine))
    tagged = placed.join(nodes, "node").withColumn("dims", F.size("embedding"))
    key = ["label", "dims", "block", "strip"]
    sizes = tagged.groupBy(*key).agg(F.count("*").alias("rows"))
    tiles = written(sizes.withColumn("tiles", F.ceil(F.col("rows") / TILE).cast("int")).drop("rows"))
    tile = F.pmod(F.xxhash64("node"), F.col("tiles")).cast("int")
    # Both sides know how many tiles the other has in the strip where they meet.
    here = tagged.join(tiles, key).withColumn("own", tile).drop("tiles")
    around = here.withColumn("at", F.explode(F.array(F.col("strip") - 1, F.col("strip"), F.col("strip") + 1)))
    their = tiles.select("label", "dims", "block", F.col("strip").alias("at"), F.col("tiles").alias("tiles"))
    probes = around.join(their, ["label", "dims", "block", "at"]).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    probes = probes.select("label", "dims", "block", F.col("at"), F.col("strip").alias("from"), F.col("own").alias("p"), F.col("other").alias("t"), F.lit(1).alias("probe"), "node", "n", "embedding")
    table = here.withColumn("from", F.explode(F.array(F.col("strip") - 1, F.col("strip"), F.col("strip") + 1)))
    theirs = tiles.select("label", "dims", "block", F.col("strip").alias("from"), "tiles")
    table = table.join(theirs, ["label", "dims", "block", "from"]).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    table = table.select("label", "dims", "block", F.col("strip").alias("at"), "from", F.col("other").alias("p"), F.col("own").alias("t"), F.lit(0).alias("probe"), "node", "n", "embedding")
    return probes.union(table).groupBy("label", "dims", "block", "at", "from", "p", "t").applyInArrow(_tile(cosine), "node long, links long, root long")


def groups(vectors: DataFrame, cosine: float = COSINE) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row."""
    v = F.transform("embedding", lambda x: x.cast("double"))
    norm = F.aggregate(v, F.lit(0.0), lambda a, x: a + x * x)
    fine = F.col("label").isNotNull() & F.col("embedding").isNotNull() & (F.size("embedding") > 0) & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & (norm > 0) & (norm < float("inf"))
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "label", "embedding", F.coalesce(fine, F.lit(False)).alias("fine"))
    rows = rows.withColumns({"h1": F.when(F.col("fine"), F.xxhash64("label", "embedding")), "h2": F.when(F.col("fine"), F.xxhash64(F.lit(SEED), "embedding", "label"))})
    nodes = rows.filter("fine").groupBy("h1", "h2").agg(F.first("label").alias("label"), F.first("embedding").alias("embedding"), F.min("vec_id").alias("first"), F.count("*").alias("n"))
    nodes = written(nodes.withColumn("node", F.monotonically_increasing_id()))
    found = written(links(nodes.select("node", "label", "embedding", "n"), cosine))
    sums = found.groupBy("node").agg(F.sum("links").alias("links"))
    roots = components(found.filter("node <> root"), "node", "root").withColumnRenamed("node", "member")
    rooted = nodes.select("h1", "h2", "node", "first", "n").join(sums, "node", "left").join(roots, F.col("node") == F.col("member"), "left")
    rooted = written(rooted.select("h1", "h2", "first", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("root", "node").alias("root")))
    least = rooted.groupBy("root").agg(F.min("first").alias("component"))
    named = rooted.join(least, "root").select(F.col("h1").alias("g1"), F.col("h2").alias("g2"), "n_links", "component")
    slim = rows.select("vec_id", "h1", "h2")
    out = slim.join(named, (slim["h1"] == named["g1"]) & (slim["h2"] == named["g2"]), "left")
    out = out.select("vec_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.when(F.col("g1").isNull(), F.col("vec_id")).otherwise(F.col("component")).alias("component_id"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return groups(read(spark, sf_dir, "embeddings").select("vec_id", "label", "embedding"))


ORACLE = """
WITH RECURSIVE e AS (SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL),
g AS (SELECT a.vec_id AS a, b.vec_id AS b FROM e a JOIN e b ON a.label = b.label AND a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.v, b.v) >= 0.93),
r(node, seen) AS (SELECT vec_id, vec_id FROM embeddings UNION SELECT r.node, g.b FROM r JOIN g ON g.a = r.seen),
c AS (SELECT node, min(seen) AS component_id FROM r GROUP BY node),
n AS (SELECT a, count(*) AS n FROM g GROUP BY a)
SELECT vec_id, coalesce(n, 0)::BIGINT AS n_links, component_id, vec_id = component_id AS kept
FROM embeddings JOIN c ON c.node = vec_id LEFT JOIN n ON n.a = vec_id
"""
