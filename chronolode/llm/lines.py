r"""Line dedup: keys found in several documents keep their lines only in the document with the smallest id.

One pass over the texts gives a row for each line with a long enough key: a 128-bit hash of the key, the document, the line's position; and a row for each document with its number of lines.
Lines are range-partitioned by hash, document and position, sorted inside partitions, and streamed: the first document of a key keeps its lines, rows of later documents are drops. As document and position are part of
the range, a key that many documents share is spread over partitions; its rows in all but the first of them ("edges") are settled by the smallest document found for the last key of a partition, a table of at most
one row a partition. The positions to drop go back to their document, whose number of lines then gives a compressed bitmap of the lines it keeps. No text is moved until somebody applies a bitmap.

A document row is known by its id and a hash of its text, so that rows of one id with different texts have bitmaps of their own.

Defined results: a null or empty text is one empty line, kept; rows with the same id are one document; a null id is a document of its own that comes last; repeated rows give repeated rows; an empty table gives an empty
table; extra columns of any name are kept as they are; keys are compared by a 128-bit hash, equal keys always meet. A text is held whole by one task, and its lines are rows, however long it is.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode.llm.common import per_batch, read, written

LEAST = 10
#: Lines whose hashes a task keeps at hand, between documents.
KNOWN = 100_000
BLANKS = " \t\n\x0b\f\r"


def line_key(line: str) -> tuple[int, bytes]:
    """The key's number of code points, and its bytes."""
    key = line.strip(BLANKS)
    return len(key), key.encode().lower()  # of bytes: A-Z


def identified(docs: DataFrame) -> DataFrame:
    """(unknown, doc, sig, text): what a row is known by, beside its text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.col("doc_id").isNull().cast("int").alias("unknown"), F.coalesce(F.col("doc_id").cast("long"), F.lit(0)).alias("doc"), F.xxhash64(text).alias("sig"), text.alias("text"))


def keyed_lines(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """(h1, h2, unknown, doc, sig, pos, n): a row for each line with a long enough key (n null), and a row for each document row with its number of lines (the hash null)."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        row, pos, digests, total, known = [], [], [], [], {}
        for r, text in enumerate(batch["text"].to_pylist()):
            if len(known) > KNOWN:
                known.clear()
            parts = text.split("\n")
            total.append(len(parts))
            for i, part in enumerate(parts):
                if (digest := known.get(part)) is None:
                    size, key = line_key(part)
                    digest = known[part] = xxhash.xxh3_128_digest(key) if size >= least else b""
                if digest:
                    row.append(r)
                    pos.append(i)
                    digests.append(digest)
        hashes = np.frombuffer(b"".join(digests), np.int64).reshape(-1, 2)
        at, none, n = np.array(row, np.int64), pa.nulls(len(total), pa.int64()), len(row)
        both = lambda lines, rows, kind: pa.concat_arrays([pa.array(lines, kind), rows.cast(kind)])
        columns = [both(hashes[:, i], none, pa.int64()) for i in (0, 1)]
        columns += [both(batch[c].to_numpy()[at], batch[c], k) for c, k in (("unknown", pa.int32()), ("doc", pa.int64()), ("sig", pa.int64()))]
        columns += [both(pos, none, pa.int32()), pa.concat_arrays([pa.nulls(n, pa.int32()), pa.array(total, pa.int32())])]
        return pa.RecordBatch.from_arrays(columns, ["h1", "h2", "unknown", "doc", "sig", "pos", "n"])

    return per_batch(identified(docs), make, "h1 long, h2 long, unknown int, doc long, sig long, pos int, n int")


#: What a streamed row is: a line of a later document, a row of the partition's first key, the first row of its last key.
DROP, EDGE, HEAD = 0, 1, 2
STREAMED = "h1 long, h2 long, unknown int, doc long, sig long, pos int, kind int"
_NAMES = ["h1", "h2", "unknown", "doc", "sig", "pos", "kind"]


def _firsts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Streams one sorted partition. Holds the running key and its first document."""
    key, first, edge = None, None, True
    for batch in batches:
        if not batch.num_rows:
            continue
        h1, h2, unknown, doc, sig, pos = (batch[c].to_numpy() for c in _NAMES[:6])
        begins = np.empty(len(h1), bool)
        begins[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
        begins[0] = key != (h1[0], h2[0])
        if key is not None and begins[0]:
            edge = False
        run = np.cumsum(begins)  # 0: the key that came before this batch
        starts = np.flatnonzero(begins)
        u0, d0 = (np.concatenate([[x], a[starts]]) for x, a in zip(first or (0, 0), (unknown, doc), strict=True))
        later = (unknown != u0[run]) | (doc != d0[run])
        on_edge = run <= (1 if key is None else 0) if edge else np.zeros(len(run), bool)
        kind = np.where(on_edge, EDGE, np.where(later, DROP, -1))
        out = kind >= 0
        if out.any():
            yield pa.RecordBatch.from_arrays([pa.array(x[out]) for x in (h1, h2, unknown, doc, sig, pos, kind.astype(np.int32))], _NAMES)
        edge = bool(on_edge[-1])
        key, first = (h1[-1], h2[-1]), (u0[run[-1]], d0[run[-1]])
    if key is not None and not edge:
        kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int32()]
        yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip((*key, *first, 0, 0, HEAD), kinds, strict=True)], _NAMES)


def drops(keyed: DataFrame) -> DataFrame:
    """(unknown, doc, sig, pos): the lines that a document loses, from rows of `keyed_lines`."""
    order = ["h1", "h2", "unknown", "doc", "pos"]
    lines = keyed.filter(F.col("h1").isNotNull()).select(*order[:4], "sig", "pos")
    seen = written(lines.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(_firsts, STREAMED))
    open_keys = seen.filter(F.col("kind") != DROP)
    first = open_keys.groupBy(F.col("h1").alias("k1"), F.col("h2").alias("k2")).agg(F.min(F.struct("unknown", "doc")).alias("keeper"))  # a key for each partition at most
    edges = seen.filter(F.col("kind") == EDGE).join(F.broadcast(first), (F.col("h1") == F.col("k1")) & (F.col("h2") == F.col("k2")))
    edges = edges.filter(F.struct("unknown", "doc") != F.col("keeper"))
    columns = ["unknown", "doc", "sig", "pos"]
    return seen.filter(F.col("kind") == DROP).select(columns).union(edges.select(columns))


def bitmap(flags: list[bool] | np.ndarray) -> bytes:
    return zlib.compress(np.packbits(np.asarray(flags, bool)).tobytes())


def flags_of(n: int, gone: np.ndarray) -> np.ndarray:
    """Which of n lines stay, without those at the positions."""
    flags = np.ones(n, bool)
    flags[gone] = False
    return flags


def apply_bitmap(text: str, data: bytes) -> str:
    """The lines that a bitmap keeps."""
    parts = text.split("\n")
    flags = np.unpackbits(np.frombuffer(zlib.decompress(data), np.uint8), count=len(parts))
    return "\n".join(p for p, keep in zip(parts, flags, strict=True) if keep)


def _bitmaps(docs: DataFrame, least: int) -> DataFrame:
    """(unknown, doc, sig, copies, n_lines, n_dropped, keep_bitmap): one row for each different document row."""
    keyed = written(keyed_lines(docs, least))
    rows = keyed.filter(F.col("n").isNotNull()).select("unknown", "doc", "sig", "n", F.lit(None).cast("int").alias("pos"))
    rows = rows.unionByName(drops(keyed).withColumn("n", F.lit(None).cast("int")))
    rows = rows.groupBy("unknown", "doc", "sig").agg(F.count("n").alias("copies"), F.max("n").alias("n"), F.collect_set("pos").alias("gone"))  # of one document's lines

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        ends, flat, n = batch["gone"].offsets.to_numpy(), batch["gone"].values.to_numpy(), batch["n"].to_pylist()
        maps = [bitmap(flags_of(x, flat[a:b])) for x, a, b in zip(n, ends, ends[1:], strict=False)]
        columns = [*(batch[c] for c in ("unknown", "doc", "sig", "copies")), pa.array(n, pa.int64()), pa.array(np.diff(ends).astype(np.int64)), pa.array(maps, pa.binary())]
        return pa.RecordBatch.from_arrays(columns, ["unknown", "doc", "sig", "copies", "n_lines", "n_dropped", "keep_bitmap"])

    return per_batch(rows, make, "unknown int, doc long, sig long, copies long, n_lines long, n_dropped long, keep_bitmap binary")


def _doc_id(docs: DataFrame) -> Column:
    return F.when(F.col("unknown") == 0, F.col("doc")).cast(docs.schema["doc_id"].dataType).alias("doc_id")


def keep_bitmaps(docs: DataFrame, least: int = LEAST, digest: bool = False) -> DataFrame:
    """(doc_id, n_lines, n_dropped, keep_bitmap) of every row: the operator's result, without any text. With digest also kept_sha256, of the text that the bitmap keeps."""
    if digest:
        return _digests(docs, least)
    rows = _bitmaps(docs, least).withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    return rows.select(_doc_id(docs), "n_lines", "n_dropped", "keep_bitmap")


_KEYS = ["unknown", "doc", "sig"]


def _digests(docs: DataFrame, least: int) -> DataFrame:
    """The bitmaps, each applied to its text: here the texts are moved once, to their bitmaps."""
    rows = identified(docs).join(_bitmaps(docs, least).drop("copies"), _KEYS)

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        sums = []
        for text, gone, data in zip(batch["text"].to_pylist(), batch["n_dropped"].to_pylist(), batch["keep_bitmap"].to_pylist(), strict=True):
            sums.append(hashlib.sha256((apply_bitmap(text, data) if gone else text).encode()).hexdigest())
        names = ["unknown", "doc", "n_lines", "n_dropped", "keep_bitmap"]
        return pa.RecordBatch.from_arrays([*(batch[c] for c in names), pa.array(sums, pa.string())], [*names, "kept_sha256"])

    out = per_batch(rows, make, "unknown int, doc long, n_lines long, n_dropped long, keep_bitmap binary, kept_sha256 string")
    return out.select(_doc_id(docs), "n_lines", "n_dropped", "keep_bitmap", "kept_sha256")


def _applied(text: Column, data: Column) -> Column:
    @F.pandas_udf("string")
    def kept(texts, maps):  # noqa: ANN001, ANN202
        import pandas as pd

        return pd.Series([t if m is None else apply_bitmap(t or "", m) for t, m in zip(texts, maps, strict=True)], dtype=object)

    return kept(text, data)


def deduplicated(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """docs with the kept lines as text, and n_chars if there is one; all other columns stay, whatever their names."""
    text = F.coalesce(F.col("text"), F.lit(""))
    keys = [F.col("doc_id").isNull().cast("int"), F.coalesce(F.col("doc_id").cast("long"), F.lit(0)), F.xxhash64(text)]
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), *(k.alias(c) for k, c in zip(keys, _KEYS, strict=True)))
    lost = _bitmaps(docs, least).filter("n_dropped > 0").select(*_KEYS, "keep_bitmap")
    rows = rows.join(lost, _KEYS, "left")
    changed, old = F.col("keep_bitmap").isNotNull(), F.col("row")
    rows = rows.select("row", "keep_bitmap", F.when(changed, _applied(old.getField("text"), F.col("keep_bitmap"))).otherwise(old.getField("text")).alias("kept"))
    new = {"text": F.col("kept"), "n_chars": F.when(changed, F.length("kept").cast(docs.schema["n_chars"].dataType)).otherwise(old.getField("n_chars")) if "n_chars" in docs.columns else None}
    return rows.select(*(new.get(c, old.getField(c)).alias(c) for c in docs.columns))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keep_bitmaps(read(spark, sf_dir, "documents"), digest=True).select("doc_id", "n_lines", "n_dropped", "kept_sha256")


ORACLE = r"""
WITH l AS (SELECT doc_id, unnest(range(1, len(parts) + 1)) AS pos, unnest(parts) AS line FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents)),
k AS (SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
f AS (SELECT key, min(doc_id) AS keeper FROM k WHERE length(key) >= 10 GROUP BY key HAVING count(DISTINCT doc_id) > 1),
j AS (SELECT k.doc_id, k.pos, k.line, f.key IS NOT NULL AND k.doc_id <> f.keeper AS gone FROM k LEFT JOIN f USING (key))
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (gone)::BIGINT AS n_dropped, sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM j GROUP BY doc_id
"""
