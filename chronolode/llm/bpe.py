"""Byte-level BPE encoding and decoding by DuckDB queries inside each Python worker.

Pre-tokens are found by the public split pattern. Each distinct pre-token that a worker has not met is encoded by a recursive query:
rows (word, position, token) meet the merge table on the joined bytes of neighbours, every word contracts its leftmost pair of least rank, and
words without a mergeable pair stop. A word's state between steps is the list of its tokens, taken apart into rows in each. In words of more than SHORT bytes the state is the rows, and further pairs are contracted in the same step
where that gives the same result: equal pairs where no vocabulary entry of lower rank begins or ends with the merged token, and pairs that no lower rank can reach from either side.
Decoding joins token rows with the vocabulary and puts their bytes together in the order of position.

Memory: a worker holds the words of about CHUNK characters of text (or of one longer text), two generations of CACHE words with their ids, and a DuckDB of at most DUCK_MEMORY.
A short word needs as many steps as it has contractions; a long one fewer, at most as many as it has different merged pairs.

Defined results: a null text counts as empty and has no tokens; repeated rows give repeated rows; an empty table gives an empty table; other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator
from functools import cache

import duckdb
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from chronolode.llm.common import id_and_text, per_batch, read

CHUNK, WORDS, TOKENS, CACHE, DUCK_MEMORY = 2_000_000, 50_000, 500_000, 400_000, "400MB"
#: Bytes of a word that is contracted pair by pair.
SHORT = 64

#: White space as the pattern's library reads it: the Unicode property.
SPACE = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: The alternatives of the public pattern; {l}, {n} and {s} stand for letters, numbers and white space.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?[{l}]+| ?[{n}]+| ?[^{s}{l}{n}]+|[{s}]+(?![^{s}])|[{s}]+"
#: Texts below this code point take the standard library's matcher with classes written out.
NARROW = 0x250


@cache
def _splitters() -> tuple:
    wide = regex.compile(SPLIT.format(l=r"\p{L}", n=r"\p{N}", s=SPACE))
    chars = [chr(i) for i in range(NARROW)]
    of = lambda p: "".join(re.escape(c) for c in chars if regex.fullmatch(p, c))
    narrow = re.compile(SPLIT.format(l=of(r"\p{L}"), n=of(r"\p{N}"), s=of(f"[{SPACE}]")))
    return narrow.findall, wide.findall, re.compile(f"[^\\x00-{chr(NARROW - 1)}]").search


def pretokens(text: str) -> list[str]:
    narrow, wide, other = _splitters()
    return (wide if other(text) else narrow)(text)


def load_ranks(path: str) -> dict[bytes, int]:
    """A public rank file: base64 of the token's bytes, then its rank."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


#: A step: the token-position rows of each word meet the merge table; the leftmost of its pairs of least rank is contracted.
ENCODE = """
WITH RECURSIVE step(w, ids, turn) AS (
  SELECT w, list_transform(string_split(s, ''), lambda c: code[unicode(c) + 1]), 0 FROM words, codes WHERE s NOT IN (SELECT tok FROM vocab)
  UNION ALL (
  WITH neighbours AS (SELECT w, unnest(range(1, len(ids))) AS pos, unnest(ids[:-2]) * 65536 + unnest(ids[2:]) AS pair FROM step),
  best AS (SELECT w, min(id * 65536 + pos) AS least FROM neighbours JOIN merges USING (pair) GROUP BY w),
  placed AS (SELECT w, least // 65536 AS id, least % 65536 AS pos FROM best)
  SELECT s.w, s.ids[:pos - 1] || [p.id] || s.ids[pos + 2:], s.turn + 1 FROM step s JOIN placed p ON s.w = p.w)
)
SELECT w, arg_max(ids, turn) AS ids FROM step GROUP BY w
UNION ALL SELECT w, [rank] FROM words JOIN vocab ON s = tok
ORDER BY w
"""

#: The same for long words: rows are the state, and a step also contracts all pairs that no lower rank can reach first (see `guards`), and every second one of a chain of equal pairs of least rank where that is safe.
ENCODE_LONG = """
WITH RECURSIVE step(w, pos, id, turn) AS (
  SELECT w, pos, bytes.id, 0 FROM (SELECT w, unnest(range(1, len(s) + 1)) AS pos, unnest(string_split(s, '')) AS c FROM words WHERE s NOT IN (SELECT tok FROM vocab)) JOIN bytes ON c = bytes.tok
  UNION ALL (
  WITH neighbours AS (SELECT w, pos, id * 65536 + lead(id) OVER o AS pair, lead(pos) OVER o AS next FROM step WINDOW o AS (PARTITION BY w ORDER BY pos)),
  rated AS MATERIALIZED (SELECT n.w, n.pos, n.next, m.id, m.safe, lag(g.ending) OVER o AS before, lead(g.beginning) OVER o AS after
    FROM neighbours n LEFT JOIN merges m ON n.pair = m.pair LEFT JOIN guards g ON n.pair = g.pair WINDOW o AS (PARTITION BY n.w ORDER BY n.pos)),
  best AS MATERIALIZED (SELECT w, min(id) AS least FROM rated WHERE id IS NOT NULL GROUP BY w),
  least AS (SELECT r.*, row_number() OVER (PARTITION BY r.w ORDER BY pos) AS n FROM rated r JOIN best ON r.w = best.w AND r.id = best.least),
  chained AS (SELECT *, pos = lag(next) OVER (PARTITION BY w ORDER BY pos) AS linked FROM least),
  placed AS (SELECT *, n - max(CASE WHEN linked IS DISTINCT FROM true THEN n END) OVER (PARTITION BY w ORDER BY pos) AS place FROM chained),
  taken AS MATERIALIZED (SELECT w, pos, next, id FROM placed WHERE CASE WHEN safe THEN place % 2 = 0 ELSE n = 1 END
    UNION SELECT w, pos, next, id FROM rated WHERE id < coalesce(before, 65536) AND id < coalesce(after, 65536))
  SELECT s.w, s.pos, coalesce(t.id, s.id), s.turn + 1
  FROM step s JOIN best ON s.w = best.w LEFT JOIN taken t ON t.w = s.w AND t.pos = s.pos
  WHERE NOT EXISTS (SELECT 1 FROM taken g WHERE g.w = s.w AND g.next = s.pos))
)
SELECT w, list(id ORDER BY pos) AS ids
FROM (SELECT w, pos, id FROM (SELECT *, max(turn) OVER (PARTITION BY w) AS final FROM step) WHERE turn = final
  UNION ALL SELECT w, 1, rank FROM words JOIN vocab ON s = tok)
GROUP BY w ORDER BY w
"""

#: Positions rise over all documents, so that one sort serves the groups; `Codec` checks that the aggregate keeps that order.
DECODE = "SELECT doc, string_agg(tok, '') AS s FROM (SELECT doc, tok FROM tokens JOIN vocab ON rank = id ORDER BY pos) GROUP BY doc ORDER BY doc"


def guards(ranks: dict[bytes, int]) -> pa.Table:
    """(pair, ending, beginning): for neighbouring tokens the least rank of all entries that end with their joined bytes, and that begin with them.

    A token's left neighbour only ever grows to the left, so the two can be joined at rank `ending` at the earliest, and so on the right. A pair of lower rank than what either side can reach is contracted in the end
    whatever happens around it, so it may be contracted at once."""
    sides: list[dict[bytes, int]] = [{}, {}]
    for t, r in ranks.items():
        for i in range(len(t) - 1):
            for side, part in zip(sides, (t[i:], t[: len(t) - i]), strict=True):
                side[part] = min(r, side.get(part, r))
    never, rows = 1 << 16, {}
    for part in {*sides[0], *sides[1]}:
        for i in range(1, len(part)):
            a, b = ranks.get(part[:i]), ranks.get(part[i:])
            if a is not None and b is not None:
                rows[a << 16 | b] = (sides[0].get(part, never), sides[1].get(part, never))
    return pa.table({"pair": pa.array(rows.keys(), pa.int64()), "ending": pa.array([x for x, _ in rows.values()], pa.int32()), "beginning": pa.array([x for _, x in rows.values()], pa.int32())})


class Codec:
    """A worker's codec for one rank file. Bytes are held as the text of the same code points, which DuckDB can join and concatenate."""

    def __init__(self, path: str) -> None:
        ranks = load_ranks(path)
        assert max(ranks.values()) < 1 << 16
        pairs: dict[int, int] = {}
        ends: dict[int, int] = {}  # of a token: the least rank of those that begin or end with it
        for t, r in ranks.items():
            for i in range(1, len(t)):
                a, b = ranks.get(t[:i]), ranks.get(t[i:])
                for part in (a, b):
                    if part is not None:
                        ends[part] = min(r, ends.get(part, r))
                if a is not None and b is not None:
                    pairs[a << 16 | b] = r
        self.db = duckdb.connect(config={"threads": 1, "memory_limit": DUCK_MEMORY})
        vocab = pa.table({"tok": [t.decode("latin-1") for t in ranks], "rank": pa.array(ranks.values(), pa.int64())})
        merges = pa.table({"pair": pa.array(pairs.keys(), pa.int64()), "id": pa.array(pairs.values(), pa.int64()), "safe": [ends.get(r, r) >= r for r in pairs.values()]})
        self._store(vocab=vocab, merges=merges)
        self.path, self.guarded = path, False
        self.db.execute("CREATE TABLE bytes AS SELECT tok, rank AS id FROM vocab WHERE length(tok) = 1")
        self.db.execute("CREATE TABLE codes AS SELECT list(id ORDER BY tok) AS code FROM bytes")
        assert len(self.db.sql("SELECT unnest(code) FROM codes").fetchall()) == 256
        self.known: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        turned = pa.table({"doc": pa.array([0, 0, 0], pa.int32()), "pos": pa.array([2, 1, 0], pa.int32()), "id": pa.array([ranks[x] for x in (b"c", b"b", b"a")], pa.int32())})
        assert self._decoded(turned) == [(0, "abc")]

    def _store(self, **tables: pa.Table) -> None:
        for name, table in tables.items():
            self.db.register("given", table)
            self.db.execute(f"CREATE TABLE {name} AS SELECT * FROM given")
            self.db.unregister("given")

    def learn(self, words: list[str]) -> None:
        """Encodes words that are not known yet, so many at a time."""
        short, long = [], []
        for x in words:
            (short if len(x) <= SHORT and len(x.encode()) <= SHORT else long).append(x)
        if long and not self.guarded:
            self._store(guards=guards(load_ranks(self.path)))
            self.guarded = True
        for group, query in ((short, ENCODE), (long, ENCODE_LONG)):
            at = 0
            while at < len(group):
                some, size = [], 0
                while at < len(group) and (not some or size + len(group[at]) < 10 * WORDS):
                    some.append(group[at])
                    size += len(group[at])
                    at += 1
                self.db.register("words", pa.table({"w": pa.array(range(len(some)), pa.int32()), "s": [x.encode().decode("latin-1") for x in some]}))
                ids = self.db.sql(query).to_arrow_table()["ids"].combine_chunks()
                self.db.unregister("words")
                ids = ids.chunk(0) if isinstance(ids, pa.ChunkedArray) else ids
                data, ends = ids.flatten().to_numpy(zero_copy_only=False).astype("<u4").tobytes(), ((ids.offsets.to_numpy() - ids.offsets[0].as_py()) * 4).tolist()
                self.known.update((x, data[a:b]) for x, a, b in zip(some, ends, ends[1:], strict=False))

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit integers."""
        split = [pretokens(t) for t in texts]
        new = set().union(*split).difference(self.known)
        if new:
            if len(self.known) + len(new) > CACHE:  # words of the older generation stay only if they are met again
                self.known, self.older = {}, self.known
                new = set().union(*split)
            again = [w for w in new if w in self.older]
            self.known.update((w, self.older[w]) for w in again)
            self.learn(list(new.difference(again)))
        of = self.known.__getitem__
        return [b"".join(map(of, s)) for s in split]

    def _decoded(self, tokens: pa.Table) -> list[tuple[int, str]]:
        self.db.register("tokens", tokens)
        got = self.db.sql(DECODE).to_arrow_table()
        self.db.unregister("tokens")
        return list(zip(got["doc"].to_pylist(), got["s"].to_pylist(), strict=True))

    def decode(self, ids: list[bytes]) -> list[bytes]:
        """The bytes that the ids of each text stand for; a long text is decoded in parts."""
        out, rows, size = [b""] * len(ids), [], 0

        def flush() -> None:
            nonlocal size
            if rows:
                counts = [len(x) // 4 for _, x in rows]
                flat = np.frombuffer(b"".join(x for _, x in rows), "<u4").astype(np.int32)
                tokens = pa.table({"doc": np.repeat(np.arange(len(rows), dtype=np.int32), counts), "pos": np.arange(len(flat), dtype=np.int32), "id": flat})
                for doc, s in self._decoded(tokens):
                    out[rows[doc][0]] += s.encode("latin-1")
            rows.clear()
            size = 0

        for i, x in enumerate(ids):
            for at in range(0, len(x), 4 * TOKENS):
                rows.append((i, x[at : at + 4 * TOKENS]))
                size += len(rows[-1][1]) // 4
                if size >= TOKENS:
                    flush()
        flush()
        return out


@cache
def codec(path: str) -> Codec:
    return Codec(path)


def chunks(texts: list[str]) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about CHUNK characters."""
    start, size = 0, 0
    for i, t in enumerate(texts):
        size += len(t)
        if size >= CHUNK:
            yield start, i + 1
            start, size = i + 1, 0
    if start < len(texts):
        yield start, len(texts)


def encode(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, n_tokens, ids): the ids of every whole text, little-endian unsigned 32-bit."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts, use = batch["text"].to_pylist(), codec(path)
        ids = [x for a, b in chunks(texts) for x in use.encode(texts[a:b])]
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary())], ["doc_id", "n_tokens", "ids"])

    return per_batch(id_and_text(docs), make, "doc_id long, n_tokens long, ids binary")


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, data): the bytes of every row's ids."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(codec(path).decode([x or b"" for x in batch["ids"].to_pylist()]), pa.binary())], ["doc_id", "data"])

    return per_batch(encoded.select("doc_id", "ids"), make, "doc_id long, data binary")


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): encodes every whole text and decodes its ids."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts, use, rows = batch["text"].to_pylist(), codec(path), []
        for a, b in chunks(texts):
            ids = use.encode(texts[a:b])
            rows += [(len(x) // 4, hashlib.sha256(x).hexdigest(), hashlib.sha256(y).hexdigest()) for x, y in zip(ids, use.decode(ids), strict=True)]
        kinds = [pa.int64(), pa.string(), pa.string()]
        return pa.RecordBatch.from_arrays([batch["doc_id"], *(pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds))], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return per_batch(id_and_text(docs), make, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def rank_file() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(read(spark, sf_dir, "documents"), rank_file())
