"""Token counts by a map-side look-up in two tiers.

The first tier is a broadcast table of the lengths, in tokens, of frequent pre-tokens: the commonest words of all texts, counted in a pass of its own, and the vocabulary's own words; it has at most FREQUENT entries.
What it misses is encoded once by a worker and kept in the worker's cache. Only sums by word are shuffled, for the first tier; counts do not depend on what either tier holds.

Texts below U+0250 are split by classes that are probed from the tokenizer itself, other texts by the tokenizer's own normalizer and splitter.

Defined results: a null text counts as empty, with no bytes and no tokens; special strings in a text count as one token each, as the library has it; repeated rows give repeated rows; an empty table gives an empty table; other columns are not read.
"""

from __future__ import annotations

import os
import re
from collections import Counter
from functools import cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode.llm.bpe import NARROW, chunks
from chronolode.llm.common import id_and_text, per_batch, read

FREQUENT, CACHE, LIMIT = 65_536, 400_000, 2048

#: The alternatives of the tokenizer's split pattern; {l}, {n} and {o} stand for letters, numbers and all else but white space.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[{l}]+|[{n}]|[{o}]+"


class LengthTable:
    """One worker's tokenizer with its two tiers."""

    def __init__(self, path: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.no_truncation()
        self.tok.no_padding()
        split = self.tok.pre_tokenizer.pre_tokenize_str
        kinds: dict[str, list[str]] = {"l": [], "n": [], "o": []}
        for c in map(chr, range(NARROW)):
            if n := len(split(c + c)):
                kinds["n" if n == 2 else "l" if len(split("a" + c)) == 1 else "o"].append(re.escape(c))
        self.words = re.compile(SPLIT.format(**{k: "".join(v) for k, v in kinds.items()})).findall
        self.wide = re.compile(f"[^\\x00-{chr(NARROW - 1)}]").search
        self.special = re.compile("|".join(re.escape(t.content) for t in self.tok.get_added_tokens_decoder().values()) or r"(?!)")
        self.first: dict[str, int] = {}
        self.known: dict[str, int] = {}

    def pretokens(self, text: str) -> tuple[list[str], int]:
        """The pre-tokens of a text, and how many special strings it holds."""
        if n := len(self.special.findall(text)):
            return [w for part in self.special.split(text) for w in self.pretokens(part)[0]], n
        low = text.lower()
        if not self.wide(low):
            return self.words(low), 0
        norm = self.tok.normalizer.normalize_str(text)
        return [norm[a:b] for _, (a, b) in self.tok.pre_tokenizer.pre_tokenize_str(norm)], 0

    def lengths(self, words: list[str]) -> list[int]:
        return [len(e.ids) for e in self.tok.encode_batch(words, add_special_tokens=False)]

    def first_tier(self, table: dict[str, int]) -> None:
        if self.first is not table:
            self.first, self.known = table, dict(table)

    def count(self, texts: list[str]) -> list[int]:
        split = [self.pretokens(t) for t in texts]
        wanted = set().union(*(w for w, _ in split))
        if len(new := wanted.difference(self.known)) + len(self.known) > CACHE:
            self.known = dict(self.first)
            new = wanted.difference(self.known)
        self.known.update(zip(new, self.lengths(list(new)), strict=True))
        of = self.known.__getitem__
        return [n + sum(map(of, words)) for words, n in split]


@cache
def length_table(path: str) -> LengthTable:
    return LengthTable(path)


def vocabulary_words(table: LengthTable) -> list[str]:
    """The pre-tokens that are vocabulary entries with a word end."""
    alphabet = {v: k for k, v in byte_alphabet().items()}
    out = []
    for t in table.tok.get_vocab():
        if t.endswith("</w>"):
            try:
                w = bytes(alphabet[c] for c in t[:-4]).decode()
            except (KeyError, UnicodeDecodeError):
                continue
            if table.pretokens(w) == ([w], 0):
                out.append(w)
    return out


def byte_alphabet() -> dict[int, str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    kept = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out = {b: chr(b) for b in kept}
    return out | {b: chr(256 + i) for i, b in enumerate(b for b in range(256) if b not in out)}


def frequent_lengths(docs: DataFrame, path: str, size: int = FREQUENT) -> dict[str, int]:
    """The first tier: lengths of the commonest pre-tokens of all texts, and of the vocabulary's words; `size` entries at most.

    Every text is read; each batch of texts gives a row (word, count) for each of its words, and the sums of the `size` commonest come to the driver."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        seen: Counter[str] = Counter()
        for t in batch["text"].to_pylist():
            seen.update(length_table(path).pretokens(t)[0])
        return pa.RecordBatch.from_arrays([pa.array(seen.keys(), pa.string()), pa.array(seen.values(), pa.int64())], ["word", "n"])

    sums = per_batch(id_and_text(docs), make, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    total = {r.word: r.n for r in sums.orderBy(F.desc("n"), "word").limit(size).collect()}
    table = length_table(path)
    words = ([*total] + [w for w in vocabulary_words(table) if w not in total])[:size]
    return dict(zip(words, table.lengths(words), strict=True))


def token_counts(docs: DataFrame, path: str, limit: int = LIMIT) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of every whole text."""
    tier = docs.sparkSession.sparkContext.broadcast(frequent_lengths(docs, path))

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts, table = batch["text"].to_pylist(), length_table(path)
        table.first_tier(tier.value)
        n = [x for a, b in chunks(texts) for x in table.count(texts[a:b])]
        columns = [pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())]
        return pa.RecordBatch.from_arrays([batch["doc_id"], *columns], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return per_batch(id_and_text(docs), make, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def vocabulary_file() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(read(spark, sf_dir, "documents"), vocabulary_file())
