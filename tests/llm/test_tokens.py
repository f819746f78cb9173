import hashlib
import random

import numpy as np
import public_tokenizers
import tiktoken
from chronolode.llm import bpe, counts
from fixtures import documents, empty, rows_of
from tokenizers import Tokenizer

HARD = ["", " ", "\n\n  x", "a" * 3000, "日本語のテキスト" * 20, "it's we'll DON'T", "".join(map(chr, range(0x300))), "\x00\x01\x1c\x1d x\x85y z  ", "😀😃" * 9, "<|endoftext|> hi", "ΑΣ Σ ΟΔΟΣ", "é İ ŉ", "ab" * 300 + "\t\t \n", "١٢٣ ²³½ Ⅷ"]


def mixed(n):
    r = random.Random(3)
    return ["".join(r.choice(["a", "b", " ", "'", "s", "1", "\n", "é", "中", "  ", "!", "́", "Σ", "ll", "\x1c"]) for _ in range(r.randrange(1, 60))) for _ in range(n)]


def reference():
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.load_ranks(bpe.rank_file()), special_tokens={})


def test_ids_equal_the_library():
    codec, enc, texts = bpe.codec(bpe.rank_file()), reference(), HARD + mixed(200)
    ids = codec.encode(texts)
    assert [np.frombuffer(x, "<u4").tolist() for x in ids] == [enc.encode_ordinary(t) for t in texts]
    assert codec.decode(ids) == [t.encode() for t in texts]


def test_cache_is_bounded_and_long_texts_are_cut_for_decoding(monkeypatch):
    monkeypatch.setattr(bpe, "CACHE", 50)
    monkeypatch.setattr(bpe, "TOKENS", 7)
    codec, enc, texts = bpe.Codec(bpe.rank_file()), reference(), mixed(60)
    for t in texts:
        (ids,) = codec.encode([t])
        assert np.frombuffer(ids, "<u4").tolist() == enc.encode_ordinary(t) and codec.decode([ids]) == [t.encode()]
    assert len(codec.known) < 200


def test_words_of_any_length(monkeypatch):
    """Words on both sides of the length that parts the two recursive queries, alone and mixed, over turning cache generations."""
    r, enc = random.Random(11), reference()
    codec = bpe.Codec(bpe.rank_file())
    texts = ["".join(r.choice(a) for _ in range(n)) for n in (1, 2, 31, 32, 33, 63, 64, 65, 66, 300) for a in ("ab", "abcdefghijklmnopqrstuvwxyz", "é漢", "0123456789", "!?-", "  \t\n")]
    for cache in (400_000, 7):
        monkeypatch.setattr(bpe, "CACHE", cache)
        for some in (texts, texts[::-1], texts[:20] * 2):
            ids = codec.encode(some)
            assert [np.frombuffer(x, "<u4").tolist() for x in ids] == [enc.encode_ordinary(t) for t in some] and codec.decode(ids) == [t.encode() for t in some]


def test_very_long_text(spark):
    text = "A long text, with words and 123 numbers.\n" * 8000
    (row,) = bpe.round_trip(documents(spark, [text]).filter("doc_id = 0").dropDuplicates(), bpe.rank_file()).collect()
    assert row.n_tokens == len(reference().encode_ordinary(text)) and row.decoded_sha256 == hashlib.sha256(text.encode()).hexdigest()


def test_rows(spark):
    docs, enc, path = documents(spark), reference(), bpe.rank_file()
    ids = {t: np.array(enc.encode_ordinary(t), "<u4").tobytes() for _, t, _ in rows_of(docs)}
    sha = lambda b: hashlib.sha256(b).hexdigest()
    got = sorted((r.doc_id or -1, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in bpe.round_trip(docs, path).collect())
    assert got == sorted((d or -1, len(ids[t]) // 4, sha(ids[t]), sha(t.encode())) for d, t, _ in rows_of(docs))
    back = bpe.decode(bpe.encode(docs, path), path)
    assert sorted(bytes(r.data) for r in back.collect()) == sorted(t.encode() for _, t, _ in rows_of(docs))
    assert bpe.round_trip(empty(spark), path).count() == 0


def test_counts_equal_the_library(spark):
    path = counts.vocabulary_file()
    tok, texts = Tokenizer.from_file(path), HARD + mixed(300)
    assert counts.length_table(path).count(texts) == [len(e.ids) for e in tok.encode_batch(texts, add_special_tokens=False)]
    docs = documents(spark)
    got = sorted((r.doc_id or -1, r.n_bytes, r.n_tokens, r.over_limit) for r in counts.token_counts(docs, path).collect())
    n = {t: len(tok.encode(t, add_special_tokens=False).ids) for _, t, _ in rows_of(docs)}
    assert got == sorted((d or -1, len(t.encode()), n[t], n[t] > 2048) for d, t, _ in rows_of(docs))
    assert counts.token_counts(empty(spark), path).count() == 0
    assert len(counts.frequent_lengths(docs, path, size=100)) == 100


def test_frequent_words_are_those_of_all_texts(spark):
    """A word of the last texts alone, commoner than any of the many before."""
    rows = [(i, " ".join(f"w{i}x{j} w{i}x{j}" for j in range(40))) for i in range(400)] + [(400 + i, "zyzzyvas " * 50) for i in range(20)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1).sortWithinPartitions("doc_id")
    conf, before = "spark.sql.execution.arrow.maxRecordsPerBatch", spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set(conf, "10")
    try:
        assert "zyzzyvas" in counts.frequent_lengths(docs, counts.vocabulary_file(), size=50)
    finally:
        spark.conf.set(conf, before)
