"""The whole pipeline on the small tables, beside plain Python for every stage."""

import hashlib
from collections import Counter

import corpus_pipeline
import numpy as np
import public_tokenizers
import tiktoken
from chronolode.llm import bpe, quality
from fixtures import roots
from test_dedup import slow_fingerprint
from test_mixing_pipeline import slow_targets

SF = "/root/testdata/sf0.01"
WHITE = " \t\n\x0b\f\r"


def lower(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text)


def words_of(text):
    return [w for w in text.translate({ord(c): 32 for c in WHITE}).split(" ") if w]


def without_repeated_lines(rows):
    key = lambda line: lower(line.strip(WHITE))
    first = {}
    for d, text, _ in sorted(rows):
        for k in map(key, text.split("\n")):
            first.setdefault(k, d)
    return [(d, "\n".join(x for x in text.split("\n") if len(key(x)) < 10 or first[key(x)] == d), s) for d, text, s in rows]


def without_near_copies(rows):
    def shingles(text):
        ws = words_of(lower(text))
        return {tuple(ws[i : i + 5]) for i in range(max(1, len(ws) - 4))} if ws else set()

    def one_of_each(some, linked):
        root = roots(some, [(a, b) for a in some for b in some if a < b and linked(some[a], some[b])])
        return {d for d in some if root[d] == d}

    kept = one_of_each({d: shingles(t) for d, t, _ in rows}, lambda x, y: x == y or min(len(x), len(y)) >= 0.8 * max(len(x), len(y)) and len(x & y) >= 0.8 * len(x | y))
    rows = [r for r in rows if r[0] in kept]
    kept = one_of_each({d: slow_fingerprint(t) for d, t, _ in rows}, lambda x, y: (x ^ y).bit_count() <= 4)
    return [r for r in rows if r[0] in kept]


def mixed(rows):
    sizes, run, queue = Counter(), Counter(), []
    for _, t, s in rows:
        sizes[s] += len(words_of(t))
    target = slow_targets(sizes)
    for d, t, s in sorted(rows, key=lambda r: (hashlib.md5(str(r[0]).encode()).hexdigest(), r[0])):
        if size := len(words_of(t)):
            run[s] += size
            queue += [((run[s] + c * sizes[s]) / target[s], s is None, s or "", hashlib.md5(str(d).encode()).hexdigest(), d, size, c, t) for c in (0, 1)]
    out, total = [], 0
    for x in sorted(queue):
        total += x[5]
        if 2 * total > 3 * sum(sizes.values()):
            break
        out.append((x[4], x[7]))
    return out


def test_pipeline_equals_plain_python(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = quality.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    rows = [(r.doc_id, r.text or "", r.source) for r in docs.collect()]
    good = model.score(np.array([quality.statistics(t) for _, t, _ in rows])) >= quality.CUT
    rows = [r for r, keep in zip(rows, good, strict=True) if keep]
    n = len(rows)
    rows = without_near_copies(without_repeated_lines(rows))
    assert 500 < len(rows) < n
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.load_ranks(bpe.rank_file()), special_tokens={})
    want = Counter()
    for d, t in mixed(rows):
        ids = enc.encode_ordinary(t)
        want[d, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(t.encode()).hexdigest()] += 1
    for _, stage in corpus_pipeline.STAGES:
        path = corpus_pipeline.shared_folder(spark)
        stage(spark, docs, SF).write.parquet(path)
        docs = spark.read.parquet(path)
    got = Counter((r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in docs.collect())
    assert got == want and max(got.values()) == 2
