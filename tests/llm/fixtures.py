"""Small documents with the awkward cases, and plain-Python references."""

from __future__ import annotations

import random

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score double, component_id string"


def documents(spark, texts=None):
    r = random.Random(5)
    words = ["alpha", "beta", "Gamma,", "delta.", "the", "of", "été", "中文", "x1", "it's"]
    body = [" ".join(r.choice(words) for _ in range(r.randrange(5, 60))) for _ in range(30)]
    base = texts or [None, "", " \n\t", "same line of text here\nother", "same line of text here\nother", "SAME line of text here \nmore words follow", "short\nshort", *body, body[0], body[0] + " tail", "word " * 3000, "a\x00b <|endoftext|> c"]
    rows = [(i, t, "en", ["s1", "s2", None, "s10"][i % 4], None if t is None else len(t), 0.5, "x") for i, t in enumerate(base)]
    rows += [rows[min(7, len(rows) - 1)], (None, "text without an id of its own", None, "s1", 5, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def rows_of(docs):
    return [(r.doc_id, r.text or "", r.source) for r in docs.select("doc_id", "text", "source").collect()]


def roots(nodes, links):
    parent = {n: n for n in nodes}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}
