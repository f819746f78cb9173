import zlib

import numpy as np
from chronolode.llm import licenses, quality, toxicity
from compare import differences, duck
from fixtures import documents, empty

SF = "/root/testdata/sf0.1"


def held(spark, query, label, fold, left):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    rows = query(spark, SF).join(labels, "doc_id").select("doc_id", "held_out", "predicted", label).collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % fold == left) for r in rows)
    return [(r.predicted, r[label]) for r in rows if r.held_out]


def test_quality_on_held_out_rows(spark):
    rows = held(spark, quality.query, "quality", 5, 0)
    bad, good = ([p for p, y in rows if y == c] for c in (0, 1))
    assert np.mean(bad) <= 0.05 and np.mean(good) >= 0.98


def test_toxicity_on_held_out_rows(spark):
    rows = held(spark, toxicity.query, "toxic", 3, 1)
    toxic, clean = ([p for p, y in rows if y == c] for c in (1, 0))
    # Some 280 toxic rows to learn from here: words of a language with few rows stay unknown. With the 2,000 rows of the larger tables all are found.
    assert np.mean(toxic) >= 0.85 and np.mean(clean) <= 0.015


def test_discriminant_matches_direct_densities():
    r = np.random.default_rng(0)
    x = np.concatenate([r.normal(0, 1, (200, 3)), r.normal(2, 0.5, (300, 3))])
    y = np.repeat([0, 1], [200, 300])
    m = quality.fit(x, y)
    z = (x - m.centre) / m.scale
    for c in (0, 1):
        cov = np.cov(z[y == c].T, bias=True)
        cov = (1 - quality.SHRINK) * cov + quality.SHRINK * np.trace(cov) / 3 * np.eye(3)
        d = z - z[y == c].mean(0)
        want = -0.5 * np.einsum("ij,jk,ik->i", d, np.linalg.inv(cov), d) - 0.5 * np.linalg.slogdet(cov)[1]
        got = -0.5 * ((d @ m.factors[c].T) ** 2).sum(1) - 0.5 * m.log_dets[c]
        assert np.allclose(got, want)
    assert (m.score(x) >= 0.5).astype(int).tolist() == y.tolist() or ((m.score(x) >= 0.5) == y).mean() > 0.97


def test_marginals_match_enumeration():
    """Runs of words without features as matrix powers, against all state sequences."""
    from itertools import product

    t = toxicity.Tagger({b"=bad": 2.5, b"=odd": -1.0, b"4fool": 1.5, b"<you": 0.8, b">head": -0.6}, -1.2, np.array([[0.4, -0.3], [-0.5, 0.7]]))
    for text in ("bad", "so bad", "a b c bad d e f odd g foolish", "bad bad x y", "odd", "you x bad head", "x head you", "you"):
        found = toxicity.words(text)
        at, p = t.marginals(found)
        total, hot = 0.0, np.zeros(len(found))
        for states in product((0, 1), repeat=len(found)):
            s = sum(t.potential(found, i) for i, y in enumerate(states) if y) + sum(t.moves[a, b] for a, b in zip(states, states[1:], strict=False))
            total += np.exp(s)
            hot += np.exp(s) * np.array(states)
        assert np.allclose(p, (hot / total)[at]), text


def test_gradient_matches_differences():
    """The objective against its own small differences, and its value against all state sequences of one record."""
    from itertools import product

    records = [(5, [(1, [0, 2], 1), (2, [1], 0)], 3), (3, [], 7), (4, [(0, [2], 0), (3, [0], 1)], 1), (1, [(0, [1], 1)], 2)]
    s, theta = toxicity.Sequences.of(records), np.random.default_rng(3).normal(0, 0.7, 8)
    loss, grad = toxicity.objective(theta, s)
    for i in range(len(theta)):
        step = np.zeros(len(theta))
        step[i] = 1e-5
        assert abs((toxicity.objective(theta + step, s)[0] - toxicity.objective(theta - step, s)[0]) / 2e-5 - grad[i]) < 1e-5
    want, moves = toxicity.DECAY / 2 * theta @ theta, theta[-4:].reshape(2, 2)
    for size, marked, n in records:
        hot, gold = np.full(size, theta[-5]), [0] * size
        for place, ids, y in marked:
            hot[place] += theta[ids].sum()
            gold[place] = y
        value = lambda states, hot=hot: hot @ np.array(states) + sum(moves[a, b] for a, b in zip(states, states[1:], strict=False))
        want += n * (np.log(sum(np.exp(value(x)) for x in product((0, 1), repeat=size))) - value(gold))
    assert abs(loss - want) < 1e-9


def test_lexicon_and_features_match_counting(spark):
    """Word counts, prefixes and neighbours made by the executors, against plain loops over the texts."""
    import random
    from collections import Counter

    r = random.Random(8)
    plain = [f"word{i}" for i in range(60)]
    rows = []
    for i in range(60):
        ws = [r.choice(plain) for _ in range(30)]
        if i % 3 == 0:
            ws[10:10] = ["you", r.choice(["scumbag", "scumface", "scumhead", "vermin"])]
        rows.append((i, " ".join(ws[:20]) + ". " + " ".join(ws[20:]), int(i % 3 == 0)))
    rows += [(100, rows[0][1], 1), (101, rows[0][1], 1)]
    some = spark.createDataFrame(rows, "doc_id long, text string, label int")
    docs = {}
    for _, t, y in rows:
        ws = toxicity.words(t)
        docs.setdefault((y, min(zlib.crc32(b" ".join(ws[i : i + 5])) for i in range(len(ws) - 4))), set()).update(ws)
    toxic, clean = (Counter(w for (y, _), ws in docs.items() if y == c for w in ws) for c in (1, 0))
    copies = Counter(w for _, t, y in rows if y for w in set(toxicity.words(t)))
    got = {bytes(x.word): (x.toxic, x.clean, x.copies) for x in toxicity._word_counts(some).collect()}
    assert got.pop(b"") == (sum(y for y, _ in docs), sum(1 - y for y, _ in docs), 22)
    assert got == {w: (toxic[w], clean[w], copies[w]) for w in {*toxic, *clean}}
    bad = {b"scumbag", b"scumface", b"scumhead"}
    counts = spark.createDataFrame([(bytearray(w), *x) for w, x in got.items()], "word binary, toxic long, clean long, copies long")
    assert toxicity._prefix_features(counts, bad) == [b"4scum"]
    hot, cold = Counter(), Counter()
    for _, t, y in rows:
        for part in t.split(". "):
            ws = toxicity.words(part)
            for i, w in enumerate(ws):
                (hot if y and w in bad else cold).update(([b"<" + ws[i - 1]] if i else []) + ([b">" + ws[i + 1]] if i + 1 < len(ws) else []))
    assert sorted(toxicity._context_features(some, bad)) == sorted(f for f, n in hot.items() if n >= max(3, 0.9 * (n + cold[f])))
    names = [b"=scumbag", b"4scum", b"<you"]
    records = toxicity._records(some, bad, names)
    assert sum(n for _, _, n in records) == 2 * len(rows) and sum(n * sum(y for _, _, y in marked) for _, marked, n in records) == sum(w in bad for _, t, y in rows if y for w in toxicity.words(t))
    assert len(toxicity.lexicon([(b"a", 5, 0, 5), (b"b", 2, 0, 2), (b"c", 5, 5, 5), (b"d", 3, 0, 30)], {5: 1, 2: 1, 10: 1, 3: 1}, 0.3)) == 1


def test_statistics_match_counting():
    """op7's statistics by plain loops over characters, words and lines."""
    import math

    for text in ("", "Ab c.1\n\nthe THE the, x", "é日本 der die das! (ok) #$%\n" * 3, "A" * 50):
        data = text.encode()
        n, ws, ls = max(1, len(data)), data.split(), data.split(b"\n")
        w, share = max(1, len(ws)), lambda test: math.sqrt(sum(map(test, data)) / max(1, len(data)))
        letter, blank = (lambda b: b >= 128 or chr(b).isalpha()), (lambda b: b == 32 or 9 <= b <= 13)
        digit, stop = (lambda b: 48 <= b <= 57), (lambda b: chr(b) in ".,;:!?'\"-()")
        p = [data.count(bytes([b])) / n for b in set(data)]
        want = [
            math.log1p(len(data)), math.log1p((n - sum(map(blank, data))) / w), share(lambda b: 65 <= b <= 90), share(digit), share(stop), share(lambda b: not (letter(b) or digit(b) or stop(b) or blank(b))),
            math.sqrt(len(set(ws)) / w), math.sqrt(sum(x in quality.COMMON for x in ws) / w), math.log1p(len(data) / len(ls)), math.sqrt(1 - len(set(ls)) / len(ls)), math.sqrt(data.count(b".") / w), -sum(x * math.log(x) for x in p),
        ]
        assert np.allclose(quality.statistics(text), want), text


def test_calibration_is_the_best_of_a_grid():
    r = np.random.default_rng(4)
    margin, y = r.normal(0, 3, 400), r.integers(0, 2, 400)
    margin += 2 * y
    slope, offset = quality.calibrated(margin, y)
    weight = np.where(y == 1, 0.5 / (y == 1).sum(), 0.5 / (y == 0).sum())
    loss = lambda a, b: (weight * np.logaddexp(0, np.where(y == 1, -1, 1) * (a * margin + b))).sum() + 5e-5 * (a * a + b * b)
    assert loss(slope, offset) <= min(loss(a, b) for a in np.linspace(-1, 2, 61) for b in np.linspace(-3, 3, 61)) + 1e-9


def test_spans_are_offsets_of_the_text():
    t = toxicity.Tagger({b"=idiot": 9.0}, -3.0, np.zeros((2, 2)))
    text = "Été, IDIOT! no\nidiot"
    assert [text[a:b] for a, b, _ in t.spans(text)] == ["IDIOT", "idiot"]


def test_awkward_rows(spark):
    docs = documents(spark)
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    some = spark.createDataFrame([(i, i % 2, int(i == 9)) for i in range(7, 30)] + [(None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")
    for labels in (none, some):
        q, t = quality.train(docs, labels), toxicity.train(docs, labels)
        assert quality.scores(docs, q).count() == docs.count() == toxicity.scores(docs, t).count()
        assert quality.scores(docs, q).filter("score IS NULL OR score < 0 OR score > 1 OR isnan(score)").count() == 0
        assert quality.accepted(docs, q).columns == docs.columns
        assert quality.scores(empty(spark), q).count() == 0 and toxicity.span_rows(empty(spark), t).count() == 0
    toxicity.span_rows(docs, t).count()
    twice = spark.createDataFrame([(i, i % 2, i % 2) for i in range(7, 30)] * 2, "doc_id long, quality int, toxic int")
    assert quality.scores(docs, quality.train(docs, twice)).count() == docs.count() == toxicity.scores(docs, toxicity.train(docs, twice)).count()
    long = documents(spark, ["word " * 200_000, "x" * 300_000, "good text. " * 30_000])
    assert toxicity.scores(long, toxicity.Tagger({b"=word": 1.0}, -2.0, np.zeros((2, 2)))).filter("isnan(score)").count() == 0 and quality.scores(long, quality.train(docs, none)).count() == long.count()


def test_licences(spark):
    import re

    assert all(re.search(licenses.ANCHORS, s) for s in licenses.SENTENCES.values())
    texts = [
        "Released under the MIT License.", "Prose.\nLicensed under the Apache License,\nVersion 2.0. More.", "This program is free software: you can redistribute it and/or modify it\nunder the terms of the GNU General Public License as published by\nthe Free Software Foundation, either version 3 of the License, or\n(at your option) any later version.\n\nThis program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of merchantability or fitness for a particular purpose.",
        "the license plate", None, "SPDX-License-Identifier: MIT\nLicensed under CC BY-NC 4.0.",
    ]
    docs = documents(spark, texts)
    got = {r.doc_id: r.licenses for r in licenses.scan(docs).collect()}
    assert [got[i] for i in range(6)] == ["MIT", "Apache-2.0", "GPL-3.0-or-later", "", "", "CC-BY-NC-4.0,MIT"]
    assert licenses.scan(empty(spark)).count() == 0


def test_licences_equal_sql(spark):
    a, b, _ = differences(licenses.query(spark, "/root/testdata/sf0.01"), licenses.ORACLE, duck("/root/testdata/sf0.01"))
    assert not a and not b


def test_reserved_rights_are_a_notice(spark):
    texts = ["Prose.\nAll rights reserved.", "Prose. ALL RIGHTS\nRESERVED. More.", "all rights were reserved", "Released under the MIT License.\nAll rights reserved."]
    got = {r.doc_id: r.licenses for r in licenses.scan(documents(spark, texts), licenses.ALL_SENTENCES, licenses.ALL_RULES, licenses.ALL_ANCHORS).collect()}
    assert [got[i] for i in range(4)] == ["Proprietary", "Proprietary", "", "MIT,Proprietary"]
    a, b, _ = differences(licenses.notices_query(spark, "/root/testdata/sf0.01"), licenses.NOTICES_ORACLE, duck("/root/testdata/sf0.01"))
    assert not a and not b


def test_licence_texts(spark):
    """Further licences, rules with bounded gaps, repeated rows and long texts."""
    import re

    assert all(re.search(licenses.TEXT_ANCHORS, s) for s in licenses.TEXT_SENTENCES.values())
    isc = "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.\n\n"
    end = "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS."
    texts = [isc + end, isc + "Some other sentence here. " * 30 + "\n\n" + end, isc + "Some other sentence here. " * 5 + "\n\n" + end, "prose. " * 40_000 + "Distributed under the Boost Software License, Version 1.0.", "SPDX-License-Identifier: MPL-2.0", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."]
    docs = documents(spark, texts)
    rows = licenses.scan(docs, licenses.TEXT_SENTENCES, licenses.TEXT_RULES, licenses.TEXT_ANCHORS, licenses.GAP).collect()
    got = {r.doc_id: r.licenses for r in rows}
    assert [got[i] for i in range(6)] == ["ISC", "", "ISC", "BSL-1.0", "MPL-2.0", "Unlicense"] and len(rows) == docs.count()
    assert sum(r.doc_id == 5 for r in rows) == 2
    a, b, n = differences(licenses.texts_query(spark, "/root/testdata/sf0.01"), licenses.TEXTS_ORACLE, duck("/root/testdata/sf0.01"))
    assert not a and not b and n
