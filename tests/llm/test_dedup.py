import hashlib
import random
from collections import defaultdict

import numpy as np
import pytest
import xxhash
from chronolode.llm import embeddings, graph, lines, near, simhash
from fixtures import documents, empty, roots, rows_of


def test_components(spark):
    r = random.Random(2)
    links = [(r.randrange(300), r.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(1000, 1060)] + [(5, 5)]
    got = {x.node: x.root for x in graph.components(spark.createDataFrame(links, "a long, b long")).collect()}
    want = {n: x for n, x in roots({n for e in links for n in e}, links).items() if n != x}
    assert got == want
    assert graph.components(spark.createDataFrame([], "a long, b long")).count() == 0


def slow_fingerprint(text):
    words = [w for w in "".join(c.lower() if "A" <= c <= "Z" else c for c in text).translate({i: 32 for i in (9, 10, 11, 12, 13)}).split(" ") if w]
    if not words:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(words[i : i + 4]).encode(), 42) for i in range(max(1, len(words) - 3))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


@pytest.mark.parametrize("few", [1 << 24, 0])
def test_simhash_links_and_groups(spark, monkeypatch, few):
    monkeypatch.setattr(simhash, "FEW", few)
    monkeypatch.setattr(simhash, "PART", 100)
    r = random.Random(4)
    base = [r.getrandbits(64) for _ in range(40)]
    fps = sorted({b ^ sum(1 << r.randrange(64) for _ in range(r.randrange(6))) & (2**64 - 1) for b in base for _ in range(6)})
    signed = np.array(fps, np.uint64).view(np.int64).tolist()
    got = {(x.a, x.b) for x in simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long"), len(fps)).collect()}
    want = {(a, b) for a in signed for b in signed if a < b and ((a ^ b) & (2**64 - 1)).bit_count() <= 4}
    assert got == want and want
    docs = documents(spark)
    rows = [(d, slow_fingerprint(t)) for d, t, _ in rows_of(docs)]
    nodes = {f for _, f in rows}
    root = roots(nodes, [(a, b) for a in nodes for b in nodes if (a ^ b).bit_count() <= 4])
    least = defaultdict(list)
    for d, f in rows:
        least[root[f]] += [d] if d is not None else []
    got = sorted((x.doc_id if x.doc_id is not None else -1, x.fp & (2**64 - 1), x.component_id) for x in simhash.groups(docs).collect())
    assert got == sorted((d if d is not None else -1, f, min(least[root[f]], default=None)) for d, f in rows)
    kept = simhash.deduplicated(docs)
    assert kept.columns == docs.columns
    assert sorted(x.doc_id for x in kept.collect() if x.doc_id is not None) == sorted({min(v) for v in least.values() if v})
    linked = {x.node: x.root for x in simhash.roots(spark.createDataFrame([(x,) for x in signed], "fp long"), len(fps)).collect()}
    assert {n: linked.get(n, n) for n in signed} == roots(signed, want)
    twins = documents(spark, ["a"]).limit(0).unionByName(spark.createDataFrame([(3, "one text", "en", "s", 8, 0.0, "x"), (3, "other text", "en", "s", 10, 0.0, "x")], docs.schema))
    assert len({x.text for _ in range(3) for x in simhash.deduplicated(twins.repartition(2)).collect()}) == 1
    assert simhash.groups(empty(spark)).count() == 0 and simhash.deduplicated(empty(spark)).count() == 0


def test_shared_counts(monkeypatch):
    monkeypatch.setattr(near, "COLUMNS", 64)
    r = np.random.default_rng(0)
    found = [np.unique(r.integers(0, 300, r.integers(0, 90)).astype(np.uint64)) for _ in range(40)]
    want = np.array([[len(np.intersect1d(a, b)) for b in found] for a in found])
    assert ((near.shared(found) == want) | np.eye(40, dtype=bool)).all()


def test_near_copies_at_five_words(spark, monkeypatch):
    """Copies with edits here and there, beside the Jaccard similarity of all pairs; the fingerprints of most are too far apart for op5."""
    import corpus_pipeline

    r = random.Random(9)
    base = [[f"w{r.randrange(5000)}" for _ in range(120)] for _ in range(12)]
    edited = lambda ws, n: [f"e{r.randrange(9999)}" if i in at else w for at in [set(r.sample(range(120), n))] for i, w in enumerate(ws)]
    texts = [None, "", " \n", "one two", "One  TWO", *(" ".join(edited(ws, n)) for ws in base for n in (0, 0, 1, 2, 2, 3, 6))]
    docs = documents(spark, texts)

    def slow(text):
        ws = (text or "").encode().lower().split()
        return {tuple(ws[i : i + 5]) for i in range(max(1, len(ws) - 4))} if ws else set()

    sets = {d: slow(t) for d, t, _ in rows_of(docs) if d is not None}
    like = lambda x, y: x == y or len(x & y) >= 0.8 * len(x | y)
    root = roots(sets, [(a, b) for a in sets for b in sets if a < b and like(sets[a], sets[b])])
    got = {x.doc_id: x.component_id for x in near.groups(docs).collect() if x.doc_id is not None}
    assert got == root and len(set(root.values())) < len(root)
    monkeypatch.setattr(near, "TILE", 2)
    assert {x.doc_id: x.component_id for x in near.groups(docs).collect() if x.doc_id is not None} == root
    kept = near.deduplicated(docs)
    assert kept.columns == docs.columns and sorted(x.doc_id for x in kept.collect() if x.doc_id is not None) == sorted(set(root.values()))
    assert near.groups(empty(spark)).count() == 0
    names = ("id", "sig", "row", "kept_id", "component_id2", "node", "fp", "key", "keys", "a b")
    clash = docs.selectExpr("*", *(f"'{c}' AS `{c}`" for c in names))
    for module in (near, simhash):
        same = module.deduplicated(clash).collect()
        assert sorted(x.doc_id for x in same if x.doc_id is not None) == sorted(x.doc_id for x in module.deduplicated(docs).collect() if x.doc_id is not None) and all(x[c] == c for x in same for c in names)
    stayed = {x.doc_id for x in corpus_pipeline.drop_near_copies(spark, docs, "").collect() if x.doc_id is not None}
    assert stayed <= set(root.values()) and not {x.doc_id for x in simhash.deduplicated(docs).collect() if x.doc_id is not None} <= set(root.values())


TO_LOWER = {i: i + 32 for i in range(ord("A"), ord("Z") + 1)}


def slow_lines(rows, least=10):
    key = lambda s: s.strip(" \t\n\x0b\f\r").translate(TO_LOWER)
    order = lambda d: (d is None, d or 0)
    first = {}
    for d, t, _ in rows:
        for k in map(key, t.split("\n")):
            if len(k) >= least:
                first[k] = min(first.get(k, order(d)), order(d))
    out = []
    for d, t, _ in rows:
        parts = t.split("\n")
        kept = [p for p in parts if len(key(p)) < least or first[key(p)] == order(d)]
        out.append((-1 if d is None else d, len(parts), len(parts) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out)


def test_line_dedup(spark):
    r = random.Random(6)
    texts = ["\n".join(r.choice(["a common line of text", "Another common line ", "one more common line", f"own line {i}", "short"]) for _ in range(r.randrange(1, 9))) for i in range(200)]
    for docs in (documents(spark), documents(spark, texts).repartition(7)):
        got = sorted((-1 if x.doc_id is None else x.doc_id, x.n_lines, x.n_dropped, x.kept_sha256) for x in lines.keep_bitmaps(docs, digest=True).collect())
        assert got == slow_lines(rows_of(docs))
        kept = lines.deduplicated(docs)
        assert kept.columns == docs.columns and kept.count() == docs.count()
        texts_by = sorted(hashlib.sha256((x.text or "").encode()).hexdigest() for x in kept.collect())
        assert texts_by == sorted(x[3] for x in slow_lines(rows_of(docs)))
    assert lines.keep_bitmaps(empty(spark)).count() == 0 and lines.deduplicated(empty(spark)).count() == 0
    own = documents(spark, ["one line that is shared\nfirst"]).drop("score", "component_id")
    twins = own.unionByName(spark.createDataFrame([(5, "one line that is shared\nx", "en", "s", 3), (5, "y\none line that is shared", "en", "s", 3), (5, "y\none line that is shared", "en", "s", 3)], own.schema))
    assert sorted((x.doc_id, x.text) for x in lines.deduplicated(twins).collect() if x.doc_id == 5) == [(5, "x"), (5, "y"), (5, "y")]
    clash = documents(spark).selectExpr("*", *(f"'{c}' AS `{c}`" for c in ("doc", "unknown", "sig", "row", "kept", "pos", "n", "copies", "keep_bitmap", "line_doc", "line_drops", "h1", "a b")))
    same = lines.deduplicated(clash)
    assert same.columns == clash.columns and same.count() == clash.count() and {(x.doc, x.sig, x.row, x["a b"]) for x in same.collect()} == {("doc", "sig", "row", "a b")}
    assert lines.keep_bitmaps(clash).count() == clash.count()
    flags = [True, False, True]
    assert lines.apply_bitmap("a\nb\nc", lines.bitmap(flags)) == "a\nc"


def test_first_occurrences_over_partition_edges():
    """A key that spans several sorted partitions: edges and heads name the rows that one stream would drop."""
    import pyarrow as pa

    rows = sorted([(h, 0, 0, d) for h, n in ((1, 1), (2, 12), (3, 2), (4, 7)) for d in range(n)])
    for cuts in ([], [3], [2, 5, 9], [1, 2, 3, 4, 13, 15], [13]):
        found = []
        for a, b in zip([0, *cuts], [*cuts, len(rows)], strict=True):
            part = [pa.RecordBatch.from_arrays([pa.array([x[i] for x in rows[s : s + 2]], pa.int64()) for i in (0, 1, 2, 3, 3, 3)], ["h1", "h2", "unknown", "doc", "sig", "pos"]) for s in range(a, b, 2)]
            part = [p.slice(0, min(p.num_rows, b - s)) for p, s in zip(part, range(a, b, 2), strict=True)]
            found += [x for p in lines._firsts(iter(part)) for x in p.to_pylist()]
        keeper = {}
        for x in found:
            if x["kind"] != lines.DROP:
                keeper[x["h1"]] = min(keeper.get(x["h1"], 99), x["doc"])
        gone = sorted((x["h1"], x["doc"]) for x in found if x["kind"] == lines.DROP or x["kind"] == lines.EDGE and x["doc"] != keeper[x["h1"]])
        assert gone == [(h, d) for h, _, _, d in rows if d > 0], cuts


def test_embeddings(spark, monkeypatch):
    monkeypatch.setattr(embeddings, "TILE", 16)
    r = np.random.default_rng(1)
    base = r.standard_normal((20, 24)).astype(np.float32)
    vectors = [(base[i % 20] + 0.25 * r.standard_normal(24)).astype(np.float32).tolist() for i in range(120)]
    rows = [(i, v, i % 3) for i, v in enumerate(vectors)] + [(200 + i, vectors[3], 0) for i in range(30)]
    rows += [(300, None, 1), (301, [0.0] * 24, 1), (302, [1.0, None] * 12, 1), (303, [float("nan")] * 24, 1), (304, vectors[0], None), (305, vectors[0], None), (306, [1.0, 2.0], 0), (307, [2.0, 4.0], 0), (308, [], 0), (309, [float("inf")] * 24, 2)]
    df = spark.createDataFrame([(*x, "extra") for x in rows], "vec_id long, embedding array<float>, label int, node string")
    fine = {i: (lab, np.array(v, np.float64)) for i, v, lab in rows if lab is not None and v and None not in v and np.isfinite(v).all() and any(v)}
    links = [(a, b) for a, (la, x) in fine.items() for b, (lb, y) in fine.items() if a != b and la == lb and len(x) == len(y) and x @ y / (np.linalg.norm(x) * np.linalg.norm(y)) >= 0.93]
    root = roots([i for i, _, _ in rows], links)
    n = defaultdict(int)
    for a, _ in links:
        n[a] += 1
    got = sorted(map(tuple, embeddings.groups(df).select("vec_id", "n_links", "component_id", "kept").collect()))
    assert got == sorted((i, n[i], root[i], root[i] == i) for i, _, _ in rows) and links
    assert embeddings.groups(df.limit(0)).count() == 0
