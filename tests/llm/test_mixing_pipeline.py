import corpus_pipeline
import pytest
from chronolode.llm import lines, mixing, simhash
from compare import differences, duck
from fixtures import documents, empty, rows_of

SF = "/root/testdata/sf0.01"


def slow_targets(sizes, weights=(5, 2, 1)):
    """By repeated resharing."""
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % 3] for i, s in enumerate(names)}
    fixed, left = {}, 1.5 * sum(sizes.values())
    while True:
        open_ = [s for s in names if s not in fixed]
        total = sum(w[s] for s in open_)
        share = {s: left * w[s] / total for s in open_}
        over = [s for s in open_ if share[s] >= 2 * sizes[s]]
        if not over:
            return fixed | share
        for s in over:
            fixed[s] = 2.0 * sizes[s]
        left = 1.5 * sum(sizes.values()) - sum(fixed.values())
        if len(fixed) == len(names):
            return fixed


def test_mix(spark, monkeypatch):
    monkeypatch.setattr(mixing, "BUCKET_ROWS", 4)
    docs = documents(spark)
    rows = mixing.mix(docs).collect()
    sizes = {}
    for _, t, s in rows_of(docs):
        sizes[s] = sizes.get(s, 0) + len(t.split())
    want = slow_targets(sizes)
    assert len(rows) == docs.count()
    largest = max(r.size for r in rows)
    for s, target in want.items():
        mine = [r for r in rows if r.source == s]
        assert all(abs(r.target - target) < 1e-6 and r.source_size == sizes[s] and r.taken in (0, r.size, 2 * r.size) for r in mine)
        assert abs(sum(r.taken for r in mine) - target) <= largest
    assert sum(r.taken for r in rows) <= 1.5 * sum(sizes.values())
    assert sorted(map(str, rows)) == sorted(map(str, mixing.mix(docs.repartition(5)).collect()))
    many = mixing.mixed_documents(docs)
    assert many.columns == docs.columns and many.count() == sum(r.copies for r in rows)
    assert mixing.mix(empty(spark)).count() == 0
    names = ("s", "b", "before", "size", "copies", "copy", "taken", "target", "source_size", "mix_key", "mix_source", "vft0", "key", "row", "id", "known", "sig", "number", "a b")
    clash = docs.selectExpr("*", *(f"'{c}' AS `{c}`" for c in names))
    kept = mixing.mixed_documents(clash)
    assert kept.columns == clash.columns and kept.count() == many.count() and all(x[c] == c for x in kept.collect() for c in names)
    assert mixing.mixed_documents(empty(spark)).columns == docs.columns


def test_mix_of_repeated_rows(spark):
    """The cut falls among rows of one id and text: the right number of them is taken, and sums stay near the target."""
    docs = spark.createDataFrame([(7, "one two three", "s")] * 50 + [(i, "word " * 5, "t") for i in range(100, 110)] + [(None, "a b", "s")] * 9, "doc_id long, text string, source string")
    rows = mixing.mix(docs).collect()
    assert len(rows) == 69
    for s in ("s", "t"):
        mine = [r for r in rows if r.source == s]
        assert abs(sum(r.taken for r in mine) - mine[0].target) <= 5 and all(r.copies in (0, 1, 2) for r in mine)
    assert mixing.mixed_documents(docs).count() == sum(r.copies for r in rows)


@pytest.mark.parametrize("module", [mixing, lines])
def test_equal_sql(spark, module):
    a, b, _ = differences(module.query(spark, SF), module.ORACLE, duck(SF))
    assert not a and not b


def test_pipeline_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    n, sizes = docs.count(), []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns, name
        path = corpus_pipeline.shared_folder(spark)
        out.write.parquet(path)
        docs = spark.read.parquet(path)
        sizes.append(docs.count())
    assert sizes[0] < n and sizes[1] == sizes[0] and sizes[2] < sizes[1] and sizes[3] > sizes[2]
    assert docs.groupBy("doc_id").count().agg({"count": "max"}).first()[0] <= 2
    before = spark.read.parquet(path)
    out = corpus_pipeline.STAGES[-1][1](spark, before, SF)
    assert out.count() == sizes[-1] and out.filter("n_tokens IS NULL").count() == 0
    assert simhash.groups(before).filter("doc_id <> component_id").count() == 0


def test_empty_pipeline_tables(spark):
    none = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, none, SF).count() == 0
