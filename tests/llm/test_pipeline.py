"""The pipeline's stages against plain statements of what each does."""

import pytest

from rasterflow.llm import pii
from tests.llm.test_operators import VOCABULARY, brute_components

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = {}
    for name, stage in pipeline.STAGES:
        before, docs = docs, pipeline.written(stage(spark, docs, SF))
        kept[name] = docs
        if name != "bpe":
            assert set(docs.columns) == set(before.columns)
    good = [(r["doc_id"], r["text"]) for r in kept["quality"].collect()]
    assert 0 < len(good) < spark.read.parquet(f"{SF}/documents.parquet").count()
    want = {i for i, (_, root) in brute_components(good, 5).items() if i == root}
    assert {r["doc_id"] for r in kept["near_duplicates"].select("doc_id").collect()} == want
    finder = pii.Finder()
    assert all(not any(finder.spans(r["text"])[k] for k in pii.BASE) for r in kept["pii"].collect())
    mixed, ids = kept["mixing"].count(), kept["bpe"]
    assert ids.count() == mixed and ids.where("n_tokens <> size(ids)").count() == 0
    tokenizers = pytest.importorskip("tokenizers").Tokenizer.from_file(VOCABULARY)
    texts = {r["doc_id"]: r["text"] for r in kept["pii"].collect()}
    for r in ids.collect():
        assert r["ids"] == tokenizers.encode(texts[r["doc_id"]], add_special_tokens=False).ids


ROWS = [
    (1, "one two three four five six seven", "en", "s1", 33),
    (2, "one two three four five six seven", "en", "s2", 33),  # a copy
    (3, None, None, None, None),
    (4, "", "en", "", 0),
    (5, "word " * 40_000, "en", "s1", 200_000),
    (5, "word " * 40_000, "en", "s1", 200_000),  # a row that repeats an id
    (None, "no id at all, but mail me@here.org", "de", "s1", 34),
    (7, "eins zwei drei vier fünf sechs", "de", "s1", 30),
]
KIND = "doc_id long, text string, lang string, source string, n_chars long"


def folder(spark, path, rows, labels):
    spark.createDataFrame(rows, KIND).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    return str(path)


def test_edge_rows(spark, tmp_path):
    pipeline = pytest.importorskip("corpus_pipeline")
    sf = folder(spark, tmp_path, ROWS, [(1, 1, 0), (2, 1, 0), (7, 1, 0), (4, None, 0)])  # one class: a prior of more than 0.7
    docs, kept = spark.read.parquet(f"{sf}/documents.parquet"), {}
    for name, stage in pipeline.STAGES:
        docs = pipeline.written(stage(spark, docs, sf))
        kept[name] = docs.collect()
    assert len(kept["quality"]) == len(ROWS)
    ids = [r["doc_id"] for r in kept["near_duplicates"]]
    assert 1 in ids and 2 not in ids and {3, 4, 7, None} <= set(ids)
    assert any(r["doc_id"] is None and "[EMAIL]" in r["text"] for r in kept["pii"]) and any(r["text"] is None for r in kept["pii"])
    assert {r["doc_id"] for r in kept["mixing"]} <= set(ids) and all(r["text"] for r in kept["mixing"])
    assert len(kept["bpe"]) == len(kept["mixing"])


def test_empty_tables(spark, tmp_path):
    pipeline = pytest.importorskip("corpus_pipeline")
    sf = folder(spark, tmp_path, [], [])
    assert pipeline.run(spark, sf).count() == 0
