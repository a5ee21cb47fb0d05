"""The pipeline's stages on planted documents, and every query of the subpackage on the smallest tables."""

from __future__ import annotations

import os

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")
from thresher.llm import entries  # noqa: E402

SF = "/root/testdata/sf0.001"


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the test tables")
def test_pipeline_drops_what_it_should(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 4
    now = docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, now, SF)
        assert after.columns == docs.columns
        after = spark.createDataFrame(after.collect(), docs.schema)
        assert after.count() <= now.count()
        now = after
    kept = {r.doc_id for r in now.select("doc_id").collect()}
    got = corpus_pipeline.run(spark, SF).collect()
    assert {r.doc_id for r in got} == kept


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the test tables")
def test_every_query_returns_every_row(spark):
    n = spark.read.parquet(f"{SF}/documents.parquet").count()
    turns = spark.read.parquet(f"{SF}/conversations.parquet").count()
    vectors = spark.read.parquet(f"{SF}/embeddings.parquet")
    found = entries.queries()
    assert [x.split("_")[0] for x in found] == [f"op{k}" for k in range(1, 11)]
    for name, query in found.items():
        got = query(spark, SF)
        if name.startswith("op4_"):
            assert got.count() == 5 * vectors.where("vec_id % 50 = 0").count()
        elif name.startswith("op7_"):
            assert got.select("doc_id").distinct().count() == n
        else:
            assert got.count() == (turns if name.startswith("op8_") else n), name


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the test tables")
def test_pipeline_equals_a_plain_version(spark):
    """All cosines, all pairs of shingle sets, sets of windows, and the plain tokenizer."""
    import numpy as np

    from thresher.llm import packing, tokens, toxicity
    from thresher.llm.common import blank_words

    from .test_scans import plain_scan

    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    scorer = toxicity.fit(docs, labels)
    finder, index = scorer.finder(), scorer.index
    texts = dict(rows)
    size = len(index.weight)

    def dense(text):
        out = np.zeros(size)
        terms, weights = index.vector(*finder.of(text))
        out[terms] = weights
        return out

    examples = np.array([dense(texts[i]) for i in index.names])

    def is_clean(text):
        cosines = examples @ dense(text) if len(examples) else np.zeros(0)
        best = [n for n in sorted(range(len(cosines)), key=lambda n: (-round(cosines[n], 12), n))[: toxicity.K] if cosines[n] > 1e-15]
        return index.votes([(float(cosines[n]), n) for n in best])[0] < 0.5

    rows = [(i, t) for i, t in rows if is_clean(t)]
    sets = {}
    for i, t in rows:
        w = blank_words(t)
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else None
    ids = sorted(sets)
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for k, a in enumerate(ids):
        for b in ids[:k]:
            x, y = sets[a], sets[b]
            if x and y and len(x & y) >= 0.8 * len(x | y):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    rows = [(i, t) for i, t in rows if find(i) == i]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    hit = {x[0] for x in plain_scan(rows, items) if x[-1]}
    rows = [(i, t) for i, t in rows if i not in hit]
    full = tokens.load(packing.TOKENIZER).full
    want = {i: len(full.encode(t, add_special_tokens=False).ids) + 1 for i, t in rows}
    got = corpus_pipeline.run(spark, SF).collect()
    assert {r.doc_id: r.doc_tokens for r in got} == want
    assert sum(r.length for r in got) == sum(want.values())


def test_stages_on_hard_and_empty_tables(spark, hard, empty, tmp_path):
    """Nulls, empty and very long texts, repeated rows and clashing names go through every stage."""
    spark.createDataFrame([(4, 0), (5, 1), (6, 0), (None, 1), (7, None)], "doc_id long, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    spark.createDataFrame([(1, "the cat sat"), (None, "x"), (2, None)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    for docs in (hard, hard.where("false"), empty):
        now = docs
        for name, stage in corpus_pipeline.STAGES[:-1]:
            now = stage(spark, now, str(tmp_path))
            assert now.columns == docs.columns, name
        assert corpus_pipeline.STAGES[-1][1](spark, now, str(tmp_path)).count() >= now.count()
    kept = now = hard
    for _, stage in corpus_pipeline.STAGES[1:-1]:
        kept = stage(spark, kept, str(tmp_path))
    ids = [r.doc_id for r in kept.collect()]
    # Texts without words and rows without an id stay; of equal texts one row does; the item stands in the long text.
    assert sorted(i for i in ids if i is not None) == [1, 2, 3, 4, 7, 8, 9, 10] and ids.count(None) == 1


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the test tables")
def test_run_leaves_its_result_only(spark):
    from thresher.llm.common import SharedTable, drop_tables

    drop_tables()
    found = corpus_pipeline.run(spark, SF)
    assert len(SharedTable.made) == 1 and found.count() > 0
