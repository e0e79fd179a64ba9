"""The pipeline against a plain Python version of its stages, and on awkward tables."""

from __future__ import annotations

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from ruleweave.llm import decontaminate, near_dedup, quality  # noqa: E402
from ruleweave.llm.common import table  # noqa: E402
from tests.llm.test_operators import DOCS, _base, _classes  # noqa: E402


def test_stages_take_effect(spark, data):
    docs = table(spark, data, "documents")
    kept, sizes = docs, []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r.doc_id: r for r in kept.collect()}
        kept = corpus_pipeline.staged(stage(spark, kept, data))
        assert kept.columns == docs.columns, name
        after = {r.doc_id: r for r in kept.collect()}
        assert set(after) <= set(before)
        if name == "near-duplicates":
            classes = _classes([(i, r.text) for i, r in before.items()])
            assert set(after) == set(classes.values())
        if name == "secret masking":
            assert set(after) == set(before)
            assert all((r.text == before[i].text) == (not _base(before[i].text)) for i, r in after.items())
            assert all(r.n_chars == len(r.text) for i, r in after.items() if r.text != before[i].text)
        sizes.append(len(after))
    final = corpus_pipeline.STAGES[-1][1](spark, kept, data).collect()
    assert len(final) == sizes[-1] and all(r.decoded_ok for r in final)
    assert sizes[0] < docs.count() and sizes[1] < sizes[0]


def test_quality_stage_matches_the_operator(spark, data):
    docs = table(spark, data, "documents")
    model = quality.train(docs, table(spark, data, "labels"))
    good = {r.doc_id for r in quality.scores(docs, model).collect() if r.score >= 0.7}
    assert {r.doc_id for r in corpus_pipeline.quality_classifier(spark, docs, data).collect()} == good


def test_stages_on_awkward_rows(spark, data):
    rows = [(1, None, "en", "s", None, 1, "a", "b", 2), (2, "", None, None, 0, None, None, None, None), (None, "some text here", "en", "s", 14, 1, "a", "b", 2), (3, "token = abcdefgh ends", "en", "s", 21, 1, "a", "b", 2), (3, "token = abcdefgh ends", "en", "s", 21, 1, "a", "b", 2)]
    odd = spark.createDataFrame(rows, DOCS)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, odd, data).columns == odd.columns, name
        assert stage(spark, odd.limit(0), data).count() == 0, name
    near = corpus_pipeline.near_duplicates(spark, odd, data).collect()
    assert sorted((r.doc_id for r in near), key=str) == sorted([1, None, 3], key=str)
    masked = {r.doc_id: r.text for r in corpus_pipeline.secret_masking(spark, odd, data).collect()}
    assert masked[3] == "[secret] ends" and masked[1] is None


def test_rows_that_share_an_id_are_documents_of_their_own(spark, data, tmp_path):
    text = lambda k: " ".join(f"w{k}x{j}" for j in range(30))
    row = lambda i, k: (i, text(k), "en", "s", 1, 1, "a", "b", 2)
    odd = spark.createDataFrame([row(None, k) for k in range(6)] + [row(5, 3), row(7, 10), row(7, 11), row(7, 11), row(8, 11)], DOCS)
    near = sorted(((r.doc_id, r.text) for r in corpus_pipeline.near_duplicates(spark, odd, data).collect()), key=str)
    assert near == sorted([(None, text(k)) for k in range(6) if k != 3] + [(5, text(3)), (7, text(10)), (7, text(11))], key=str)
    classes = [r.class_id for r in near_dedup.classes(odd).collect()]
    assert len(set(classes)) == 7 and sum(i < 0 for i in classes) == 5  # class 7 has texts 10 and 11
    halves = [text(3).rsplit(" ", 12)[0], " ".join(text(3).split()[10:])]
    spark.createDataFrame([("a", halves[0]), ("a", halves[1]), (None, text(1))], "item_id string, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    left = corpus_pipeline.benchmark_decontamination(spark, odd, str(tmp_path)).collect()
    assert sorted(r.text for r in left) == sorted([text(k) for k in (0, 2, 4, 5, 10, 11, 11, 11)])
    half = spark.createDataFrame([(1, halves[0])], "doc_id long, text string")
    items = spark.read.parquet(str(tmp_path / "benchmark.parquet"))
    assert decontaminate.leaks(half, items).count() == 0  # the item is both rows
