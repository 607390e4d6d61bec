"""The pipeline on awkward tables: nulls in every column, repeated and missing ids, equal texts, clashing names, no rows."""

import re

import pytest

import corpus_pipeline

EXTRA = ["score", "predicted", "keep_id", "group_size", "kept", "size", "copies", "taken", "root", "node", "h", "row"]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"{x} string" for x in EXTRA)


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


@pytest.fixture(scope="module")
def docs(spark, sf):
    real = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").limit(30).collect()]
    long_text = real[0][1]
    odd = [(None, None), (None, ""), (None, long_text + " end"), (None, long_text + " end"), (7, long_text), (7, long_text), (9, real[1][1]), (9, real[2][1] + " other"), (-5, "　 Ə"), (11, None)]
    rows = [(i, t, None if k % 5 == 0 else "en", None if k % 7 == 0 else f"s{k % 3}", None, *[f"{x}{k}" for x in EXTRA]) for k, (i, t) in enumerate(real + odd)]
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


def test_stages_on_awkward_rows(spark, sf, docs, monkeypatch):
    rows = {tuple(r) for r in docs.collect()}
    now = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = corpus_pipeline.materialize(stage(spark, now, sf), "case")
        assert out.columns == docs.columns
        assert {tuple(r) for r in out.collect()} <= rows  # every column of every row is as it came
        if name in ("exact dedup", "SimHash near-dedup"):
            texts = [re.sub(r"[\x20\x09-\x0D]+", " ", r.text or "") for r in out.collect()]
            assert len(texts) == len(set(texts))
        now = out
    pieces = corpus_pipeline.STAGES[-1][1](spark, now, sf)
    assert pieces.where("piece = 0").count() == now.count()


def test_each_stage_judges_all_rows_that_it_gets(spark, sf, docs):
    """Straight to each stage: nothing is lost but what the stage decides on."""
    normal = lambda t: re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
    all_rows = docs.collect()
    exact = corpus_pipeline.exact_stage(spark, docs, sf).collect()
    assert sorted(normal(r.text) for r in exact) == sorted({normal(r.text) for r in all_rows})
    for r in exact:
        ids = [x.doc_id for x in all_rows if normal(x.text) == normal(r.text) and x.doc_id is not None]
        assert r.doc_id == min(ids, default=None)
    mixed = corpus_pipeline.mix_stage(spark, docs, sf).collect()
    assert {tuple(r) for r in mixed} <= {tuple(r) for r in all_rows}
    again = corpus_pipeline.mix_stage(spark, docs.repartition(5), sf).collect()
    count = lambda rows: sorted((str(r.doc_id), normal(r.text)) for r in rows)
    assert count(mixed) == count(again)
    near = corpus_pipeline.near_stage(spark, docs, sf)
    assert near.columns == docs.columns and {tuple(r) for r in near.collect()} <= {tuple(r) for r in all_rows}


def test_no_rows(spark, sf, docs):
    now = docs.limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, now, sf).count() == 0
