import re

import pytest
from pyspark.sql import functions as F

from roadweave.llm import exact, neardup, packing, secrets


@pytest.fixture(scope="module")
def pipeline():
    import corpus_pipeline

    return corpus_pipeline


def test_stages_against_their_operators(spark, pipeline, odd_docs):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").unionByName(odd_docs.selectExpr("doc_id + 1000000 as doc_id", "text", "lang", "source", "n_chars"))
    names = docs.columns
    by = dict(pipeline.STAGES)
    assert list(by) == ["language ID", "exact dedup", "MinHash near-dedup", "secret scans", "packing"]
    known = by["language ID"](spark, docs, "").cache()
    assert known.columns == names
    letters = docs.where("regexp_like(text, '[A-Za-zÀ-ÿ]{3}')").count()
    assert 0.97 * letters <= known.count() <= docs.count() and known.where("text is null").count() == 0
    single = by["exact dedup"](spark, known, "").cache()
    assert single.columns == names and single.count() == exact.exact_groups(known).where("kept").count()
    assert len({re.sub("[\x20\x09-\x0d]", "", r["text"]) for r in single.collect()}) == single.count()
    apart = by["MinHash near-dedup"](spark, single, "").cache()
    assert apart.columns == names and apart.count() == neardup.classes(single).where("kept").count()
    clean = by["secret scans"](spark, apart, "").cache()
    assert clean.columns == names and clean.count() == apart.count()
    spans = {r["doc_id"]: r["spans"] for r in secrets.scan(apart).collect()}
    before = {r["doc_id"]: r["text"] for r in apart.collect()}
    for r in clean.collect():
        assert (r["text"] != before[r["doc_id"]]) == bool(spans[r["doc_id"]]) and r["n_chars"] == len(r["text"])
    assert secrets.scan(clean).where("n_assign + n_access + n_hex > 0").count() == 0
    packed = by["packing"](spark, clean, "")
    assert packed.columns == packing.pack(clean).columns and packed.where("start = 0").count() == clean.count()


def test_run_is_the_stages_in_turn(spark, pipeline):
    packed = pipeline.run(spark, "/root/testdata/sf0.001")
    assert packed.where("start = 0").count() > 150
    assert packed.groupBy("doc_id").agg({"length": "sum", "doc_tokens": "max"}).where("`sum(length)` <> `max(doc_tokens)`").count() == 0


def test_stages_leave_columns_of_any_name_alone(spark, pipeline):
    """Names that stages use themselves, in other case too, and one with a dot."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    odd = ["__text", "__key", "key", "v", "c", "lang_pred", "Lang_Score", "secrets", "SECRETS_", "content_key", "text.x", "kept", "row_id", "base"]
    own = docs.withColumns({name: F.concat(F.lit(f"{name}/"), F.col("doc_id").cast("string")) for name in odd})
    for name, stage in pipeline.STAGES[:-1]:
        out = stage(spark, own, "")
        assert out.columns == own.columns, name
        rows = out.collect()
        assert len(rows) > 100 and all(r[c] == f"{c}/{r['doc_id']}" for r in rows for c in odd), name
    assert pipeline.STAGES[-1][1](spark, own, "").where("start = 0").count() == docs.count()
