import corpus_pipeline as p
import numpy as np
import public_tokenizers as P
from pyspark.sql import functions as F

from pacedfl.llm.decontaminate import find_leaks
from pacedfl.llm.secret_scan import base_spans
from pacedfl.llm.simhash_dedup import fingerprint
from pacedfl.llm.similar_dedup import similar_components


def test_stages_take_effect(spark):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    names, out = [n for n, _ in p.STAGES], {}
    assert names == ["quality", "near_dedup", "decontamination", "secrets", "tokens"]
    for name, stage in p.STAGES:
        before = docs
        docs = stage(spark, docs, sf).cache()
        out[name] = docs
        if name != "tokens":
            assert docs.columns == before.columns
            assert docs.join(before.select("doc_id"), "doc_id", "left_anti").count() == 0
    good = labels.where("toxic = 0 and quality = 1").select("doc_id")
    kept = out["quality"].join(labels, "doc_id")
    assert kept.where("toxic = 1").count() <= 0.25 * labels.where("toxic = 1").count()  # 51 toxic labels teach few words
    assert out["quality"].join(good, "doc_id", "left_semi").count() >= 0.97 * good.count()
    groups = similar_components(out["near_dedup"])
    assert groups.where("doc_id <> component_id").count() == 0
    assert find_leaks(out["decontamination"], spark.read.parquet(f"{sf}/benchmark.parquet")).count() == 0
    assert out["decontamination"].count() > 0.9 * out["near_dedup"].count()
    assert all(not base_spans(r.text) for r in out["secrets"].collect())
    assert out["secrets"].count() == out["decontamination"].count() == out["tokens"].count()
    row = out["tokens"].where(F.size("ids") > 0).first()
    text = out["secrets"].where(F.col("doc_id") == row.doc_id).first().text
    from pacedfl.llm.byte_bpe import loaded

    assert loaded(P.path("byte_bpe_50k.tiktoken"), P.PATTERN).decode(np.array(row.ids, "<u4").tobytes()).decode() == text


def test_near_dedup_links_by_fingerprint(spark, small):
    """Texts within three bits are near-duplicates, also where most of their shingles differ."""
    rows = [(1, "spam " * 300 + "alpha beta gamma delta epsilon zeta"), (2, "spam " * 300 + "one two three four five six"), (3, "other words of a text of its own")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert (fingerprint(rows[0][1].encode()) ^ fingerprint(rows[1][1].encode())).bit_count() <= 3
    assert sorted(r.doc_id for r in p.near_dedup(spark, docs, small).collect()) == [1, 3]


def test_run(spark, small):
    assert p.run(spark, small).count() > 0


def test_stages_take_an_empty_table(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").limit(0)
    for _, stage in p.STAGES:
        docs = stage(spark, docs, small)
        assert docs.count() == 0


def test_stages_take_odd_rows(spark, small):
    """Nulls in any column, empty and very long texts, repeated rows, ties, extra columns with clashing names."""
    base = spark.read.parquet(f"{small}/documents.parquet").limit(30).collect()
    rows = [(*r, "x", 1) for r in base]
    rows += [(None, None, None, None, None, None, None), (9001, None, None, None, None, "x", 1), (9002, "", "en", None, 0, None, None), (9003, "word " * 100_000, "en", "s", 1, "x", 2), (9004, "a" * 200_000, None, "s", 1, "x", 2), rows[0], rows[0], rows[1]]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, __loser string, node int")
    for name, stage in p.STAGES:
        after = stage(spark, docs, small)
        got = after.collect()
        if name == "tokens":
            assert len(got) == docs.count()
            break
        assert after.columns == docs.columns and len(got) <= docs.count()
        assert [r for r in got if r.doc_id is None] or name == "quality"
        docs = spark.createDataFrame(got, docs.schema)
