import math
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from pacedfl.llm import language_id as lang, quality
from pacedfl.llm.queries import op7_language, op10_quality


def test_language_held_out_accuracy(spark):
    d = "/root/testdata/sf0.01"
    rows = op7_language(spark, d).join(spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "lang"), "doc_id")
    held = rows.where("held_out")
    assert held.count() > 100 and held.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0] > 0.97
    assert rows.agg(F.min("score"), F.max("score")).first()[0] >= 0 and rows.agg(F.max("score")).first()[0] <= 1


def test_unseen_words_back_off():
    model = lang.LanguageModel(["a", "b"], {"the": np.log([0.9, 0.1])}, {"<x": np.log([0.1, 0.9]), "q": np.log([0.5, 0.5])}, np.zeros(2))
    scores = model.of_words(["the", "xq", "zz"])
    assert scores[0, 0] > scores[0, 1] and scores[1, 1] > scores[1, 0] and scores[2, 0] == scores[2, 1]


def test_language_edges(spark):
    base = [(i, "the cat and the dog" if i % 2 else "der hund und die katze", "en" if i % 2 else "de", "k") for i in range(40)]
    odd = [(100, None, "en", "k"), (101, "123 !? ²", "en", "k"), (102, "", None, "k"), (None, "der hund", None, "k"), (None, "der hund", None, "k"), (103, "the " * 30000, None, "k")]
    docs = spark.createDataFrame(base + odd, "doc_id long, text string, lang string, score string")
    rows = lang.identify_documents(docs).collect()
    assert len(rows) == len(base) + len(odd)
    by = {r.doc_id: r for r in rows}
    assert [by[i].lang_pred for i in (100, 101, 102)] == ["und"] * 3 and by[None].lang_pred == "de" and by[103].lang_pred == "en" and by[None].held_out is False
    none = lang.identify_documents(docs.withColumn("lang", F.lit(None).cast("string"))).collect()
    assert {r.lang_pred for r in none} == {"und"} and {r.score for r in none} == {0.0}
    assert lang.identify_documents(docs.limit(0)).count() == 0


def test_sample_takes_all_of_a_rare_language(spark):
    docs = spark.range(5000).selectExpr("id AS doc_id", "CASE WHEN id % 500 = 0 THEN 'rare' ELSE 'common' END AS lang", "concat('text ', id) AS text")
    n = {r.lang: r["count"] for r in lang.training_sample(docs, "doc_id", "lang", 400).groupBy("lang").count().collect()}
    assert n["rare"] == 10 and 300 < n["common"] < 500


def brute_language(train, texts):
    """The scores by dictionaries and loops: the word's own log share, else the mean of its longest known n-grams'."""
    words, grams = {}, {}
    for text, own in train:
        for w in lang.WORD.findall((text or "").lower()):
            words.setdefault(own, Counter())[w] += 1
            f = f"<{w}>"
            grams.setdefault(own, Counter()).update(f[k : k + n] for n in range(1, 5) for k in range(len(f) - n + 1))
    langs = sorted(words)
    vocabulary, pieces = set().union(*words.values()), set().union(*grams.values())
    of_size = {(x, n): sum(c for g, c in grams[x].items() if len(g) == n) for x in langs for n in range(1, 5)}

    def piece(g, x):
        return math.log((grams[x][g] + 0.5) / (of_size[x, len(g)] + 0.5 * len(pieces)))

    def score(w, x):
        if w in vocabulary:
            return math.log((words[x][w] + 0.5) / (words[x].total() + 0.5 * len(vocabulary)))
        f, at, found = f"<{w}>", 0, []
        while at < len(f):
            n = next((n for n in (4, 3, 2, 1) if f[at : at + n] in pieces and at + n <= len(f)), None)
            if n:
                found.append(piece(f[at : at + n], x))
            at += n or 1
        return sum(found) / len(found) if found else 0.0

    out = []
    for text in texts:
        own = lang.WORD.findall((text or "").lower())
        own = [w for w in own if any(c.isalpha() for c in w)]
        if not own:
            out.append(("und", 0.0))
            continue
        total = [sum(score(w, x) for w in own) for x in langs]
        best = max(range(len(langs)), key=lambda i: total[i])
        out.append((langs[best], 1 / sum(math.exp((t - total[best]) / len(own) * min(len(own), 20)) for t in total)))
    return out


def test_language_equals_brute_force(spark, small):
    rows = spark.read.parquet(f"{small}/documents.parquet").collect()
    train = [(r.text, r.lang) for r in rows if r.lang is not None and zlib.crc32(str(r.doc_id).encode()) % 4 != 2]
    want = dict(zip((r.doc_id for r in rows), brute_language(train, [r.text for r in rows]), strict=True))
    got = {r.doc_id: (r.lang_pred, r.score) for r in op7_language(spark, small).collect()}
    assert got.keys() == want.keys()
    for i, (name, score) in want.items():
        assert got[i][0] == name and got[i][1] == pytest.approx(score, abs=1e-3)


def test_language_never_reads_lang_of_predicted_rows(spark):
    rows = [(i, "the cat and the dog" if i % 2 else "der hund und die katze", "en" if i % 2 else "de") for i in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    wrong = docs.withColumn("lang", F.when(lang.held_out(), F.lit("zz")).otherwise(F.col("lang")))
    a, b = ({r.doc_id: r.lang_pred for r in lang.identify_documents(x).collect()} for x in (docs, wrong))
    assert a == b


def test_quality_held_out(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), quality.graded_labels(spark.read.parquet(f"{d}/labels.parquet"))
    model = quality.fit_quality_model(docs, labels.where("doc_id % 4 <> 0"))
    assert (np.diff(model.thresholds) > 0).all()
    rows = quality.grade_documents(docs.where("doc_id % 4 = 0"), model).join(labels, "doc_id")
    by = {r.grade: r for r in rows.groupBy("grade").agg(F.avg(F.col("selected").cast("int")).alias("selected"), F.avg("expected_grade").alias("e")).collect()}
    assert by[0].selected < 0.05 and by[2].selected > 0.985 and by[0].e < by[1].e < by[2].e


def test_quality_edges(spark):
    docs = spark.createDataFrame([(1, None, "c"), (2, "", "c"), (None, "good words", "c"), (3, "good words", "c"), (3, "good words", "c")], "doc_id long, text string, selected string")
    labels = spark.createDataFrame([(3, 1, 0), (3, 1, 1), (None, 1, 0), (2, None, 0)], "doc_id long, quality int, toxic int")
    assert [(r.doc_id, r.grade) for r in quality.graded_labels(labels).collect()] == [(3, 0)]
    model = quality.fit_quality_model(docs, quality.graded_labels(labels))  # one grade only: all are selected
    rows = quality.grade_documents(docs, model).collect()
    assert len(rows) == 5 and all(r.selected for r in rows)
    assert quality.select_documents(docs, model).columns == docs.columns and quality.select_documents(docs, model).count() == 5
    empty = quality.fit_quality_model(docs.limit(0), quality.graded_labels(labels.limit(0)))
    assert quality.grade_documents(docs.limit(0), empty).count() == 0


def test_ordinal_gradient_recovers_order():
    rng = np.random.default_rng(0)
    x = [np.sort(rng.choice(40, 6, replace=False)).astype(np.int32) for _ in range(600)]
    w = rng.normal(size=40)
    score = np.array([w[i].sum() for i in x]) + rng.logistic(size=600)
    grades = np.digitize(score, [-1.0, 1.0])
    model = quality.fit_ordinal(x, [np.ones(6, np.float32)] * 600, grades, screen=1.0)
    expected = np.array([model.tails(model.weights[i].sum()).sum() for i in x])
    assert np.corrcoef(expected, score)[0, 1] > 0.5 and all(np.diff(model.tails(s))[0] <= 0 for s in (-3.0, 0.0, 3.0))


@pytest.mark.parametrize("text", ["ALLCAPS!! WORDS!!", "réeuxment, ok", "*** ### 12a"])
def test_features_same_with_live_buckets(text):
    at, value = quality.features(text.encode(), quality.WordFeatures())
    live = np.zeros(quality.WIDTH)
    live[at] = 1
    again, v = quality.features(text.encode(), quality.WordFeatures(live))
    assert (at == again).all() and (value == v).all()


def test_query_covers_the_table(spark, small):
    assert op10_quality(spark, small).count() == spark.read.parquet(f"{small}/documents.parquet").count()


def test_language_reads_whole_runs_of_letters(spark):
    """Text without blanks is one word: all of it counts, in the fit and in the prediction."""
    base = [(i, "the cat and the dog with this thing" if i % 2 else "der hund und die katze nicht auch", "en" if i % 2 else "de") for i in range(40)]
    run = "thecatandthedogwiththisthing" * 3 + "derhundunddiekatzenichtauch" * 5000
    rows = lang.identify_documents(spark.createDataFrame([*base, (100, run, None), (101, run[:64], None)], "doc_id long, text string, lang string")).collect()
    assert {r.doc_id: r.lang_pred for r in rows if r.doc_id > 99} == {100: "de", 101: "en"}
    head = "x" * 80
    model = lang.fit_language_model(spark.createDataFrame([("a", head + "bcbcd" * 30), ("b", head + "fgfgh" * 30)], "lang string, text string"))
    scores = model.of_words(["fgfghfgf", "bcbcdbcb"])
    assert scores[0, 1] > scores[0, 0] and scores[1, 0] > scores[1, 1]


def test_ordinal_gradient_by_differences():
    """Against the likelihood written as a loop over rows and grades."""
    rng = np.random.default_rng(1)
    n, width, n_grades = 30, 6, 4
    row, column = np.repeat(np.arange(n), 3), rng.integers(0, width, 3 * n)
    value, grades, weight = rng.normal(size=3 * n), rng.permutation(np.arange(n) % n_grades), rng.uniform(0.5, 2, n)
    params = rng.normal(size=width + n_grades - 1)

    def loss(params):
        theta = [params[width]]
        for x in params[width + 1 :]:
            theta.append(theta[-1] + math.exp(x))
        total = 0.0
        for i in range(n):
            s = sum(params[c] * v for r, c, v in zip(row, column, value, strict=True) if r == i)
            below = [0.0, *(1 / (1 + math.exp(s - t)) for t in theta), 1.0]
            total -= weight[i] * math.log(below[grades[i] + 1] - below[grades[i]])
        return total / n + 0.01 * sum(x * x for x in params[:width]) / 2

    value_, grad = quality.ordinal_loss(params, row, column, value, grades, weight, 0.01)
    assert value_ == pytest.approx(loss(params))
    for k in range(len(params)):
        step = np.zeros_like(params)
        step[k] = 1e-5
        assert grad[k] == pytest.approx((loss(params + step) - loss(params - step)) / 2e-5, abs=1e-6)


def test_grades_equal_brute_force(spark, small):
    """Expected grade and tail of every document, by loops over its features and thresholds."""
    docs = spark.read.parquet(f"{small}/documents.parquet")
    model = quality.fit_quality_model(docs, quality.graded_labels(spark.read.parquet(f"{small}/labels.parquet")))
    want = {}
    for r in docs.collect():
        at, value = quality.features((r.text or "").encode(), quality.WordFeatures())
        score = sum(float(model.weights[i]) * float(v) for i, v in zip(at, value, strict=True))
        tails = [1 / (1 + math.exp(min(60.0, max(-60.0, t - score)))) for t in model.thresholds]
        want[r.doc_id] = (sum(tails), tails[min(quality.SELECT_GRADE, len(tails)) - 1])
    got = {r.doc_id: (r.expected_grade, r.tail_probability) for r in op10_quality(spark, small).collect()}
    assert got.keys() == want.keys() and all(got[i] == pytest.approx(want[i], abs=1e-5) for i in want)
