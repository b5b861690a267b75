"""Co-training over all unlabelled rows."""

import random

import numpy as np
from pyspark.sql import functions as F

from posterior_mesh.llm import quality

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def corpus(spark, n):
    rng = random.Random(3)
    rows, labels = [], []
    for i in range(n):
        good = i % 2
        words = ["".join(rng.choice("abcdefghij" if good else "0123456789#|") for _ in range(5)) for _ in range(60)]
        rows.append((i, " ".join(words), "en", f"{'good' if good else 'poor'}{rng.randrange(3)}", None))
        if i < 120:
            labels.append((i, good))
    return spark.createDataFrame(rows, DOCS), spark.createDataFrame(labels, "doc_id long, quality int")


def test_pseudo_labels_grow_with_the_unlabelled_rows(spark, monkeypatch):
    monkeypatch.setattr(quality, "AT_LEAST", 10)
    monkeypatch.setattr(quality, "EACH", 0.1)
    few, many = (quality.fit(*corpus(spark, n))["given"] for n in (500, 4000))
    assert sum(map(sum, many)) > 5 * sum(map(sum, few)) > 0 and sum(map(sum, many)) > 800


def test_long_unlabelled_texts_take_part(spark):
    docs, labels = corpus(spark, 130)
    rest = docs.withColumn("text", F.when(F.col("doc_id") >= 120, F.repeat("text", 80)).otherwise(F.col("text")))
    expected = rest.where((F.col("doc_id") >= 120) & (F.length("text") > 20_000) & ~quality.held_out(F.col("doc_id"))).count()
    assert quality.unlabelled(rest, labels).count() == expected > 0


def test_a_column_for_each_of_many_sources():
    columns = {tuple(quality.metadata_of("en", f"s{i}", 10)) for i in range(1000)}
    assert len(columns) == quality.SOURCES


def test_fit_over_all_rows_is_the_fit_of_one_machine(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(60, quality.CONTENT + quality.META)).astype(np.float32)
    y = (x[:, 0] + 0.3 * rng.normal(size=60) > 0).astype(float)
    views = [x[:, : quality.CONTENT].astype(float), x[:, quality.CONTENT :].astype(float)]
    own = [(v[:40], y[:40]) for v in views]
    start = [quality.fit_logistic(*o, 1e-3) for o in own]
    history = [(start, [(-0.5, 0.5), (-0.5, 0.5)])]
    labels, _ = quality.given([v[40:] for v in views], history)
    pool = spark.createDataFrame([(bytearray(one.tobytes()),) for one in x[40:]], "x binary")
    got = quality.refit(pool, own, start, history, steps=30)
    for (v, t), more, label, w in zip(own, views, labels, got):
        some = ~np.isnan(label)
        alone = quality.fit_logistic(np.vstack([v, more[40:][some]]), np.append(t, label[some]), 1e-3)
        assert some.any() and np.allclose(w, alone, atol=1e-3)
