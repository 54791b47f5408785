import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from noisytree.llm import quality_model
from noisytree.llm.common import table
from tests.conftest import TINY
from tests.llm.conftest import prose


def test_linear_time_sum_equals_pairs():
    rng = np.random.default_rng(1)
    model = {"b": 0.3, "w": rng.normal(size=quality_model.WIDTH), "v": rng.normal(size=(quality_model.WIDTH, 4))}
    at, x = np.array([3, 99, 2000, 16_400]), np.array([0.5, 1.0, 0.2, 0.7])
    pairs = sum(model["v"][at[i]] @ model["v"][at[j]] * x[i] * x[j] for i in range(4) for j in range(i))
    assert abs(quality_model.margin(model, at, x)[0] - (0.3 + model["w"][at] @ x + pairs)) < 1e-9


def test_pairs_are_learnt():
    # Exclusive or of two features: weights alone cannot tell the classes.
    one = np.ones(2, np.float32)
    rows = [(np.array([a, b]), one, float((a == 1) != (b == 3))) for a in (0, 1) for b in (2, 3)] * 60
    model = quality_model.train(rows, epochs=60, rate=0.2)
    for at, x, y in rows[:4]:
        assert (quality_model.margin(model, at, x)[0] > 0) == (y == 1)


def test_held_out_accuracy(spark):
    sf = TINY.replace("0.001", "0.01")
    docs, labels = table(spark, sf, "documents"), table(spark, sf, "labels")
    model = quality_model.fit(docs, labels)
    got = quality_model.score(docs, model, keep=("doc_id",)).join(labels, "doc_id").withColumn("held", quality_model.held_out(F.col("doc_id")))
    rows = got.collect()
    assert all(r.held == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) and 0 <= r._score <= 1 for r in rows)
    held = [r for r in rows if r.held]
    assert np.mean([(r._score >= quality_model.THRESHOLD) == bool(r.quality) for r in held]) > 0.93


def test_labels_of_held_out_rows_are_not_read(spark, docs):
    rng = np.random.default_rng(2)
    df = docs([" ".join(prose(rng, 60)) for _ in range(80)])
    labels = df.select("doc_id", (F.col("doc_id") % 3 == 0).cast("int").alias("quality"))
    other = labels.withColumn("quality", F.when(quality_model.held_out(F.col("doc_id")), 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = quality_model.fit(df, labels), quality_model.fit(df.repartition(3), other)
    assert np.array_equal(a["w"], b["w"]) and np.array_equal(a["v"], b["v"])
    few = quality_model.fit(df, labels, sample=10)
    assert not np.array_equal(few["w"], a["w"])


def test_odd_inputs(spark, docs):
    df = docs(["", None, "a", "x" * 200_000], extra=["_score2", "label", "quality"])
    none = quality_model.fit(df, spark.createDataFrame([], "doc_id long, quality int"))
    assert none is None
    rows = quality_model.score(df, None).collect()
    assert len(rows) == 4 and all(r._score == 0.5 for r in rows)
    one = quality_model.fit(df, spark.createDataFrame([(0, 1), (0, 1), (1, None), (3, 1)], "doc_id long, quality int"))
    assert all(0 <= r._score <= 1 for r in quality_model.score(df, one).collect())
    assert quality_model.score(docs([]), one).count() == 0


@pytest.mark.parametrize("text", ["", "a b", "A! *#|\n\nA! *#|"])
def test_features_are_in_range(text):
    at, x = quality_model.features(text)
    assert len(set(at.tolist())) == len(at) and (len(at) == 0 or at.max() < quality_model.WIDTH) and np.isfinite(x).all()
