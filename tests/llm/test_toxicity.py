"""Risk estimator and held-out accuracy."""

import numpy as np
from pyspark.sql import functions as F

from partgraph.llm import toxicity as T


def test_fit_separates_with_unlabelled():
    rng = np.random.default_rng(0)
    truth = rng.random(3000) < 0.2
    x = (rng.random((3000, 4)) < np.where(truth[:, None], 0.7, 0.05)).astype(float)
    w, b = T.fit_nnpu(x[truth][:200], x, 0.2)
    z = x @ w + b
    assert z[truth].mean() > 0 > z[~truth].mean()


def test_held_out_and_odd_rows(spark, tmp_path):
    words = ["good", "plain", "sky", "river", "stone", "bread"]
    rng = np.random.default_rng(1)
    docs, labels = [(None, None, "x"), (9001, "", "x")], []
    for i in range(400):
        t = [words[k] for k in rng.integers(0, 6, 12)] + [f"u{i}"]
        bad = i % 5 == 0
        docs.append((i, " ".join([*t, "Vile!", "rotten"] if bad else t), "x"))
        labels.append((i, int(bad)))
    spark.createDataFrame(docs, "doc_id long, text string, score string").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(labels, "doc_id long, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    got = T.op10_nnpu_toxicity(spark, str(tmp_path))
    assert got.count() == 402 and got.where("score < 0 or score > 1 or score is null").count() == 0
    bad = got.where("held_out").withColumn("truth", (F.col("doc_id") % 5 == 0) & (F.col("doc_id") < 400))
    assert bad.where("truth <> (predicted = 1)").count() == 0
