"""The quality model is fitted on every labelled document."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from webtraverse.llm import quality


def labelled(spark, n, every):
    text = F.concat(F.repeat(F.lit("Word "), (F.col("id") % 7 + 1).cast("int")), F.lit("x; "), F.repeat(F.lit("! "), F.when(F.col("id") % every == 0, F.col("id") % 5 + 1).otherwise(F.col("id") % 2).cast("int")), F.col("id").cast("string"))
    docs = spark.range(n).select(F.col("id").alias("doc_id"), text.alias("text"))
    return docs, spark.range(n).select(F.col("id").alias("doc_id"), (F.col("id") % every != 0).cast("int").alias("quality"))


@pytest.mark.parametrize("n, every", [(18_000, 2), (9_500, 400)])
def test_quality_learns_from_every_label(spark, n, every):
    docs, labels = labelled(spark, n, every)
    rows = quality.training_rows(docs, labels)
    assert rows.where("copy = 0").count() == n == rows.select("doc_id").distinct().count()
    sides = rows.groupBy("block").agg(F.countDistinct("quality").alias("k"))
    assert sides.where("k < 2").count() == 0, "every document meets a rival"
    model = quality.train(docs, labels)
    x = np.array([quality.features(r["text"]) for r in docs.select("text").collect()])
    assert np.allclose(model.centre, x.mean(0)) and np.allclose(model.scale, np.maximum(x.std(0), 1e-6))
    strength = np.sort(np.clip((x - model.centre) / model.scale, -8, 8) @ model.weights)
    bad = labels.where("quality = 0").count()
    assert np.isclose(model.threshold, (strength[bad - 1] + strength[bad]) / 2)


def test_pairs_of_a_block_equal_pairs_written_out():
    rng = np.random.default_rng(1)
    good, bad, w = rng.normal(size=(5, 4)), rng.normal(size=(3, 4)), rng.normal(size=4)
    d = (good[:, None, :] - bad[None, :, :]).reshape(-1, 4)
    p = 1 / (1 + np.exp(d @ w))
    want = np.concatenate([[15], d.T @ p, ((d * (p * (1 - p))[:, None]).T @ d).ravel()])
    assert np.allclose(quality._preferences(good, bad, w), want)


def test_the_pipelines_quality_stage_learns_from_every_label(spark, tmp_path, monkeypatch):
    import corpus_pipeline

    docs, labels = labelled(spark, 17_000, 2)
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    used, fit = [], quality.fit
    monkeypatch.setattr(quality, "fit", lambda rows: used.append(rows.where("copy = 0").count()) or fit(rows))
    corpus_pipeline.quality_stage(spark, docs, str(tmp_path))
    assert used == [17_000]
