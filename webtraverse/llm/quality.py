"""Pairwise-ranking quality classifier: a Bradley-Terry model over text features.

The strength of a document is a linear function of features of its whole text. Preference pairs set a document labelled
good against one labelled bad; the weights maximise the likelihood that the good one wins, i.e. they minimise the logistic
loss of feature differences. The decision threshold is a quantile of the training strengths: the share of bad labels
among all training labels. A score is the logistic function of the scaled distance to it, so 0.5 is the threshold.

The model is fitted on every labelled document. Documents of the commoner label are dealt to blocks by a hash of their ids; those of
the other label go to as many blocks as give each block enough rivals, one at least; within a block every good document is set against every
bad one. Features of the labelled documents stay in a table, over which each Newton step is one pass; the driver gets sums. The threshold
is the exact order statistic of all their strengths.

Behaviour at the edges: null text is empty text and gets a score like any other; labels that are null or neither 0 nor 1 are ignored; of
several labels of a document the lowest counts; with labels of one kind or none, every score is 0.5; equal texts get
equal scores; an empty table gives no rows; other columns, whatever their names, are never read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.reach import ranked
from ..session import discard, ship_package
from .common import map_arrow, materialize, partitions_for, runs, text_column

BLOCK = 512  # documents of the commoner label in a block, on average
RIVALS = 64  # documents of the other label in a block, on average, if there are as many
RIDGE = 1e-3
FILE_BYTES = 32 << 20  # of training features in a file, so that no block is split between tasks
PUNCTUATION = np.frombuffer(b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~", dtype=np.uint8)


def features(text: str) -> np.ndarray:
    """Shares of byte classes, and sizes and variety of words and lines."""
    data = text.encode()
    n = max(len(data), 1)
    seen = np.bincount(np.frombuffer(data, dtype=np.uint8), minlength=256) if data else np.zeros(256, dtype=np.int64)
    words, lines = data.split(), data.split(b"\n")
    k = max(len(words), 1)
    marks = seen[PUNCTUATION] / k
    shares = np.array([seen[97:123].sum(), seen[65:91].sum(), seen[48:58].sum(), seen[128:].sum(), seen[32], seen[10], seen[:32].sum()]) / n
    distinct = len(set(words))
    sizes = [np.log1p(len(words)), np.log1p(len(lines)), np.log1p(len(words) / len(lines)), len(data) / k / 10, distinct / k, np.log1p(k / max(distinct, 1)), len(set(lines)) / len(lines), float(not words)]
    return np.concatenate([np.minimum(marks, 4), np.sqrt(marks), shares, np.sqrt(shares), sizes]).astype(np.float64)


WIDTH = len(features(""))


@dataclass(frozen=True)
class BradleyTerry:
    weights: np.ndarray
    centre: np.ndarray
    scale: np.ndarray
    threshold: float
    slope: float

    def score(self, x: np.ndarray) -> np.ndarray:
        strength = np.clip((x - self.centre) / self.scale, -8, 8) @ self.weights
        return 1 / (1 + np.exp(-np.clip(self.slope * (strength - self.threshold), -60, 60)))


def _totals(df: DataFrame, work, size: int) -> np.ndarray:
    """The sum over all rows of the vectors that ``work`` makes of batches, one vector of ``size`` from each task."""

    def task(batches):
        got = np.zeros(size)
        for part in work(batches):
            got += part
        yield pa.record_batch([pa.array([got.tobytes()], pa.binary())], ["sums"])

    parts = map_arrow(df, task, "sums binary").toArrow()["sums"].to_pylist()
    return np.sum([np.frombuffer(x) for x in parts], axis=0) if parts else np.zeros(size)


def _newton(totals, width: int, ridge: float, rounds: int = 40) -> np.ndarray:
    """Weights for which the preferences are likeliest; ``totals`` gives their number, gradient and curvature at given weights."""
    w = np.zeros(width)
    for _ in range(rounds):
        got = totals(w)
        n, grad, curve = max(got[0], 1.0), got[1 : 1 + width], got[1 + width :].reshape(width, width)
        step = np.linalg.solve(curve / n + ridge * np.eye(width), grad / n - ridge * w)
        w += step * min(1.0, 5 / max(np.abs(step).max(), 1e-12))
        if np.abs(step).max() < 1e-7:
            break
    return w


def _matrix(column) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), dtype=np.float64).reshape(-1, WIDTH)


def _preferences(good: np.ndarray, bad: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Number, gradient and curvature of all pairs of a good and a bad row; the pairs themselves are never written out."""
    p = 1 / (1 + np.exp(np.clip((good @ w)[:, None] - (bad @ w)[None, :], -60, 60)))
    q = p * (1 - p)
    mixed = good.T @ q @ bad
    curve = (good * q.sum(1)[:, None]).T @ good + (bad * q.sum(0)[:, None]).T @ bad - mixed - mixed.T
    return np.concatenate([[p.size], p.sum(1) @ good - p.sum(0) @ bad, curve.ravel()])


def known_labels(labels: DataFrame) -> DataFrame:
    """(doc_id, quality) of every labelled document."""
    return labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").alias("quality"))


def training_rows(docs: DataFrame, labels: DataFrame) -> DataFrame | None:
    """(block, copy, doc_id, quality, x), sorted by block in whole files: the features of every labelled document; only the rarer label has copies."""
    known = known_labels(labels)
    n, bad = known.agg(F.count("*"), F.sum((F.col("quality") == 0).cast("long"))).first()
    if not n or not bad or bad == n:
        return None
    rare, n_rare = (0, bad) if 2 * bad <= n else (1, n - bad)
    blocks = -(-(n - n_rare) // BLOCK)
    copies = min(blocks, max(1, -(-blocks * RIVALS // n_rare)))

    def work(batches):
        for batch in batches:
            yield pa.record_batch([batch.column(0), pa.array([features(t.as_py()).tobytes() for t in batch.column(1)], pa.binary())], ["doc_id", "x"])

    # Features come before the join, as they are smaller than texts where the labels are too many to be sent to all tasks.
    found = map_arrow(docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_column(docs).alias("text")), work, "doc_id long, x binary").join(known, "doc_id")
    copy = F.explode(F.when(F.col("quality") == rare, F.sequence(F.lit(0), F.lit(copies - 1))).otherwise(F.array(F.lit(0))))
    dealt = found.select("doc_id", "quality", "x", copy.alias("copy")).withColumn("block", F.pmod(F.xxhash64("doc_id") + F.col("copy") * F.lit(blocks // copies), F.lit(blocks)))
    files = max(partitions_for(docs.sparkSession), -(-(n + (copies - 1) * n_rare) * WIDTH * 8 // FILE_BYTES))
    return materialize(dealt.repartition(files, "block").sortWithinPartitions("block", "doc_id", "copy", "x"), "training")


def train(docs: DataFrame, labels: DataFrame) -> BradleyTerry:
    none = BradleyTerry(np.zeros(WIDTH), np.zeros(WIDTH), np.ones(WIDTH), 0.0, 1.0)
    rows = training_rows(docs, labels)
    if rows is None:
        return none
    model = fit(rows)
    discard(rows)
    return model or none


def fit(rows: DataFrame) -> BradleyTerry | None:
    """The model of all ``training_rows``; None if none of one label is among them."""
    width, once = WIDTH, rows.where("copy = 0").select("quality", "x")

    def moments(batches):
        for batch in batches:
            x, bad = _matrix(batch.column(1)), batch.column(0).to_numpy() == 0
            yield np.concatenate([[len(x), bad.sum()], x.sum(0)])

    got = _totals(once, moments, 2 + width)
    n, n_bad = int(got[0]), int(got[1])
    if not n_bad or n_bad == n:
        return None
    centre = got[2:] / n
    scale = np.maximum(np.sqrt(_totals(once, lambda batches: (np.square(_matrix(b.column(1)) - centre).sum(0) for b in batches), width) / n), 1e-6)

    def standard(x):
        return np.clip((x - centre) / scale, -8, 8)

    def preferences(w):
        def work(batches):
            for block in runs(batches, "block"):
                z, good = standard(_matrix(block["x"])), block["quality"].to_numpy() == 1
                yield _preferences(z[good], z[~good], w)

        return _totals(rows.select("block", "quality", "x"), work, 1 + width + width * width)

    w = _newton(preferences, width, RIDGE)

    def strengths(batches):
        for batch in batches:
            yield pa.record_batch([batch.column(0), pa.array(standard(_matrix(batch.column(1))) @ w)], ["quality", "strength"])

    line = ranked(map_arrow(once, strengths, "quality int, strength double"), "strength")
    threshold = float(line.where(F.col("rank").isin(n_bad, n_bad + 1)).agg(F.avg("strength")).first()[0])

    def margins(v):
        def work(batches):
            for batch in batches:
                m = np.where(batch.column(0).to_numpy() == 1, 1, -1) * (batch.column(1).to_numpy() - threshold)
                p = 1 / (1 + np.exp(np.clip(m * v[0], -60, 60)))
                yield np.array([len(m), m @ p, m * m @ (p * (1 - p))])

        return _totals(line.select("quality", "strength"), work, 3)

    return BradleyTerry(w, centre, scale, threshold, max(float(_newton(margins, 1, 1e-3)[0]), 1e-3))


def held_out(doc_id):
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def score_documents(docs: DataFrame, model: BradleyTerry, carry: list[str] | None = None) -> DataFrame:
    """doc_id, held_out, score and predicted of each row."""

    def work(batches):
        for batch in batches:
            x = np.array([features(t.as_py()) for t in batch.column(2)], dtype=np.float64).reshape(-1, WIDTH)
            s = model.score(x)
            yield pa.record_batch([batch.column(0), batch.column(1), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    doc = docs["doc_id"].cast("long")
    return map_arrow(docs.select(doc.alias("doc_id"), held_out(doc).alias("held_out"), text_column(docs).alias("text")), work, "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, model: BradleyTerry) -> DataFrame:
    """The rows of ``docs`` whose text scores at the threshold or above, with all their columns."""

    ship_package(docs.sparkSession)

    @F.pandas_udf("boolean")
    def good(texts):
        import pandas as pd

        x = np.array([features(t) for t in texts], dtype=np.float64).reshape(-1, WIDTH)
        return pd.Series(model.score(x) >= 0.5)

    return docs.where(good(text_column(docs)))
