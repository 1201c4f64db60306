"""Averaged-vector text classifier: hashed BPE tokens and token pairs, their mean vector, one logistic unit.

Texts are segmented by a public BPE vocabulary first, which bounds the features and splits text that has no spaces. The model is fitted on the
driver from at most `rows` seed texts, drawn by the hash of their ids (a documented bound); it has a fixed size, is broadcast, and
scores whole texts batch by batch. Null and empty texts score by the bias alone.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusmill.functions.bpe import VOCABULARY, token_ids
from corpusmill.functions.hashing import mix
from corpusmill.operators.sampling import unit_hash


@dataclass(frozen=True)
class Settings:
    """Size of the model and of its fit; rows bounds the seed texts that are fetched."""

    buckets: int = 1 << 16
    dim: int = 16
    pairs: bool = True
    epochs: int = 6
    rate: float = 0.3
    rows: int = 20_000
    seed: int = 1
    vocabulary: str = VOCABULARY


@dataclass
class Model:
    vectors: np.ndarray
    weights: np.ndarray
    bias: float
    settings: Settings

    def score(self, text: str | None) -> float:
        rows, counts = features(text, self.settings)
        mean = counts @ self.vectors[rows] / counts.sum() if len(rows) else np.zeros(self.settings.dim)
        return float(1 / (1 + np.exp(-(mean @ self.weights + self.bias))))


def features(text: str | None, settings: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of a text's tokens and pairs of neighbours, with their counts."""
    ids = token_ids(text, settings.vocabulary).astype(np.uint64)
    keys = np.concatenate([ids, (ids[:-1] + np.uint64(1)) * np.uint64(1_000_003) + ids[1:]]) if settings.pairs else ids
    return np.unique((mix(keys) % np.uint64(settings.buckets)).astype(np.int64), return_counts=True)


def fit(seed: DataFrame, settings: Settings = Settings()) -> Model:
    """Model of seed rows (id, text, y), classes weighted alike; rows are taken in the order of their ids' hashes."""
    drawn = seed.where("y is not null").select("id", "text", "y").orderBy(unit_hash(F.col("id")), "id", "text").limit(settings.rows).collect()
    rng = np.random.default_rng(settings.seed)
    model = Model(rng.normal(0, 0.1, (settings.buckets, settings.dim)), np.zeros(settings.dim), 0.0, settings)
    cases = [(*features(r["text"], settings), float(r["y"])) for r in drawn]
    positive = sum(y for _, _, y in cases)
    share = {1.0: len(cases) / (2 * positive) if positive else 0.0, 0.0: len(cases) / (2 * (len(cases) - positive)) if positive < len(cases) else 0.0}
    model.weights[:] = rng.normal(0, 0.1, settings.dim)
    steps = max(1, settings.epochs * len(cases))
    for step, k in enumerate(np.concatenate([rng.permutation(len(cases)) for _ in range(settings.epochs)]) if cases else []):
        rows, counts, y = cases[k]
        if not len(rows):
            continue
        part = counts / counts.sum()
        mean = part @ model.vectors[rows]
        pull = settings.rate * (1 - step / steps) * share[y] * (y - 1 / (1 + np.exp(-(mean @ model.weights + model.bias))))
        before = model.weights.copy()
        model.weights += pull * mean
        model.bias += pull
        model.vectors[rows] += pull * np.minimum(1.0, part * len(rows))[:, None] * before
    return model


def score(rows: DataFrame, model: Model) -> DataFrame:
    """(id, score): the chance of the target class for each row's whole text."""
    held = rows.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def chance(texts: pd.Series) -> pd.Series:
        return texts.map(held.value.score)

    return rows.select("id", F.round(chance("text"), 6).alias("score"))


def report(scored: DataFrame, cuts: list[float], digits: int = 3) -> DataFrame:
    """For each cut: precision, recall and F1 of score > cut, with the area under the curve, of rows (score, y).

    Scores are counted by value to `digits` places, so the ordered sums run over a table whose size is bounded by the digits, not by the rows.
    """
    cells = scored.groupBy(F.round("score", digits).alias("score")).agg(F.sum(F.col("y").cast("long")).alias("p"), F.sum((1 - F.col("y")).cast("long")).alias("q"))
    low = cells.select(F.col("score").alias("s2"), F.col("q").alias("q2"))
    below = cells.crossJoin(F.broadcast(low)).groupBy("score", "p").agg(F.sum(F.when(F.col("s2") < F.col("score"), F.col("q2")).when(F.col("s2") == F.col("score"), F.col("q2") / 2).otherwise(0.0)).alias("b"))
    auc = below.agg(F.sum(F.col("p") * F.col("b")).alias("won")).crossJoin(cells.agg(F.sum("p").alias("tp"), F.sum("q").alias("tq"))).select(F.round(F.try_divide("won", F.col("tp") * F.col("tq")), 6).alias("auc"))
    grid = scored.sparkSession.createDataFrame([(float(c),) for c in cuts], "cut double")
    at = cells.crossJoin(F.broadcast(grid)).groupBy("cut").agg(F.sum(F.when(F.col("score") > F.col("cut"), F.col("p")).otherwise(0)).alias("hit"), F.sum(F.when(F.col("score") > F.col("cut"), F.col("p") + F.col("q")).otherwise(0)).alias("out"), F.sum("p").alias("all_p"))
    precision, recall = F.try_divide("hit", "out"), F.try_divide("hit", "all_p")
    rows = at.select("cut", F.col("out").alias("n_out"), F.round(precision, 6).alias("precision"), F.round(recall, 6).alias("recall"), F.round(F.try_divide(2.0 * F.col("hit"), F.col("out") + F.col("all_p")), 6).alias("f1"))
    return rows.crossJoin(F.broadcast(auc))
