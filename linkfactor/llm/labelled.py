"""A bounded sample of labelled rows for fitting classifiers, and a small logistic regression."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Folds by crc32(doc_id as text) mod FOLDS; fold 0 is never learned from.
FOLDS = 5


def fold_of(key: str = "doc_id"):
    return F.pmod(F.crc32(F.coalesce(F.col(key).cast("string"), F.lit("")).cast("binary")), F.lit(FOLDS)).cast("int")


def label_sample(labels: DataFrame, label: str, rows: int, key: str = "doc_id", held_out: tuple[int, ...] = (0,)) -> DataFrame:
    """About ``rows`` labelled rows at most (all if there are fewer): key, label and fold, one per key, chosen by a hash of the key."""
    usable = labels.select(key, F.col(label).cast("int").alias("label")).dropna().withColumn("fold", fold_of(key)).where(~F.col("fold").isin(*held_out))
    n = usable.count()
    span = 1 << 30
    if n > rows:
        usable = usable.where(F.pmod(F.xxhash64(F.lit("label sample"), F.col(key)), F.lit(span)) < int(span * rows / n))
    return usable.groupBy(key).agg(F.max("label").alias("label"), F.first("fold").alias("fold"))


def labelled_texts(docs: DataFrame, labels: DataFrame, label: str, rows: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """label, fold and text of the sample; the sample has a bounded number of narrow rows, so it is broadcast."""
    chosen = label_sample(labels, label, rows, key)
    return docs.select(key, F.coalesce(F.col(text), F.lit("")).alias("text")).join(F.broadcast(chosen), key).select("label", "fold", "text")


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(x, -40, 40)))


def fit_logistic(features: np.ndarray, labels: np.ndarray, ridge: float = 1e-2, steps: int = 60) -> np.ndarray:
    """Weights of a small dense problem (the last is the intercept) by Newton steps."""
    x = np.column_stack([features, np.ones(len(features))])
    w = np.zeros(x.shape[1])
    penalty = np.diag([ridge] * (x.shape[1] - 1) + [1e-6])
    for _ in range(steps):
        p = sigmoid(x @ w)
        slope = x.T @ (p - labels) + penalty @ w
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + penalty + 1e-9 * np.eye(len(w)), slope)
        w -= step * min(1.0, 5.0 / max(1e-12, float(np.abs(step).max())))
        if np.abs(step).max() < 1e-9:
            break
    return w
