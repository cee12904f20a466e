"""Small fits on bounded samples of labelled rows."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def sigmoid(x):
    return 1.0 / (1.0 + np.exp(-np.clip(x, -500, 500)))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, weight: np.ndarray | None = None, rounds: int = 25) -> np.ndarray:
    """Ridge logistic regression by Newton steps; the last coefficient is the intercept."""
    x = np.column_stack([x, np.ones(len(x))])
    w = np.zeros(x.shape[1])
    weight = np.ones(len(y)) if weight is None else weight
    pen = np.full(len(w), ridge)
    pen[-1] = 1e-3
    for _ in range(rounds):
        p = sigmoid(x @ w)
        g = x.T @ (weight * (p - y)) + pen * w
        h = (x * (weight * p * (1 - p) + 1e-9)[:, None]).T @ x + np.diag(pen)
        step = np.linalg.solve(h, g)
        w -= step * min(1.0, 5.0 / (np.abs(step).max() + 1e-12))
        if np.abs(step).max() < 1e-7:
            break
    return w


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, train, per_class: dict[int, int]) -> DataFrame:
    """doc_id, text, y of at most per_class[y] labelled rows for each label, by
    the order of a hash of the id; ``train`` is a column over doc_id that tells
    which labels may be seen.  Conflicting labels of an id count as 1."""
    spark = docs.sparkSession
    one = labels.where(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull() & train).groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
    ids = [(r["doc_id"], y) for y, n in per_class.items() for r in one.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n).collect()]
    rows = spark.createDataFrame(ids, "doc_id bigint, y int")  # bounded by per_class
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(rows), "doc_id")
