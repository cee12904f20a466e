"""Statistics of segments; all merge, so partial aggregation does the work."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def geometry(px: DataFrame, label: str = "label") -> DataFrame:
    return px.groupBy("scene_id", label).agg(
        F.min("y").alias("y0"), F.max("y").alias("y1"), F.min("x").alias("x0"), F.max("x").alias("x1"), F.count("*").alias("n"), F.sum("y").alias("sy"), F.sum("x").alias("sx")
    )


def mean_vector(px: DataFrame, column: str, width: int, label: str = "label", name: str | None = None) -> DataFrame:
    """Mean of an array column of known width, as one aggregate per entry."""
    aggs = [F.avg(F.element_at(column, i + 1)).alias(f"_{i}") for i in range(width)]
    return px.groupBy("scene_id", label).agg(*aggs).select("scene_id", label, F.array(*[F.col(f"_{i}") for i in range(width)]).alias(name or column))


def statistics(px: DataFrame, emb: int, sem: int, label: str = "label") -> DataFrame:
    """Box, size, mean embedding and mean class distribution in one shuffle."""
    return px.groupBy("scene_id", label).agg(
        F.min("y").alias("y0"), F.max("y").alias("y1"), F.min("x").alias("x0"), F.max("x").alias("x1"), F.count("*").alias("n"),
        F.array(*[F.avg(F.element_at("emb", i + 1)) for i in range(emb)]).alias("emb"), F.array(*[F.avg(F.element_at("sem", i + 1)) for i in range(sem)]).alias("sem"),
    )


def top_class(sem: str = "sem"):
    """Class of a distribution; the smaller of equals."""
    return (F.array_position(sem, F.array_max(sem)) - 1).cast("int")


def classify(px: DataFrame, edges: DataFrame, sem: int, label: str = "label") -> DataFrame:
    """Class and score of segments: top mean class, its probability times the
    mean affinity inside (1 for a single pixel)."""
    m = mean_vector(px, "sem", sem, label)
    l_ = px.select("scene_id", "pixel", label)
    inside = edges.join(l_.toDF("scene_id", "u", "_a"), ["scene_id", "u"]).join(l_.toDF("scene_id", "v", "_b"), ["scene_id", "v"]).where("_a = _b").groupBy("scene_id", F.col("_a").alias(label)).agg(F.avg("aff").alias("_in"))
    return m.join(inside, ["scene_id", label], "left").select("scene_id", label, top_class().alias("cls"), (F.array_max("sem") * F.coalesce("_in", F.lit(1.0))).alias("score"))


def classify_arrays(lab: np.ndarray, sem: np.ndarray, right: np.ndarray, down: np.ndarray):
    """classify() of one raster (0 is no segment): labels of the segments, their classes and scores."""
    ids, inv = np.unique(lab, return_inverse=True)
    inv, n = inv.reshape(lab.shape), len(ids)
    mean = np.stack([np.bincount(inv.ravel(), sem[..., c].ravel(), n) for c in range(sem.shape[-1])], 1) / np.bincount(inv.ravel(), minlength=n)[:, None]
    total, count = np.zeros(n), np.zeros(n)
    for a, b, w in ((inv[:, :-1], inv[:, 1:], right[:, :-1]), (inv[:-1], inv[1:], down[:-1])):
        ok = (a == b) & ~np.isnan(w)
        total += np.bincount(a[ok], w[ok], n)
        count += np.bincount(a[ok], minlength=n)
    score = mean.max(1) * np.where(count > 0, total / np.maximum(count, 1), 1.0)
    real = ids > 0
    return ids[real], mean.argmax(1)[real], score[real]
