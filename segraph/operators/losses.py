"""Training losses as aggregates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .affinity import LN2, squared_distance

# Affinity loss weights of the four settings, finest to coarsest level.
LAMBDA_SETTINGS = {"a": (0.125, 0.25, 0.5, 1.0), "b": (0.25, 0.5, 1.0, 1.0), "c": (0.5, 1.0, 1.0, 1.0), "d": (1.0, 1.0, 1.0, 1.0)}
LAMBDA_SEM, LAMBDA_PUSH, LAMBDA_PULL = 2.0, 0.5, 0.5


def loss_semantic(px: DataFrame, cls: str = "cls", eps: float = 1e-7) -> DataFrame:
    """Mean cross-entropy of sem at the true class."""
    p = F.element_at("sem", (F.coalesce(cls, F.lit(0)) + 1).cast("int"))
    return px.agg(F.avg(-F.ln(F.greatest(p, F.lit(eps)))).alias("value"))


def loss_affinity(edges: DataFrame, rim: DataFrame, part: str = "rim", eps: float = 1e-7) -> DataFrame:
    """Binary cross-entropy of affinities, summed over a pixel's directions and
    averaged over rim or solid pixels.  edges: scene_id, u, v, aff, truth;
    rim: scene_id, pixel, rim, optionally w (a pixel weight)."""
    want = rim.where(F.col("rim") == F.lit(part == "rim"))
    w = F.col("w") if "w" in rim.columns else F.lit(1.0)
    a = F.least(F.greatest("aff", F.lit(eps)), F.lit(1 - eps))
    bce = -(F.col("truth") * F.ln(a) + (1 - F.col("truth")) * F.ln(1 - a))
    d = edges.select("scene_id", F.col("u").alias("pixel"), bce.alias("b")).union(edges.select("scene_id", "v", bce))
    total = d.join(want.select("scene_id", "pixel", w.alias("w")), ["scene_id", "pixel"]).agg(F.sum(F.col("b") * F.col("w")).alias("s"))
    return total.join(want.agg(F.count("*").alias("n"))).select((F.coalesce("s", F.lit(0.0)) / F.greatest("n", F.lit(1))).alias("value"))


def loss_push(means: DataFrame, key: str = "label", alpha: float = LN2) -> DataFrame:
    """By scene: mean over pairs of different segments of -ln(1 - affinity);
    0 with a single segment.  The stable form is -ln(-expm1(-alpha d^2))."""
    a, b = means.select("scene_id", F.col(key).alias("a"), F.col("emb").alias("ea")), means.select("scene_id", F.col(key).alias("b"), F.col("emb").alias("eb"))
    term = -F.ln(-F.expm1(-alpha * F.greatest(squared_distance("ea", "eb"), F.lit(1e-12))))
    p = a.join(b, "scene_id").where("a < b").groupBy("scene_id").agg(F.avg(term).alias("value"))
    return means.select("scene_id").distinct().join(p, "scene_id", "left").select("scene_id", F.coalesce("value", F.lit(0.0)).alias("value"))


def loss_pull(px: DataFrame, k: int, key: str = "label", alpha: float = LN2) -> DataFrame:
    """By scene: mean over segments of alpha times the mean squared distance to
    the segment's mean, from counts, sums and squared norms alone."""
    norm = F.aggregate("emb", F.lit(0.0), lambda s, x: s + x * x)
    g = px.groupBy("scene_id", key).agg(F.count("*").alias("n"), F.sum(norm).alias("q"), *[F.sum(F.element_at("emb", i + 1)).alias(f"s{i}") for i in range(k)])
    mean2 = sum((F.pow(F.col(f"s{i}") / F.col("n"), 2) for i in range(k)), F.lit(0.0))
    return g.select("scene_id", (alpha * (F.col("q") / F.col("n") - mean2)).alias("x")).groupBy("scene_id").agg(F.avg("x").alias("value"))


def loss_total(losses: DataFrame, lambdas: DataFrame) -> DataFrame:
    """Weighted sum of (level, loss, value) by setting."""
    return losses.join(F.broadcast(lambdas), ["level", "loss"]).groupBy("setting").agg(F.sum(F.col("value") * F.col("weight")).alias("total"))


def lambda_table(spark) -> DataFrame:
    """(setting, level, loss, weight) of all settings."""
    rows = []
    for s, ws in LAMBDA_SETTINGS.items():
        for lvl, w in enumerate(ws, 1):
            rows += [(s, lvl, "rim", w), (s, lvl, "solid", w), (s, lvl, "sem", LAMBDA_SEM), (s, lvl, "push", LAMBDA_PUSH), (s, lvl, "pull", LAMBDA_PULL)]
    return spark.createDataFrame(rows, "setting string, level int, loss string, weight double")
