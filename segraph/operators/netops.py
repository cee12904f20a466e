"""Network arithmetic on pixel tables, learning-rate plan and augmentation."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def conv2d(px: DataFrame, weights: list[list[float]], bias: float = 0.0, value: str = "z", dilation: int = 1) -> DataFrame:
    """One-channel convolution with zero padding of (scene_id, y, x, value);
    weights is an odd square kernel."""
    r = len(weights) // 2
    taps = [(dy, dx, w) for dy, row in enumerate(weights) for dx, w in enumerate(row)]
    o = F.explode(F.array(*[F.struct(F.lit((r - dy) * dilation).alias("dy"), F.lit((r - dx) * dilation).alias("dx"), F.lit(float(w)).alias("w")) for dy, dx, w in taps]))
    spread = px.withColumn("o", o).select("scene_id", (F.col("y") + F.col("o.dy")).cast("int").alias("y"), (F.col("x") + F.col("o.dx")).cast("int").alias("x"), (F.col(value) * F.col("o.w")).alias("p"))
    s = spread.groupBy("scene_id", "y", "x").agg(F.sum("p").alias("_s"))
    return px.select("scene_id", "y", "x").join(s, ["scene_id", "y", "x"], "left").select("scene_id", "y", "x", (F.coalesce("_s", F.lit(0.0)) + bias).alias(value))


def leaky_relu(c, slope: float = 0.01) -> Column:
    c = F.col(c) if isinstance(c, str) else c
    return F.when(c > 0, c).otherwise(slope * c)


def bn_act(df: DataFrame, value: str = "z", gamma: float = 1.0, beta: float = 0.0, eps: float = 1e-5, slope: float = 0.01) -> DataFrame:
    """Batch normalisation over all rows, then leaky activation."""
    m = df.agg(F.avg(value).alias("_m"), F.var_pop(value).alias("_v"))
    return df.join(F.broadcast(m)).withColumn(value, leaky_relu(gamma * (F.col(value) - F.col("_m")) / F.sqrt(F.col("_v") + eps) + beta, slope)).drop("_m", "_v")


def bn_act_inverse(c, gamma: float = 1.0, beta: float = 0.0, slope: float = 0.01) -> Column:
    """The normalised value behind an activation, as in-place layers recover it."""
    c = F.col(c) if isinstance(c, str) else c
    return (F.when(c > 0, c).otherwise(c / slope) - beta) / gamma


def head(px: DataFrame, k3a, k3b, k1, value: str = "z") -> DataFrame:
    """Two 3x3 convolutions with normalised activation and a 1x1 convolution."""
    return conv2d(bn_act(conv2d(bn_act(conv2d(px, k3a, value=value), value), k3b, value=value), value), k1, value=value)


def deconv2(px: DataFrame, kernel: list[list[float]], value: str = "z") -> DataFrame:
    """Transposed convolution of stride 2 with a 2x2 kernel: doubles a raster."""
    o = F.explode(F.array(*[F.struct(F.lit(dy).alias("dy"), F.lit(dx).alias("dx"), F.lit(float(kernel[dy][dx])).alias("w")) for dy in (0, 1) for dx in (0, 1)]))
    return px.withColumn("o", o).select("scene_id", (2 * F.col("y") + F.col("o.dy")).cast("int").alias("y"), (2 * F.col("x") + F.col("o.dx")).cast("int").alias("x"), (F.col(value) * F.col("o.w")).alias(value))


def topdown_merge(fine: DataFrame, coarse: DataFrame, value: str = "z") -> DataFrame:
    """Fine plus doubled coarse."""
    up = deconv2(coarse, [[1, 1], [1, 1]], value).withColumnRenamed(value, "_u")
    return fine.join(up, ["scene_id", "y", "x"], "left").withColumn(value, F.col(value) + F.coalesce("_u", F.lit(0.0))).drop("_u")


def lr_at(step, base: float = 0.01, warm: int = 1000, flat: int = 10000, total: int = 55500, power: float = 0.9) -> Column:
    """Linear warm-up, flat stretch, polynomial decay to 0."""
    s = F.col(step) if isinstance(step, str) else step
    return F.when(s < warm, base * s / warm).when(s < warm + flat, F.lit(base)).otherwise(base * F.pow(F.greatest((total - s) / F.lit(float(total - warm - flat)), F.lit(0.0)), F.lit(power)))


def augment_flip(px: DataFrame, width: int, flip: Column) -> DataFrame:
    return px.withColumn("x", F.when(flip, width - 1 - F.col("x")).otherwise(F.col("x")).cast("int"))


def augment_crop(px: DataFrame, top: Column, left: Column, height: int, width: int) -> DataFrame:
    y, x = F.col("y") - top, F.col("x") - left
    return px.withColumns({"y": y.cast("int"), "x": x.cast("int")}).where(F.col("y").between(0, height - 1) & F.col("x").between(0, width - 1))


def augment_scale(px: DataFrame, factor: Column, height: int, width: int, value: str = "z") -> DataFrame:
    """Nearest scaling by a factor per scene: every target cell reads source floor(t / factor)."""
    f = px.select("scene_id", factor.alias("f")).distinct()
    t = f.withColumn("y", F.explode(F.sequence(F.lit(0), F.floor(height * F.col("f")).cast("int") - 1))).withColumn("x", F.explode(F.sequence(F.lit(0), F.floor(width * F.col("f")).cast("int") - 1)))
    t = t.withColumns({"sy": F.least(F.floor(F.col("y") / F.col("f")), F.lit(height - 1)).cast("int"), "sx": F.least(F.floor(F.col("x") / F.col("f")), F.lit(width - 1)).cast("int")})
    return t.join(px.select("scene_id", F.col("y").alias("sy"), F.col("x").alias("sx"), value), ["scene_id", "sy", "sx"]).select("scene_id", F.col("y").cast("int").alias("y"), F.col("x").cast("int").alias("x"), value)


def normalise(px: DataFrame, value: str = "z") -> DataFrame:
    """Per scene: mean 0, population variance 1 (constant scenes to 0)."""
    w = Window.partitionBy("scene_id")
    v = F.var_pop(value).over(w)
    return px.withColumn(value, F.when(v > 1e-18, (F.col(value) - F.avg(value).over(w)) / F.sqrt(v)).otherwise(F.lit(0.0)))


def train_projection(px: DataFrame, k: int, steps: int = 8, lr: float = 0.05, decay: float = 5e-4, alpha: float = math.log(2.0)) -> list[float]:
    """Pull loss of a diagonal linear head over emb, by gradient steps with
    weight decay; returns the loss before each step.  One aggregate per step,
    the weights are k numbers."""
    w = [1.0] * k
    seg = px.groupBy("scene_id", "label").agg(F.count("*").alias("n"), *[F.avg(F.element_at("emb", i + 1)).alias(f"m{i}") for i in range(k)], *[F.avg(F.pow(F.element_at("emb", i + 1), 2)).alias(f"q{i}") for i in range(k)])
    var = seg.agg(*[F.avg(F.col(f"q{i}") - F.col(f"m{i}") * F.col(f"m{i}")).alias(f"v{i}") for i in range(k)]).first()
    out = []
    for _ in range(steps):
        out.append(alpha * sum(var[i] * w[i] ** 2 for i in range(k)))
        w = [x - lr * (2 * alpha * var[i] * x + decay * x) for i, x in enumerate(w)]
    return out
