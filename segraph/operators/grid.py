"""Graph construction on pixel rasters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

N4 = ((0, 1), (1, 0))
WINDOW5 = tuple((dy, dx) for dy in range(3) for dx in range(-2, 3) if dy > 0 or dx > 0)


def dilated(d: int) -> tuple[tuple[int, int], ...]:
    """Axis and diagonal offsets at distance d."""
    return ((0, d), (d, 0), (d, d), (d, -d))


def grid_edges(px: DataFrame, offsets=N4, carry: tuple[str, ...] = ()) -> DataFrame:
    """(scene_id, u, v) of pixels that stand one of the offsets apart.

    ``carry`` columns come along as <name>_u, <name>_v.  N4 needs no join: one
    sorted pass per direction by lead(), which checks that the next row really
    is the neighbour, as rasters may have holes.  Other offsets are an
    equi-join with each pixel's few targets.
    """
    carry_s = lambda p: [F.col(f"{p}{c}").alias(f"{c}_{'u' if not p else 'v'}") for c in carry]
    if tuple(offsets) == N4:
        parts = []
        for line, along in (("y", "x"), ("x", "y")):
            w = Window.partitionBy("scene_id", line).orderBy(along)
            nxt = px.withColumns({f"n_{c}": F.lead(c).over(w) for c in {along, "pixel", *carry}})
            parts.append(nxt.where(F.col(f"n_{along}") == F.col(along) + 1).select("scene_id", F.col("pixel").alias("u"), F.col("n_pixel").alias("v"), *carry_s(""), *carry_s("n_")))
        return parts[0].unionByName(parts[1]).hint("merge")  # a row or more a pixel: never to be broadcast
    targets = F.array(*[F.struct(F.lit(dy).alias("dy"), F.lit(dx).alias("dx")) for dy, dx in offsets])
    a = px.withColumn("o", F.explode(targets)).select("scene_id", (F.col("y") + F.col("o.dy")).alias("y"), (F.col("x") + F.col("o.dx")).alias("x"), F.col("pixel").alias("u"), *carry_s(""))
    b = px.select("scene_id", "y", "x", F.col("pixel").alias("v"), *[F.col(c).alias(f"{c}_v") for c in carry])
    return a.hint("merge").join(b, ["scene_id", "y", "x"]).drop("y", "x").hint("merge")


def symmetrise(directed: DataFrame) -> DataFrame:
    """Undirected mean of (scene_id, p, q, a) rows given in either direction."""
    return directed.groupBy("scene_id", F.least("p", "q").alias("u"), F.greatest("p", "q").alias("v")).agg(F.avg("a").alias("aff"))


def true_affinity(edges: DataFrame, gt: DataFrame, what: str = "inst_no") -> DataFrame:
    """0/1 affinity of (scene_id, u, v) from labels of both ends; unlabelled ends give 0."""
    a = gt.select("scene_id", F.col("pixel").alias("u"), F.col(what).alias("_a"))
    b = gt.select("scene_id", F.col("pixel").alias("v"), F.col(what).alias("_b"))
    return edges.join(a, ["scene_id", "u"], "left").join(b, ["scene_id", "v"], "left").withColumn("truth", F.coalesce((F.col("_a") == F.col("_b")).cast("int"), F.lit(0))).drop("_a", "_b")


def rim_flag(px: DataFrame, label: str = "label", include_frame: bool = False, side: tuple[int, int] | None = None) -> DataFrame:
    """Adds rim: whether a 4-neighbour within the raster has another label (or
    none).  The frame is a rim only with include_frame; side = (height, width)
    tells where it is, else the raster's own extent does."""
    out = px
    other = F.lit(False)
    for line, along in (("y", "x"), ("x", "y")):
        w = Window.partitionBy("scene_id", line).orderBy(along)
        for f, d in ((F.lag, -1), (F.lead, 1)):
            near = F.when(f(along).over(w) == F.col(along) + d, f(label).over(w))
            name = f"_{along}{d > 0:d}"
            out = out.withColumn(name, near)
            limit = (side[0] if along == "y" else side[1]) - 1 if side else None
            edge = (F.col(along) == 0) if d < 0 else (F.col(along) == limit if limit is not None else F.lit(False))
            other = other | F.when(edge, F.lit(include_frame)).otherwise(~F.col(name).eqNullSafe(F.col(label)))
    return out.withColumn("rim", other).drop("_x0", "_x1", "_y0", "_y1")


def region_graph(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """Graph of segments: mean affinity and number of crossing edges."""
    a = labels.select("scene_id", F.col("node").alias("u"), F.col("label").alias("_a"))
    b = labels.select("scene_id", F.col("node").alias("v"), F.col("label").alias("_b"))
    j = edges.join(a, ["scene_id", "u"]).join(b, ["scene_id", "v"]).where("_a <> _b")
    return j.groupBy("scene_id", F.least("_a", "_b").alias("u"), F.greatest("_a", "_b").alias("v")).agg(F.avg("aff").alias("aff"), F.count("*").alias("n"))


def segment_pairs(seg: DataFrame, key: str = "label") -> DataFrame:
    """All pairs of a scene's segments; columns of both ends as <name>_u and <name>_v."""
    cols = [c for c in seg.columns if c != "scene_id"]
    a = seg.select("scene_id", *[F.col(c).alias(f"{c}_u") for c in cols])
    b = seg.select("scene_id", *[F.col(c).alias(f"{c}_v") for c in cols])
    return a.join(b, "scene_id").where(F.col(f"{key}_u") < F.col(f"{key}_v"))


def foreground(px: DataFrame) -> DataFrame:
    """Pixels whose top class is not the background, class 0."""
    return px.where(F.array_position("sem", F.array_max("sem")) != 1)
