"""Accuracy of partitions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

TAUS = tuple(round(0.5 + 0.05 * i, 2) for i in range(10))


def iou_pairs(pred: DataFrame, gt: DataFrame) -> DataFrame:
    """Overlaps of predicted and true segments of one scene and class.
    pred, gt: scene_id, pixel, label, cls (one row per pixel)."""
    p = pred.select("scene_id", "pixel", F.col("label").alias("pred"), F.col("cls").alias("pcls"))
    g = gt.select("scene_id", "pixel", F.col("label").alias("truth"), F.col("cls").alias("gcls"))
    both = p.join(g, ["scene_id", "pixel"]).where("pcls = gcls").groupBy("scene_id", F.col("pcls").alias("cls"), "pred", "truth").agg(F.count("*").alias("both"))
    np_ = p.groupBy("scene_id", "pred").agg(F.count("*").alias("np"))
    ng = g.groupBy("scene_id", "truth").agg(F.count("*").alias("ng"))
    j = both.join(np_, ["scene_id", "pred"]).join(ng, ["scene_id", "truth"])
    return j.select("scene_id", "cls", "pred", "truth", (F.col("both") / (F.col("np") + F.col("ng") - F.col("both"))).alias("iou"))


OVERLAP_DDL = "scene_id bigint, m int, pred bigint, truth bigint, cls int, score double, depth double, n bigint, iou double"


def overlap_rows(lab: np.ndarray, segments, inst: np.ndarray, cls: np.ndarray, depth: np.ndarray) -> dict[str, np.ndarray]:
    """What average precision takes of one scene, with nan for null: a row a segment (no truth), a row an instance
    (no pred) and a row for a segment and an instance of one class that overlap.  lab: segments by cell, 0 none;
    segments: their labels, classes and scores; inst, cls, depth: owners by cell, nan none."""
    ids, pcls, score = segments
    owned = ~np.isnan(inst)
    truths, first, g = np.unique(inst[owned], return_index=True, return_inverse=True)
    tcls, far = cls[owned][first], np.full(len(truths), np.inf)
    np.minimum.at(far, g, depth[owned])
    n_pred, n_truth = np.bincount(np.searchsorted(ids, lab[lab > 0]), minlength=len(ids)), np.bincount(g, minlength=len(truths))
    both = lab[owned] > 0
    p, t = np.searchsorted(ids, lab[owned][both]), g[both]
    same = pcls[p] == cls[owned][both]
    pair, count = np.unique(p[same] * max(1, len(truths)) + t[same], return_counts=True)
    p, t = pair // max(1, len(truths)), pair % max(1, len(truths))
    no = lambda k: np.full(k, np.nan)
    a, b, c = len(ids), len(truths), len(pair)
    parts = {
        "pred": (ids, no(b), ids[p]), "truth": (no(a), truths, truths[t]), "cls": (pcls, tcls, pcls[p]), "score": (score, no(b), no(c)),
        "depth": (no(a), far, no(c)), "n": (n_pred, n_truth, no(c)), "iou": (no(a), no(b), count / (n_pred[p] + n_truth[t] - count)),
    }
    return {k: np.concatenate([np.asarray(x, float) for x in v]) for k, v in parts.items()}


def match(iou: DataFrame, scores: DataFrame, taus=TAUS) -> DataFrame:
    """(scene_id, cls, pred, tau) of matched predictions.  Masks are disjoint,
    so an overlap above one half has one partner on either side; only at
    exactly one half can there be two, and then the higher score, the smaller
    prediction and the smaller truth win."""
    t = iou.join(scores.select("scene_id", "pred", "score"), ["scene_id", "pred"]).withColumn("tau", F.explode(F.array(*[F.lit(x) for x in taus]))).where(F.col("iou") >= F.col("tau") - 1e-12)
    w1 = Window.partitionBy("scene_id", "truth", "tau").orderBy(F.col("iou").desc(), F.col("score").desc(), "pred")
    w2 = Window.partitionBy("scene_id", "pred", "tau").orderBy(F.col("iou").desc(), "truth")
    return t.withColumn("a", F.row_number().over(w1)).where("a = 1").withColumn("b", F.row_number().over(w2)).where("b = 1").select("scene_id", "cls", "pred", "truth", "tau")


def average_precision(pred: DataFrame, gt: DataFrame, taus=TAUS, depth_max: float | None = None, reading: str = "area", bins: dict[str, Column] | None = None) -> DataFrame:
    """(cls, tau, value).  pred: scene_id, pixel, label, cls, score; gt:
    scene_id, pixel, label, cls, depth.  Truth beyond depth_max is ignored:
    predictions that match it count neither way.  reading "area" is the area
    under the interpolated precision-recall curve, "precision" TP/(TP+FP).
    bins, disjoint conditions on a truth's n (pixels) or depth by name, give (bin, cls, tau,
    value) in one pass: truth of other bins is ignored as far truth is."""
    scores = pred.groupBy("scene_id", F.col("label").alias("pred")).agg(F.first("cls").alias("cls"), F.max("score").alias("score"))
    truths = gt.groupBy("scene_id", F.col("label").alias("truth")).agg(F.first("cls").alias("cls"), F.min("depth").alias("depth"), F.count("*").alias("n"))
    return precision_of(scores, truths, iou_pairs(pred, gt), taus, depth_max, reading, bins)


def precision_of(scores: DataFrame, truths: DataFrame, iou: DataFrame, taus=TAUS, depth_max: float | None = None, reading: str = "area", bins: dict[str, Column] | None = None) -> DataFrame:
    """average_precision() of segments (scene_id, pred, cls, score), instances (scene_id, truth, cls, depth, n) and
    their overlaps (scene_id, cls, pred, truth, iou).  A segment is one row throughout, with an entry a threshold."""
    key = ["bin", "cls"] if bins else ["cls"]
    far = F.col("depth") > depth_max if depth_max is not None else F.lit(False)
    truths = truths.withColumn("far", far).withColumn("bin", F.coalesce(*[F.when(c, F.lit(b)) for b, c in (bins or {"": F.lit(True)}).items()]))
    m = match(iou, scores, taus).join(truths.select("scene_id", "truth", "far", F.coalesce("bin", F.lit("")).alias("of")), ["scene_id", "truth"])
    n_gt = truths.where(~F.col("far") & F.col("bin").isNotNull()).groupBy(*key).agg(F.count("*").alias("n_gt"))
    got = m.groupBy("scene_id", "pred").agg(F.collect_list(F.struct("tau", "far", "of")).alias("got"))
    hit = scores.join(got, ["scene_id", "pred"], "left")
    if bins:
        hit = hit.withColumn("bin", F.explode(F.array(*[F.lit(b) for b in bins])))
    for i, tau in enumerate(taus):
        one = F.get(F.filter("got", lambda x: x["tau"] == F.lit(tau)), F.lit(0))  # noqa: B023
        other = F.coalesce(one["far"], F.lit(False))
        if bins:
            other = other | (one["of"].isNotNull() & (one["of"] != F.col("bin")))
        hit = hit.withColumn(f"tp{i}", F.when(other, None).otherwise(one["far"].isNotNull().cast("int")))  # null: counts neither way
    hit = hit.drop("got")
    grid = n_gt.withColumn("tau", F.explode(F.array(*[F.lit(x) for x in taus])))
    by_tau = lambda what: F.explode(F.array(*[F.struct(F.lit(tau).alias("tau"), what(i).alias("value")) for i, tau in enumerate(taus)])).alias("v")
    if reading == "precision":
        v = hit.groupBy(*key).agg(*[F.avg(f"tp{i}").alias(f"s{i}") for i in range(len(taus))]).select(*key, by_tau(lambda i: F.col(f"s{i}"))).select(*key, "v.*")
        return grid.join(v, [*key, "tau"], "left").select(*key, "tau", F.coalesce("value", F.lit(0.0)).alias("value"))
    w = Window.partitionBy(*key).orderBy(F.col("score").desc(), "scene_id", "pred").rowsBetween(Window.unboundedPreceding, 0)
    pr = hit.select(*key, "score", "scene_id", "pred", *[f"tp{i}" for i in range(len(taus))], *[(F.sum(f"tp{i}").over(w) / F.count(f"tp{i}").over(w)).alias(f"prec{i}") for i in range(len(taus))])
    # the best precision from here on, as a running maximum from the end: a frame that ends at the last row costs its square
    back = Window.partitionBy(*key).orderBy("score", F.col("scene_id").desc(), F.col("pred").desc()).rowsBetween(Window.unboundedPreceding, 0)
    env = pr.select(*key, *[F.when(F.col(f"tp{i}") == 1, F.max(F.when(F.col(f"tp{i}").isNotNull(), F.col(f"prec{i}"))).over(back)).alias(f"e{i}") for i in range(len(taus))])
    area = env.groupBy(*key).agg(*[F.sum(f"e{i}").alias(f"s{i}") for i in range(len(taus))]).select(*key, by_tau(lambda i: F.col(f"s{i}"))).select(*key, "v.*")
    return grid.join(area, [*key, "tau"], "left").select(*key, "tau", (F.coalesce("value", F.lit(0.0)) / F.col("n_gt")).alias("value"))


def miou(px: DataFrame, pred: str = "pred", truth: str = "truth") -> DataFrame:
    """(cls, iou) from one confusion table."""
    c = px.groupBy(F.col(pred).alias("p"), F.col(truth).alias("t")).agg(F.count("*").alias("n"))
    by = lambda k: c.groupBy(F.col(k).alias("cls")).agg(F.sum("n").alias(f"n{k}"))
    same = c.where("p = t").select(F.col("p").alias("cls"), F.col("n").alias("both"))
    j = by("t").join(by("p"), "cls", "left").join(same, "cls", "left")
    b = F.coalesce("both", F.lit(0))
    return j.select("cls", (b / (F.col("nt") + F.coalesce("np", F.lit(0)) - b)).alias("iou"))


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rand and adjusted Rand index, variation of information (bits) and purity
    of two labellings, from their contingency table."""
    c = a.select("scene_id", "node", F.col("label").alias("a")).join(b.select("scene_id", "node", F.col("label").alias("b")), ["scene_id", "node"]).groupBy("scene_id", "a", "b").agg(F.count("*").alias("n"))
    two = lambda x: x * (x - 1) / 2
    rows = c.groupBy("scene_id", "a").agg(F.sum("n").alias("n"), F.max("n").alias("top"))
    cols = c.groupBy("scene_id", "b").agg(F.sum("n").alias("n"))
    s = c.groupBy("scene_id").agg(F.sum("n").alias("n"), F.sum(two(F.col("n"))).alias("ij"), F.sum(F.col("n") * F.log2("n")).alias("hij"))
    s = s.join(rows.groupBy("scene_id").agg(F.sum(two(F.col("n"))).alias("i"), F.sum(F.col("n") * F.log2("n")).alias("hi"), F.sum("top").alias("top")), "scene_id")
    s = s.join(cols.groupBy("scene_id").agg(F.sum(two(F.col("n"))).alias("j"), F.sum(F.col("n") * F.log2("n")).alias("hj")), "scene_id")
    t = two(F.col("n"))
    want = F.col("i") * F.col("j") / t
    most = (F.col("i") + F.col("j")) / 2
    return s.select(
        "scene_id", F.when(t > 0, (t + 2 * F.col("ij") - F.col("i") - F.col("j")) / t).otherwise(1.0).alias("rand"),
        F.when((t > 0) & (F.abs(most - want) > 1e-12), (F.col("ij") - want) / (most - want)).otherwise(1.0).alias("adjusted_rand"),
        ((F.col("hi") + F.col("hj") - 2 * F.col("hij")) / F.col("n")).alias("vi"), (F.col("top") / F.col("n")).alias("purity"),
    )


def merge_split_errors(pred: DataFrame, gt: DataFrame) -> DataFrame:
    """Segments over several true pieces, and pieces over several segments."""
    c = pred.select("scene_id", "node", F.col("label").alias("a")).join(gt.select("scene_id", "node", F.col("label").alias("b")), ["scene_id", "node"]).select("scene_id", "a", "b").distinct()
    m = c.groupBy("scene_id", "a").agg(F.count("*").alias("k")).where("k > 1").groupBy("scene_id").agg(F.count("*").alias("merged"))
    s = c.groupBy("scene_id", "b").agg(F.count("*").alias("k")).where("k > 1").groupBy("scene_id").agg(F.count("*").alias("split"))
    base = c.select("scene_id").distinct()
    return base.join(m, "scene_id", "left").join(s, "scene_id", "left").select("scene_id", F.coalesce("merged", F.lit(0)).alias("merged"), F.coalesce("split", F.lit(0)).alias("split"))
