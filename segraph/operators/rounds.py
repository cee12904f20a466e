"""Contraction of one graph of any size, many merges a round.

A round contracts edges that outrank every edge around them, so the result is
that of the sequential kernel: for "max" and "mean_edges" an edge must be the
best of both ends; for "avg" it must outrank all edges of its ends'
neighbours too, so that two merges of a round are never adjacent.  "sum" has
no such proof and is approximate.  A contraction that max_rounds don't end is an error.  State is written to the shared folder after each round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import materialise


def contract_rounds(edges: DataFrame, nodes: DataFrame, threshold: float = 0.5, rule: str = "avg", max_rounds: int = 1000) -> DataFrame:
    state = edges.select("scene_id", "u", "v", F.col("aff").alias("s"), F.lit(1).cast("bigint").alias("c"))
    labels = nodes.select("scene_id", "node", F.col("node").alias("label"))
    for _ in range(max_rounds):
        state = materialise(state, "rounds")
        if state.where(F.col("s") > threshold).limit(1).count() == 0:
            break
        rank = F.struct(F.col("s"), (-F.col("u")).alias("a"), (-F.col("v")).alias("b"))
        sym = state.select("scene_id", F.col("u").alias("node"), F.col("v").alias("near"), rank.alias("r")).union(state.select("scene_id", F.col("v"), F.col("u"), rank))
        best = sym.where(F.col("r.s") > threshold).groupBy("scene_id", "node").agg(F.max("r").alias("best"))
        if rule == "avg" or rule == "sum":
            around = sym.join(best.select("scene_id", F.col("node").alias("near"), F.col("best").alias("r2")), ["scene_id", "near"]).groupBy("scene_id", "node").agg(F.max("r2").alias("far"))
            best = best.join(around, ["scene_id", "node"], "left").select("scene_id", "node", F.greatest("best", F.coalesce("far", "best")).alias("best"))
        own = best.select("scene_id", "node", F.col("best.s").alias("bs"), (-F.col("best.a")).alias("bu"), (-F.col("best.b")).alias("bv"))
        pick = lambda n: own.where(F.col("node") == F.col(n)).select("scene_id", "bu", "bv")
        merge = materialise(pick("bu").intersect(pick("bv")).select("scene_id", F.col("bv").alias("gone"), F.col("bu").alias("kept")), "rounds")
        to = lambda df, c: df.join(merge.withColumnRenamed("gone", c), ["scene_id", c], "left").withColumn(c, F.coalesce("kept", c)).drop("kept")
        moved = to(to(state, "u"), "v").where("u <> v").groupBy("scene_id", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
        new = {"avg": F.avg("s"), "mean_edges": F.sum(F.col("s") * F.col("c")) / F.sum("c"), "sum": F.sum("s"), "max": F.max("s"), "min": F.min("s")}[rule]
        state = moved.agg(new.alias("s"), F.sum("c").alias("c"))
        labels = materialise(to(labels.withColumnRenamed("label", "v"), "v").withColumnRenamed("v", "label"), "rounds")
    else:
        raise RuntimeError(f"the contraction did not end within {max_rounds} rounds")
    return labels.select("scene_id", "node", "label")
