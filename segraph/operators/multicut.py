"""The exact problem: objective, feasibility and the optimum of tiny graphs."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from .components import components


def _ends(edges: DataFrame, labels: DataFrame) -> DataFrame:
    a = labels.select("scene_id", F.col("node").alias("u"), F.col("label").alias("_a"))
    b = labels.select("scene_id", F.col("node").alias("v"), F.col("label").alias("_b"))
    return edges.join(a, ["scene_id", "u"]).join(b, ["scene_id", "v"])


def multicut_cost(edges: DataFrame, labels: DataFrame, cost: str = "c") -> DataFrame:
    """Objective of a partition: summed cost of cut edges, and their number."""
    cut = F.col("_a") != F.col("_b")
    return _ends(edges, labels).groupBy("scene_id").agg(F.sum(F.when(cut, F.col(cost)).otherwise(0.0)).alias("cost"), F.sum(cut.cast("long")).alias("cut"))


def is_multicut(cuts: DataFrame, nodes: DataFrame) -> DataFrame:
    """Whether a cut vector meets all cycle inequalities: every cut edge joins
    different components of the uncut ones."""
    lab = components(cuts.select("scene_id", "u", "v", (~F.col("cut")).cast("double").alias("aff")), 0.5, nodes)
    bad = F.col("cut") & (F.col("_a") == F.col("_b"))
    return _ends(cuts, lab).groupBy("scene_id").agg((F.max(bad.cast("int")) == 0).alias("feasible"), F.sum(bad.cast("long")).alias("violated"))


@udtf(returnType="labels array<int>")
class SetPartitions:
    """All partitions of n items as restricted growth strings."""

    def eval(self, n: int) -> Iterator[tuple[list[int]]]:
        a = [0] * n

        def go(i: int, top: int):
            if i == n:
                yield (list(a),)
                return
            for c in range(top + 2):
                a[i] = c
                yield from go(i + 1, max(top, c))

        yield from go(1, 0) if n > 0 else ()


def multicut_exact(edges: DataFrame, t: float = 0.5, most: int = 9) -> DataFrame:
    """Least objective by enumeration for graphs with nodes 1..n, n <= most;
    larger ones are refused."""
    spark = edges.sparkSession
    from ..session import prepare

    prepare(spark)
    n = edges.groupBy("scene_id").agg(F.max("v").alias("n"))
    if n.where(F.col("n") > most).limit(1).count():
        raise ValueError(f"enumeration is for at most {most} nodes")
    sizes = [r["n"] for r in n.select("n").distinct().collect()]  # at most `most` numbers
    parts = None
    for k in sizes:
        one = SetPartitions(F.lit(int(k))).select(F.lit(k).cast("long").alias("n"), "labels")
        parts = one if parts is None else parts.union(one)
    if parts is None:
        return spark.createDataFrame([], "scene_id bigint, partitions bigint, best double")
    # a graph is one row, so that only graphs times partitions are formed
    e = edges.groupBy("scene_id").agg(F.max("v").alias("n"), F.array_sort(F.collect_list(F.struct(F.col("u").cast("int").alias("u"), F.col("v").cast("int").alias("v"), (F.col("aff") - t).alias("c")))).alias("e"))
    j = e.join(F.broadcast(parts), "n")  # Bell(most) rows
    at = lambda i: F.element_at("labels", i)
    total = F.aggregate("e", F.lit(0.0), lambda s, x: s + F.when(at(x["u"]) != at(x["v"]), x["c"]).otherwise(0.0))
    cost = j.select("scene_id", total.alias("cost"))
    return cost.groupBy("scene_id").agg(F.count("*").alias("partitions"), F.min("cost").alias("best"))


def gap(edges: DataFrame, t: float = 0.5) -> DataFrame:
    """Greedy objective against the optimum, by graph and rule."""
    from .contract import contract

    best = multicut_exact(edges, t)
    out = None
    for rule in ("avg", "mean_edges", "max"):
        g = multicut_cost(edges.withColumn("c", F.col("aff") - t), contract(edges, t, rule)).select("scene_id", F.lit(rule).alias("rule"), F.col("cost").alias("greedy"))
        out = g if out is None else out.union(g)
    return out.join(best, "scene_id").select("scene_id", "rule", "greedy", "best", (F.col("greedy") - F.col("best")).alias("gap"))
