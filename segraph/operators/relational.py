"""Joins and rankings that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, take: list[str], strict: bool = True) -> DataFrame:
    """Each left row with the ``take`` columns of the latest right row of its
    key at an earlier (or, if not strict, the same) time; null where none.
    One sort of the union by key and time; no pairs are formed."""
    cols = left.columns
    l_ = left.select(*cols, F.lit(1 if not strict else 0).alias("_side"), *[F.lit(None).cast(right.schema[t].dataType).alias(f"_r_{t}") for t in take], F.lit(None).cast("boolean").alias("_is"))
    missing = [c for c in cols if c not in (by, at)]
    r_ = right.select(by, at, *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in missing], F.lit(0 if not strict else 1).alias("_side"), *[F.col(t).alias(f"_r_{t}") for t in take], F.lit(True).alias("_is"))
    w = Window.partitionBy(by).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    packed = F.when(F.col("_is"), F.struct(*[F.col(f"_r_{t}").alias(t) for t in take]))
    u = l_.unionByName(r_).withColumn("_p", F.last(packed, ignorenulls=True).over(w)).where("_is is null")
    return u.select(*cols, *[F.col(f"_p.{t}").alias(f"asof_{t}") for t in take])


def interval_join(left: DataFrame, right: DataFrame, by: str, at_left: str, at_right: str, within: float) -> DataFrame:
    """Pairs of one key whose numbers differ by at most ``within``: an
    equi-join on buckets of that width, each left row meeting three."""
    l_ = left.withColumn("_b", F.explode(F.array(*[F.floor(F.col(at_left) / within) + d for d in (-1, 0, 1)])))
    r_ = right.withColumn("_b", F.floor(F.col(at_right) / within))
    return l_.join(r_, [by, "_b"]).where(F.abs(F.col(at_left) - F.col(at_right)) <= within).drop("_b")


def overlap_join(left: DataFrame, right: DataFrame, lo: str, hi: str, width: int, by: str) -> DataFrame:
    """Pairs of one key whose closed intervals overlap; columns of right get
    the suffix _r.  Cells of ``width`` make it an equi-join; the pair counts in the
    first cell both touch."""
    cells = lambda df: df.withColumn("_c", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    r_ = cells(right)
    r_ = r_.select(by, "_c", *[F.col(c).alias(f"{c}_r") for c in right.columns if c != by])
    j = cells(left).join(r_, [by, "_c"]).where((F.col(lo) <= F.col(f"{hi}_r")) & (F.col(f"{lo}_r") <= F.col(hi)))
    return j.where(F.col("_c") == F.floor(F.greatest(F.col(lo), F.col(f"{lo}_r")) / width)).drop("_c")


def top_per_key(df: DataFrame, keys: list[str], order: list, k: int) -> DataFrame:
    """First k rows of each key; Spark prunes each task to k rows before the shuffle."""
    w = Window.partitionBy(*keys).orderBy(*order)
    return df.withColumn("_rn", F.row_number().over(w)).where(F.col("_rn") <= k).drop("_rn")
