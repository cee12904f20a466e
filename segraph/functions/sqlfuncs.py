"""SQL names for the engine's functions."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

SQL_FUNCTIONS = {
    "seg_phi": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN exp(-ln(2) * aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))",
    "seg_js": "(p ARRAY<DOUBLE>, q ARRAY<DOUBLE>) RETURNS DOUBLE RETURN 1 - aggregate(zip_with(p, q, (x, y) -> IF(x > 0, x * log2(x / ((x + y) / 2)), 0D) + IF(y > 0, y * log2(y / ((x + y) / 2)), 0D)), 0D, (s, x) -> s + x) / 2",
    "seg_damping": "(h DOUBLE, w DOUBLE, gap_y DOUBLE, gap_x DOUBLE, beta DOUBLE) RETURNS DOUBLE RETURN IF(gap_y = 0, 1D, pow(least(1D, 0.5D * h / gap_y), beta)) * IF(gap_x = 0, 1D, pow(least(1D, 0.5D * w / gap_x), beta))",
}


@udtf(returnType="u bigint, v bigint")
class GridNeighbours:
    """4-neighbour pairs of an h x w raster."""

    def eval(self, h: int, w: int) -> Iterator[tuple[int, int]]:
        for y in range(h):
            for x in range(w):
                n = y * w + x
                if x + 1 < w:
                    yield n, n + 1
                if y + 1 < h:
                    yield n, n + w


def vector_sum():
    """Grouped aggregate: entrywise sum of array columns, in Arrow batches."""
    import numpy as np
    from pyspark.sql.functions import PandasUDFType

    def seg_vecsum(v):
        return np.stack(v.to_numpy()).sum(0).tolist() if len(v) else []

    return pandas_udf(seg_vecsum, "array<double>", PandasUDFType.GROUPED_AGG)


def register_all(spark: SparkSession) -> None:
    """Adds every function, so that plain SQL can use the engine."""
    from ..operators.multicut import SetPartitions

    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("grid_neighbours", GridNeighbours)
    spark.udtf.register("set_partitions", SetPartitions)
    spark.udf.register("seg_vecsum", vector_sum())
