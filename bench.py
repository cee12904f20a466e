"""Headline queries, timed; one JSON line.

BENCH_SF_DIR (default /root/testdata/sf0.1) and BENCH_CPUS (default 4).
"""

from __future__ import annotations

import json
import math
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import functions as F  # noqa: E402

from segraph.plans import graphs, measures, partitions  # noqa: E402
from segraph.session import local_session  # noqa: E402

HEADLINE = {
    "grid_edges_n4": graphs.grid_edges_n4, "rim_flag": graphs.rim_flag, "group_affinity": graphs.group_affinity, "gc_scenes_avg": partitions.gc_scenes_avg, "pgc_scenes": partitions.pgc_scenes,
    "la_sync": partitions.la_sync, "loss_pull": measures.loss_pull, "ap_overall": measures.ap_overall,
}


def timed(df) -> float:
    t = time.time()
    df.write.format("noop").mode("overwrite").save()
    return round(time.time() - t, 2)


def planted_rasters(spark, side: int, scenes: int = 8, emb: int = 8):
    """Pixels and edges of rasters of any side, planted by rule: tiles of 13 by 11 cells are the
    instances, one in five is background."""
    at = spark.range(scenes * side * side).select(F.floor(F.col("id") / side**2).alias("scene_id"), (F.col("id") % side**2).alias("pixel"))
    at = at.withColumns({"y": F.floor(F.col("pixel") / side), "x": F.col("pixel") % side})
    unit = lambda *c: F.pmod(F.xxhash64(*c), F.lit(1 << 20)) / (1 << 20)
    inst = lambda y, x: F.xxhash64("scene_id", F.floor(y / 13), F.floor(x / 11))
    cls = lambda i: F.when(F.pmod(i, F.lit(5)) == 0, 0).otherwise(1 + F.pmod(i, F.lit(8)))
    at = at.withColumn("inst", inst(F.col("y"), F.col("x")))
    noise = 0.4 * unit("scene_id", "pixel")
    sem = F.array(*[F.when(cls(F.col("inst")) == k, 1 - noise).otherwise(noise / 8) for k in range(9)])
    vec = F.array(*[2 * unit("inst", F.lit(k)) + 0.1 * unit("scene_id", "pixel", F.lit(k)) for k in range(emb)])
    px = at.select("scene_id", "pixel", sem.alias("sem"), vec.alias("emb"))
    e = at.select("*", F.explode(F.array(F.struct(F.lit(0).alias("dy"), F.lit(1).alias("dx")), F.struct(F.lit(1).alias("dy"), F.lit(0).alias("dx")))).alias("o")).where((F.col("y") + F.col("o.dy") < side) & (F.col("x") + F.col("o.dx") < side))
    e = e.withColumn("near", inst(F.col("y") + F.col("o.dy"), F.col("x") + F.col("o.dx"))).where((cls(F.col("inst")) > 0) & (cls(F.col("near")) > 0))
    h = 0.45 * unit("scene_id", "pixel", "o.dy")
    e = e.select("scene_id", F.col("pixel").alias("u"), (F.col("pixel") + side * F.col("o.dy") + F.col("o.dx")).alias("v"), F.when(F.col("inst") == F.col("near"), 1 - h).otherwise(h).alias("aff"))
    return px, e


def slope(seconds: dict[int, float]) -> float:
    """Log-log slope of time against pixels, by least squares over the sizes."""
    x, y = [math.log(n) for n in seconds], [math.log(max(t, 1e-3)) for t in seconds.values()]
    mx, my = sum(x) / len(x), sum(y) / len(y)
    return round(sum((a - mx) * (b - my) for a, b in zip(x, y)) / sum((a - mx) ** 2 for a in x), 2)


def main() -> None:
    sf, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "4")
    spark = local_session(cpus, "6g", 2 * int(cpus))
    spark.sparkContext.setLogLevel("ERROR")
    out = {name: timed(fn(spark, sf)) for name, fn in HEADLINE.items()}
    # partition time alone: whole scenes, inputs written before
    from segraph.operators.contract import contract
    from segraph.operators.pyramid import partition_pyramid
    from segraph.session import materialise

    gt = materialise(graphs.full(spark, sf), "bench")
    e = materialise(graphs.edges_of(gt, partitions.NOISY).select("scene_id", "u", "v", "aff"), "bench")
    px = materialise(graphs.pixels(spark, sf, 8).select("scene_id", "pixel", "sem", "emb"), "bench")
    scenes, cells = px.select("scene_id").distinct().count(), px.count()
    rates = {}
    for name, df in (
        ("flat", contract(e, nodes=gt.select("scene_id", F.col("pixel").alias("node")))), ("cascade", partition_pyramid(px, e, 32, 8)), ("cascade_adopt", partition_pyramid(px, e, 32, 8, finest="adopt")),
    ):
        out[f"part_{name}"] = timed(df)
        rates[name] = {"s_per_scene": round(out[f"part_{name}"] / scenes, 5), "cells_per_s": round(cells / out[f"part_{name}"])}
    sizes, cascades = {}, {"contract": {}, "adopt": {}}
    if os.environ.get("BENCH_SIZES", "1") == "1":
        from segraph.sources.planted import PlantedScenes

        spark.dataSource.register(PlantedScenes)
        for side in (32, 64, 128, 256):
            d = materialise(spark.read.format("planted_scenes").option("scenes", 8).option("side", side).load(), "bench")
            sizes[side * side] = timed(contract(d))
        for side in (64, 128, 256, 512):
            px, e = (materialise(d, "bench") for d in planted_rasters(spark, side))
            for finest, got in cascades.items():
                got[side * side] = timed(partition_pyramid(px, e, side, 8, finest=finest))
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(out.values()), 2), "unit": "sec", "queries": out, "sf": os.path.basename(sf.rstrip("/")), "cpus": int(cpus), "partition": rates, "seconds_by_pixels": sizes, "cascade_seconds_by_pixels": cascades, "cascade_slope": {k: slope(v) for k, v in cascades.items() if v}}))
    spark.stop()


if __name__ == "__main__":
    main()
