"""Planted scenes and graphs over the given tables (see FIXTURES.md).

Each builder has a twin in SQL (``CTE``), so that both engines derive the same
rows by the same integer arithmetic.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import table

P = 1000003
SIDE = 32


def unit_hash(a, b, c, seed: int) -> Column:
    """Portable hash of three non-negative integers in [0, 1)."""
    a, b, c = (x if isinstance(x, Column) else F.lit(x) for x in (a, b, c))
    z0 = (F.lit(7919).cast("long") * (a.cast("long") % P) + F.lit(10007).cast("long") * b + F.lit(30011).cast("long") * c + 65537 * seed) % P
    z1 = (z0 * z0 + 97 * b.cast("long") + c) % P
    return ((z1 * z1 + z0) % P) / F.lit(float(P))


def hash_sql(a: str, b: str, c: str, seed: int) -> str:
    z0 = f"((7919::BIGINT*(({a})::BIGINT % {P}) + 10007::BIGINT*({b}) + 30011::BIGINT*({c}) + {65537 * seed}) % {P})"
    z1 = f"(({z0}*{z0} + 97*({b})::BIGINT + ({c})) % {P})"
    return f"((({z1}*{z1} + {z0}) % {P}) / {P}.0::DOUBLE)"


def instances(spark, sf: str, every: int = 50, parts: int = 0) -> DataFrame:
    """Declared boxes, one per order line, numbered front to back; with parts, scenes are dealt
    whole to so many tasks, and what is derived by scene needs no other shuffle."""
    li = table(spark, sf, "lineitem").where(F.col("l_orderkey") % every == 0)
    pt = table(spark, sf, "part").select("p_partkey", "p_size").hint("merge")  # two narrow columns look small in files: a million parts would be broadcast
    w = Window.partitionBy("l_orderkey").orderBy("l_extendedprice", "l_partkey", "l_suppkey", "l_linenumber")
    odd, lin = F.col("l_linenumber") % 2 == 1, F.col("l_linenumber")
    pick = lambda a, b: F.when(odd, a).otherwise(b).cast("int")
    slide = 7 * F.col("l_suppkey") + 5 * lin
    both = li.join(pt, li["l_partkey"] == pt["p_partkey"])
    return (both.repartition(parts, "l_orderkey") if parts else both).select(
        F.col("l_orderkey").alias("scene_id"), F.row_number().over(w).alias("inst_no"), (F.col("l_extendedprice") / 1000).alias("depth"), (1 + F.col("p_size") % 8).cast("int").alias("cls"),
        pick(F.col("l_partkey") % 8, 4 + F.col("l_partkey") % 24).alias("x0"), pick(3 + slide % 25, slide % 8).alias("y0"),
        pick(16 + F.floor("l_quantity") % 9, 3 + F.floor("l_quantity") % 4).alias("w"), pick(3 + F.floor("l_extendedprice") % 4, 16 + F.floor("l_extendedprice") % 9).alias("h"),
    )


def ground_truth(spark, sf: str, every: int = 50, parts: int = 0) -> DataFrame:
    """Visible pixels: the nearest box owns a pixel.  Spark underrates the size of what is exploded,
    filtered and windowed; the hint keeps joins from sending pixels through the driver."""
    i = instances(spark, sf, every, parts)
    px = i.withColumn("y", F.explode(F.sequence("y0", F.least(F.lit(SIDE - 1), F.col("y0") + F.col("h") - 1)))).withColumn("x", F.explode(F.sequence("x0", F.least(F.lit(SIDE - 1), F.col("x0") + F.col("w") - 1))))
    best = px.groupBy("scene_id", "y", "x").agg(F.min(F.struct("inst_no", "cls", "depth")).alias("b"))
    return best.select("scene_id", "y", "x", (SIDE * F.col("y") + F.col("x")).cast("long").alias("pixel"), "b.inst_no", "b.cls", "b.depth").hint("merge")


def raster_cells(gt: DataFrame) -> DataFrame:
    """All SIDE x SIDE cells of scenes that lie whole in a task, scene after scene: what owns a cell, or
    null, and the owners of its right and lower neighbours (ri, di), null where either cell has none."""
    import numpy as np
    import pyarrow as pa

    from ..operators.streams import arrow_schema, scenes_of
    from ..session import prepare

    prepare(gt.sparkSession)
    ddl = "scene_id bigint, pixel bigint, inst_no int, cls int, depth double, ri int, di int"
    schema = arrow_schema(ddl)
    n = SIDE * SIDE

    def work(it):
        for scene, t in scenes_of(it, "scene_id"):
            at, inst, cls, depth = (t.column(c).combine_chunks() for c in ("pixel", "inst_no", "cls", "depth"))
            at = at.to_numpy()
            row = np.full(n, -1, np.int64)
            row[at] = np.arange(len(at))
            own = np.full(n, 0, np.int32)
            own[at] = inst.to_numpy(zero_copy_only=False)
            own = own.reshape(SIDE, SIDE)
            right, down = np.zeros_like(own), np.zeros_like(own)
            right[:, :-1] = np.where(own[:, :-1] > 0, own[:, 1:], 0)
            down[:-1] = np.where(own[:-1] > 0, own[1:], 0)
            take = pa.array(row, mask=row < 0)
            owners = [pa.array(a.ravel(), mask=a.ravel() == 0) for a in (right, down)]  # instances count from 1
            yield pa.RecordBatch.from_arrays([pa.array(np.full(n, scene)), pa.array(np.arange(n)), inst.take(take), cls.take(take), depth.take(take), *owners], schema=schema)

    return gt.select("scene_id", "pixel", "inst_no", "cls", F.col("depth").cast("double").alias("depth")).sortWithinPartitions("scene_id").mapInArrow(work, ddl)


def thin(gt: DataFrame, stride: int = 4) -> DataFrame:
    """Every stride-th row and column, renumbered."""
    w = SIDE // stride
    return gt.where((F.col("y") % stride == 0) & (F.col("x") % stride == 0)).withColumns({"y": (F.col("y") / stride).cast("int"), "x": (F.col("x") / stride).cast("int")}).withColumn("pixel", (w * F.col("y") + F.col("x")).cast("long"))


def edge_hash() -> Column:
    return unit_hash(F.col("scene_id"), F.col("u"), F.col("v"), 42)


def neighbour_affinity(eps: float, rogue: float = 0.0, h: Column | None = None) -> Column:
    """Affinity of u and v with instances iu, iv; h: edge_hash(), where it is a column already."""
    h = edge_hash() if h is None else h
    a = F.when(F.col("iu") == F.col("iv"), 1 - eps * h).otherwise(eps * h)
    if rogue:
        a = F.when(unit_hash(F.col("scene_id"), F.col("u"), F.col("v"), 7) < rogue, 1 - a).otherwise(a)
    return a


def semantic(pixels: DataFrame) -> DataFrame:
    """Adds sem, the nine-class distribution; class 0 is background."""
    c, d = F.coalesce(F.col("cls"), F.lit(0)), F.col("_d")  # a column of its own: the plan would else hold the hash 18 times
    px = pixels.withColumn("_d", 0.4 * unit_hash(F.col("scene_id"), F.col("pixel"), F.lit(0), 11))
    return px.withColumn("sem", F.array(*[F.when(c == k, 1 - d).otherwise(d / 8) for k in range(9)])).drop("_d")


def embedding(spark, sf: str, pixels: DataFrame, k: int, gain: float = 2.0, sigma: float = 0.3) -> DataFrame:
    """Adds emb: gain times the instance's anchor and sigma times noise."""
    e = table(spark, sf, "embeddings").where("vec_id < 500").select("vec_id", F.slice("embedding", 1, k).cast("array<double>").alias("e"))  # 500 rows
    a = F.pmod(31 * F.col("scene_id") + 17 * F.coalesce("inst_no", F.lit(0)), F.lit(500))
    b = F.floor(500 * unit_hash(F.col("scene_id"), F.col("pixel"), F.lit(0), 13))
    px = pixels.withColumns({"_a": a.cast("long"), "_b": b.cast("long")})
    px = px.join(F.broadcast(e.toDF("_a", "_ea")), "_a").join(F.broadcast(e.toDF("_b", "_eb")), "_b")
    return px.withColumn("emb", F.zip_with("_ea", "_eb", lambda x, y: gain * x + sigma * y)).drop("_a", "_b", "_ea", "_eb").hint("merge")


def cte(stride: int = 1, every: int = 50, eps: float = 0.45, rogue: float = 0.0) -> str:
    """SQL twin: inst, gt (full), g (thinned), edges(scene_id,u,v,iu,iv,aff)."""
    w = SIDE // stride
    aff = f"CASE WHEN iu=iv THEN 1-{eps}::DOUBLE*{hash_sql('scene_id', 'u', 'v', 42)} ELSE {eps}::DOUBLE*{hash_sql('scene_id', 'u', 'v', 42)} END"
    if rogue:
        aff = f"CASE WHEN {hash_sql('scene_id', 'u', 'v', 7)} < {rogue} THEN 1-({aff}) ELSE {aff} END"
    return f"""inst AS (SELECT l_orderkey AS scene_id,
  row_number() OVER (PARTITION BY l_orderkey ORDER BY l_extendedprice,l_partkey,l_suppkey,l_linenumber)::INT AS inst_no,
  l_extendedprice/1000 AS depth, (1+p_size%8)::INT AS cls,
  (CASE WHEN l_linenumber%2=1 THEN l_partkey%8 ELSE 4+l_partkey%24 END)::INT AS x0,
  (CASE WHEN l_linenumber%2=1 THEN 3+(7*l_suppkey+5*l_linenumber)%25 ELSE (7*l_suppkey+5*l_linenumber)%8 END)::INT AS y0,
  (CASE WHEN l_linenumber%2=1 THEN 16+floor(l_quantity)::INT%9 ELSE 3+floor(l_quantity)::INT%4 END)::INT AS w,
  (CASE WHEN l_linenumber%2=1 THEN 3+floor(l_extendedprice)::BIGINT%4 ELSE 16+floor(l_extendedprice)::BIGINT%9 END)::INT AS h
  FROM lineitem JOIN part ON l_partkey=p_partkey WHERE l_orderkey%{every}=0),
gt AS MATERIALIZED (SELECT scene_id,y,x,({SIDE}*y+x)::BIGINT AS pixel,inst_no,cls,depth FROM (
  SELECT i.*,yy.y,xx.x,row_number() OVER (PARTITION BY scene_id,yy.y,xx.x ORDER BY inst_no) AS rn FROM inst i
  JOIN (SELECT range::INT AS y FROM range({SIDE})) yy ON yy.y>=i.y0 AND yy.y<i.y0+i.h
  JOIN (SELECT range::INT AS x FROM range({SIDE})) xx ON xx.x>=i.x0 AND xx.x<i.x0+i.w) WHERE rn=1),
g AS MATERIALIZED (SELECT scene_id,(y//{stride})::INT AS y,(x//{stride})::INT AS x,({w}*(y//{stride})+x//{stride})::BIGINT AS pixel,inst_no,cls,depth FROM gt WHERE y%{stride}=0 AND x%{stride}=0),
pairs AS MATERIALIZED (SELECT a.scene_id,a.pixel AS u,b.pixel AS v,a.inst_no AS iu,b.inst_no AS iv FROM g a JOIN g b ON b.scene_id=a.scene_id AND b.y=a.y AND b.x=a.x+1 UNION ALL SELECT a.scene_id,a.pixel,b.pixel,a.inst_no,b.inst_no FROM g a JOIN g b ON b.scene_id=a.scene_id AND b.x=a.x AND b.y=a.y+1),
edges AS (SELECT scene_id,u,v,iu,iv,{aff} AS aff FROM pairs)"""
