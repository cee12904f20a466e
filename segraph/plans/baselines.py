"""Baseline partitioners on the planted scenes."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..fixtures import scenes as S
from ..operators import baselines as B
from ..operators import grid as G
from .graphs import FULL, PX, SIX, edges_of, full, pixels, planted, tiny
from .partitions import NOISY, TINY, tiny_graph
from .registry import query


def boxes(spark, sf):
    i = S.instances(spark, sf)
    clip = lambda o, n: F.least(F.col(n), 32 - F.col(o)).cast("int")
    return i.select("scene_id", F.col("inst_no").cast("bigint").alias("box"), "cls", "y0", "x0", clip("y0", "h").alias("h"), clip("x0", "w").alias("w"))


BOXES = ", boxes AS (SELECT scene_id,inst_no::BIGINT AS box,cls,y0,x0,least(h,32-y0) AS h,least(w,32-x0) AS w FROM inst)"


@query("base_level_by_size", FULL + " SELECT scene_id,inst_no,least(greatest(floor(log2(sqrt(w*h)/8.0))+1,1),4)::INT AS level FROM inst")
def base_level_by_size(spark, sf):
    return B.level_by_size(S.instances(spark, sf)).select("scene_id", "inst_no", "level")


@query("base_position_sensitive", PX + BOXES + " SELECT b.scene_id,b.box,(((p.y-b.y0)*3//b.h)*3+(p.x-b.x0)*3//b.w)::INT AS cell,round(avg(p.sem[b.cls+1]),6) AS score FROM boxes b JOIN px p ON p.scene_id=b.scene_id AND p.y>=b.y0 AND p.y<b.y0+b.h AND p.x>=b.x0 AND p.x<b.x0+b.w GROUP BY 1,2,3")
def base_position_sensitive(spark, sf):
    px = pixels(spark, sf).select("scene_id", "y", "x", "sem")
    value = F.element_at("sem", F.col("cls") + 1)
    return B.position_sensitive(px, boxes(spark, sf), value=value).withColumn("score", SIX("score"))


NOISE = {a: S.hash_sql("g.scene_id", "g.pixel", a, 29) for a in ("1", "2")}
CENTRES = f"""cen AS (SELECT scene_id,inst_no::BIGINT AS label,(min(y)+max(y))/2.0::DOUBLE AS cy,(min(x)+max(x))/2.0::DOUBLE AS cx FROM gt GROUP BY 1,2),
off AS (SELECT g.scene_id,g.pixel,c.cy+6*({NOISE['1']}-0.5) AS py,c.cx+6*({NOISE['2']}-0.5) AS px_ FROM gt g JOIN cen c ON c.scene_id=g.scene_id AND c.label=g.inst_no)"""


def offsets(spark, sf):
    gt = full(spark, sf)
    cen = gt.groupBy("scene_id", F.col("inst_no").cast("bigint").alias("label")).agg(((F.min("y") + F.max("y")) / 2).alias("cy"), ((F.min("x") + F.max("x")) / 2).alias("cx"))
    n = lambda a: 6 * (S.unit_hash(F.col("scene_id"), F.col("pixel"), a, 29) - 0.5)
    j = gt.select("scene_id", "pixel", F.col("inst_no").cast("bigint").alias("label")).join(cen, ["scene_id", "label"])
    return j.select("scene_id", "pixel", (F.col("cy") + n(1)).alias("py"), (F.col("cx") + n(2)).alias("px_")), cen


@query("base_centre_offset", FULL + ", " + CENTRES + " SELECT o.scene_id,o.pixel,arg_min(c.label,(pow(py-cy,2)+pow(px_-cx,2),c.label)) AS label FROM off o JOIN cen c ON c.scene_id=o.scene_id GROUP BY 1,2")
def base_centre_offset(spark, sf):
    return B.centre_offset(*offsets(spark, sf))


@query("base_hough", FULL + ", " + CENTRES + ", v AS (SELECT scene_id,pixel,(floor(py/2)*1000+floor(px_/2))::BIGINT AS cell FROM off) SELECT scene_id,pixel,CASE WHEN count(*) OVER (PARTITION BY scene_id,cell)>=3 THEN cell ELSE 0 END AS label FROM v")
def base_hough(spark, sf):
    return B.hough_assign(offsets(spark, sf)[0])


@query("base_box_mask", FULL + BOXES + " SELECT g.scene_id,g.pixel,arg_min(b.box,(b.h*b.w,b.box)) AS label FROM gt g JOIN boxes b ON b.scene_id=g.scene_id AND b.cls=g.cls AND g.y>=b.y0 AND g.y<b.y0+b.h AND g.x>=b.x0 AND g.x<b.x0+b.w GROUP BY 1,2")
def base_box_mask(spark, sf):
    return B.box_mask(full(spark, sf).select("scene_id", "y", "x", "pixel", "cls"), boxes(spark, sf))


@query("base_box_affinity")
def base_box_affinity(spark, sf):
    g = full(spark, sf)
    return B.box_affinity(edges_of(g, NOISY), g, boxes(spark, sf))


@query("base_window_pyramid")
def base_window_pyramid(spark, sf):
    def w5(g):
        e = G.grid_edges(g, G.WINDOW5, carry=("inst_no",)).withColumnsRenamed({"inst_no_u": "iu", "inst_no_v": "iv"})
        return e.withColumn("aff", S.neighbour_affinity(NOISY)).select("scene_id", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "aff")

    fine, coarse = tiny(spark, sf, 2), tiny(spark, sf, 4)
    return B.window_pyramid(coarse.select("scene_id", "y", "x", "pixel"), w5(coarse), fine.select("scene_id", "y", "x", "pixel"), w5(fine), 16, 16)


@query("base_seed_margin")
def base_seed_margin(spark, sf):
    px = planted(spark, sf, 8)
    return B.seed_margin(px.withColumn("seed", F.array_max("sem")))


@query("base_embedding_cluster")
def base_embedding_cluster(spark, sf):
    g = S.embedding(spark, sf, tiny(spark, sf), 8)
    return B.embedding_cluster(g)


ENERGY = S.hash_sql("scene_id", "pixel", "4", 37)


@query("base_watershed", f"""WITH RECURSIVE {TINY}, en AS (SELECT scene_id,y,x,pixel,{ENERGY} AS e FROM g), ptr AS (SELECT a.scene_id,a.pixel,arg_min(b.pixel,(b.e,b.pixel)) AS nxt FROM en a JOIN en b ON b.scene_id=a.scene_id AND abs(a.y-b.y)+abs(a.x-b.x)<=1 GROUP BY 1,2),
 walk AS (SELECT scene_id,pixel,nxt,0 AS k FROM ptr UNION ALL SELECT w.scene_id,w.pixel,p.nxt,k+1 FROM walk w JOIN ptr p ON p.scene_id=w.scene_id AND p.pixel=w.nxt WHERE p.nxt<>w.nxt) SELECT scene_id,pixel,arg_max(nxt,k) AS label FROM walk GROUP BY 1,2""")
def base_watershed(spark, sf):
    g = tiny(spark, sf)
    return B.watershed(g.withColumn("energy", S.unit_hash(F.col("scene_id"), F.col("pixel"), 4, 37)))


@query("ncut_value", f"WITH {TINY}, d AS (SELECT scene_id,iu AS s,aff,CASE WHEN iu<>iv THEN aff ELSE 0 END AS c FROM edges UNION ALL SELECT scene_id,iv,aff,CASE WHEN iu<>iv THEN aff ELSE 0 END FROM edges) SELECT scene_id,round(sum(r),6) AS ncut FROM (SELECT scene_id,s,sum(c)/sum(aff) AS r FROM d GROUP BY 1,2) GROUP BY 1")
def ncut_value(spark, sf):
    g = tiny(spark, sf)
    lab = g.select("scene_id", F.col("pixel").alias("node"), F.col("inst_no").alias("label"))
    return B.ncut_value(edges_of(g, NOISY).select("scene_id", "u", "v", "aff"), lab).withColumn("ncut", SIX("ncut"))


@query("base_ncut")
def base_ncut(spark, sf):
    e, _ = tiny_graph(spark, sf)
    return B.normalised_cut(e)


@query("base_spectral")
def base_spectral(spark, sf):
    e, _ = tiny_graph(spark, sf)
    return B.spectral(e)


@query("gibbs_energy", PX + ", un AS (SELECT scene_id,sum(-ln(greatest(sem[cls+1],1e-7))) AS u FROM px WHERE inst_no IS NOT NULL GROUP BY 1), pw AS (SELECT e.scene_id,sum(CASE WHEN a.cls<>b.cls THEN aff ELSE 0 END) AS p FROM edges e JOIN gt a ON a.scene_id=e.scene_id AND a.pixel=e.u JOIN gt b ON b.scene_id=e.scene_id AND b.pixel=e.v GROUP BY 1) SELECT un.scene_id,round(u+coalesce(p,0),5) AS energy FROM un LEFT JOIN pw ON pw.scene_id=un.scene_id")
def gibbs_energy(spark, sf):
    px = planted(spark, sf)
    return B.gibbs_energy(px, edges_of(full(spark, sf)).select("scene_id", "u", "v", "aff")).withColumn("energy", F.round("energy", 5))


@query("base_crf")
def base_crf(spark, sf):
    px = planted(spark, sf, 8)
    return B.mean_field(px, edges_of(full(spark, sf)).select("scene_id", "u", "v", "aff"))


MIRROR = "((({c})//8)*8+7-({c})%8)"


@query("flip_average", f"WITH {TINY}, f AS (SELECT scene_id,u,v,aff,{S.hash_sql('scene_id', 'u', 'v', 41)} AS aff_flip FROM edges) SELECT scene_id,u,v,round(avg(aff),6) AS aff FROM (SELECT scene_id,u,v,aff FROM f UNION ALL SELECT scene_id,least({MIRROR.format(c='u')},{MIRROR.format(c='v')}),greatest({MIRROR.format(c='u')},{MIRROR.format(c='v')}),aff_flip FROM f) GROUP BY 1,2,3")
def flip_average(spark, sf):
    e, _ = tiny_graph(spark, sf)
    return B.flip_average(e.withColumn("aff_flip", S.unit_hash(F.col("scene_id"), F.col("u"), F.col("v"), 41)), 8).withColumn("aff", SIX("aff"))
