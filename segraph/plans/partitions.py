"""Partitioners on the planted scenes and the derived graphs."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..fixtures import graphs as FG
from ..fixtures import scenes as S
from ..operators import adopt as AD
from ..operators import affinity as A
from ..operators import components as CC
from ..operators import contract as C
from ..operators import grid as G
from ..operators import multicut as M
from ..operators import positional as PO
from ..operators import pyramid as PY
from ..operators import rounds as R
from ..session import materialise
from .graphs import FULL, GEO, GROUP_SQL, SIX, edges_of, full, px_cte, pixels, seg_sql, seg_stats, tiny
from .registry import query

NOISY = 0.7
TINY = S.cte(stride=4, eps=NOISY)
NODES = "nodes AS (SELECT scene_id,pixel AS node FROM g)"


def tiny_graph(spark, sf, eps=NOISY):
    g = tiny(spark, sf)
    return edges_of(g, eps).select("scene_id", "u", "v", "aff"), g.select("scene_id", F.col("pixel").alias("node"))


def gc_sql(**kw):
    return C.recursive_sql("(SELECT scene_id,u,v,aff FROM edges)", "nodes", kw.pop("threshold", 0.5), prefix=TINY + ", " + NODES, **kw)


@query("gc_scenes_avg", gc_sql())
def gc_scenes_avg(spark, sf):
    e, n = tiny_graph(spark, sf)
    return C.contract(e, nodes=n)


@query("gc_rounds_avg", gc_sql())
def gc_rounds_avg(spark, sf):
    e, n = tiny_graph(spark, sf)
    return R.contract_rounds(e, n, rule="avg")


@query("gc_recursive_sql", gc_sql())
def gc_recursive_sql(spark, sf):
    e, n = tiny_graph(spark, sf)
    arrays = e.groupBy("scene_id").agg(F.collect_list(F.struct(F.col("aff").alias("s"), "u", "v")).alias("e"))
    nodes = n.groupBy("scene_id").agg(F.collect_list(F.struct("node", F.col("node").alias("label"))).alias("l"))
    empty = F.array().cast("array<struct<s:double,u:bigint,v:bigint>>")
    nodes.join(arrays, "scene_id", "left").select("scene_id", F.coalesce("e", empty).alias("e"), "l").createOrReplaceTempView("segraph_states")
    return spark.sql(C.recursive_arrays_sql("segraph_states", 0.5))


def _rule(rule):
    name = {"mean_edges": "mean"}.get(rule, rule)

    @query(f"gc_rule_{name}", gc_sql(rule=rule))
    def run(spark, sf):
        e, n = tiny_graph(spark, sf)
        return C.contract(e, rule=rule, nodes=n)


for _r in C.RULES:
    _rule(_r)


@query("gc_drop_literal", gc_sql(exclusive="drop"))
def gc_drop_literal(spark, sf):
    e, n = tiny_graph(spark, sf)
    return C.contract(e, exclusive="drop", nodes=n)


THRESHOLDS = (0.3, 0.5, 0.7)


def _sweep_sql():
    parts = [f"SELECT {t}::DOUBLE AS threshold, count(DISTINCT (scene_id,label)) AS segments FROM ({gc_sql(threshold=t)})" for t in THRESHOLDS]
    return " UNION ALL ".join(parts)


@query("gc_threshold_sweep", _sweep_sql())
def gc_threshold_sweep(spark, sf):
    e, n = tiny_graph(spark, sf)
    out = None
    for t in THRESHOLDS:
        one = C.contract(e, t, nodes=n).select("scene_id", "label").distinct().agg(F.count("*").alias("segments")).select(F.lit(t).alias("threshold"), "segments")
        out = one if out is None else out.union(one)
    return out


@query("gc_trace", f"SELECT scene_id,step,u,v,round(aff,6) AS aff FROM ({gc_sql(last='trace')})")
def gc_trace(spark, sf):
    e, n = tiny_graph(spark, sf)
    return C.contract(e, nodes=n, output="trace").withColumn("aff", SIX("aff"))


START = "init AS (SELECT scene_id,pixel AS node,min(pixel) OVER (PARTITION BY scene_id,inst_no,y//2,x//2) AS label FROM g), re AS (SELECT e.scene_id,least(a.label,b.label) AS u,greatest(a.label,b.label) AS v,avg(aff) AS aff FROM edges e JOIN init a ON a.scene_id=e.scene_id AND a.node=e.u JOIN init b ON b.scene_id=e.scene_id AND b.node=e.v WHERE a.label<>b.label GROUP BY 1,2,3), rn AS (SELECT DISTINCT scene_id,label AS node FROM init)"


@query("gc_from_partition", "WITH " + TINY + ", " + START + " SELECT i.scene_id,i.node,r.label FROM init i JOIN (" + C.recursive_sql("re", "rn", 0.5, prefix=TINY + ", " + START) + ") r ON r.scene_id=i.scene_id AND r.node=i.label")
def gc_from_partition(spark, sf):
    g = tiny(spark, sf)
    from pyspark.sql.window import Window

    w = Window.partitionBy("scene_id", "inst_no", F.floor(F.col("y") / 2), F.floor(F.col("x") / 2))
    init = g.select("scene_id", F.col("pixel").alias("node"), F.min("pixel").over(w).alias("label"))
    return C.contract(edges_of(g, NOISY).select("scene_id", "u", "v", "aff"), init=init)


SEGS = "segs AS (SELECT scene_id,inst_no::BIGINT AS label,y0,y1,x0,x1 FROM geo)"
PAIRS_SQL = "prs AS (SELECT scene_id,u::BIGINT AS u,v::BIGINT AS v,aff FROM (" + GROUP_SQL + "))"


def pgc_sql(beta):
    pre = seg_sql(8)[5:] + ", " + GEO + ", " + SEGS + ", " + PAIRS_SQL
    return PO.positional_recursive_sql("segs", "prs", beta, 0.5, pre)


def segs_and_pairs(spark, sf, k=8):
    st = seg_stats(spark, sf, k).withColumn("label", F.col("inst_no").cast("bigint"))
    p = G.segment_pairs(st, "label").select("scene_id", F.col("label_u").alias("u"), F.col("label_v").alias("v"), A.group_affinity("sem_u", "sem_v", "emb_u", "emb_v").alias("aff"))
    return st.select("scene_id", "label", "y0", "y1", "x0", "x1"), p


@query("pgc_scenes", pgc_sql(0.5))
def pgc_scenes(spark, sf):
    return PO.contract_positional(*segs_and_pairs(spark, sf), beta=0.5, threshold=0.5)


@query("gc_grouping", pgc_sql(0.0))
def gc_grouping(spark, sf):
    return PO.contract_positional(*segs_and_pairs(spark, sf), beta=0.0, threshold=0.5)


@query("pgc_rounds")
def pgc_rounds(spark, sf):
    """Rounds on damped affinities that are not updated as boxes grow:
    approximate; the share of segments labelled as the exact kernel does."""
    segs, pairs = segs_and_pairs(spark, sf)
    b = segs.select("scene_id", F.col("label").alias("n"), "y0", "y1", "x0", "x1")
    j = pairs.join(b.toDF("scene_id", "u", "y0u", "y1u", "x0u", "x1u"), ["scene_id", "u"]).join(b.toDF("scene_id", "v", "y0v", "y1v", "x0v", "x1v"), ["scene_id", "v"])
    damped = j.select("scene_id", "u", "v", (F.col("aff") * A.damping(A.box(suffix="u"), A.box(suffix="v"))).alias("aff"))
    approx = R.contract_rounds(damped, segs.select("scene_id", F.col("label").alias("node")), 0.5, "avg")
    exact = PO.contract_positional(segs, pairs, 0.5, 0.5)
    return approx.join(exact.select("scene_id", F.col("segment").alias("node"), F.col("label").alias("exact")), ["scene_id", "node"]).agg(F.count("*").alias("segments"), F.avg((F.col("label") == F.col("exact")).cast("double")).alias("agreement"))


# ---- adoption: every third pixel by hash is open

HOLE = S.hash_sql("scene_id", "pixel", "1", 17)
OPEN = f"lab AS (SELECT scene_id,pixel AS node,CASE WHEN {HOLE}<0.6 THEN NULL ELSE inst_no::BIGINT END AS label FROM g)"


def open_labels(spark, sf):
    g = tiny(spark, sf)
    hole = S.unit_hash(F.col("scene_id"), F.col("pixel"), F.lit(1), 17) < 0.6
    return g.select("scene_id", F.col("pixel").alias("node"), F.when(hole, F.lit(None)).otherwise(F.col("inst_no").cast("bigint")).alias("label")), edges_of(g, NOISY).select("scene_id", "u", "v", "aff")


@query("la_sync", AD.adopt_sql("lab", "edges", 0.5, 24, TINY + ", " + OPEN))
def la_sync(spark, sf):
    return AD.adopt(*open_labels(spark, sf))


@query("la_sync_rounds", AD.adopt_sql("lab", "edges", 0.5, 24, TINY + ", " + OPEN))
def la_sync_rounds(spark, sf):
    return AD.adopt(*open_labels(spark, sf), engine="rounds")


@query("la_seeded")
def la_seeded(spark, sf):
    return AD.adopt(*open_labels(spark, sf), order="seeded", seed=3)


# ---- pyramid steps

POOL = ", pool AS (SELECT scene_id,(y//2)::INT AS y,(x//2)::INT AS x,i-1 AS cls,avg(sem[i]) AS p FROM px,(SELECT unnest(range(1,10))::INT AS i) GROUP BY 1,2,3,4)"


@query("pool_level", "WITH " + S.cte() + ", " + px_cte(8) + POOL + " SELECT scene_id,y,x,cls,round(p,6) AS p FROM pool")
def pool_level(spark, sf):
    p = PY.pool2(pixels(spark, sf, 8))
    return p.select("scene_id", "y", "x", F.posexplode("sem").alias("cls", "p")).withColumn("p", SIX("p"))


@query("pool_edges", FULL + " SELECT scene_id,least(cu,cv) AS u,greatest(cu,cv) AS v,round(avg(aff),6) AS aff FROM (SELECT scene_id,aff,((u//32)//2*16+(u%32)//2)::BIGINT AS cu,((v//32)//2*16+(v%32)//2)::BIGINT AS cv FROM edges) WHERE cu<>cv GROUP BY 1,2,3")
def pool_edges(spark, sf):
    return PY.pool_edges(edges_of(full(spark, sf)).select("scene_id", "u", "v", "aff"), 32).withColumn("aff", SIX("aff"))


COARSE = "SELECT scene_id,(y//4)::INT AS y,(x//4)::INT AS x,min(inst_no)::BIGINT AS label FROM gt GROUP BY 1,2,3"


def coarse(spark, sf):
    return full(spark, sf).groupBy("scene_id", F.floor(F.col("y") / 4).cast("int").alias("y"), F.floor(F.col("x") / 4).cast("int").alias("x")).agg(F.min("inst_no").cast("bigint").alias("label"))


@query("upsample_labels", FULL + f" SELECT scene_id,(2*y+dy)::INT AS y,(2*x+dx)::INT AS x,label FROM ({COARSE}) CROSS JOIN (VALUES (0,0),(0,1),(1,0),(1,1)) o(dy,dx) WHERE 2*y+dy<15 AND 2*x+dx<13")
def upsample_labels(spark, sf):
    return PY.upsample2(coarse(spark, sf), 15, 13)


RECLAIM = FULL + f", c AS ({COARSE}), d AS (SELECT a.scene_id,a.y,a.x,a.label,bool_or(b.label IS DISTINCT FROM a.label) AS rim FROM (SELECT c.*,c.y+dy AS oy,c.x+dx AS ox FROM c CROSS JOIN (VALUES (-1,0),(1,0),(0,-1),(0,1)) o(dy,dx)) a LEFT JOIN c b ON b.scene_id=a.scene_id AND b.y=a.oy AND b.x=a.ox WHERE a.oy>=0 AND a.ox>=0 GROUP BY 1,2,3,4) SELECT scene_id,y,x,CASE WHEN NOT rim THEN label ELSE -1 END AS label FROM d"


@query("reclaim_rim", RECLAIM)
def reclaim_rim(spark, sf):
    return PY.reclaim_rim(coarse(spark, sf)).withColumn("label", F.coalesce("label", F.lit(-1)))


def _cascade(name, **kw):
    @query(name)
    def run(spark, sf):
        px = pixels(spark, sf, 8)
        return PY.partition_pyramid(px.select("scene_id", "pixel", "sem", "emb"), edges_of(full(spark, sf), NOISY).select("scene_id", "u", "v", "aff"), 32, 8, **kw)


_cascade("cfp_exact", finest="contract")
_cascade("cfp_adopt", finest="adopt")


@query("cfp_one_level", "SELECT scene_id,node-1 AS pixel,label FROM (" + C.recursive_sql("(SELECT scene_id,u+1 AS u,v+1 AS v,aff FROM edges)", "(SELECT scene_id,pixel+1 AS node FROM g)", 0.5, prefix=S.cte(stride=2, eps=NOISY)) + ")")
def cfp_one_level(spark, sf):
    """One level without grouping is plain contraction."""
    g = tiny(spark, sf, 2)
    cells = g.select("scene_id").distinct().withColumn("pixel", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(255).cast("long"))))
    px = S.semantic(cells.join(g, ["scene_id", "pixel"], "left")).select("scene_id", "pixel", "sem", F.array(F.lit(0.0)).alias("emb"))
    return PY.partition_pyramid(px, edges_of(g, NOISY).select("scene_id", "u", "v", "aff"), 16, 1, levels=1, beta="none")


# ---- components, exact optimum, costs

COMP = """, sym AS (SELECT scene_id,u,v FROM edges WHERE aff>0.5 UNION ALL SELECT scene_id,v,u FROM edges WHERE aff>0.5)"""


def comp_sql(prefix=TINY):
    return f"""WITH RECURSIVE {prefix}, {NODES}{COMP}, reach AS (SELECT scene_id,node,node AS seen FROM nodes UNION SELECT r.scene_id,r.node,s.v FROM reach r JOIN sym s ON s.scene_id=r.scene_id AND s.u=r.seen) SELECT scene_id,node,min(seen) AS label FROM reach GROUP BY 1,2"""


@query("base_components", comp_sql())
def base_components(spark, sf):
    e, n = tiny_graph(spark, sf)
    return CC.components(e, 0.5, n)


@query("components_rounds", comp_sql())
def components_rounds(spark, sf):
    e, n = tiny_graph(spark, sf)
    return CC.components(e, 0.5, n, "rounds")


@query("multicut_cost", "WITH " + TINY + " SELECT scene_id,round(sum(CASE WHEN iu<>iv THEN aff-0.5 ELSE 0 END),6) AS cost,sum((iu<>iv)::INT)::BIGINT AS cut FROM edges GROUP BY 1")
def multicut_cost(spark, sf):
    g = tiny(spark, sf)
    lab = g.select("scene_id", F.col("pixel").alias("node"), F.col("inst_no").cast("bigint").alias("label"))
    return M.multicut_cost(edges_of(g, NOISY).withColumn("c", A.to_cost("aff")), lab).withColumn("cost", SIX("cost"))


CUT = S.hash_sql("scene_id", "u", "v", 23)


@query("multicut_feasible", f"""WITH RECURSIVE {TINY}, {NODES}, cuts AS (SELECT scene_id,u,v,{CUT}<0.3 AS cut FROM edges), sym AS (SELECT scene_id,u,v FROM cuts WHERE NOT cut UNION ALL SELECT scene_id,v,u FROM cuts WHERE NOT cut),
 reach AS (SELECT scene_id,node,node AS seen FROM nodes UNION SELECT r.scene_id,r.node,s.v FROM reach r JOIN sym s ON s.scene_id=r.scene_id AND s.u=r.seen), l AS (SELECT scene_id,node,min(seen) AS label FROM reach GROUP BY 1,2)
 SELECT c.scene_id,bool_and(NOT cut OR a.label<>b.label) AS feasible,sum((cut AND a.label=b.label)::INT)::BIGINT AS violated FROM cuts c JOIN l a ON a.scene_id=c.scene_id AND a.node=c.u JOIN l b ON b.scene_id=c.scene_id AND b.node=c.v GROUP BY 1""")
def multicut_feasible(spark, sf):
    e, n = tiny_graph(spark, sf)
    cuts = e.withColumn("cut", S.unit_hash(F.col("scene_id"), F.col("u"), F.col("v"), 23) < 0.3)
    return M.is_multicut(cuts, n)


def small_sql():
    bell = """RECURSIVE {pre}, nn AS (SELECT scene_id,max(v) AS n FROM rnd GROUP BY 1),
 grow AS (SELECT [0] AS lab UNION ALL SELECT list_append(lab,c::INT) FROM grow, (SELECT range AS c FROM range(8)) WHERE len(lab)<7 AND c<=list_max(lab)+1)"""
    return "WITH " + bell.format(pre=FG.ORDER_SQL) + ", cost AS (SELECT r.scene_id,g.lab,sum(CASE WHEN g.lab[r.u]<>g.lab[r.v] THEN r.aff-0.5 ELSE 0 END) AS cost FROM rnd r JOIN nn ON nn.scene_id=r.scene_id JOIN grow g ON len(g.lab)=nn.n GROUP BY 1,2) SELECT scene_id,count(*) AS partitions,round(min(cost),6) AS best FROM cost GROUP BY 1"


@query("multicut_exact_tiny", small_sql())
def multicut_exact_tiny(spark, sf):
    return M.multicut_exact(FG.order_graphs(spark, sf)).withColumn("best", SIX("best"))


@query("greedy_gap")
def greedy_gap(spark, sf):
    return M.gap(FG.order_graphs(spark, sf))


@query("op_counts")
def op_counts(spark, sf):
    e, n = tiny_graph(spark, sf)
    return C.contract(e, nodes=n, output="counts")


# ---- hand graphs and other tables

ROGUE = 0.05


@query("w_rogue_edge", " UNION ALL ".join(f"SELECT '{r}' AS rule,scene_id,node,label FROM ({C.recursive_sql('(SELECT scene_id,u,v,aff FROM edges)', 'nodes', 0.5, r, prefix=S.cte(stride=4, eps=NOISY, rogue=ROGUE) + ', ' + NODES)})" for r in C.RULES))
def w_rogue_edge(spark, sf):
    """One edge in twenty of the thin scenes says the contrary: what each rule makes of that."""
    g = tiny(spark, sf)
    e = materialise(edges_of(g, NOISY, ROGUE).select("scene_id", "u", "v", "aff"), "rogue")
    n = materialise(g.select("scene_id", F.col("pixel").alias("node")), "rogue")
    out = None
    for r in C.RULES:
        one = C.contract(e, rule=r, nodes=n).select(F.lit(r).alias("rule"), "scene_id", "node", "label")
        out = one if out is None else out.union(one)
    return out


@query("event_runs", "WITH " + FG.EVENT_SQL + ", cut AS (SELECT e.user_id,e.event_id,e.ts,coalesce(x.aff>0.5,false) AS stay FROM events e LEFT JOIN event_edges x ON x.user_id=e.user_id AND x.v=e.event_id) SELECT user_id,event_id,sum((NOT stay)::INT) OVER (PARTITION BY user_id ORDER BY ts,event_id)::BIGINT AS run FROM cut")
def event_runs(spark, sf):
    """On a line, components of edges above the threshold are runs."""
    from pyspark.sql.window import Window

    from ..session import table

    e = table(spark, sf, "events").select("user_id", "event_id", "ts")
    x = FG.event_edges(spark, sf).select("user_id", F.col("v").alias("event_id"), (F.col("aff") > 0.5).alias("stay"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return e.join(x, ["user_id", "event_id"], "left").select("user_id", "event_id", F.sum((~F.coalesce("stay", F.lit(False))).cast("long")).over(w).alias("run"))


def max_sql(pre, edges, t):
    return f"""WITH RECURSIVE {pre}, k AS (SELECT u,v FROM {edges} WHERE aff>{t}), sym AS (SELECT u,v FROM k UNION ALL SELECT v,u FROM k), reach AS (SELECT DISTINCT u AS node,u AS seen FROM sym UNION SELECT r.node,s.v FROM reach r JOIN sym s ON s.u=r.seen) SELECT 0::BIGINT AS scene_id,node,min(seen) AS label FROM reach GROUP BY 2"""


def _max_parts(e, t):
    k = e.where(F.col("aff") > t)
    nodes = k.select("scene_id", F.col("u").alias("node")).union(k.select("scene_id", "v")).distinct()
    return CC.components(k.select("scene_id", "u", "v", "aff"), t, nodes, "rounds")


@query("docs_partition", max_sql(FG.DOC_SQL, "doc_edges", 0.5))
def docs_partition(spark, sf):
    """With the rule max, contraction gives the components above the threshold."""
    return _max_parts(FG.document_edges(spark, sf), 0.5)


@query("emb_partition", max_sql(FG.EMB_SQL, "emb_edges", 0.4))
def emb_partition(spark, sf):
    return _max_parts(FG.embedding_edges(spark, sf), 0.4)


@query("parts_partition", max_sql(FG.PART_SQL, "part_edges", 0.8))
def parts_partition(spark, sf):
    return _max_parts(FG.copurchase_edges(spark, sf), 0.8)


@query("nation_partition", C.recursive_sql("nation_edges", "nn", 0.5, prefix=FG.NATION_SQL + ", nn AS (SELECT DISTINCT 0::BIGINT AS scene_id,u AS node FROM nation_edges UNION SELECT 0::BIGINT,v FROM nation_edges)"))
def nation_partition(spark, sf):
    return C.contract(FG.nation_edges(spark, sf))


@query("base_superpixel_multicut", None)
def base_superpixel_multicut(spark, sf):
    e, n = tiny_graph(spark, sf)
    from ..operators.baselines import superpixel_multicut

    return superpixel_multicut(e, n, 0.7)


@query("base_flat_gc", gc_sql(threshold=0.5))
def base_flat_gc(spark, sf):
    return gc_scenes_avg(spark, sf)


@query("base_gc_grouping", pgc_sql(0.0))
def base_gc_grouping(spark, sf):
    return gc_grouping(spark, sf)
