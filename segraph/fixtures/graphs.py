"""Small and derived graphs over the given tables (see FIXTURES.md)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import materialise, table

# Hand-made graphs (graph, u, v, affinity).
HAND = [
    (1, 1, 2, 0.9), (1, 2, 3, 0.8), (1, 1, 3, 0.1), (1, 3, 4, 0.7),
    (2, 1, 2, 0.9), (2, 3, 4, 0.8), (2, 1, 3, 0.6), (2, 2, 3, 0.55), (2, 1, 4, 0.7),
    (3, 1, 2, 0.5),
    (4, 1, 2, 0.9), (4, 2, 3, 0.9), (4, 3, 4, 0.9), (4, 4, 5, 0.9),
]


def two_blocks() -> list[tuple[int, int, int, float]]:
    """Graph 5: a 4-wide, 4-high grid of two 2x4 blocks that touch with .1,
    one rogue contact edge with .97."""
    out = []
    for y in range(4):
        for x in range(4):
            n = 4 * y + x + 1
            if x < 3:
                out.append((5, n, n + 1, 0.95))
            if y < 3:
                out.append((5, n, n + 4, 0.95 if y != 1 else (0.97 if x == 0 else 0.1)))
    return out


def hand_graphs(spark) -> DataFrame:
    return spark.createDataFrame(HAND + two_blocks(), "scene_id bigint, u bigint, v bigint, aff double")


def hand_sql() -> str:
    return "hand AS (SELECT * FROM (VALUES " + ",".join(f"({g}::BIGINT,{u}::BIGINT,{v}::BIGINT,{a}::DOUBLE)" for g, u, v, a in HAND + two_blocks()) + ") t(scene_id,u,v,aff))"


def event_edges(spark, sf: str) -> DataFrame:
    """Consecutive events of a user: half-life decay in the gap, a quarter of it if the types differ."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, sf, "events").select("user_id", "event_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    e = e.withColumns({"u": F.lag("event_id").over(w), "pt": F.lag("event_type").over(w), "pts": F.lag("ts").over(w)}).where("u is not null")
    gap = F.expr("(unix_micros(ts) - unix_micros(pts)) / 1e6")
    aff = F.pow(F.lit(2.0), -gap / 3600 / 24) * F.when(F.col("pt") == F.col("event_type"), 1.0).otherwise(0.25)
    return e.select("user_id", "u", F.col("event_id").alias("v"), gap.alias("gap_s"), aff.alias("aff"))


EVENT_SQL = """ev AS (SELECT user_id,event_id,event_type,ts,lag(event_id) OVER w AS u,lag(event_type) OVER w AS pt,lag(ts) OVER w AS pts FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts,event_id)),
event_edges AS (SELECT user_id,u,event_id AS v,(epoch_us(ts)-epoch_us(pts))/1e6::DOUBLE AS gap_s,pow(2.0::DOUBLE,-((epoch_us(ts)-epoch_us(pts))/1e6::DOUBLE)/3600/24)*(CASE WHEN pt=event_type THEN 1.0::DOUBLE ELSE 0.25::DOUBLE END) AS aff FROM ev WHERE u IS NOT NULL)"""


def nearest(e: DataFrame, near: int, block: int = 8192) -> DataFrame:
    """q, vec_id, f: the ``near`` others of every vector by Gaussian affinity,
    ties by id; e has vec_id and e, an array of floats.  Vectors are dealt to
    blocks, and every pair of blocks is one group of 2 * block vectors at most
    on average; of equal vectors in a block only the near + 1 smallest ids can
    be somebody's nearest, so the others stand aside as neighbours there."""
    import numpy as np
    import pyarrow as pa

    from ..operators.affinity import LN2

    n = max(1, -(-e.count() // block))

    def one_way(q, qi, c, ci):
        kind, order = np.unique(c, axis=0, return_inverse=True)[1].ravel(), np.argsort(ci)
        order = order[np.argsort(kind[order], kind="stable")]
        start = np.flatnonzero(np.concatenate([[True], np.diff(kind[order]) != 0]))
        rank = np.arange(len(order)) - np.repeat(start, np.diff(np.append(start, len(order))))
        keep = order[rank <= near]
        c, ci = c[keep], ci[keep]
        cc, out = (c * c).sum(1), []
        for a in range(0, len(q), 256):
            x, xi = q[a : a + 256], qi[a : a + 256]
            d = (x * x).sum(1)[:, None] + cc - 2 * x @ c.T
            d[xi[:, None] == ci] = np.inf
            most = np.partition(d, near - 1, axis=1)[:, near - 1] if near < len(c) else np.full(len(x), np.inf)
            i, j = np.nonzero((d <= most[:, None] + 1e-9 * (1 + cc.max())) & (d < np.inf))
            exact = np.zeros(len(i))
            for t in range(c.shape[1]):  # term by term, as the column expression sums
                exact += (x[i, t] - c[j, t]) ** 2
            o = np.lexsort((ci[j], exact, i))
            i, j, exact = i[o], j[o], exact[o]
            first = np.searchsorted(i, np.arange(len(x)))
            o = np.arange(len(i)) - first[i] < near
            out.append((xi[i[o]], ci[j[o]], exact[o]))
        return out

    def work(t: pa.Table) -> pa.Table:
        pair = t.column("pair")[0].as_py()
        ids, blk = t.column("vec_id").to_numpy(), t.column("blk").to_numpy()
        col = t.column("e").combine_chunks()
        v = col.flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1).astype(np.float64)
        l, r = blk == pair // n, blk == pair % n
        got = []
        for x, y in [(l, r)] if pair // n == pair % n else [(l, r), (r, l)]:
            if x.any() and y.any():
                got += one_way(v[x], ids[x], v[y], ids[y])
        q, c, d = (np.concatenate(z) for z in zip(*got)) if got else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        return pa.table({"q": q, "vec_id": c, "d": d})

    b = e.withColumn("blk", F.pmod(F.xxhash64("vec_id"), F.lit(n)))
    o = b.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))))
    o = o.select((F.least("blk", "other") * n + F.greatest("blk", "other")).alias("pair"), "blk", "vec_id", "e")
    top = o.groupBy("pair").applyInArrow(work, "q bigint, vec_id bigint, d double").select("q", "vec_id", F.exp(-LN2 * F.col("d")).alias("f"))
    w = Window.partitionBy("q").orderBy(F.col("f").desc(), "vec_id")
    return top.withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= near).drop("rn")


def embedding_edges(spark, sf: str, k: int = 64, near: int = 10, block: int = 8192) -> DataFrame:
    """Each vector's nearest by Gaussian affinity, over the whole table."""
    e = table(spark, sf, "embeddings").where("vec_id is not null and embedding is not null").select(F.col("vec_id").cast("long").alias("vec_id"), F.slice("embedding", 1, k).alias("e"))
    top = nearest(e, near, block)
    return top.select(F.lit(0).cast("bigint").alias("scene_id"), F.least("q", "vec_id").alias("u"), F.greatest("q", "vec_id").alias("v"), F.col("f").alias("aff")).groupBy("scene_id", "u", "v").agg(F.max("aff").alias("aff"))


EMB_SQL = """e AS (SELECT vec_id,list_transform(list_slice(embedding,1,64),lambda t: t::DOUBLE) AS e FROM embeddings),
nb AS (SELECT q.vec_id AS q,a.vec_id,exp(-ln(2)*list_sum(list_transform(list_zip(a.e,q.e),lambda t: (t[1]-t[2])*(t[1]-t[2])))) AS f FROM e a JOIN e q ON a.vec_id<>q.vec_id),
emb_edges AS MATERIALIZED (SELECT 0::BIGINT AS scene_id,least(q,vec_id) AS u,greatest(q,vec_id) AS v,max(f) AS aff FROM (SELECT *,row_number() OVER (PARTITION BY q ORDER BY f DESC,vec_id) AS rn FROM nb) WHERE rn<=10 GROUP BY 2,3)"""


def document_edges(spark, sf: str, above: float = 0.5) -> DataFrame:
    """Documents whose distinct word 3-grams have more than ``above`` of their
    union in common, by 64-bit gram hashes; no gram is too frequent to count.
    Of documents with equal grams the smallest id stands for all and gets an edge
    to each.  Two others above the bound share a gram among each one's rarest
    n - ceil(above * n) + 1, so these make the candidates; all grams confirm."""
    d = table(spark, sf, "documents").select("doc_id", F.split(F.lower("text"), r"\s+").alias("w"))
    n = F.size("w")
    g = d.where(n >= 3).select("doc_id", F.array_sort(F.array_distinct(F.transform(F.sequence(F.lit(1), n - 2), lambda i: F.xxhash64(F.array_join(F.slice("w", i, 3), " "))))).alias("gs"))
    g = materialise(g, "doc-all").withColumns({"n": F.size("gs"), "same": F.sha2(F.array_join(F.col("gs").cast("array<string>"), ","), 256)})
    first = g.groupBy("same").agg(F.min("doc_id").alias("u"), F.first("n").alias("shared"))
    copies = g.select("same", F.col("doc_id").alias("v")).join(first, "same").where("u < v").select("u", "v", F.col("shared").cast("long").alias("shared"), F.lit(1.0).alias("aff")).distinct()
    one = materialise(g.join(first.select("same", F.col("u").alias("doc_id")), ["same", "doc_id"], "left_semi").dropDuplicates(["doc_id", "same"]).select("doc_id", "n", "gs"), "doc-grams")
    flat = one.select("doc_id", "n", F.explode("gs").alias("g"))
    often = flat.groupBy("g").agg(F.count("*").alias("c"))
    w = Window.partitionBy("doc_id").orderBy("c", "g")
    rare = flat.join(often, "g").withColumn("rn", F.row_number().over(w)).where((F.col("rn") <= F.col("n") - F.ceil(above * F.col("n")) + 1) & (F.col("c") > 1)).select("g", "doc_id", "n")
    pair = rare.toDF("g", "u", "nu").join(rare.toDF("g", "v", "nv"), "g").where((F.col("u") < F.col("v")) & (F.least("nu", "nv") > above * F.greatest("nu", "nv"))).select("u", "v").distinct()
    j = pair.join(one.toDF("u", "nu", "gu"), "u").join(one.toDF("v", "nv", "gv"), "v").withColumn("shared", F.size(F.array_intersect("gu", "gv")).cast("long"))
    near = j.select("u", "v", "shared", (F.col("shared") / (F.col("nu") + F.col("nv") - F.col("shared"))).alias("aff")).where(F.col("aff") > above)
    return materialise(copies.union(near).select(F.lit(0).cast("bigint").alias("scene_id"), "u", "v", "shared", "aff"), "doc-edges")


DOC_SQL = """dw AS (SELECT doc_id,regexp_split_to_array(lower(text),'\\s+') AS w FROM documents),
dg AS MATERIALIZED (SELECT DISTINCT doc_id,w[i]||' '||w[i+1]||' '||w[i+2] AS g FROM (SELECT doc_id,w,unnest(range(1,len(w)-1)) AS i FROM dw WHERE len(w)>=3)),
dn AS MATERIALIZED (SELECT doc_id,count(*) AS n,md5(string_agg(g,chr(10) ORDER BY g)) AS same FROM dg GROUP BY 1),
rep AS MATERIALIZED (SELECT same,min(doc_id) AS u,any_value(n) AS n FROM dn GROUP BY 1),
og AS MATERIALIZED (SELECT dg.doc_id,dg.g,rep.n FROM dg JOIN rep ON rep.u=dg.doc_id),
oc AS (SELECT g,count(*) AS c FROM og GROUP BY 1),
rare AS MATERIALIZED (SELECT doc_id,g,n FROM (SELECT og.*,c,row_number() OVER (PARTITION BY doc_id ORDER BY c,og.g) AS rn FROM og JOIN oc ON oc.g=og.g) WHERE rn<=n-ceil(0.5*n)+1 AND c>1),
cand AS MATERIALIZED (SELECT DISTINCT a.doc_id AS u,b.doc_id AS v FROM rare a JOIN rare b ON a.g=b.g AND a.doc_id<b.doc_id AND least(a.n,b.n)>0.5*greatest(a.n,b.n)),
ds AS (SELECT c.u,c.v,x.n AS nu,y.n AS nv,count(*) AS shared FROM cand c JOIN og x ON x.doc_id=c.u JOIN og y ON y.doc_id=c.v AND y.g=x.g GROUP BY ALL),
doc_edges AS MATERIALIZED (SELECT 0::BIGINT AS scene_id,u,v,shared,shared/(nu+nv-shared)::DOUBLE AS aff FROM ds UNION ALL SELECT 0::BIGINT,rep.u,dn.doc_id,dn.n,1.0::DOUBLE FROM dn JOIN rep ON rep.same=dn.same AND rep.u<dn.doc_id)"""


def copurchase_edges(spark, sf: str) -> DataFrame:
    """Parts bought in one order; affinity 1 - 2^-(orders shared)."""
    p = table(spark, sf, "lineitem").select("l_orderkey", "l_partkey").distinct()
    k = p.toDF("o", "u").join(p.toDF("o", "v"), "o").where("u < v").groupBy("u", "v").agg(F.count("*").alias("k"))
    return k.select(F.lit(0).cast("bigint").alias("scene_id"), "u", "v", "k", (1 - F.pow(F.lit(2.0), -F.col("k"))).alias("aff"))


PART_SQL = """lp AS (SELECT DISTINCT l_orderkey,l_partkey FROM lineitem),
part_edges AS (SELECT 0::BIGINT AS scene_id,a.l_partkey AS u,b.l_partkey AS v,count(*) AS k,1-pow(2.0::DOUBLE,-count(*)) AS aff FROM lp a JOIN lp b ON a.l_orderkey=b.l_orderkey AND a.l_partkey<b.l_partkey GROUP BY 2,3)"""


def nation_edges(spark, sf: str) -> DataFrame:
    """Revenue between two nations in either direction over the largest such."""
    o = table(spark, sf, "orders").join(table(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_nationkey")
    li = table(spark, sf, "lineitem").join(table(spark, sf, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).select("l_orderkey", "s_nationkey", F.round(F.col("l_extendedprice") * 100).cast("long").alias("cents"))
    r = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).where("c_nationkey <> s_nationkey").groupBy(F.least("c_nationkey", "s_nationkey").cast("bigint").alias("u"), F.greatest("c_nationkey", "s_nationkey").cast("bigint").alias("v")).agg(F.sum("cents").alias("r"))
    top = r.agg(F.max("r").alias("top"))
    return r.join(F.broadcast(top)).select(F.lit(0).cast("bigint").alias("scene_id"), "u", "v", (F.col("r") / F.col("top")).alias("aff"))


NATION_SQL = """nr AS (SELECT least(c_nationkey,s_nationkey)::BIGINT AS u,greatest(c_nationkey,s_nationkey)::BIGINT AS v,sum(round(l_extendedprice*100)::BIGINT)::BIGINT AS r FROM lineitem JOIN orders ON l_orderkey=o_orderkey JOIN customer ON o_custkey=c_custkey JOIN supplier ON l_suppkey=s_suppkey WHERE c_nationkey<>s_nationkey GROUP BY 1,2),
nation_edges AS (SELECT 0::BIGINT AS scene_id,u,v,r/(SELECT max(r) FROM nr)::DOUBLE AS aff FROM nr)"""


def order_graphs(spark, sf: str, every: int = 50) -> DataFrame:
    """Complete graphs over the lines of orders with 4 to 7 lines; lines are alike as their quantities are."""
    li = table(spark, sf, "lineitem").where(F.col("l_orderkey") % every == 0)
    w = Window.partitionBy("l_orderkey").orderBy("l_extendedprice", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity")
    n = F.count("*").over(Window.partitionBy("l_orderkey"))
    k = li.select(F.col("l_orderkey").alias("scene_id"), F.row_number().over(w).cast("long").alias("k"), n.alias("n"), F.col("l_quantity").alias("q")).where("n between 4 and 7").drop("n")
    p = k.toDF("scene_id", "u", "qu").join(k.toDF("scene_id", "v", "qv"), "scene_id").where("u < v")
    return p.select("scene_id", "u", "v", (1 - F.abs(F.col("qu") - F.col("qv")) / 50).alias("aff"))


ORDER_SQL = """ol AS (SELECT l_orderkey AS scene_id,row_number() OVER (PARTITION BY l_orderkey ORDER BY l_extendedprice,l_partkey,l_suppkey,l_linenumber,l_quantity) AS k,count(*) OVER (PARTITION BY l_orderkey) AS n,l_quantity AS q FROM lineitem WHERE l_orderkey%50=0),
rnd AS MATERIALIZED (SELECT a.scene_id,a.k AS u,b.k AS v,1-abs(a.q-b.q)/50 AS aff FROM ol a JOIN ol b ON a.scene_id=b.scene_id AND a.k<b.k WHERE a.n BETWEEN 4 AND 7)"""
