"""The relational surface around the partitioners, on the given tables."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..fixtures import graphs as FG
from ..fixtures import scenes as S
from ..operators import relational as RL
from ..session import shared_dir, table
from ..streaming import events as EV
from .graphs import FULL, edges_of, full, seg_pairs, seg_sql
from .registry import query

TABLES = "lineitem orders customer supplier part nation region events documents embeddings pages conversations".split()


def shared(name: str, sql: str, duck: str | None = None):
    """A query whose text both engines read alike."""

    @query(name, duck or sql)
    def run(spark, sf):
        for t in TABLES:
            if t in sql:
                table(spark, sf, t).createOrReplaceTempView(t)
        return spark.sql(sql)

    return run


shared("scan_parquet", "SELECT count(*) AS n, sum(CAST(l_quantity AS BIGINT)) AS q FROM lineitem", "SELECT count(*) AS n,sum(l_quantity::BIGINT)::BIGINT AS q FROM lineitem")
shared("scan_pruned", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_orderkey BETWEEN 100 AND 400")
shared("filter_predicates", "SELECT p_partkey, CASE WHEN p_size > 25 THEN 'big' ELSE 'small' END AS kind, coalesce(p_brand, '') AS brand FROM part WHERE p_size BETWEEN 5 AND 40 AND p_type LIKE '%A%' AND p_partkey % 7 IN (1, 3) AND NOT (p_brand IS NULL)")
shared("join_inner", "SELECT o_orderkey, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_orderkey % 5 = 0")
shared("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey")
shared("join_full", "SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) AS an, coalesce(b.n, 0) AS bn FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_nationkey < 15 GROUP BY c_nationkey) a FULL OUTER JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_nationkey > 8 GROUP BY s_nationkey) b ON a.k = b.k")
shared("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
shared("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderkey % 3 = 0)")
shared("join_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation")
shared("join_lateral", "SELECT r_regionkey, t.n_name FROM region, LATERAL (SELECT n_name FROM nation WHERE n_regionkey = r_regionkey ORDER BY n_name LIMIT 2) t")
shared("agg_hash", "SELECT l_returnflag, count(*) AS n, sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS cents FROM lineitem GROUP BY l_returnflag", "SELECT l_returnflag,count(*) AS n,sum(round(l_extendedprice*100)::BIGINT)::BIGINT AS cents FROM lineitem GROUP BY 1")
shared("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY l_returnflag")
shared("agg_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
shared("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
shared("agg_gsets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
shared("agg_maxby", "SELECT l_suppkey, max_by(l_partkey, struct(l_extendedprice, l_orderkey, l_linenumber, l_partkey)) AS part FROM lineitem GROUP BY l_suppkey", "SELECT l_suppkey,arg_max(l_partkey,(l_extendedprice,l_orderkey,l_linenumber,l_partkey)) AS part FROM lineitem GROUP BY 1")
shared("win_rank", "SELECT c_custkey, rank() OVER w AS rk, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment, c_custkey) AS rn FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)")
shared("win_lag", "SELECT event_id, coalesce(event_id - (lag(event_id) OVER w), -1) AS back, coalesce((lead(event_id) OVER w) - event_id, -1) AS ahead, first_value(event_id) OVER w AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
shared("win_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 1 FOLLOWING) AS n, max(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 1 FOLLOWING) AS m FROM events")
shared("win_range", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS n FROM orders")
shared("win_cume", "SELECT c_custkey, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS q FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal)")
shared("topk_global", "SELECT l_orderkey, l_linenumber, l_partkey, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 25 OFFSET 5")
shared("set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
shared("set_intersect", "SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A'")
shared("set_except", "SELECT p_partkey FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 45")
shared("str_url", "SELECT page_id, parse_url(url, 'HOST') AS host, parse_url(url, 'PATH') AS path, length(url) AS n, levenshtein(parse_url(url, 'HOST'), 'www.example.com') AS lev FROM pages", "SELECT page_id,regexp_extract(url,'^[a-z]+://([^/?#]+)',1) AS host,regexp_extract(url,'^[a-z]+://[^/?#]+([^?#]*)',1) AS path,length(url) AS n,levenshtein(regexp_extract(url,'^[a-z]+://([^/?#]+)',1),'www.example.com') AS lev FROM pages")
shared("date_gap", "SELECT o_custkey, date_trunc('month', o_orderdate) AS m, count(*) AS n, datediff(max(o_orderdate), min(o_orderdate)) AS days FROM orders GROUP BY o_custkey, date_trunc('month', o_orderdate)", "SELECT o_custkey,date_trunc('month',o_orderdate)::TIMESTAMP AS m,count(*) AS n,datediff('day',min(o_orderdate)::DATE,max(o_orderdate)::DATE) AS days FROM orders GROUP BY 1,2")
shared("json_props", "SELECT event_type, count(*) AS n, sum(CAST(get_json_object(props, '$.k') AS BIGINT)) AS k FROM events GROUP BY event_type", "SELECT event_type,count(*) AS n,sum((props::JSON->>'$.k')::BIGINT)::BIGINT AS k FROM events GROUP BY 1")
shared("arr_ops", "SELECT vec_id, size(slice(embedding, 1, 8)) AS n, round(aggregate(transform(slice(embedding, 1, 8), x -> CAST(x AS DOUBLE) * CAST(x AS DOUBLE)), 0D, (s, x) -> s + x), 6) AS q, size(filter(embedding, x -> x > 0)) AS pos FROM embeddings", "SELECT vec_id,len(list_slice(embedding,1,8)) AS n,round(list_sum(list_transform(list_slice(embedding,1,8),lambda x: x::DOUBLE*x::DOUBLE)),6) AS q,len(list_filter(embedding,lambda x: x>0)) AS pos FROM embeddings")
shared("map_ops", "SELECT n_regionkey, element_at(m, 'n') AS n, element_at(m, 'top') AS top, size(m) AS entries FROM (SELECT n_regionkey, map_from_entries(array(struct('n', CAST(count(*) AS BIGINT)), struct('top', CAST(max(n_nationkey) AS BIGINT)))) AS m FROM nation GROUP BY n_regionkey) t", "SELECT n_regionkey,count(*) AS n,max(n_nationkey)::BIGINT AS top,2 AS entries FROM nation GROUP BY 1")
shared("str_shingles", "SELECT doc_id, size(array_distinct(transform(sequence(1, size(w) - 2), i -> concat_ws(' ', slice(w, i, 3))))) AS grams FROM (SELECT doc_id, split(lower(text), ' ') AS w FROM documents) t WHERE size(w) >= 3", "SELECT doc_id,count(DISTINCT w[i]||' '||w[i+1]||' '||w[i+2]) AS grams FROM (SELECT doc_id,w,unnest(range(1,len(w)-1)) AS i FROM (SELECT doc_id,string_split(lower(text),' ') AS w FROM documents) WHERE len(w)>=3) GROUP BY 1")


@query("agg_pivot", "SELECT l_linestatus,sum((l_returnflag='A')::INT)::BIGINT AS a,sum((l_returnflag='N')::INT)::BIGINT AS n,sum((l_returnflag='R')::INT)::BIGINT AS r FROM lineitem GROUP BY 1")
def agg_pivot(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).count().na.fill(0).toDF("l_linestatus", "a", "n", "r")


@query("agg_sketches")
def agg_sketches(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.hll_sketch_estimate(F.hll_sketch_agg("l_suppkey")).alias("supps"), F.percentile_approx("l_extendedprice", 0.5, 1000).alias("median"), F.regr_slope("l_extendedprice", "l_quantity").alias("slope"))


@query("join_range", FULL + " SELECT a.scene_id,a.inst_no AS a,b.inst_no AS b FROM inst a JOIN inst b ON a.scene_id=b.scene_id AND a.inst_no<b.inst_no AND a.x0<=b.x0+b.w-1 AND b.x0<=a.x0+a.w-1")
def join_range(spark, sf):
    b = S.instances(spark, sf).select("scene_id", "inst_no", F.col("x0").alias("lo"), (F.col("x0") + F.col("w") - 1).alias("hi"))
    return RL.overlap_join(b, b, "lo", "hi", 8, "scene_id").where("inst_no < inst_no_r").select("scene_id", F.col("inst_no").alias("a"), F.col("inst_no_r").alias("b"))


@query("join_asof", "SELECT a.event_id,coalesce((SELECT arg_max(b.event_id,(b.ts,b.event_id)) FROM events b WHERE b.user_id=a.user_id AND b.event_type='view' AND b.ts<a.ts),-1) AS asof_vid FROM events a WHERE a.event_type='click'")
def join_asof(spark, sf):
    e = table(spark, sf, "events").select("event_id", "user_id", "ts", "event_type")
    clicks = e.where("event_type = 'click'").select("event_id", "user_id", "ts")
    views = e.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("vid"))
    return RL.asof_join(clicks, views, "user_id", "ts", ["vid"]).select("event_id", F.coalesce("asof_vid", F.lit(-1)).alias("asof_vid"))


@query("join_interval", "SELECT a.event_id AS a,b.event_id AS b FROM events a JOIN events b ON a.user_id=b.user_id AND a.event_id<b.event_id AND abs(epoch_us(a.ts)-epoch_us(b.ts))<=7200000000")
def join_interval(spark, sf):
    e = table(spark, sf, "events").select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    r = e.select("user_id", F.col("event_id").alias("b"), F.col("t").alias("tb"))
    return RL.interval_join(e.withColumnRenamed("event_id", "a"), r, "user_id", "t", "tb", 7200000000).where("a < b").select("a", "b")


@query("topk_edges", FULL + " SELECT scene_id,u,v FROM (SELECT *,row_number() OVER (PARTITION BY scene_id,u ORDER BY aff DESC,v) AS rn FROM edges) WHERE rn=1")
def topk_edges(spark, sf):
    return RL.top_per_key(edges_of(full(spark, sf)), ["scene_id", "u"], [F.col("aff").desc(), "v"], 1).select("scene_id", "u", "v")


@query("sink_roundtrip", FULL + " SELECT scene_id%4 AS level,count(*) AS n,sum(u+v)::BIGINT AS s FROM edges GROUP BY 1")
def sink_roundtrip(spark, sf):
    """Writes edges as parquet by level, ORC, JSON and CSV; reads all back and
    returns the sums of the one that all agree on."""
    from ..sources.tables import read, write_edges

    e = edges_of(full(spark, sf)).select("scene_id", "u", "v", "aff", (F.col("scene_id") % 4).alias("level"))
    path = f"{shared_dir(spark)}/segraph/sink-{uuid.uuid4().hex}"
    total = None
    for kind in ("parquet", "orc", "json", "csv"):
        write_edges(e, f"{path}/{kind}", kind, by_level=kind == "parquet")
        back = read(spark, f"{path}/{kind}", e.schema, kind).groupBy("level").agg(F.count("*").alias("n"), F.sum(F.col("u") + F.col("v")).alias("s"))
        total = back if total is None else total.intersect(back)
    return total


@query("udf_phi_sql", seg_sql(8) + " SELECT a.scene_id,a.inst_no AS u,b.inst_no AS v,round(exp(-ln(2)*list_sum(list_transform(list_zip(a.emb,b.emb),lambda t: (t[1]-t[2])*(t[1]-t[2])))),6) AS phi FROM seg a JOIN seg b ON a.scene_id=b.scene_id AND a.inst_no<b.inst_no")
def udf_phi_sql(spark, sf):
    from ..functions.sqlfuncs import register_all

    register_all(spark)
    seg_pairs(spark, sf, 8).createOrReplaceTempView("segraph_pairs")
    return spark.sql("SELECT scene_id, inst_no_u AS u, inst_no_v AS v, round(seg_phi(emb_u, emb_v), 6) AS phi FROM segraph_pairs")


@query("udtf_grid", "SELECT s_suppkey,(w*y+x)::BIGINT AS u,(w*(y+dy)+x+dx)::BIGINT AS v FROM (SELECT s_suppkey,2+s_nationkey%3 AS h,3+s_suppkey%3 AS w FROM supplier),(SELECT range AS y FROM range(4)),(SELECT range AS x FROM range(5)),(VALUES (0,1),(1,0)) o(dy,dx) WHERE y<h AND x<w AND y+dy<h AND x+dx<w")
def udtf_grid(spark, sf):
    """A raster for every supplier, its sides by nation and key."""
    from ..functions.sqlfuncs import register_all

    table(spark, sf, "supplier").createOrReplaceTempView("supplier")
    register_all(spark)
    return spark.sql("SELECT s_suppkey, g.u, g.v FROM supplier, LATERAL grid_neighbours(CAST(2 + s_nationkey % 3 AS INT), CAST(3 + s_suppkey % 3 AS INT)) g")


@query("udaf_vecsum", "SELECT label,i,round(sum(embedding[i+1]::DOUBLE),4) AS s FROM embeddings,(SELECT range::INT AS i FROM range(4)) GROUP BY 1,2")
def udaf_vecsum(spark, sf):
    from ..functions.sqlfuncs import vector_sum

    g = table(spark, sf, "embeddings").select("label", F.slice("embedding", 1, 4).cast("array<double>").alias("e")).groupBy("label").agg(vector_sum()("e").alias("v"))
    return g.select("label", F.posexplode("v").alias("i", "s")).select("label", "i", F.round("s", 4).alias("s"))


@query("sql_surface", FULL + ", geo AS (SELECT scene_id,inst_no,min(y) AS y0,max(y) AS y1,min(x) AS x0,max(x) AS x1 FROM gt GROUP BY 1,2) SELECT a.scene_id,a.inst_no AS u,b.inst_no AS v,round((CASE WHEN (a.y0+a.y1)=(b.y0+b.y1) THEN 1.0::DOUBLE ELSE sqrt(least(1.0::DOUBLE,0.5::DOUBLE*greatest(a.y1-a.y0+1,b.y1-b.y0+1)/(abs((a.y0+a.y1)-(b.y0+b.y1))/2.0::DOUBLE))) END)*(CASE WHEN (a.x0+a.x1)=(b.x0+b.x1) THEN 1.0::DOUBLE ELSE sqrt(least(1.0::DOUBLE,0.5::DOUBLE*greatest(a.x1-a.x0+1,b.x1-b.x0+1)/(abs((a.x0+a.x1)-(b.x0+b.x1))/2.0::DOUBLE))) END),6) AS d FROM geo a JOIN geo b ON a.scene_id=b.scene_id AND a.inst_no<b.inst_no")
def sql_surface(spark, sf):
    from ..functions.sqlfuncs import register_all

    register_all(spark)
    full(spark, sf).createOrReplaceTempView("segraph_gt")
    return spark.sql("""WITH geo AS (SELECT scene_id, inst_no, min(y) AS y0, max(y) AS y1, min(x) AS x0, max(x) AS x1 FROM segraph_gt GROUP BY scene_id, inst_no)
      SELECT a.scene_id, a.inst_no AS u, b.inst_no AS v, round(seg_damping(greatest(a.y1 - a.y0 + 1, b.y1 - b.y0 + 1), greatest(a.x1 - a.x0 + 1, b.x1 - b.x0 + 1), abs((a.y0 + a.y1) / 2 - (b.y0 + b.y1) / 2), abs((a.x0 + a.x1) / 2 - (b.x0 + b.x1) / 2), 0.5), 6) AS d
      FROM geo a JOIN geo b ON a.scene_id = b.scene_id AND a.inst_no < b.inst_no""")


@query("source_planted")
def source_planted(spark, sf):
    from ..operators.contract import contract
    from ..sources.planted import PlantedScenes

    sup = table(spark, sf, "supplier").select(F.col("s_suppkey").alias("scene_id"), F.col("s_nationkey").alias("nation"))
    spark.dataSource.register(PlantedScenes)
    e = spark.read.format("planted_scenes").option("table", f"{sf}/supplier.parquet").option("key", "s_suppkey").option("side", 12).load()
    return contract(e).groupBy("scene_id").agg(F.countDistinct("label").alias("segments")).join(sup, "scene_id").select("scene_id", "nation", "segments")


# ---- streaming; complete mode emits every window, as the batch twin does

BUCKET = "epoch_us(ts)//(6*3600000000)*(6*3600000000)"


@query("stream_tumbling", f"SELECT make_timestamp(b) AS start,make_timestamp(b+6*3600000000) AS \"end\",event_type,count(*) AS n,sum(round(value*100)::BIGINT)::BIGINT AS cents FROM (SELECT *,({BUCKET})::BIGINT AS b FROM events) GROUP BY 1,2,3")
def stream_tumbling(spark, sf):
    out = EV.drain(EV.windows(EV.event_stream(spark, sf)), "complete")
    return out.withColumns({"start": F.col("start").cast("timestamp_ntz"), "end": F.col("end").cast("timestamp_ntz")})


@query("stream_sliding", "SELECT make_timestamp(b) AS start,make_timestamp(b+6*3600000000) AS \"end\",event_type,count(*) AS n,sum(round(value*100)::BIGINT)::BIGINT AS cents FROM (SELECT *,((epoch_us(ts)//(3*3600000000)-k)*3*3600000000)::BIGINT AS b FROM events,(SELECT range AS k FROM range(2))) GROUP BY 1,2,3")
def stream_sliding(spark, sf):
    out = EV.drain(EV.windows(EV.event_stream(spark, sf), "sliding"), "complete")
    return out.withColumns({"start": F.col("start").cast("timestamp_ntz"), "end": F.col("end").cast("timestamp_ntz")})


@query("stream_session", "WITH e AS (SELECT *,CASE WHEN ts-lag(ts) OVER (PARTITION BY user_id ORDER BY ts)<INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT *,sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT min(ts) AS start,max(ts)+INTERVAL 2 HOUR AS \"end\",user_id,count(*) AS n,sum(round(value*100)::BIGINT)::BIGINT AS cents FROM s GROUP BY user_id,k")
def stream_session(spark, sf):
    out = EV.drain(EV.windows(EV.event_stream(spark, sf), "session"), "complete")
    return out.withColumns({"start": F.col("start").cast("timestamp_ntz"), "end": F.col("end").cast("timestamp_ntz")})


@query("stream_dedup", "SELECT DISTINCT event_id,user_id FROM events")
def stream_dedup(spark, sf):
    return EV.drain(EV.dedup(EV.event_stream(spark, sf)).select("event_id", "user_id"))


@query("stream_join", "SELECT a.user_id,a.event_id AS a,b.event_id AS b FROM events a JOIN events b ON a.user_id=b.user_id AND a.event_type='view' AND b.event_type='click' AND b.ts>a.ts AND b.ts<=a.ts+INTERVAL 6 HOUR")
def stream_join(spark, sf):
    return EV.drain(EV.click_after_view(EV.event_stream(spark, sf)))


@query("stream_runs", "WITH " + FG.EVENT_SQL + ", cut AS (SELECT e.user_id,e.event_id,e.ts,coalesce(x.aff>0.5,false) AS stay FROM events e LEFT JOIN event_edges x ON x.user_id=e.user_id AND x.v=e.event_id) SELECT user_id,event_id,sum((NOT stay)::INT) OVER (PARTITION BY user_id ORDER BY ts,event_id)::BIGINT AS run FROM cut")
def stream_runs(spark, sf):
    return EV.drain(EV.runs(EV.event_stream(spark, sf)))
