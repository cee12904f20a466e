"""Plans and queries that must hold at sizes the tests don't have."""

import pytest

from segraph.plans import baselines, graphs, measures, partitions, surface  # noqa: F401
from segraph.plans.registry import QUERIES


def broadcast_explosions(df) -> list[str]:
    """Lines of the plan that ran where rows are exploded and then broadcast, with no shuffle between
    that would tell Spark their size."""
    df.collect()
    bad, under = [], None
    for line in df._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0].split("\n"):
        at = len(line) - len(line.lstrip(" :+-*(0123456789)"))
        if under is not None and (at <= under or "ShuffleQueryStage" in line):
            under = None
        if "BroadcastExchange" in line:
            under = at
        elif under is not None and "Generate explode" in line:
            bad.append(line.strip())
    return bad


@pytest.mark.parametrize("name", ["group_affinity", "l2_pairs", "mean_embedding", "loss_pull", "segment_class", "base_position_sensitive", "gibbs_energy"])
def test_no_broadcast_of_exploded_rows(name, spark, sf):
    assert not broadcast_explosions(QUERIES[name](spark, sf))


def test_planted_are_the_owned_pixels(spark, sf):
    cols = ["scene_id", "y", "x", "pixel", "inst_no", "cls", "depth", "sem", "emb"]
    a = graphs.pixels(spark, sf, 8).where("inst_no is not null").select(cols)
    b = graphs.planted(spark, sf, 8).select(cols)
    assert a.exceptAll(b).count() == b.exceptAll(a).count() == 0 < b.count()


def test_large_tables_are_not_broadcast(spark, sf):
    a = measures.truth(spark, sf)
    j = a.join(a.where("cls > 1").select("scene_id", "pixel"), ["scene_id", "pixel"])
    assert "Broadcast" not in j._jdf.queryExecution().executedPlan().toString()


def test_parts_are_not_broadcast(spark, sf):
    """Two columns of a million parts look like a few MB in files, and are 134 MB in the driver's memory."""
    from segraph.fixtures import scenes

    assert "Broadcast" not in scenes.instances(spark, sf)._jdf.queryExecution().executedPlan().toString()


def test_sizes_in_one_pass_equal_one_by_one(spark, sf):
    from pyspark.sql import functions as F

    from segraph.operators.metrics import average_precision

    p, t = measures.pred_truth(spark, sf)
    n = t.groupBy("scene_id", "label").agg(F.count("*").alias("n"))
    got = average_precision(p, t, bins={b: F.col("n").between(lo, hi - 1) for b, lo, hi in measures.SIZES}).collect()
    for b, lo, hi in measures.SIZES:
        sized = t.join(n, ["scene_id", "label"]).withColumn("depth", F.when(F.col("n").between(lo, hi - 1), 0.0).otherwise(1.0)).drop("n")
        want = {(r["cls"], r["tau"]): round(r["value"], 9) for r in average_precision(p, sized, depth_max=0.5).collect()}
        assert {(r["cls"], r["tau"]): round(r["value"], 9) for r in got if r["bin"] == b} == want
    assert len(got) > 10


def test_average_precision_is_not_quadratic(spark):
    """A frame that runs to the last row from each of n rows visits n * n / 2."""
    import time

    from pyspark.sql import functions as F

    from segraph.operators.metrics import average_precision

    n = 60_000
    gt = spark.range(n).select(F.col("id").alias("scene_id"), F.lit(0).cast("long").alias("pixel"), F.lit(1).cast("long").alias("label"), F.lit(1).alias("cls"), F.lit(1.0).alias("depth"))
    pred = gt.drop("depth").withColumn("score", F.rand(3)).withColumn("cls", F.when(F.col("scene_id") % 3 == 0, 2).otherwise(1))
    plan = average_precision(pred, gt, taus=(0.5,))
    t = time.time()
    value = plan.collect()[0]["value"]
    assert 0.6 < value <= 2 / 3 + 1e-9 and time.time() - t < 60
    assert "specifiedwindowframe(RowFrame, currentrow$(), unboundedfollowing$())" not in plan._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["greedy_gap", "multicut_exact_tiny", "w_rogue_edge", "loss_total", "lr_schedule", "source_planted", "udtf_grid"])
def test_reads_a_table(name, spark, sf):
    assert QUERIES[name](spark, sf).inputFiles()


def test_rogue_edge_of_the_hand_graph(spark):
    """Graph 5: one contact edge above the blocks' own joins them under max, not under min."""
    from segraph.fixtures.graphs import hand_graphs
    from segraph.operators.contract import contract

    e = hand_graphs(spark).where("scene_id = 5")
    assert contract(e, rule="max").select("label").distinct().count() == 1
    assert contract(e, rule="min").select("label").distinct().count() == 2


def test_partitions_equal_sql_without_caps(spark, sf, tmp_path):
    """Ids beyond 500, and a text in more than 60 copies."""
    import duckdb

    from segraph.plans.registry import ORACLE_SQL

    con = duckdb.connect()
    con.sql(f"copy (select * replace (vec_id + 450 as vec_id) from '{sf}/embeddings.parquet' order by vec_id limit 120) to '{tmp_path}/embeddings.parquet'")
    con.sql(f"copy (select doc_id, text from '{sf}/documents.parquet' where doc_id < 60 union all select 1000 + range, 'one text of seven words in copies' from range(70)) to '{tmp_path}/documents.parquet'")
    for name, t in (("emb_partition", "embeddings"), ("docs_partition", "documents")):
        con.sql(f"create view {t} as select * from '{tmp_path}/{t}.parquet'")
        want = sorted(con.sql(ORACLE_SQL[name]).fetchall())
        assert sorted(tuple(r) for r in QUERIES[name](spark, str(tmp_path)).collect()) == want
        assert len(want) > (60 if t == "documents" else 0)


def pixel_wise(spark, sf, k=16, **kw):
    """Average precision of a cascade by the operators on rows a pixel."""
    from pyspark.sql import functions as F

    from segraph.operators.metrics import average_precision

    a = average_precision(measures.cascade_pred(spark, sf, k, **kw), measures.truth(spark, sf))
    return tuple(a.agg(F.avg("value"), F.avg(F.when(F.col("tau") == 0.5, F.col("value")))).first())


def test_one_pass_over_scenes_equals_the_pixel_wise_cascade(spark, sf):
    """Scores of all settings in one pass, in which no row a pixel is shuffled."""
    got = [tuple(r)[1:] for r in measures.cascade_ap(spark, sf, [{"finest": "adopt"}, {"k": 8}]).orderBy("m").collect()]
    assert got[0] == pytest.approx(pixel_wise(spark, sf, finest="adopt"), abs=1e-9) and got[0][1] > 0
    assert got[1] == pytest.approx(pixel_wise(spark, sf, 8), abs=1e-9)


def test_rasters_are_the_pixels_and_edges(spark, sf):
    from pyspark.sql import functions as F

    r = graphs.rasters(spark, sf, 8, 0.7)
    plan = r._jdf.queryExecution().executedPlan().toString().split("Generate explode")
    assert "Exchange hashpartitioning" not in plan[0]  # once boxes are drawn, nothing is shuffled
    cols = ["scene_id", "pixel", "inst_no", "cls", "depth", "sem", "emb"]
    a, b = r.select(cols), graphs.pixels(spark, sf, 8).select(cols)
    assert a.exceptAll(b).count() == b.exceptAll(a).count() == 0 < b.count()
    e = r.select("scene_id", F.col("pixel").alias("u"), F.explode(F.create_map(F.lit(1), "right", F.lit(32), "down")).alias("d", "aff")).where("aff is not null")
    e = e.select("scene_id", "u", (F.col("u") + F.col("d")).alias("v"), "aff")
    want = graphs.edges_of(graphs.full(spark, sf), 0.7).select("scene_id", "u", "v", "aff")
    assert e.exceptAll(want).count() == want.exceptAll(e).count() == 0 < want.count()


def test_regrouped_are_instances_in_several_pieces():
    """An instance in one piece doesn't count; of those in two, one is found as one segment, one in two."""
    import numpy as np

    nan = np.nan
    inst = np.array([[1, 1, 2, 2], [3, nan, 3, nan], [4, 5, 4, 5]], float)
    lab = np.array([[1, 1, 2, 2], [7, 0, 7, 0], [8, 9, 3, 9]])
    edge = np.full(inst.shape, 0.5)
    got = measures.regrouped_rows(lab, inst, edge, edge)
    assert got["inst"].tolist() == [1, 2, 3, 4, 5] and got["pieces"].tolist() == [1, 1, 2, 2, 2]
    assert got["whole"].tolist()[2:] == [True, False, True] and got["main"].tolist()[2:] == [1.0, 0.5, 1.0]


def test_regrouped_counts_what_the_truth_has_in_pieces(spark, sf):
    pieces = {r["pieces"]: r["instances"] for r in QUERIES["w_disjoint_recall"](spark, sf).collect()}
    got = QUERIES["w_regrouped"](spark, sf).first()
    assert got["instances"] == sum(n for k, n in pieces.items() if k > 1) > 0
