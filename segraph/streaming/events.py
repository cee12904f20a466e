"""Streaming twins of the event workloads.

Every function takes a streaming dataframe of events (event_id, ts timestamp,
user_id, event_type, value); rows later than the watermark are dropped.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import shared_dir


def event_stream(spark: SparkSession, sf: str) -> DataFrame:
    """The events table as a file stream; local timestamps are read as UTC."""
    path = f"{sf}/events.parquet"
    schema = spark.read.parquet(path).schema
    s = spark.readStream.schema(schema).parquet(f"{sf}/events.parque[t]")  # a pattern, as a stream's source is a folder or a pattern
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def windows(df: DataFrame, kind: str = "tumbling", size: str = "6 hours", slide: str = "3 hours", gap: str = "2 hours", late: str = "12 hours") -> DataFrame:
    """Counts and values by window and type (tumbling, sliding) or user (session)."""
    d = df.withWatermark("ts", late)
    if kind == "session":
        g = d.groupBy(F.session_window("ts", gap).alias("w"), "user_id")
        keys = ["user_id"]
    else:
        w = F.window("ts", size, slide) if kind == "sliding" else F.window("ts", size)
        g, keys = d.groupBy(w.alias("w"), "event_type"), ["event_type"]
    return g.agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n", "cents")


def dedup(df: DataFrame, late: str = "12 hours") -> DataFrame:
    return df.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def click_after_view(df: DataFrame, late: str = "12 hours", within: str = "6 hours", first: str = "view", second: str = "click") -> DataFrame:
    """Stream-stream join: second events of a user within a time after first ones."""
    a = df.where(F.col("event_type") == first).select(F.col("user_id").alias("ua"), F.col("ts").alias("ta"), F.col("event_id").alias("a")).withWatermark("ta", late)
    b = df.where(F.col("event_type") == second).select(F.col("user_id").alias("ub"), F.col("ts").alias("tb"), F.col("event_id").alias("b")).withWatermark("tb", late)
    return a.join(b, F.expr(f"ua = ub AND tb > ta AND tb <= ta + INTERVAL {within}")).select(F.col("ua").alias("user_id"), "a", "b")


def runs(df: DataFrame, half_life_h: float = 24.0, t: float = 0.5, late: str = "12 hours") -> DataFrame:
    """Stateful event runs: (user_id, event_id, run); state is one open run a user."""
    import pandas as pd

    def step(key, pdfs, state):
        last_ts, last_type, run = state.get if state.exists else (None, None, 0)
        rows = pd.concat(list(pdfs)).sort_values(["ts", "event_id"])
        out = []
        for ts, typ, eid in zip(rows["ts"], rows["event_type"], rows["event_id"]):
            if last_ts is None:
                run += 1
            else:
                gap = (ts.value // 1000 - last_ts) / 1e6
                if 2 ** (-gap / 3600 / half_life_h) * (1.0 if typ == last_type else 0.25) <= t:
                    run += 1
            last_ts, last_type = ts.value // 1000, typ
            out.append((key[0], eid, run))
        state.update((last_ts, last_type, run))
        yield pd.DataFrame(out, columns=["user_id", "event_id", "run"])

    d = df.select("user_id", "event_id", "event_type", "ts").withWatermark("ts", late)
    return d.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, event_id bigint, run bigint", "ts bigint, type string, run bigint", "append", "NoTimeout")


def drain(df: DataFrame, mode: str = "append", name: str | None = None) -> DataFrame:
    """Runs a streaming query over what there is and returns its rows."""
    spark = df.sparkSession
    name = name or f"segraph_{uuid.uuid4().hex}"
    path = f"{shared_dir(spark)}/segraph/stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = df.writeStream.format("parquet").option("checkpointLocation", f"{path}/log").option("path", f"{path}/out").outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{path}/out")
    seen: list[DataFrame] = []

    def keep(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/out/{epoch}")
        seen[:] = [epoch]

    q = df.writeStream.foreachBatch(keep).option("checkpointLocation", f"{path}/log").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{path}/out/{seen[0]}") if seen else spark.createDataFrame([], df.schema)


def scenes(df: DataFrame, out: str, threshold: float = 0.5):
    """Partitions every arriving micro-batch of whole scenes and appends its labels to out."""
    from ..operators.contract import contract

    def one(batch: DataFrame, epoch: int) -> None:
        contract(batch.select("scene_id", "u", "v", "aff"), threshold).write.mode("overwrite").parquet(f"{out}/epoch={epoch}")

    return df.writeStream.foreachBatch(one)
