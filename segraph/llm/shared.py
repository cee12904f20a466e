"""Cluster plumbing shared by the text operators."""

from __future__ import annotations

import ctypes
import os
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


#: Rows handed to a Python worker at a time: some MB of ordinary texts.
BATCH_ROWS, BATCH_CONF = 1024, "spark.sql.execution.arrow.maxRecordsPerBatch"


def prepare(spark: SparkSession) -> None:
    """Lets Python workers import this package wherever the driver started, and
    bounds the rows of an Arrow batch, as texts are wide."""
    if not 0 < int(spark.conf.get(BATCH_CONF, "10000")) <= BATCH_ROWS:
        spark.conf.set(BATCH_CONF, str(BATCH_ROWS))
    env = spark.sparkContext.environment
    if ROOT not in env.get("PYTHONPATH", "").split(":"):
        env["PYTHONPATH"] = ":".join(x for x in (ROOT, env.get("PYTHONPATH", "")) if x)


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; a local one only where none is set and the master is local, as in tests."""
    set_ = spark.conf.get("spark.checkpoint.dir", "")
    if not set_ and not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    return (set_ or "file:///tmp/checkpoints").rstrip("/")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Writes df once to the shared folder and reads it back: lineage ends here
    and a lost executor costs no more than a re-read."""
    return Scratch(df.sparkSession, name).write(df)


class Scratch:
    """Written tables of one call, which are deleted when it needs them no more."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.name, self.paths = spark, name, {}

    def write(self, df: DataFrame) -> DataFrame:
        path = f"{shared_dir(self.spark)}/segraph/{self.name}-{uuid.uuid4().hex}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[path] = out
        return out

    def clear(self, *kept: DataFrame) -> None:
        """Deletes all tables but those."""
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        for path in [p for p, df in self.paths.items() if not any(df is k for k in kept)]:
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(conf).delete(at, True)
            del self.paths[path]


def free_names(columns, *names: str) -> list[str]:
    """Those names, with underscores behind them as far as columns already have them."""
    out = []
    for n in names:
        while n.lower() in {c.lower() for c in columns}:
            n += "_"
        out.append(n)
    return out


def tidy(work):
    """work, which at its end hands memory that it freed back to the system: a
    worker goes on to other tasks, and an executor holds several."""

    def run(it):
        try:
            yield from work(it)
        finally:
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except AttributeError:  # another C library
                pass

    return run


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def range_bounds(df: DataFrame, key: str, blocks: int) -> list[int]:
    """At most blocks-1 cut points of an integer key, for blocks of even row
    counts; the result is as small as the number of blocks."""
    if blocks < 2:
        return []
    probs = [i / blocks for i in range(1, blocks)]
    got = df.agg(F.percentile_approx(F.col(key).cast("long"), probs, 20 * blocks).alias("b")).first()["b"]
    return sorted(set(got or []))


def block_of(key: str, bounds: list[int]):
    """Block number (0..len(bounds)) of a key: how many cut points are below it; null goes to 0."""
    if not bounds:
        return F.lit(0)
    k = F.col(key).cast("long")
    literal = lambda xs: F.expr(f"array({','.join(f'{int(x)}L' for x in xs)})")
    below = lambda arr: F.size(F.filter(arr, lambda b: b < k))
    if len(bounds) <= 64:
        return F.coalesce(below(literal(bounds)), F.lit(0)).cast("int")
    step = int(len(bounds) ** 0.5) + 1  # two short searches rather than one long
    coarse = below(literal(bounds[step - 1 :: step])) * step
    return F.coalesce(coarse + below(F.slice(literal(bounds), coarse + 1, F.lit(step))), F.lit(0)).cast("int")


def batches(schema: pa.Schema, columns: dict) -> pa.RecordBatch:
    """One record batch from a dict of lists or arrays, typed by schema."""
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], type=f.type) for f in schema], schema=schema)


def arrow_schema(ddl: str) -> pa.Schema:
    """Arrow schema of a flat Spark DDL string."""
    kinds = {
        "bigint": pa.int64(), "long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string(), "boolean": pa.bool_(),
        "binary": pa.binary(), "array<bigint>": pa.list_(pa.int64()), "array<int>": pa.list_(pa.int32()), "array<string>": pa.list_(pa.string()), "array<double>": pa.list_(pa.float64()), "array<binary>": pa.list_(pa.binary()),
    }
    return pa.schema([(n, kinds[k]) for n, k in (x.split(" ", 1) for x in ddl.split(", "))])


def texts_of(df: DataFrame, *keep: str) -> DataFrame:
    """Only the named columns, so that extra ones never travel; text as string."""
    return df.select(*[F.col(c) for c in keep], F.col("text").cast("string").alias("text"))


def held(remainder: int, modulus: int, key: str = "doc_id"):
    """Whether crc32 of the id as text leaves that remainder; null ids count as the empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(key).cast("string"), F.lit("")).cast("binary")), F.lit(modulus)) == remainder


def as_numpy(col) -> np.ndarray:
    return col.to_numpy(zero_copy_only=False)
