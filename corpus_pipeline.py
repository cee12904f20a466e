"""Corpus pipeline: quality filter, near-duplicates, decontamination, secrets, sampled pieces.

Every stage takes (spark, docs, sf_dir) and works on all that the stage before
kept.  The first four return the columns of documents; the last gives one row
per document and sampled segmentation.

quality           keeps what the line field scores at QUALITY or more
near_duplicates   keeps the smallest id of each group (five words, 0.8); rows
                  with a null id stay, rows of a repeated id share its fate
decontamination   drops documents that hold a benchmark window
secrets           masks every secret and updates n_chars; keeps all rows
sampled_pieces    doc_id, sample, n_pieces, log_prob, inclusion, ids

Null texts count as empty, and an empty table passes through all stages.  The
first four stages hand every column on as it came, whatever its name, but for text and
n_chars of documents with secrets.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segraph.llm import decontam, neardup, quality, secret_scan, sp_sampling
from segraph.llm.queries import PIECES, tokenizer_path
from segraph.llm.shared import free_names, materialise, prepare, table

QUALITY = 0.5


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = quality.fit(docs, table(spark, sf_dir, "labels"))
    _, score = free_names(docs.columns, *quality.RESULTS)
    return quality.score(docs, model).where(F.col(score) >= QUALITY).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    gone = neardup.clusters(docs, 5, (80, 100)).where("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    _, hit_from, _, _ = free_names(docs.columns, *decontam.RESULTS)
    return decontam.mark(docs, table(spark, sf_dir, "benchmark")).where(F.size(hit_from) == 0).select(*docs.columns)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    (count,) = free_names(docs.columns, "n_masked")
    masked = secret_scan.mask(docs)
    return masked.withColumn("n_chars", F.when(F.col(count) > 0, F.char_length("text").cast("long")).otherwise(F.col("n_chars"))).select(*docs.columns)


def sampled_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sp_sampling.encode(docs, tokenizer_path(PIECES), whole=True).select("doc_id", "sample", "n_pieces", "log_prob", "inclusion", "ids")


STAGES = [("quality", quality_filter), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("secrets", secrets), ("sampled_pieces", sampled_pieces)]
ORACLE_SQL = None  # no stage but the decontamination is within SQL's reach


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    prepare(spark)
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
