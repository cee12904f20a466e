"""The text operators' queries over the given tables, and their SQL."""

from __future__ import annotations

from . import decontam, fingerprint, lmscore, neardup, quality, secret_scan, sp_sampling, token_counts, toxicity, wavelet
from .shared import prepare, table

PIECES = "piece_bpe_32k.model"
WORD_TOKENIZER = "word_bpe_49k.json"


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_toxicity(spark, sf_dir):
    prepare(spark)
    return toxicity.digest(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_secret_scan(spark, sf_dir):
    prepare(spark)
    return secret_scan.digest(table(spark, sf_dir, "documents"))


def op3_decontamination(spark, sf_dir):
    prepare(spark)
    return decontam.digest(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_token_counts(spark, sf_dir):
    prepare(spark)
    return token_counts.digest(table(spark, sf_dir, "documents"), tokenizer_path(PIECES), whole=True)


def op5_fingerprints(spark, sf_dir):
    prepare(spark)
    return fingerprint.digest(table(spark, sf_dir, "documents"))


def op6_near_duplicates(spark, sf_dir):
    prepare(spark)
    return neardup.digest(table(spark, sf_dir, "documents"))


def op7_quality(spark, sf_dir):
    prepare(spark)
    return quality.digest(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_sampled_pieces(spark, sf_dir):
    prepare(spark)
    return sp_sampling.encode(table(spark, sf_dir, "documents"), tokenizer_path(PIECES), whole=True)


def op9_token_store(spark, sf_dir):
    prepare(spark)
    path = wavelet.store_path(spark)
    wavelet.write_shards(table(spark, sf_dir, "documents"), path, tokenizer_path(WORD_TOKENIZER))
    return wavelet.read_documents(spark, path, ("ids_crc32", "bigint", wavelet.ids_crc32))


def op10_lm_scores(spark, sf_dir):
    prepare(spark)
    return lmscore.digest(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_toxicity, op2_secret_scan, op3_decontamination, op4_token_counts, op5_fingerprints, op6_near_duplicates, op7_quality, op8_sampled_pieces, op9_token_store, op10_lm_scores)}
ORACLE_SQL: dict[str, str] = {}
