"""Queries of the training-data operators, with production parameters over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bitplanes, decontaminate, hilbert, licenses, packing, quality, simhash, suffix_dedup, surrogates, token_counts
from .common import tokenizer_path
from .oracles import ORACLES

#: Key of the surrogates; a deployment passes its own.
KEY = b"cellstream surrogate key"


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_packing(spark, sf_dir):
    return packing.pack(_documents(spark, sf_dir), tokenizer_path("word_bpe_49k.json"), 2048)


def op2_surrogates(spark, sf_dir):
    return surrogates.pseudonymised(_documents(spark, sf_dir).select("doc_id", "text"), KEY, count="n_entities")


def op3_quality(spark, sf_dir):
    return quality.measures(_documents(spark, sf_dir))


def op4_decontamination(spark, sf_dir):
    return decontaminate.contained(_documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op5_bitplanes(spark, sf_dir):
    return bitplanes.read_documents(bitplanes.write_ids(_documents(spark, sf_dir), tokenizer_path("byte_bpe_50k.json")))


def op6_simhash(spark, sf_dir):
    named = simhash.classes(_documents(spark, sf_dir))
    return named.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op7_suffix_dedup(spark, sf_dir):
    return suffix_dedup.deduplicated(_documents(spark, sf_dir), texts=False)


def op8_hilbert(spark, sf_dir):
    return hilbert.shards(_documents(spark, sf_dir))


def op9_licenses(spark, sf_dir):
    return licenses.scan(_documents(spark, sf_dir))


def op10_token_counts(spark, sf_dir):
    return token_counts.token_counts(_documents(spark, sf_dir), tokenizer_path("word_bpe_49k.json"), 2048)


def queries() -> dict:
    named = (op1_packing, op2_surrogates, op3_quality, op4_decontamination, op5_bitplanes, op6_simhash, op7_suffix_dedup, op8_hilbert, op9_licenses, op10_token_counts)
    return {f.__name__: f for f in named}


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
