"""The queries of the training-data operators, and their SQL."""

from __future__ import annotations

import importlib

from pyspark.sql import DataFrame, SparkSession

from graphstitch.llm import bpe_tree, language_gru, license_rules, order_minhash, quality_llr, rans, recompression, toxicity_knn, warc, winnowing
from graphstitch.llm.common import read


def op8_quality_llr(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_llr.assess(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")).drop("text")


def op1_warc_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(read(spark, sf_dir, "pages")).drop("archive")


def op2_toxicity_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity_knn.score(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op3_license_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_rules.scan(read(spark, sf_dir, "documents"))


def op4_rans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rans.round_trip(read(spark, sf_dir, "documents"))


def op5_language_gru(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_gru.identify(read(spark, sf_dir, "documents"))


def op6_recompression(spark: SparkSession, sf_dir: str) -> DataFrame:
    return recompression.digests(read(spark, sf_dir, "documents"))


def op7_bpe_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_tree.digests(read(spark, sf_dir, "documents"))


def op9_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return order_minhash.membership(read(spark, sf_dir, "documents"))


def op10_winnowing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return winnowing.assess(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark")).drop("th")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return importlib.import_module("corpus_pipeline").run(spark, sf_dir)


def queries() -> dict:
    return {
        "op1_warc_revisits": op1_warc_revisits,
        "op2_toxicity_knn": op2_toxicity_knn,
        "op3_license_rules": op3_license_rules,
        "op4_rans": op4_rans,
        "op5_language_gru": op5_language_gru,
        "op6_recompression": op6_recompression,
        "op7_bpe_tree": op7_bpe_tree,
        "op8_quality_llr": op8_quality_llr,
        "op9_order_minhash": op9_order_minhash,
        "op10_winnowing": op10_winnowing,
        "pipeline": pipeline,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_warc_revisits": warc.SQL}
