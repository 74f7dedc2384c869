"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bfd_packing, crf_language, decontaminate, ffd_packing, line_dedup, masked_lm, pu_quality, simhash, top_k, wrapper


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_masked_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return masked_lm.digest(_table(spark, sf_dir, "documents"))


def op2_crf_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return crf_language.digest(_table(spark, sf_dir, "documents"))


def op3_pu_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pu_quality.digest(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op4_bfd_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bfd_packing.pack_rows(_table(spark, sf_dir, "documents"))


def op5_wrapper(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wrapper.digest(_table(spark, sf_dir, "pages"))


def op6_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k.digest(_table(spark, sf_dir, "embeddings"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.digest(_table(spark, sf_dir, "documents"))


def op8_ffd_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ffd_packing.digest(_table(spark, sf_dir, "documents"))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.digest(_table(spark, sf_dir, "documents"), line_dedup.GRAMS)


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.digest(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_masked_lm, op2_crf_language, op3_pu_quality, op4_bfd_packing, op5_wrapper,
        op6_top_k, op7_simhash, op8_ffd_packing, op9_line_dedup, op10_decontaminate,
    )
}
ORACLES: dict[str, str] = {"op6_top_k": top_k.ORACLE}
