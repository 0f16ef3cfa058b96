"""The queries of this subpackage and the SQL that expresses them, where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from embedvocab.llm import ctw, matroska, mixing, packing, quality_knn, simhash, spotsigs, substring_dedup, toxicity, warc
from embedvocab.llm.common import table


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.digest(table(spark, sf_dir, "documents"), window=35)


def op2_matroska(spark: SparkSession, sf_dir: str) -> DataFrame:
    return matroska.digest(table(spark, sf_dir, "documents"))


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.digest(table(spark, sf_dir, "pages"))


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op5_quality_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return quality_knn.scores(docs, quality_knn.fit(docs, labels))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return toxicity.scores(docs, toxicity.fit(docs, labels))


def op7_spotsigs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spotsigs.digest(table(spark, sf_dir, "documents"))


def op7_spotsigs_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The similarity join: length bands, rarest signatures, pruned Jaccard of 0.8 or more."""
    return spotsigs.neighbours(table(spark, sf_dir, "documents"))


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.digest(table(spark, sf_dir, "documents"))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.digest(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_context_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ctw.digest(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_substring_dedup": op1_substring_dedup,
    "op2_matroska": op2_matroska,
    "op3_warc": op3_warc,
    "op4_packing": op4_packing,
    "op5_quality_knn": op5_quality_knn,
    "op6_toxicity": op6_toxicity,
    "op7_spotsigs": op7_spotsigs,
    "op7_spotsigs_links": op7_spotsigs_links,
    "op8_simhash": op8_simhash,
    "op10_context_tree": op10_context_tree,
    "op9_mixing": op9_mixing,
}

ORACLES: dict[str, str] = {
    "op3_warc": warc.ORACLE,
    "op9_mixing": mixing.ORACLE,
}
