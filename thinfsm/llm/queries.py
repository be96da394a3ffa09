"""The registered queries of the training-data operators, over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, fixity, langid, mixing, pii, quality, quotes, setjoin, topk, toxicity
from .base import table


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    domains = mixing.domains_of(table(spark, sf_dir, "labels"))
    return mixing.mix(table(spark, sf_dir, "documents"), domains, mixing.TARGETS, keep=("doc_id",))


def op2_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return fixity.audit(pages, fixity.damaged(pages)).drop("path")


def op3_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.search(table(spark, sf_dir, "embeddings"), F.col("id") % 50 == 0, every=True)


def op4_quotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quotes.converse(quotes.as_mail(table(spark, sf_dir, "conversations")))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.detect(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.report(decontaminate.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")))


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(table(spark, sf_dir, "documents"))


def op8_set_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return setjoin.join(table(spark, sf_dir, "documents"))


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.rank(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.report(pii.find(table(spark, sf_dir, "documents"), keep=("doc_id",)))


QUERIES = {f.__name__: f for f in (op1_mixing, op2_fixity, op3_top_k, op4_quotation, op5_toxicity, op6_decontamination, op7_language, op8_set_join, op9_quality, op10_personal_data)}
ORACLES = {"op2_fixity": fixity.ORACLE, "op4_quotation": quotes.ORACLE, "op3_top_k": topk.ORACLE, "op6_decontamination": decontaminate.ORACLE, "op8_set_join": setjoin.ORACLE}
