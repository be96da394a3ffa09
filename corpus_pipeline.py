"""Corpus pipeline: language, near duplicates, benchmark leaks, personal data, mixture.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the
columns of documents.  Stage by stage:

* language: drops documents in which no language is found (null texts, texts without a letter);
* near duplicates: keeps the document with the least id of each group of documents linked by
  five-word shingles and a similarity of 0.8;
* decontamination: drops documents that hold a window of a benchmark item;
* personal data: replaces every span found by its kind in brackets;
* mixture: adds the tokens, the domain's posteriors and the rate at which a document is to be drawn.

Cases: null and empty texts go in the first stage; rows that repeat an id leave one, that with the
first text; rows with a null id link with nothing, and stay where their text is clean; ties go to
the lesser id; very long texts are read whole; an empty table gives an empty one with the same
columns; further columns pass through, but for those that the mixture adds itself.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from thinfsm.llm import decontaminate, langid, mixing, pii, setjoin
from thinfsm.llm.base import store, table


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return langid.keep_known(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return setjoin.keep_one(docs, width=5, percent=80)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.remove_contaminated(docs, table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pii.redact(docs)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs, mixing.domains_of(table(spark, sf_dir, "labels")), mixing.TARGETS, keep=tuple(docs.columns))


STAGES = [
    ("language", language),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("personal_data", personal_data),
    ("mixture", mixture),
]

#: Classifiers, boosting and the fit of the rates are beyond SQL; tests/llm checks each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = store(docs)
    return docs
