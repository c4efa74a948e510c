"""The training-data pipeline: quality rules, near duplicates, benchmark decontamination, pseudonyms, packing.

Every stage takes (spark, docs, sf_dir) and gives a DataFrame; all but the last give the columns of documents.
"""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession

from orderdep.llm import decontam, packing, pseudonyms, robust_rules, simhash
from orderdep.llm.common import discard, result_of, table
from orderdep.llm.queries import EXAMPLE_KEY
from orderdep.llm.tokens import tokenizer_path


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and are no outliers of their language and source."""
    return robust_rules.keep(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group with 0.8 or more of their five-word shingles in common."""
    return simhash.one_of_each(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Benchmark passages of 10 words cut out; documents mostly made of them dropped."""
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def pseudonymised(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data and secrets replaced in their own format."""
    return pseudonyms.pseudonymise(docs, EXAMPLE_KEY)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of sequences of 1024 ids."""
    return packing.pack(docs, tokenizer_path("byte_bpe_50k.json"), 0, with_ids=True, keep_encoder=False)


STAGES = [("quality_rules", quality_rules), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("pseudonyms", pseudonymised), ("packing", packed)]

#: The estimates of the first stage and the tokens of the last have no SQL; tests/llm hold rules, near duplicates, cuts and packed ids
#: against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        before, docs = docs, result_of(partial(stage, spark, docs, sf_dir), spark, f"pipeline-{name}")
        if name != STAGES[0][0]:  # the given table stays
            discard(before)
    return STAGES[-1][1](spark, docs, sf_dir)
