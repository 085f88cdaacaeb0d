"""Corpus pipeline: five stages over ``documents``, each written and read again by ``run``.

All stages but the last return the columns of ``documents``; the last one packs what is left into sequences.

Defined results: documents of null or empty text are one group of the exact stage, of which the largest doc_id goes on; a null doc_id
ranks below all others; of equal texts the largest doc_id stays, of near copies the smallest; rows that repeat a doc_id and text stay or go
together; removed passages leave the rest of a text, at times an empty one; every document that the fourth stage returns is packed; without
labels nothing is toxic; an empty table gives no rows; extra columns go through all stages but the last.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from equiscale.llm import exact_dedup, packing, passages, simhash, toxicity
from equiscale.llm.common import cut, table
from equiscale.llm.queries import tokenizer_file
from equiscale.sources.io import made, sweep


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.drop_toxic(docs, table(spark, sf_dir, "labels"))


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.drop_exact(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.drop_near(docs)


def passage_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return passages.remove_passages(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs, tokenizer_file("word_bpe_49k.json"))


STAGES = [("toxicity", toxicity_stage), ("exact dedup", exact_stage), ("SimHash near-dedup", near_stage), ("suffix-array dedup", passage_stage), ("best-fit packing", packing_stage)]

#: SQL cannot express the scores, fingerprints and packing; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        since = made()
        docs = cut(stage(spark, docs, sf_dir))
        sweep(spark, since, docs)  # what the stage wrote on its way
    return STAGES[-1][1](spark, docs, sf_dir)
