"""Corpus pipeline: quality rules, line dedup, n-gram Jaccard join, decontamination, packing.

Every stage takes (spark, docs, sf_dir); ``run`` writes each stage's rows as Parquet in the
shared folder and reads them as the next one's documents. All but the last keep the
columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from critgraph.llm import crf_quality, line_dedup, ngram_join, nnls_packing, wu_manber
from critgraph.llm.queries import table, tokenizer_path
from critgraph.runtime import materialise


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return crf_quality.keep(docs, crf_quality.train(docs, table(spark, sf_dir, "labels")))


def line_deduplication(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return line_dedup.dedup_lines(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return ngram_join.one_of_each(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return wu_manber.clean_documents(docs, table(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return nnls_packing.packed(docs, tokenizer_path())


STAGES = [
    ("quality rules", quality_rules),
    ("line dedup", line_deduplication),
    ("n-gram jaccard join", near_duplicates),
    ("benchmark decontamination", decontamination),
    ("packing", packing),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = materialise(docs, "stage")
    return docs


#: SQL can express neither the trained field nor the MinHash stage; the stages are tested against brute force.
ORACLE_SQL = None
