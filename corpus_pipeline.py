"""Prepares the documents for training: five stages, each with the whole output of the one before.

quality     documents whose tail probability of a good grade is too low go
near_copies one document of each group of near copies (Jaccard of five-word shingles 0.8 or more) stays
leaks       documents that hold a benchmark item go
secrets     secrets are replaced by a mask
packing     the documents become sequences of token ids; a row for each piece

The models are trained on the labelled documents of the input folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from kernelblocks.llm import decontamination, nearcopies, packing, quality, secretscan
from kernelblocks.llm.queries import tokenizer_path
from kernelblocks.llm.runtime import cut, table
from kernelblocks.session import ship_package


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship_package(spark)
    model = quality.train(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return quality.select_good(docs, model)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return nearcopies.keep_one(docs)


def leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return decontamination.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secretscan.masked(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return packing.pack(docs, tokenizer_path())


STAGES = [
    ("quality", good_quality),
    ("near_copies", near_copies),
    ("leaks", leaks),
    ("secrets", secrets),
    ("packing", packed),
]

#: Neither the classifier nor the byte-pair ids can be said in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on documents; what each returns is written to the checkpoint folder before the next."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
