"""The corpus pipeline: quality, toxicity, near duplicates, mixture, pieces.

Each stage is (name, function of spark, docs and the tables' folder); what one
returns is written and read again as the next one's ``docs``. Two stages filter
by models fitted to labelled rows, the third keeps one document of each group of
near duplicates, the fourth repeats or drops documents so that sources reach
their target weights, and the last encodes what is left.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rankflow.llm import mixing, neardup, pieces, quality, toxicity
from rankflow.llm.common import staged, table
from rankflow.llm.queries import PIECE_BPE


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.good_documents(docs, table(spark, sf_dir, "labels"))


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.clean_documents(docs, docs, table(spark, sf_dir, "labels"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return neardup.one_of_each_group(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pieces.piece_digests(docs, PIECE_BPE)


STAGES = [
    ("quality", keep_good),
    ("toxicity", drop_toxic),
    ("near duplicates", drop_near_copies),
    ("mixture", mix),
    ("pieces", encode),
]

#: Fitted models and pieces are not SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
