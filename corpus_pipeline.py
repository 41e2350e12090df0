"""A corpus pipeline of four text operators: language, toxicity, near-duplicates, packing.

Each stage takes all rows that the one before it kept, as Parquet in the shared folder. The first
three drop rows and keep the columns of ``documents``; the last gives the packed pieces. A stage's
null, empty and repeated rows are treated as its operator's module says; rows without an id are
never dropped.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.llm import langid, neardup, packing, toxicity
from subgraph_engine.llm.common import table, without, written
from subgraph_engine.llm.queries import VOCABULARY


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of a language that the text models know, and surely so."""
    judged = langid.identify(docs, langid.train_text(docs))
    return without(docs, judged.where(~F.col("kept")))


def clean_of_toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that aren't predicted toxic by a model of the labelled rows among them."""
    learn = (F.crc32(F.col("id").cast("string").cast("binary")) % 4) != 2
    model = toxicity.train(docs, table(spark, sf_dir, "labels"), learn)
    return without(docs, toxicity.score_documents(docs, model).where("predicted = 1"))


def deduplicated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates, that with the least id."""
    return without(docs, neardup.near_duplicates(docs).where(~F.col("kept")))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of 2048 ids."""
    return packing.pack(docs, public_tokenizers.path(VOCABULARY), capacity=2048, end_id=1)


STAGES = [("language", language), ("toxicity", clean_of_toxicity), ("near_duplicates", deduplicated), ("packing", packed)]

#: SQL has no text models and no tokenizer; tests compare each stage with plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage, from the whole table ``documents``."""
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = written(docs, name)
    return docs
