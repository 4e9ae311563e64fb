"""The corpus pipeline: five stages over documents, each a table in the shared folder.

Each stage takes (spark, docs, sf_dir) and gives the next one's docs: language ID drops what it
rejects, SimHash keeps one document of each near-duplicate group, chaining cuts repeated passages
out of the texts, mixing repeats or drops rows to the sources' target weights, and packing gives the
pieces and sequences of what is left. Nulls, empty texts, ties and repeated rows are treated as each
operator's module states; an empty table goes through to an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from aggnear.llm import chaining, langid, mixing, packing, simhash
from aggnear.llm.common import stage, table


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return langid.keep_identified(docs, langid.train(docs.select("doc_id", "text", "lang")))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_one(docs)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return chaining.cut_passages(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.repeated(docs, odds="size")


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs.select("doc_id", "text"))


STAGES = [
    ("language_id", identify_language),
    ("simhash", drop_near_copies),
    ("chaining", cut_repeats),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: None of the filtering stages can be said in SQL; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
