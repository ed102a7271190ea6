"""Corpus preparation: language, near duplicates, personal data, source mix, packing. Each stage reads the one before."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mutualgraph.llm import language, mixing, near_duplicates, packing, personal
from mutualgraph.llm.common import store


def keep_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with an identified language; those without text or letters go. lang becomes the language found."""
    found = language.identify(docs, language.fit(docs))
    return found.filter("lang_pred <> 'und'").withColumn("lang", F.col("lang_pred")).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates (five-word shingles, similarity of 0.8 or more) stays."""
    return near_duplicates.without_near_duplicates(docs)


def protect_persons(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data and the terms that give it away are replaced in text; no document goes."""
    return personal.sanitise(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as its source's target takes it."""
    return mixing.mixed_documents(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their places in sequences of at most 2048 tokens."""
    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("language", keep_languages),
    ("near duplicates", drop_near_duplicates),
    ("personal data", protect_persons),
    ("source mix", mix_sources),
    ("packing", pack_sequences),
]

#: SQL can't express tokenising, Viterbi or exponential keys; tests/llm compares what every stage keeps and makes of a whole
#: table with plain Python (test_pipeline_stages_against_brute_force).
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each one's rows written before the next reads them."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = store(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
