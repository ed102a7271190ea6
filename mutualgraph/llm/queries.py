"""The thin queries over whole tables, one an operator, and their SQL where SQL can express them.

Each gives a row for every row of its table (op4: for every piece), repeated rows, null ids and null texts included, and an
empty table for an empty one, as its operator's docstring says; columns that an operator doesn't name don't matter.
"""

from __future__ import annotations

import public_tokenizers

from pyspark.sql import functions as F

from . import language, licences, media, mixing, near_duplicates, ngram, packing, personal, token_files, vector_duplicates


def table(spark, sf_dir: str, name: str):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_mix_sources(spark, sf_dir):
    return mixing.mix(table(spark, sf_dir, "documents"))


def op2_collision_counting(spark, sf_dir):
    return vector_duplicates.vector_duplicates(table(spark, sf_dir, "embeddings"))


def op3_disclosure(spark, sf_dir):
    return personal.detect(table(spark, sf_dir, "documents"))


def op4_best_fit_packing(spark, sf_dir):
    return packing.pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op5_backoff_scoring(spark, sf_dir):
    out = ngram.score_documents(table(spark, sf_dir, "documents"), language.held_out(F.col("doc_id"), 10, 0))
    each = {"mean_score": F.col("score") / F.col("n_tokens"), "mean_gain": (F.col("score") - F.col("base_score")) / F.col("n_tokens")}
    out = out.withColumns(each)
    return out.withColumns({c: F.round(c, 6) for c in ("base_score", "score", *each)})


def op6_language_spans(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    model = language.fit(docs.filter(~language.held_out(F.col("doc_id"))))
    out = language.identify(docs.select("doc_id", "text"), model)
    return out.select("doc_id", language.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score", "n_spans")


def op7_token_files(spark, sf_dir):
    return token_files.token_shard_roundtrip(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op8_super_minhash(spark, sf_dir):
    return near_duplicates.near_duplicates(table(spark, sf_dir, "documents"), width=3, percent=85)


def op9_licence_digests(spark, sf_dir):
    return licences.scan(table(spark, sf_dir, "documents"))


def op10_media_columns(spark, sf_dir):
    return media.media_roundtrip(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_mix_sources, op2_collision_counting, op3_disclosure, op4_best_fit_packing, op5_backoff_scoring, op6_language_spans, op7_token_files, op8_super_minhash, op9_licence_digests, op10_media_columns)}
ORACLES: dict[str, str] = {
    "op2_collision_counting": vector_duplicates.ORACLE,
    "op3_disclosure": personal.ORACLE,
    "op5_backoff_scoring": ngram.ORACLE,
    "op8_super_minhash": near_duplicates.ORACLE,
    "op9_licence_digests": licences.ORACLE,
}
