"""The thin opN_ queries: each applies its operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import audio, decontamination, language, linededup, mixing, pitmanyor, simhash, tokens, toxicity, urls
from .common import table


def op1_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.tokenize_and_read(table(spark, sf_dir, "documents"), tokens.public_vocabulary())


def op2_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op3_chroma(spark: SparkSession, sf_dir: str) -> DataFrame:
    return audio.align_media(table(spark, sf_dir, "embeddings"), "vec_id", "embedding", audio.melody)


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "fingerprint", "component_id")


def op5_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge_urls(table(spark, sf_dir, "pages").select("page_id", "url")).select("page_id", "host", "path", "rule", "verdict", "template", "purity")


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify(table(spark, sf_dir, "documents").select("doc_id", "text", "lang")).select("doc_id", "held_out", "lang_pred", "score", "rejected")


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return toxicity.score_toxicity(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic")).select("doc_id", "held_out", "score", "predicted")


def op8_pitman_yor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pitmanyor.score_texts(table(spark, sf_dir, "documents"))


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.find_leaks(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = linededup.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_chunks", "removed_chunks", "removed_lines", F.md5(F.col("kept").cast("binary")).alias("kept_md5"))


def queries():
    return {f.__name__: f for f in (op1_token_store, op2_mix, op3_chroma, op4_simhash, op5_url_filter, op6_language, op7_toxicity, op8_pitman_yor,
                                       op9_decontaminate, op10_line_dedup)}


def oracle_sql() -> dict[str, str]:
    return {"op2_mix": mixing.SQL, "op5_url_filter": urls.oracle(), "op10_line_dedup": linededup.SQL}
