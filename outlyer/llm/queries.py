"""The thin queries opN_<name>: each applies its operator to its whole table and keeps the columns agreed on."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, langid, linededup, media, neardup, packing, pii, sharding, token_histogram, toxicity
from .common import cut, fold_of, table
from .sql import ORACLES


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").where(fold_of("doc_id", 3) != 1).select("doc_id", "toxic")
    hashed = docs.where("text is not null").withColumn("h", F.xxhash64("text"))
    grammar = toxicity.fit(hashed.select("doc_id", "h").join(labels, "doc_id").select("h", "toxic"), texts=hashed.select("h", "text"))
    return toxicity.scores(docs, grammar).select("doc_id", (fold_of("doc_id", 3) == 1).alias("held_out"), "score", "predicted")


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"))


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_by_bytes(table(spark, sf_dir, "documents"))


def op4_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"), width=3, threshold_pct=85)


def op5_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(pii.find_spans(table(spark, sf_dir, "documents")))


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = langid.fit(docs.where(fold_of("doc_id", 5) != 0).select("text", "lang"), levels=False)
    return langid.predict(docs.select("doc_id", "text"), model).select("doc_id", (fold_of("doc_id", 5) == 0).alias("held_out"), "lang_pred", "score")


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = linededup.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_removed", F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("text_md5"))


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).select("doc_id", "item_id", "distance")


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_histogram.document_report(token_histogram.document_lengths(table(spark, sf_dir, "documents")))


def op10_media_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.edited_copies(media.rendered_vectors(table(spark, sf_dir, "embeddings"))).withColumnRenamed("media_id", "vec_id")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    named = [op1_toxicity, op2_packing, op3_sharding, op4_near_duplicates, op5_personal_data, op6_language, op7_line_dedup, op8_decontamination, op9_token_counts, op10_media_copies, pipeline]
    return {f.__name__: f for f in named}


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)


__all__ = ["cut", "oracle_sql", "queries"]
