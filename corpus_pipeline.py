"""A training-corpus pipeline over ``documents``: five stages, each written as Parquet and read again by the next.

language ID -> line dedup -> near-duplicate removal -> benchmark decontamination -> best-fit packing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from outlyer.llm import decontam, langid, linededup, neardup, packing
from outlyer.llm.common import cut, fold_of, guarded, release, table, without, written


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose language the model recognises; ``lang`` stays as given. Without any labelled text there is no model and all stay."""
    own, back = guarded(docs, "doc_id", "text", "lang")
    seen = langid.screen(own, fold_of("doc_id", 5) != 0)
    return docs if seen is None else back(seen.where(~F.col("rejected")))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Deletes later copies of repeated line runs; a document of which nothing is left goes."""
    own, back = guarded(docs, "doc_id", "text", "n_chars")
    out = linededup.dedup_lines(own)
    blank = F.regexp_replace(F.coalesce("text", F.lit("")), r"[\s\p{Z}]+", "") == ""
    out = out.where(~((F.col("n_removed") > 0) & blank))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return back(out)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near copies: five-word shingles, similarity 0.8 or more. Rows that share an id stay or go together."""
    gone = neardup.near_duplicates(docs.select("doc_id", "text")).groupBy("doc_id").agg(F.max("kept").alias("kept")).where("not kept")
    return without(docs, gone).select(*docs.columns)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark item within its edit budget."""
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark").select("item_id", "text")).select(*docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs what is left into sequences of at most 2048 tokens."""
    return packing.pack_documents(docs)


STAGES = [("language", language), ("lines", lines), ("near_duplicates", near_duplicates), ("decontaminated", decontaminated), ("packed", packed)]

#: Language models, signatures and packing have no SQL form; tests/llm/test_pipeline.py compares each stage with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in turn; once a stage's result is written, the tables made on the way to it are deleted."""
    docs, since = table(spark, sf_dir, "documents"), written()
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), name)
        release(since=since, keep=1)
    return STAGES[-1][1](spark, docs, sf_dir)
