"""Exact histogram of encoded lengths; suffix sums answer totals, quantiles and truncated totals for every limit.

Edge cases: null or empty text has length 0; an empty table gives an empty histogram, whose totals are 0
and whose quantiles are null; repeated ids count each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import bounded, cut
from .tokens import default_vocabulary, encoded_batches


def document_lengths(docs: DataFrame, vocabulary: str | None = None, extra: int = 0) -> DataFrame:
    """doc_id and its number of ids (plus ``extra`` end ids)."""
    import pyarrow as pa

    path = vocabulary or default_vocabulary()

    def lengths(batches):
        for ids, coded in encoded_batches(batches, path, "doc_id", "text"):
            yield pa.record_batch([pa.array(ids, pa.int64()), pa.array([len(c) // 4 + extra for c in coded], pa.int64())], ["doc_id", "n_tokens"])

    return docs.select("doc_id", "text").mapInArrow(lengths, "doc_id long, n_tokens long")


def length_histogram(lengths: DataFrame, bucket_bits: int = 10) -> DataFrame:
    """Per distinct length: documents, tokens, and the same over all lengths at least this one.

    Suffix sums run in two steps, inside buckets of 2**bucket_bits lengths and over bucket totals, so
    that no window holds more than one bucket or one row a bucket.
    """
    hist = lengths.groupBy("n_tokens").agg(F.count(F.lit(1)).alias("docs")).withColumn("bucket", F.shiftright("n_tokens", bucket_bits))
    inner = Window.partitionBy("bucket").orderBy(F.desc("n_tokens")).rowsBetween(Window.unboundedPreceding, 0)
    hist = hist.withColumn("d", F.sum("docs").over(inner)).withColumn("t", F.sum(F.col("docs") * F.col("n_tokens")).over(inner))
    totals = hist.groupBy("bucket").agg(F.sum("docs").alias("bd"), F.sum(F.col("docs") * F.col("n_tokens")).alias("bt"))
    above = Window.orderBy(F.desc("bucket")).rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select("bucket", F.coalesce(F.sum("bd").over(above), F.lit(0)).alias("more_d"), F.coalesce(F.sum("bt").over(above), F.lit(0)).alias("more_t"))
    return hist.join(totals, "bucket").select(
        "n_tokens", "docs", (F.col("docs") * F.col("n_tokens")).alias("tokens"), (F.col("d") + F.col("more_d")).alias("docs_at_least"), (F.col("t") + F.col("more_t")).alias("tokens_at_least")
    )


def truncated_total(hist: DataFrame, limit: int) -> DataFrame:
    """Tokens kept when each document is cut at ``limit``: one row."""
    longer = F.col("n_tokens") > limit
    return hist.agg(
        F.coalesce(F.sum(F.least(F.col("n_tokens"), F.lit(limit)) * F.col("docs")), F.lit(0)).alias("kept_tokens"),
        F.coalesce(F.sum(F.when(longer, F.col("docs"))), F.lit(0)).alias("cut_docs"),
        F.coalesce(F.sum("tokens"), F.lit(0)).alias("total_tokens"),
    )


def length_quantile(hist: DataFrame, q: float) -> DataFrame:
    """Smallest length with at least a share ``q`` of all documents at or under it: one row, null for an empty table."""
    total = hist.agg(F.sum("docs").alias("n"))
    under: Column = F.col("n") - F.col("docs_at_least") + F.col("docs")
    return hist.crossJoin(F.broadcast(total)).where(under >= F.ceil(F.col("n") * F.lit(q))).agg(F.min("n_tokens").alias("quantile"))


def limit_table(hist: DataFrame) -> DataFrame:
    """For every length that occurs, taken as context limit: what stays after truncation, and the share of documents that fit."""
    n = hist.agg(F.sum("docs").alias("n_docs"), F.sum("tokens").alias("n_all"))
    over_docs, over_tokens = F.col("docs_at_least") - F.col("docs"), F.col("tokens_at_least") - F.col("tokens")
    return hist.crossJoin(F.broadcast(n)).select(
        "n_tokens", "docs", "docs_at_least", "tokens_at_least",
        (F.col("n_docs") - over_docs).alias("docs_fitting"),
        (F.col("n_all") - over_tokens + over_docs * F.col("n_tokens")).alias("truncated_total"),
    )


def document_report(lengths: DataFrame) -> DataFrame:
    """Per document: its length, how many documents are at least as long, and the corpus total truncated at its length.

    The histogram has one row per distinct length, far fewer than documents; it is written and broadcast within a
    bound, so that a length many documents share is no single task.
    """
    kept = cut(lengths, "lengths")
    return kept.join(bounded(cut(limit_table(length_histogram(kept)), "histogram")), "n_tokens").select("doc_id", "n_tokens", "docs_at_least", "docs_fitting", "truncated_total")
