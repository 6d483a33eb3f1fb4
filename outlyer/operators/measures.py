"""Accuracy and cost measures on DataFrames."""

from __future__ import annotations

import math
import time
from contextlib import contextmanager

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Studentised range over the square root of two at the 5 % level, by number of methods.
NEMENYI_Q = {2: 1.960, 3: 2.343, 4: 2.569, 5: 2.728, 6: 2.850, 7: 2.949, 8: 3.031, 9: 3.102, 10: 3.164}


def score_counts(df: DataFrame, score: str, label: str, by: list[str]) -> DataFrame:
    """Positives and negatives at each distinct score: what all rank measures need, pre-aggregated."""
    return df.groupBy(*by, F.col(score).alias("_s")).agg(F.sum(F.col(label).cast("long")).alias("_p"), F.sum(1 - F.col(label).cast("long")).alias("_n"))


def roc_auc(df: DataFrame, score: str = "score", label: str = "is_anom", by: list[str] | None = None, digits: int | None = None) -> DataFrame:
    """Tie-aware AUC per group; null where only one class occurs. ``digits`` rounds scores first, which bounds the sort at scale.

    Scores are ranked within slices of their range first and then slice by slice, so no task sorts a whole group.
    """
    by = by or []
    if digits is not None:
        df = df.withColumn(score, F.round(score, digits))
    s = F.col("_s").cast("double")
    slice_ = F.when(s.isNull(), F.lit(-(10**6))).when(F.isnan(s), F.lit(10**6)).otherwise(F.floor(F.atan(s) * 1024))  # nulls first and NaN last, as in sorting
    counts = score_counts(df, score, label, by).withColumn("_k", slice_.cast("long"))
    inside = Window.partitionBy(*by, "_k").orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)
    each = counts.withColumn("_b", F.coalesce(F.sum("_n").over(inside), F.lit(0))).groupBy(*by, "_k").agg(F.sum(F.col("_p") * (2 * F.col("_b") + F.col("_n"))).alias("_w"), F.sum("_p").alias("_p"), F.sum("_n").alias("_n"))
    below = Window.partitionBy(*(by or [F.lit(1)])).orderBy("_k").rowsBetween(Window.unboundedPreceding, -1)
    won = each.withColumn("_b", F.coalesce(F.sum("_n").over(below), F.lit(0))).groupBy(*by).agg(
        F.sum(F.col("_w") + 2 * F.col("_p") * F.col("_b")).alias("_w"), F.sum("_p").alias("n_pos"), F.sum("_n").alias("n_neg")
    )
    pairs = 2.0 * F.col("n_pos") * F.col("n_neg")
    return won.select(*by, "n_pos", "n_neg", F.when(pairs > 0, F.round(F.col("_w") / pairs, 6)).alias("auc"))


def roc_points(df: DataFrame, score: str = "score", label: str = "is_anom") -> DataFrame:
    """False and true positive rate when everything at or above each score is flagged."""
    counts = score_counts(df, score, label, [])
    total = counts.agg(F.sum("_p").alias("_tp"), F.sum("_n").alias("_tn"))
    above = Window.orderBy(F.desc("_s")).rowsBetween(Window.unboundedPreceding, 0)
    got = counts.select(F.col("_s"), F.sum("_p").over(above).alias("_cp"), F.sum("_n").over(above).alias("_cn"))
    return got.crossJoin(F.broadcast(total)).select(F.col("_s").alias("score"), F.round(F.try_divide(F.col("_cn"), F.col("_tn")), 6).alias("fpr"), F.round(F.try_divide(F.col("_cp"), F.col("_tp")), 6).alias("tpr"))


def prefix_auc(df: DataFrame, order: str, at: list[int], score: str = "score", label: str = "is_anom") -> DataFrame:
    """AUC over the rows with ``order`` up to each point."""
    points = df.sparkSession.createDataFrame([(a,) for a in at], "upto int")
    return roc_auc(df.join(F.broadcast(points), F.col(order) <= F.col("upto")), score, label, ["upto"])


def rolling_auc(df: DataFrame, order: str, half: int, step: int, score: str = "score", label: str = "is_anom") -> DataFrame:
    """AUC in windows centre +- half: rows go to the few centres near them by arithmetic, no range join."""
    first, last = F.ceil((F.col(order) - half) / step), F.floor((F.col(order) + half) / step)
    spread = df.withColumn("centre", F.explode(F.sequence(first.cast("long"), last.cast("long")))).withColumn("centre", F.col("centre") * step).where("centre >= 0")
    return roc_auc(spread, score, label, ["centre"])


def run_stats(df: DataFrame, by: list[str], value: str) -> DataFrame:
    v = F.col(value)
    return df.groupBy(*by).agg(
        F.round(F.avg(v), 6).alias("mean"), F.round(F.percentile(v, F.lit(0.5)), 6).alias("median"), F.round(F.stddev(v), 6).alias("std"),
        F.round(F.percentile(v, F.lit(0.75)) - F.percentile(v, F.lit(0.25)), 6).alias("iqr"), F.min(v).alias("lo"), F.max(v).alias("hi"),
    )


def mean_ranks(df: DataFrame, method: str, block: list[str], value: str, higher_is_better: bool = True) -> DataFrame:
    """Mean rank of each method over blocks (data set, run); ties share their mean rank."""
    order = F.desc(value) if higher_is_better else F.asc(value)
    w = Window.partitionBy(*block)
    ranked = df.withColumn("_r", F.rank().over(w.orderBy(order))).withColumn("_t", F.count(F.lit(1)).over(Window.partitionBy(*block, value)))
    return ranked.groupBy(method).agg(F.round(F.avg(F.col("_r") + (F.col("_t") - 1) / 2), 6).alias("mean_rank"), F.count(F.lit(1)).alias("blocks"))


def critical_difference(k: int, n: int) -> float:
    return NEMENYI_Q[k] * math.sqrt(k * (k + 1) / (6 * n))


def nemenyi_pairs(ranks: DataFrame, method: str, k: int) -> DataFrame:
    a, b = ranks.select(F.col(method).alias("a"), F.col("mean_rank").alias("ra"), "blocks"), ranks.select(F.col(method).alias("b"), F.col("mean_rank").alias("rb"))
    cd = F.lit(NEMENYI_Q[k]) * F.sqrt(F.lit(k * (k + 1)) / (6 * F.col("blocks")))
    return a.join(F.broadcast(b), F.col("a") < F.col("b")).select("a", "b", F.round(F.abs(F.col("ra") - F.col("rb")), 6).alias("gap"), F.round(cd, 6).alias("cd"), (F.abs(F.col("ra") - F.col("rb")) > cd).alias("differs"))


def paired_t(df: DataFrame, a: str, b: str) -> DataFrame:
    """Paired t statistic. Digits beyond the twelfth are float noise that depends on the order of rows; they go before the last rounding."""
    d = F.col(a) - F.col(b)
    short = lambda v: F.round(F.round(v, 12), 6)
    return df.agg(F.count(d).alias("n"), short(F.avg(d)).alias("mean_diff"), short(F.try_divide(F.avg(d), F.stddev(d) / F.sqrt(F.count(d)))).alias("t"))


def recall_confusion(df: DataFrame, truth: str, predicted: str) -> DataFrame:
    """Row-normalised confusion matrix in long form."""
    n = df.groupBy(truth, predicted).agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy(truth)), 6))


def micro_macro_recall(df: DataFrame, truth: str, predicted: str) -> DataFrame:
    per = df.groupBy(truth).agg(F.count(F.lit(1)).alias("n"), F.sum((F.col(truth) == F.col(predicted)).cast("long")).alias("hit"))
    return per.agg(F.round(F.sum("hit") / F.sum("n"), 6).alias("micro"), F.round(F.avg(F.col("hit") / F.col("n")), 6).alias("macro"))


def novelty_rates(df: DataFrame, tau: float, score: str = "score", novel: str = "is_novel") -> DataFrame:
    """Share of known rows flagged novel (false alarms) and of novel rows flagged (hits), at or under a threshold."""
    low = (F.col(score) < tau).cast("double")
    known = F.when(F.col(novel) == 0, low)
    return df.agg(F.round(F.avg(known), 6).alias("fpr"), F.round(F.avg(F.when(F.col(novel) == 1, low)), 6).alias("tpr"))


def fpr_decomposition(df: DataFrame, taus: list[float], score: str, correct: str) -> DataFrame:
    """False alarms among known rows, split by whether the closed-set class was right."""
    t = df.sparkSession.createDataFrame([(x,) for x in taus], "tau double")
    low = F.col(score) < F.col("tau")
    return df.join(F.broadcast(t)).groupBy("tau").agg(
        F.round(F.avg((low & (F.col(correct) == 1)).cast("double")), 6).alias("fpr_right"), F.round(F.avg((low & (F.col(correct) == 0)).cast("double")), 6).alias("fpr_wrong")
    )


def models_per_window(budget_bytes: int, value_bytes: int, side: int, omega: int) -> int:
    """How many models a window of side omega can have, all windows under one memory budget."""
    windows = (2 * side // omega - 1) ** 2
    return budget_bytes // (value_bytes * omega**2 * windows)


def expected_collision(d: float, b: int) -> float:
    """Chance that two vectors at distance d fall into the same of b folded branches."""
    return 1 - (b - 1) / b * d


@contextmanager
def timed(into: dict, name: str):
    began = time.perf_counter()
    try:
        yield
    finally:
        into[name] = round(time.perf_counter() - began, 3)
