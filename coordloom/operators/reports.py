"""Measures over training reports: speed-ups, reductions, status counts. A report has (variant, workers, epochs, seconds, status, objective)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def speedup(report: DataFrame, baseline: str, keys: tuple[str, ...] = ("workers",)) -> DataFrame:
    """Seconds of the baseline over seconds of each variant at the same keys."""
    base = report.filter(F.col("variant") == baseline).select(*keys, F.col("seconds").alias("_base"))
    return report.join(base, list(keys)).withColumn("speedup", F.col("_base") / F.col("seconds")).drop("_base")


def best_valid(report: DataFrame, prefix: str = "lock-free") -> DataFrame:
    """The fastest run of a kind that reached a right solution: what the others are compared with."""
    return report.filter(F.col("variant").startswith(prefix) & (F.col("status") == "converged")).agg(F.min_by("variant", "seconds").alias("variant"), F.min("seconds").alias("seconds"))


def reduction(report: DataFrame, base: str, variant: str, column: str) -> DataFrame:
    """Mean over workers of 1 - variant / base, in percent."""
    wide = report.groupBy("workers").agg(F.max(F.when(F.col("variant") == base, F.col(column))).alias("b"), F.max(F.when(F.col("variant") == variant, F.col(column))).alias("v"))
    return wide.agg(F.avg(100 * (1 - F.col("v") / F.col("b"))).alias("percent"))


def status_counts(report: DataFrame) -> DataFrame:
    return report.groupBy("status").agg(F.count("*").alias("n"))


def scaling_efficiency(report: DataFrame) -> DataFrame:
    """Speed-up over the run with one worker, and that divided by the workers."""
    one = report.filter("workers = 1").agg(F.first("seconds_per_epoch").alias("_one"))  # one row
    with_base = report.join(F.broadcast(one))
    return with_base.withColumn("speedup", F.col("_one") / F.col("seconds_per_epoch")).withColumn("efficiency", F.col("speedup") / F.col("workers")).drop("_one")


def mean_speedup(speedups: DataFrame) -> DataFrame:
    """Arithmetic mean over data sets and machines."""
    return speedups.groupBy("against").agg(F.round(F.avg("speedup"), 2).alias("mean"), F.max("speedup").alias("best"))


#: Published speed-ups by data set, machine X then P.
PUBLISHED = {"lock-free": (4.1, 6.8, 3.4, 2.3, 11.8, 1.9), "best library": (20.3, 4.4, 7.3, 30.7, 4.1, 41.7)}
