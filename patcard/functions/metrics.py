"""Accuracy and cost measures over DataFrames of estimates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def q_error(est: Column, truth: Column) -> Column:
    """The factor between estimate and truth, both at least 1."""
    e, t = F.greatest(est.cast("double"), F.lit(1.0)), F.greatest(truth.cast("double"), F.lit(1.0))
    return F.greatest(e / t, t / e)


def bias_ratio(est: Column, truth: Column) -> Column:
    """Below 1: under-estimation."""
    return F.greatest(est.cast("double"), F.lit(1.0)) / F.greatest(truth.cast("double"), F.lit(1.0))


def summarise(rows: DataFrame, *by: str) -> DataFrame:
    q = q_error(F.col("est"), F.col("truth"))
    return rows.groupBy(*by).agg(F.avg(q).alias("q_mean"), F.coalesce(F.stddev_samp(q), F.lit(0.0)).alias("q_std"), F.avg((F.col("est") == 0).cast("double")).alias("zero_rate"), F.avg(bias_ratio(F.col("est"), F.col("truth"))).alias("bias"))


def box_stats(rows: DataFrame, *by: str) -> DataFrame:
    """Quartiles of the q-error, and the outermost values within one and a half times their distance."""
    q = rows.withColumn("q", q_error(F.col("est"), F.col("truth")))
    boxes = q.groupBy(*by).agg(*[F.percentile("q", F.lit(p)).alias(n) for p, n in ((0.25, "q1"), (0.5, "median"), (0.75, "q3"))])
    inside = q.join(boxes, list(by)) if by else q.crossJoin(boxes)
    span = 1.5 * (F.col("q3") - F.col("q1"))
    inside = inside.where((F.col("q") >= F.col("q1") - span) & (F.col("q") <= F.col("q3") + span))
    return inside.groupBy(*by, "q1", "median", "q3").agg(F.min("q").alias("low"), F.max("q").alias("high"))


def zero_rate(rows: DataFrame, *by: str) -> DataFrame:
    return rows.groupBy(*by).agg(F.avg((F.col("est") == 0).cast("double")).alias("zero_rate"))


def bias_test(runs: DataFrame, truth: float) -> DataFrame:
    """(mean, se, z): how far the mean of the trials lies from the truth, in standard errors."""
    m, se = F.avg("est"), F.stddev_samp("est") / F.sqrt(F.count("*"))
    return runs.agg(m.alias("mean"), se.alias("se"), F.when(se > 0, (m - truth) / se).otherwise(0.0).alias("z"))


def exclude_timeouts(rows: DataFrame, limit_s: float, *by: str) -> DataFrame:
    """Without the methods that took longer than the limit anywhere in their group."""
    slow = rows.where(F.col("seconds") > limit_s).select("method", *by).distinct()
    return rows.join(slow, ["method", *by], "left_anti")
