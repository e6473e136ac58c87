"""Accuracy measures over trials (method, t, n, rep, t_hat)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def relative_error_summary(trials: DataFrame, by: tuple[str, ...] = ("method", "t", "n_set", "n_union")) -> DataFrame:
    """(by..., mre, ci_lo, ci_hi, p95, variance, reps): mean relative error with its 95 % band."""
    err = F.abs(F.col("t_hat") - F.col("t")) / F.col("t")
    got = trials.groupBy(*by).agg(F.avg(err).alias("mre"), F.stddev_samp(err).alias("_sd"), F.percentile_approx(err, 0.95).alias("p95"), F.var_samp("t_hat").alias("variance"), F.count("*").alias("reps"))
    half = 1.96 * F.coalesce("_sd", F.lit(0.0)) / F.sqrt("reps")
    return got.select(*by, "mre", (F.col("mre") - half).alias("ci_lo"), (F.col("mre") + half).alias("ci_hi"), "p95", "variance", "reps")


def usable_range(summary: DataFrame, plateau: float = 2.0**11) -> DataFrame:
    """(method, t, base, first_bad): the mean error of small sets and the first set size whose error is over
    twice that (null: none tried)."""
    w = Window.partitionBy("method", "t")
    base = F.avg(F.when(F.col("n_set") <= plateau, F.col("mre"))).over(w)
    rows = summary.withColumn("base", base)
    return rows.groupBy("method", "t").agg(F.first("base").alias("base"), F.min(F.when(F.col("mre") > 2 * F.col("base"), F.col("n_set"))).alias("first_bad"))


def collision_summary(trials: DataFrame, by: list[str]) -> DataFrame:
    """(by..., mean, variance, reps) of collision counts ``c``."""
    return trials.groupBy(*by).agg(F.avg("c").alias("mean"), F.var_samp("c").alias("variance"), F.count("*").alias("reps"))


def bits_for_error(summary: DataFrame, eps: float) -> DataFrame:
    """(method, t, bits): the smallest size whose mean relative error is at most ``eps``. summary has bits."""
    return summary.groupBy("method", "t").agg(F.min(F.when(F.col("mre") <= eps, F.col("bits"))).alias("bits"))
