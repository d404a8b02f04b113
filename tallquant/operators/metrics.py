"""Accuracy and cost measures over the table of fits (a parameter grid, small)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MEASURES = ("objective", "l2", "l1", "linf")


def rel_errors(fits: DataFrame, reference: DataFrame) -> DataFrame:
    """Relative error of the loss and of the coefficients in three norms; absolute where the reference is zero.

    ``reference(tau, beta_ref, f_ref)``; coefficients that were not estimable
    count as zero.
    """
    both = fits.join(F.broadcast(reference), "tau")
    gap = F.zip_with("beta", "beta_ref", lambda a, b: F.abs(F.coalesce(F.nanvl(a, F.lit(0.0)), F.lit(0.0)) - b))
    size = F.transform("beta_ref", lambda v: F.abs(v))
    add = lambda x, f: F.aggregate(x, F.lit(0.0), lambda s, v: s + f(v))

    def ratio(a, b):
        return F.when(b > 0, a / b).otherwise(a)

    return both.select(
        "method", "s", "trial", "tau",
        ratio(F.abs(F.col("objective") - F.col("f_ref")), F.abs(F.col("f_ref"))).alias("objective"),
        ratio(F.sqrt(add(gap, lambda v: v * v)), F.sqrt(add(size, lambda v: v * v))).alias("l2"),
        ratio(add(gap, lambda v: v), add(size, lambda v: v)).alias("l1"),
        ratio(F.array_max(gap), F.array_max(size)).alias("linf"),
    )


def long_errors(errors: DataFrame) -> DataFrame:
    return errors.unpivot(["method", "s", "trial", "tau"], list(MEASURES), "measure", "error")


def error_quartiles(errors: DataFrame, fail_above: float = 100.0) -> DataFrame:
    """First quartile, median and third quartile over trials (linear interpolation), and failed trials."""
    return long_errors(errors).groupBy("method", "s", "tau", "measure").agg(
        F.percentile("error", 0.25).alias("q1"), F.percentile("error", 0.5).alias("median"), F.percentile("error", 0.75).alias("q3"),
        F.count("*").alias("n_trials"), F.count(F.when(F.col("error") > fail_above, 1)).alias("n_failed"),
    )


def digits(quartiles: DataFrame) -> DataFrame:
    """Digits of accuracy of the third quartile."""
    return quartiles.withColumn("digits", F.when(F.col("q3") > 0, F.floor(-F.log10("q3"))).otherwise(F.lit(16)))


def rows_for_digits(quartiles: DataFrame, wanted: int) -> DataFrame:
    """Smallest sample size whose third quartile has that many digits."""
    return quartiles.where(F.col("q3") <= 10.0**-wanted).groupBy("method", "tau", "measure").agg(F.min("s").alias("least_s"))


def success_rate(fits: DataFrame, reference: DataFrame, eps: float) -> DataFrame:
    """Share of trials whose full loss is within the guarantee."""
    ok = F.col("objective") <= (1 + eps) / (1 - eps) * F.col("f_ref")
    return fits.join(F.broadcast(reference), "tau").groupBy("method", "s", "tau").agg(F.avg(ok.cast("double")).alias("success"))


def kept_report(fits: DataFrame) -> DataFrame:
    """Rows kept against the size asked for."""
    return fits.groupBy("method", "s").agg(F.avg("rows_kept").alias("mean_rows"), (F.avg("rows_kept") / F.first("s")).alias("share_of_s"))


def inside_interval(quartiles: DataFrame, intervals: DataFrame) -> DataFrame:
    """Coefficient quartiles against confidence intervals: inside, and the distance outside."""
    j = quartiles.join(intervals, (quartiles["tau"] == intervals["tau"]) & (quartiles["j"] == intervals["j"])).drop(intervals["tau"]).drop(intervals["j"])
    out = F.greatest(F.lit(0.0), F.col("lo") - F.col("q1"), F.col("q3") - F.col("hi"))
    return j.withColumn("outside", out).withColumn("median_inside", F.col("median_fit").between(F.col("lo"), F.col("hi")))
