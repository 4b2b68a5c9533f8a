"""When to stop: synchronously, by a master that sums what it has, or by the master and a confirming residual."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def stop_sync(norm: float, tol: float) -> bool:
    return norm < tol


def stop_master(contributions: DataFrame, polls: DataFrame, parts: int, tol: float) -> DataFrame:
    """(t): the first poll at which the parts' latest squared norms sum to less than tol^2; empty if none.

    contributions (p, t, resid_sq) arrive at times t; at each poll (t) the master uses the latest of each part, if all have sent one.
    """
    seen = polls.select(F.col("t").alias("poll")).join(contributions, F.col("t") <= F.col("poll"))
    latest = seen.groupBy("poll", "p").agg(F.max_by("resid_sq", "t").alias("r"))
    sums = latest.groupBy("poll").agg(F.count("*").alias("n"), F.sum("r").alias("r"))
    return sums.where((F.col("n") == parts) & (F.col("r") < tol * tol)).agg(F.min("poll").alias("t")).where("t is not null")


def stop_confirmed(candidates: DataFrame, true_norms: DataFrame, tol: float) -> DataFrame:
    """(t): the first candidate stop whose synchronous residual norm (t, norm) is below tol; earlier ones were false."""
    return candidates.join(true_norms, "t").where(F.col("norm") < tol).agg(F.min("t").alias("t")).where("t is not null")


def residual_drop(trace: DataFrame) -> DataFrame:
    """trace (run_id, k, norm) with the factor against the iteration before."""
    return trace.withColumn("drop", F.col("norm") / F.lag("norm").over(Window.partitionBy("run_id").orderBy("k")))
