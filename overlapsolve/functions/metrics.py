"""Measures: contraction, norms, detection, histograms, speed-up and cost, and the tests of the theory's premises."""

from __future__ import annotations

from math import pi

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from overlapsolve.session import checkpoint, discard


def contraction(r0: Column, rf: Column, iterations: Column) -> Column:
    """Mean factor of the residual norm an iteration."""
    return F.pow(rf / r0, F.lit(1.0) / iterations)


def contraction_time(r0: Column, rf: Column, seconds: Column, tau_sync: Column) -> Column:
    """The same for runs without common iterations: time is counted in synchronous iterations of tau_sync seconds."""
    return F.pow(rf / r0, tau_sync / seconds)


def solve_time(trace: DataFrame) -> DataFrame:
    """(run_id, seconds): from the common start to the last stop; setup isn't in the trace."""
    return trace.groupBy("run_id").agg((F.max("t1") - F.min("t0")).alias("seconds"))


def iteration_histogram(trace: DataFrame, width: int) -> DataFrame:
    """(low, parts): parts by their number of local iterations, in bins of `width`; trace has a row for each local iteration."""
    counts = trace.groupBy("run_id", "p").agg(F.count("*").alias("n"))
    return counts.groupBy("run_id", (F.floor(F.col("n") / width) * width).cast("long").alias("low")).agg(F.count("*").alias("parts"))


def poll_ratio(polls: DataFrame) -> DataFrame:
    """(run_id, ratio): performed coarse solves over attempted ones."""
    return polls.groupBy("run_id").agg((F.sum(F.col("performed").cast("double")) / F.count("*")).alias("ratio"))


def speedup(times: DataFrame) -> DataFrame:
    """(workload, P, sync, async, speedup) from (workload, mode, P, seconds), the mean over repeated runs."""
    wide = times.groupBy("workload", "P").pivot("mode", ["sync", "async"]).agg(F.avg("seconds"))
    return wide.withColumn("speedup", F.col("sync") / F.col("async"))


def crossover(times: DataFrame) -> DataFrame:
    """(workload, P): the smallest P from which on the asynchronous run is always the faster one; null if it never is."""
    s = speedup(times)
    last_loss = F.max(F.when(F.col("speedup") <= 1, F.col("P"))).over(Window.partitionBy("workload"))
    wins = s.withColumn("loss", last_loss).where(F.col("loss").isNull() | (F.col("P") > F.col("loss")))
    return s.select("workload").distinct().join(wins.groupBy("workload").agg(F.min("P").alias("P")), "workload", "left")


def detection_gap(detected: DataFrame, true: DataFrame) -> DataFrame:
    """(run_id, gap): true norm minus the one that the detector saw."""
    return detected.join(true, "run_id").select("run_id", (F.col("true_norm") - F.col("seen_norm")).alias("gap"))


def weighted_norm(w: DataFrame, weights: DataFrame) -> DataFrame:
    """(norm): the largest of the parts' 2-norms over their weights, from (p, i, x) and (p, wt)."""
    each = w.groupBy("p").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("n"))
    return each.join(weights, "p").agg(F.max(F.col("n") / F.col("wt")).alias("norm"))


def error_norms(u: DataFrame, d: int, n: int) -> DataFrame:
    """(max_error, l2_error) against the product of sines at the lattice nodes."""
    exact = F.lit(1.0)
    for k in range(d):
        exact = exact * F.sin(F.lit(pi / (n + 1)) * (F.pmod(F.floor(F.col("i") / F.lit(n ** (d - 1 - k))), F.lit(n)) + 1))
    e = u.select((F.col("x") - exact).alias("e"))
    return e.agg(F.max(F.abs("e")).alias("max_error"), F.sqrt(F.avg(F.col("e") * F.col("e"))).alias("l2_error"))


def is_m_matrix(entries: DataFrame) -> bool:
    """The sufficient test: positive diagonal, no positive entry off it, weakly dominant rows, and from every row a path to a strictly dominant one."""
    rows = entries.groupBy("i").agg(F.sum(F.when(F.col("i") == F.col("j"), F.col("a")).otherwise(0.0)).alias("d"), F.sum("a").alias("s"), F.max(F.when(F.col("i") != F.col("j"), F.col("a"))).alias("off"))
    rows = checkpoint(rows)
    slack = F.lit(1e-12) * F.col("d")
    if not rows.where((F.col("d") <= 0) | (F.col("off") > slack) | (F.col("s") < -slack)).isEmpty():
        return False
    good = rows.where(F.col("s") > slack).select("i")
    total = rows.count()
    edges = checkpoint(entries.where("i <> j and a < 0").select("i", "j"))
    # A row without such a path lies in a part of the graph that none of the good ones can be reached from. Marks are passed back
    # along entries until none is new; only the newest ones are passed on.
    found, front, left = checkpoint(good), checkpoint(good), total - good.count()
    while left:
        back = edges.join(front.withColumnRenamed("i", "j"), "j").select("i").distinct()
        new = checkpoint(back.join(found, "i", "left_anti"))
        n = new.count()
        if not n:
            return False
        left -= n
        merged = checkpoint(found.union(new))
        discard(found, front)
        found, front = merged, new
    return True


def contraction_constant(a: np.ndarray, sets: list[tuple[np.ndarray, np.ndarray]], weights: np.ndarray) -> float:
    """Norm of the one-level error map in the weighted max norm, for a small dense system; below 1 if the theory's premise holds.

    sets: (node indices, owned mask) of each part; weights: a positive vector.
    """
    n = len(a)
    m = np.zeros((n, n))
    for s, own in sets:
        m[np.ix_(s[own], s)] = np.linalg.inv(a[np.ix_(s, s)])[own]
    return float(((np.abs(np.eye(n) - m @ a) @ weights) / weights).max())


def cost_report(stamps: DataFrame, routes: DataFrame) -> DataFrame:
    """(updates, mean_age, max_age, bytes): what a schedule moves, at 8 bytes a shared value."""
    width = routes.groupBy(F.col("src").alias("q"), F.col("dst").alias("p")).agg(F.count("*").alias("width"))
    return stamps.join(width, ["p", "q"]).agg(F.count("*").alias("updates"), F.avg(F.col("n") - F.col("tau")).alias("mean_age"), F.max(F.col("n") - F.col("tau")).alias("max_age"), F.sum(8 * F.col("width")).alias("bytes"))


def group_report(trace: DataFrame, keys: list[str], how: str = "cube") -> DataFrame:
    """Runs, mean seconds and best residual by `keys`: cube, rollup or plain sets."""
    grouped = {"cube": trace.cube, "rollup": trace.rollup, "sets": trace.groupBy}[how](*keys)
    return grouped.agg(F.count("*").alias("runs"), F.avg("seconds").alias("seconds"), F.min("r_final").alias("r_final"))
