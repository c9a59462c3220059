"""Weighted mixtures: moments, quantiles and histograms of the ensemble, and scores against a truth."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def posterior(states: DataFrame, weights: DataFrame, functional: Column | None = None, column: str = "w_fix") -> DataFrame:
    """(cell_id, mean, var, n): weighted moments of a functional of x per cell; the small weights relation meets the states by particle."""
    x = F.col("x") if functional is None else functional
    w = weights.select("particle_id", F.col(column).cast("double").alias("__w"))
    v = states.join(w, "particle_id").select("cell_id", x.alias("v"), "__w")
    agg = v.groupBy("cell_id").agg(F.sum(F.col("v") * F.col("__w")).alias("s1"), F.sum(F.col("v") * F.col("v") * F.col("__w")).alias("s2"), F.sum("__w").alias("s"), F.count(F.lit(1)).alias("n"))
    mean = F.col("s1") / F.col("s")
    return agg.select("cell_id", F.round(mean, 6).alias("mean"), F.round(F.col("s2") / F.col("s") - mean * mean, 6).alias("var"), "n")


def histogram(states: DataFrame, weights: DataFrame, low: float, high: float, bins: int) -> DataFrame:
    """(cell_id, bin, share): weighted histogram; bins 1..n, 0 and n+1 outside."""
    w = weights.select("particle_id", F.col("w_fix").cast("double").alias("__w"))
    v = states.join(w, "particle_id").select("cell_id", F.call_function("width_bucket", F.col("x"), F.lit(low), F.lit(high), F.lit(bins)).alias("bin"), "__w")
    sums = v.groupBy("cell_id", "bin").agg(F.sum("__w").alias("s"))
    return sums.withColumn("share", F.round(F.col("s") / F.sum("s").over(Window.partitionBy("cell_id")), 9)).drop("s")


def accuracy(members: DataFrame, truth: DataFrame) -> DataFrame:
    """(rmse, bias, crps, coverage, n) of equally weighted members (cycle, particle_id, x) against (cycle, truth).

    The CRPS of a cycle is E|X - y| - E|X - X'| / 2, the second term from ranks
    of the sorted members, so no pair of members is formed.
    """
    rank = F.row_number().over(Window.partitionBy("cycle").orderBy("x", "particle_id"))
    m = members.join(F.broadcast(truth), "cycle").withColumn("r", rank)
    size = F.count(F.lit(1))
    one = m.groupBy("cycle").agg(
        size.alias("n"), F.avg("x").alias("mean"), F.first("truth").alias("truth"), F.avg(F.abs(F.col("x") - F.col("truth"))).alias("far"),
        F.sum((2 * F.col("r") - 1) * F.col("x")).alias("gini"), F.sum("x").alias("sx"),
        F.percentile("x", F.lit(0.05)).alias("p05"), F.percentile("x", F.lit(0.95)).alias("p95"),
    )
    crps = F.col("far") - (F.col("gini") / F.col("n") - F.col("sx")) / F.col("n")
    err = F.col("mean") - F.col("truth")
    return one.agg(
        F.sqrt(F.avg(err * err)).alias("rmse"), F.avg(err).alias("bias"), F.avg(crps).alias("crps"),
        F.avg(F.col("truth").between(F.col("p05"), F.col("p95")).cast("double")).alias("coverage"), F.count(F.lit(1)).alias("cycles"),
    )


def rank_histogram(members: DataFrame, truth: DataFrame) -> DataFrame:
    """(rank, n): how many members lie under the truth, over cycles."""
    under = members.join(F.broadcast(truth), "cycle").groupBy("cycle").agg(F.sum((F.col("x") < F.col("truth")).cast("int")).alias("rank"))
    return under.groupBy("rank").agg(F.count(F.lit(1)).alias("n"))
