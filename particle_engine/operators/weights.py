"""Scores: likelihood kernels, weight recursion, normalisation, evidence, degeneracy.

Everything after the kernels works on (particle_id, log_w | w_fix) rows only; no
plan here reads a state column once the scores exist.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

FIX_BITS = 30


def mask_of(x: Column, threshold: float = 0.5) -> Column:
    return x >= F.lit(threshold)


def log_kernel(kind: str, predicted: Column, y: Column, scale: float) -> Column:
    """Log-likelihood of one cell: gaussian, cauchy (rational) or mask (disagreement costs log((1-scale)/scale))."""
    if kind == "gaussian":
        r = (y - predicted) / F.lit(scale)
        return F.lit(-0.5) * r * r
    if kind == "cauchy":
        r = (y - predicted) / F.lit(scale)
        return -F.log(F.lit(1.0) + r * r)
    if kind == "mask":
        return F.when(predicted.eqNullSafe(y), F.lit(0.0)).otherwise(F.log(F.lit(scale / (1 - scale))))
    raise ValueError(f"unknown kernel {kind}")


def log_likelihood(states: DataFrame, obs: DataFrame, kind: str, scale: float, predicted: Column | None = None, broadcast_obs: bool = True) -> DataFrame:
    """(particle_id, log_w): cells without an observation add nothing; a particle without any gets 0.

    The observation of a cycle is small next to a state and is broadcast; pass
    ``broadcast_obs=False`` where its size is not known to be.
    """
    y = obs.select("cell_id", F.col("y").alias("__y"))
    joined = states.join(F.broadcast(y) if broadcast_obs else y, "cell_id", "left")
    h = F.col("x") if predicted is None else predicted
    ll = F.when(F.col("__y").isNotNull(), log_kernel(kind, h, F.col("__y"), scale)).otherwise(F.lit(0.0))
    return joined.groupBy("particle_id").agg(F.sum(ll).alias("log_w"))


def mask_mismatches(states: DataFrame, obs: DataFrame, threshold: float = 0.5, broadcast_obs: bool = True) -> DataFrame:
    """(particle_id, mismatches): cells whose mask differs from the observed one; ``broadcast_obs`` as in ``log_likelihood``."""
    mask = obs.select("cell_id", "mask")
    joined = states.join(F.broadcast(mask) if broadcast_obs else mask, "cell_id")
    return joined.groupBy("particle_id").agg(F.sum((mask_of(F.col("x"), threshold) != F.col("mask")).cast("int")).cast("long").alias("mismatches"))


def mask_weights(mismatches: DataFrame, bits: int = FIX_BITS, odds: int = 1) -> DataFrame:
    """(particle_id, mismatches, w_fix): integer weight 2^(bits - odds x excess mismatches), 0 past the last bit.

    A cell is wrong with probability 1 / (1 + 2^odds), so integers hold the likelihood ratio exactly.
    """
    least = mismatches.agg(F.min("mismatches").alias("least"))
    e = F.lit(bits) - F.lit(odds) * (F.col("mismatches") - F.col("least"))
    joined = mismatches.crossJoin(F.broadcast(least))
    return joined.select("particle_id", "mismatches", F.when(e >= 0, F.call_function("shiftleft", F.lit(1).cast("long"), e.cast("int"))).otherwise(F.lit(0)).cast("long").alias("w_fix"))


def fix_weights(scores: DataFrame, bits: int = FIX_BITS) -> DataFrame:
    """(particle_id, log_w, w_fix): floor(2^bits exp(log_w - max)); null or NaN scores weigh 0.

    Integer weights make every later sum exact in any order, so any partitioning
    draws the same offspring.
    """
    fine = F.when(F.col("log_w").isNotNull() & ~F.isnan("log_w"), F.col("log_w"))
    top = scores.agg(F.max(fine).alias("top"))
    w = F.floor(F.exp(fine - F.col("top")) * F.lit(float(1 << bits))).cast("long")
    return scores.crossJoin(F.broadcast(top)).select("particle_id", "log_w", F.coalesce(F.when(F.col("top").isNull(), F.raise_error(F.lit("no particle has a score")).cast("long")).otherwise(w), F.lit(0)).cast("long").alias("w_fix"))


def update_weights(previous: DataFrame, scores: DataFrame) -> DataFrame:
    """Recursion without a redraw: log weights add; needs the previous weights of the same particles."""
    return previous.select("particle_id", F.col("log_w").alias("__p")).join(scores, "particle_id").select("particle_id", (F.col("__p") + F.col("log_w")).alias("log_w"))


def normalise(weights: DataFrame, column: str = "w_fix") -> DataFrame:
    """Adds ``w_hat``, the share of the total; the total is a one-row aggregate joined back, not a window."""
    total = weights.agg(F.sum(column).alias("__total"))
    return weights.crossJoin(F.broadcast(total)).withColumn("w_hat", F.col(column).cast("double") / F.col("__total")).drop("__total")


def cumulative_evidence(evidences: DataFrame) -> DataFrame:
    """(cycle, log_evidence, total): evidence so far, from one row a cycle."""
    total = F.round(F.sum("log_evidence").over(Window.orderBy("cycle").rowsBetween(Window.unboundedPreceding, 0)), 6)
    return evidences.select("cycle", "log_evidence", total.alias("total"))


def evidence(scores: DataFrame) -> DataFrame:
    """(log_evidence): log of the mean likelihood, two aggregates over scores.

    Kernels leave out the constants that all particles share (a Gaussian's 1 / (scale sqrt(2 pi)) per cell), so
    evidences compare runs over the same observations and scale only.
    """
    top = scores.agg(F.max("log_w").alias("top"))
    mean = scores.crossJoin(F.broadcast(top)).agg(F.avg(F.exp(F.col("log_w") - F.col("top"))).alias("m"), F.first("top").alias("top"))
    return mean.select((F.col("top") + F.log("m")).alias("log_evidence"))


def degeneracy(weights: DataFrame, column: str = "w_fix") -> DataFrame:
    """(n, max_w, ess, weight_var, underflow_share) of one cycle, one scan."""
    w = F.col(column).cast("double")
    s = weights.agg(F.count(F.lit(1)).alias("n"), F.max(w).alias("mx"), F.sum(w).alias("s"), F.sum(w * w).alias("s2"), F.sum((F.col(column) == 0).cast("int")).alias("z"))
    return s.select(
        "n", F.round(F.col("mx") / F.col("s"), 9).alias("max_w"), F.round(F.col("s") * F.col("s") / F.col("s2"), 6).alias("ess"),
        F.round(F.col("s2") / (F.col("s") * F.col("s")) / F.col("n") - F.lit(1.0) / (F.col("n") * F.col("n")), 12).alias("weight_var"), F.round(F.col("z") / F.col("n"), 9).alias("underflow_share"),
    )


def summary(weights: DataFrame, bits: int = FIX_BITS) -> DataFrame:
    """``degeneracy`` and ``evidence`` of (log_w, w_fix) rows in one aggregate; the evidence comes from the scaled integers."""
    w = F.col("w_fix").cast("double")
    s = weights.agg(F.count(F.lit(1)).alias("n"), F.max(w).alias("mx"), F.sum(w).alias("s"), F.sum(w * w).alias("s2"), F.sum((F.col("w_fix") == 0).cast("int")).alias("z"), F.max("log_w").alias("top"))
    return s.select(
        "n", (F.col("mx") / F.col("s")).alias("max_w"), (F.col("s") * F.col("s") / F.col("s2")).alias("ess"),
        (F.col("s2") / (F.col("s") * F.col("s")) / F.col("n") - F.lit(1.0) / (F.col("n") * F.col("n"))).alias("weight_var"),
        (F.col("z") / F.col("n")).alias("underflow_share"), (F.col("top") + F.log(F.col("s") / F.lit(float(1 << bits)) / F.col("n"))).alias("log_evidence"),
    )
