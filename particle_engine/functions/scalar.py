"""Column expressions shared by the filter: clamps, log-sum-exp, effective size, weighted moments, SQL macros."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def clamp01(x: Column) -> Column:
    return F.least(F.greatest(x, F.lit(0.0)), F.lit(1.0))


def int_div(a: Column, b: Column) -> Column:
    """Integer quotient (truncated), exact for longs and decimals."""
    return F.call_function("div", a, b)


def ceil_div(a: Column, b: Column | int) -> Column:
    """Integer ceiling of a non-negative quotient."""
    b = b if isinstance(b, Column) else F.lit(b)
    return int_div(a + b - F.lit(1), b)


def log_sum_exp(df: DataFrame, column: str, keys: list[str]) -> DataFrame:
    """(keys, lse): two hash aggregates, no window over all rows."""
    top = df.groupBy(*keys).agg(F.max(column).alias("__top"))
    joined = df.join(F.broadcast(top), keys) if keys else df.crossJoin(F.broadcast(top))
    return joined.groupBy(*keys, "__top").agg(F.sum(F.exp(F.col(column) - F.col("__top"))).alias("__s")).select(*keys, (F.col("__top") + F.log("__s")).alias("lse"))


def ess(weight: Column) -> Column:
    """Effective number of equal weights: (sum w)^2 / sum w^2."""
    return F.sum(weight) * F.sum(weight) / F.sum(weight * weight)


def weighted_mean(x: Column, w: Column) -> Column:
    return F.sum(x * w) / F.sum(w)


def weighted_var(x: Column, w: Column) -> Column:
    return F.sum(x * x * w) / F.sum(w) - weighted_mean(x, w) * weighted_mean(x, w)


def weighted_quantile(df: DataFrame, x: str, w: str, q: float, keys: list[str]) -> DataFrame:
    """(keys, quantile): smallest x whose running weight reaches q of the total, exact."""
    part = Window.partitionBy(*keys)
    running = F.sum(w).over(part.orderBy(x).rangeBetween(Window.unboundedPreceding, 0))
    return df.withColumn("__r", running).withColumn("__t", F.sum(w).over(part)).where(F.col("__r") >= q * F.col("__t")).groupBy(*keys).agg(F.min(x).alias("quantile"))


def register_sql(spark: SparkSession) -> None:
    """SQL functions of the engine, without Python: ``unit_hash`` (52-bit uniform integer), ``uniform_hash`` and ``clamp01``."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION unit_hash(seed BIGINT, cycle BIGINT, pid BIGINT, cell BIGINT) RETURNS BIGINT RETURN CAST(conv(substr(md5(concat_ws('|', seed, cycle, pid, cell)), 1, 13), 16, 10) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION uniform_hash(seed BIGINT, cycle BIGINT, pid BIGINT, cell BIGINT) RETURNS DOUBLE RETURN CAST(conv(substr(md5(concat_ws('|', seed, cycle, pid, cell)), 1, 13), 16, 10) AS BIGINT) / 4503599627370496D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION clamp01(x DOUBLE) RETURNS DOUBLE RETURN least(greatest(x, 0D), 1D)")
    spark.udtf.register("offspring_slots", OffspringSlots)


@F.udtf(returnType="copy_no: int")
class OffspringSlots:
    """``offspring_slots(alpha)``: one row per copy. ``explode(sequence(...))`` does the same in the JVM and is what the engine uses."""

    def eval(self, alpha: int) -> Iterator[tuple[int]]:
        for i in range(alpha or 0):
            yield (i,)


def log_sum_exp_udf():
    """Grouped-aggregate form of log-sum-exp, for ad-hoc use."""

    @F.pandas_udf("double")
    def udf(x: pd.Series) -> float:
        top = x.max()
        return float(top + math.log(sum(math.exp(v - top) for v in x)))

    return udf


def weighted_quantile_udf(q: float):
    """Grouped-aggregate weighted quantile: a pandas UDF of (x, w)."""

    @F.pandas_udf("double")
    def udf(x: pd.Series, w: pd.Series) -> float:
        order = x.argsort(kind="stable")
        run = w.iloc[order].cumsum()
        return float(x.iloc[order].iloc[int((run >= q * w.sum()).to_numpy().argmax())])

    return udf
