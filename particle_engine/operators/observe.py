"""Observations: up-scaling to model cells, masks, hourly levels, monthly revenue, forcing fields."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from particle_engine.sources.tables import table

EPOCH = "2024-01-01 00:00:00"
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
GROUPS, CELLS = 16, 80


def cycle_of(ts: Column) -> Column:
    """Assimilation cycle: hours since the first hour."""
    return F.floor((F.unix_micros(ts) - F.unix_micros(F.lit(EPOCH).cast("timestamp"))) / F.lit(3_600_000_000)).cast("int")


def cell_of(user_id: Column, event_type: Column) -> Column:
    rank = F.array_position(F.array(*map(F.lit, EVENT_TYPES)), event_type).cast("int") - F.lit(1)
    return (F.pmod(user_id, F.lit(GROUPS)).cast("int") * F.lit(len(EVENT_TYPES)) + rank).cast("int")


def upscale(raw: DataFrame, cycle: Column, cell: Column, value: Column | None = None) -> DataFrame:
    """(cycle, cell_id, n[, mean_value]): fine observations summed to model cells; combined in each task first."""
    measures = [F.count(F.lit(1)).alias("n")] + ([F.avg(value).alias("mean_value")] if value is not None else [])
    return raw.groupBy(cycle.alias("cycle"), cell.alias("cell_id")).agg(*measures)


def grid(spark: SparkSession, cells: int = CELLS) -> DataFrame:
    return spark.range(cells).select(F.col("id").cast("int").alias("cell_id"))


def hourly(events: DataFrame) -> DataFrame:
    """(cycle, n, mean_value): hourly level of the event stream."""
    return events.groupBy(cycle_of(F.col("ts")).alias("cycle")).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 6).alias("mean_value"))


def mask_grid(events: DataFrame, cycles: int = 48) -> DataFrame:
    """(cycle, cell_id, n, mask) on the whole grid of the first ``cycles`` hours; a cell without events is clear."""
    spark = events.sparkSession
    cycle = cycle_of(F.col("ts"))
    # the time bound is on the column itself, so it reaches the scan
    first = events.where(F.col("ts") < F.expr(f"timestamp '{EPOCH}' + interval {cycles} hours")).where(cycle.between(0, cycles - 1))
    seen = upscale(first, cycle, cell_of(F.col("user_id"), F.col("event_type")))
    every = spark.range(cycles).select(F.col("id").cast("int").alias("cycle")).crossJoin(F.broadcast(grid(spark)))
    out = every.join(seen, ["cycle", "cell_id"], "left").select("cycle", "cell_id", F.coalesce("n", F.lit(0)).cast("long").alias("n"))
    return out.withColumn("mask", F.col("n") > 0)


def upscaled_mask(events: DataFrame, factor: int = 5, cycles: int = 48) -> DataFrame:
    """(cycle, super_cell, share, mask): the fine mask averaged over blocks of cells and cut at one half of a cell."""
    fine = mask_grid(events, cycles)
    block = F.floor(F.col("cell_id") / factor).cast("int")
    return fine.groupBy("cycle", block.alias("super_cell")).agg(F.sum(F.col("mask").cast("int")).cast("long").alias("hits")).withColumn("mask", F.col("hits") * 2 >= factor)


def forcing(events: DataFrame, hours: int = 3) -> DataFrame:
    """(forcing_cycle, value): boundary values refreshed every ``hours``."""
    slot = F.floor(cycle_of(F.col("ts")) / hours).cast("int") * hours
    return events.groupBy(slot.cast("int").alias("forcing_cycle")).agg(F.round(F.avg("value"), 6).alias("value"))


def forcing_asof(events: DataFrame, hours: int = 3) -> DataFrame:
    """(cycle, forcing_cycle, value): each observed hour with the latest boundary value at or before it.

    As-of join as one sorted union: forcing rows come before observation rows of
    the same hour, and the last forcing seen is carried forward.  Days are the
    window's partitions; a day that starts before its first forcing takes the
    last one of earlier days from a table of one row per day.
    """
    cyc = events.select(cycle_of(F.col("ts")).alias("cycle")).distinct()
    force = forcing(events, hours)
    day = lambda c: F.floor(c / F.lit(24)).cast("int")
    both = cyc.select("cycle", F.lit(1).alias("kind"), F.lit(None).cast("struct<forcing_cycle:int,value:double>").alias("f")).unionByName(
        force.select(F.col("forcing_cycle").alias("cycle"), F.lit(0).alias("kind"), F.struct("forcing_cycle", "value").alias("f"))
    )
    both = both.withColumn("day", day(F.col("cycle")))
    carried = F.last("f", ignorenulls=True).over(Window.partitionBy("day").orderBy("cycle", "kind").rowsBetween(Window.unboundedPreceding, 0))
    last = force.groupBy(day(F.col("forcing_cycle")).alias("day")).agg(F.max(F.struct("forcing_cycle", "value")).alias("last"))
    before = F.max("last").over(Window.partitionBy(F.lit(0)).orderBy("day").rowsBetween(Window.unboundedPreceding, -1))
    days = both.select("day").distinct().join(last, "day", "left").select("day", before.alias("earlier"))  # one row a day
    filled = both.withColumn("g", carried).where("kind = 1").join(F.broadcast(days), "day").select("cycle", F.coalesce("g", "earlier").alias("g"))
    return filled.select("cycle", F.col("g.forcing_cycle").alias("forcing_cycle"), F.col("g.value").alias("value"))


def nation_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(month, nation, revenue): summed in hundredths of cents, so exact in any order; orders and lineitem meet by order key."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.date_format(F.trunc("o_orderdate", "month"), "yyyy-MM-dd").alias("month"))
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", (F.round(F.col("l_extendedprice") * 100).cast("long") * F.round((1 - F.col("l_discount")) * 100).cast("long")).alias("r"))
    per_order = lines.groupBy("l_orderkey").agg(F.sum("r").alias("r"))
    joined = per_order.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    return joined.groupBy("month", F.col("c_nationkey").alias("nation")).agg((F.sum("r") / F.lit(10000.0)).alias("revenue"))
