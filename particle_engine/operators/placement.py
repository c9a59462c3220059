"""Data placement: ship each parent state to exactly the partitions that need it.

``assign`` turns the offspring multiset into (target_part, parent, n) rows by one of the
strategies; ``ship`` moves parent rows with ``repartitionById``, so at most
q + R - 1 state copies cross the network, and copies are made where they are used.
Strategy ``stay`` is the data form of the cache-aware schedule: a parent's first
copies, up to a partition's fair share, stay where the parent already lives and only
the overflow moves.  ``homes_of`` says where the offspring of a plan live, which the next cycle's
``stay`` needs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from particle_engine.operators.schedule import ordinals, static_schedule

STRATEGIES = ("static", "hash", "stay")
#: A plan is broadcast to the states only up to this size.
BROADCAST_BYTES = 32 << 20
PLAN_ROW_BYTES = 48


def first_homes(states: DataFrame, runners: int, n: int) -> DataFrame:
    """(parent_id, home_part) of an ensemble that has not been placed yet: equal runs of ids."""
    return states.select(F.col("particle_id").alias("parent_id"), F.least(F.expr(f"particle_id * {runners} div {n}"), F.lit(runners - 1)).alias("home_part")).distinct()


def homes_of(plan: DataFrame) -> DataFrame:
    """(parent_id, home_part): where each offspring slot of a plan with slots lives."""
    return plan.select(F.explode(F.sequence("first_slot", F.col("first_slot") + F.col("n") - 1)).alias("parent_id"), F.col("target_part").cast("long").alias("home_part"))


def assign(parents: DataFrame, runners: int, strategy: str = "static", homes: DataFrame | None = None, ranges: int = 1) -> DataFrame:
    """(target_part, parent_id, n). ``homes`` (parent_id, home_part) is needed by ``stay``."""
    if strategy not in STRATEGIES:
        raise ValueError(f"unknown strategy {strategy}; one of {STRATEGIES}")
    if strategy == "static":
        return static_schedule(parents, runners, ranges=ranges).withColumnRenamed("runner_id", "target_part")
    if strategy == "hash":
        return parents.select(F.pmod(F.xxhash64("parent_id"), F.lit(runners)).cast("long").alias("target_part"), "parent_id", F.col("alpha").alias("n"))
    if homes is None:
        raise ValueError("strategy stay needs homes (parent_id, home_part)")
    total = parents.agg(F.sum("alpha").cast("long").alias("p"))
    w = parents.join(homes, "parent_id").crossJoin(F.broadcast(total))
    share = F.expr(f"(home_part + 1) * p div {runners} - home_part * p div {runners}")
    before = F.coalesce(F.sum("alpha").over(Window.partitionBy("home_part").orderBy(F.desc("alpha"), "parent_id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    w = w.withColumn("stay", F.greatest(F.lit(0), F.least(F.col("alpha"), share - before)).cast("long"))
    kept = w.where("stay > 0").select(F.col("home_part").cast("long").alias("target_part"), "parent_id", F.col("stay").alias("n"))
    # free places of partitions and overflowing copies are both cut into ordinals and meet where these overlap
    used = kept.groupBy("target_part").agg(F.sum("n").alias("used"))  # a row a partition
    parts = parents.sparkSession.range(runners).withColumnRenamed("id", "target_part").crossJoin(F.broadcast(total)).join(F.broadcast(used), "target_part", "left")
    free = F.expr(f"(target_part + 1) * p div {runners} - target_part * p div {runners}") - F.coalesce("used", F.lit(0))
    parts = parts.select("target_part", free.alias("alpha")).where("alpha > 0").withColumnRenamed("target_part", "parent_id")
    parts = ordinals(parts).select(F.col("parent_id").alias("target_part"), F.col("from").alias("pa"), F.col("to").alias("pb"))
    over = ordinals(w.where("alpha > stay").select("parent_id", (F.col("alpha") - F.col("stay")).alias("alpha")), ranges=ranges)
    over = over.select("parent_id", F.col("from").alias("oa"), F.col("to").alias("ob"))
    # both sides are dealt over equal cells of the ordinals; a pair meets in the cell where its overlap begins
    cells = lambda d, a, b: d.crossJoin(F.broadcast(total)).withColumn("wide", F.expr(f"greatest(1, p div {runners})")).withColumn("cell", F.explode(F.expr(f"sequence({a} div wide, ({b} - 1) div wide)"))).drop("p")
    moved = cells(over, "oa", "ob").join(cells(parts, "pa", "pb").drop("wide"), "cell").where("oa < pb and pa < ob and cell = greatest(oa, pa) div wide")
    moved = moved.select("target_part", "parent_id", (F.least("ob", "pb") - F.greatest("oa", "pa")).cast("long").alias("n"))
    return kept.unionByName(moved).groupBy("target_part", "parent_id").agg(F.sum("n").cast("long").alias("n"))


def with_slots(assignment: DataFrame, ranges: int = 1) -> DataFrame:
    """Adds ``first_slot`` and ``first_copy``: slots run by parent then partition, so ids do not depend on timing."""
    starts = ordinals(assignment.groupBy("parent_id").agg(F.sum("n").alias("alpha")), ranges=ranges).select("parent_id", "from")
    copy = Window.partitionBy("parent_id").orderBy("target_part").rowsBetween(Window.unboundedPreceding, -1)
    placed = assignment.withColumn("first_copy", F.coalesce(F.sum("n").over(copy), F.lit(0)).cast("long")).join(starts, "parent_id")
    return placed.select("target_part", "parent_id", "n", (F.col("from") + F.col("first_copy")).cast("long").alias("first_slot"), "first_copy")


def ship(states: DataFrame, assignment: DataFrame, runners: int, rows: int | None = None) -> DataFrame:
    """States of the offspring: each parent's rows go once to each partition that needs them and are copied there.

    ``assignment`` is a plan, with slots or without.  It has a row per load (ids only).  If ``rows``, the most loads it
    can have, bound it to a broadcast, states meet it where they are, those not drawn stay
    behind and the only shuffle is the shipping itself; else it meets them by parent id first.
    """
    plan = assignment if "first_slot" in assignment.columns else with_slots(assignment)
    plan = plan.withColumnRenamed("parent_id", "__parent")
    if rows is not None and rows * PLAN_ROW_BYTES <= BROADCAST_BYTES:
        plan = F.broadcast(plan)
    moved = states.join(plan, states["particle_id"] == F.col("__parent")).repartitionById(runners, F.col("target_part").cast("int"))
    copies = moved.withColumn("__i", F.explode(F.sequence(F.lit(0), F.col("n").cast("int") - 1)))
    keep = [c for c in states.columns if c != "particle_id"]
    return copies.select((F.col("first_slot") + F.col("__i")).alias("particle_id"), F.col("__parent").alias("parent_id"), (F.col("first_copy") + F.col("__i")).cast("int").alias("copy_no"), F.col("target_part").cast("int").alias("target_part"), *keep)


def moved_copies(assignment: DataFrame, homes: DataFrame) -> DataFrame:
    """(loads, moved_loads, moved_tasks): loads whose target is not the parent's home."""
    j = assignment.join(homes, "parent_id")
    away = F.col("target_part") != F.col("home_part")
    return j.agg(F.count(F.lit(1)).alias("loads"), F.sum(away.cast("long")).alias("moved_loads"), F.sum(F.when(away, F.col("n")).otherwise(0)).cast("long").alias("moved_tasks"))
