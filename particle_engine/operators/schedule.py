"""Work schedules in closed form: split factors, load bounds and the static list schedule.

All take the multiset (parent_id, alpha) and a number of runners; integers
only.  The static schedule never expands copies: a parent covers the ordinals
[from, to) and so the runners from*R div P ... (to-1)*R div P.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from particle_engine.functions.scalar import ceil_div, int_div


def multiset(rows: DataFrame, parent: str) -> DataFrame:
    """(parent_id, alpha) of a table's natural multiset; rows without a parent are left out."""
    return rows.where(F.col(parent).isNotNull()).groupBy(F.col(parent).alias("parent_id")).agg(F.count(F.lit(1)).alias("alpha"))


def _with_total(parents: DataFrame) -> DataFrame:
    return parents.crossJoin(F.broadcast(parents.agg(F.coalesce(F.sum("alpha"), F.lit(0)).cast("long").alias("p"))))


def split_factor(parents: DataFrame, runners: int) -> DataFrame:
    """(parent_id, alpha, s): on how many runners a parent should run, ceil(alpha R / P)."""
    return _with_total(parents).select("parent_id", "alpha", ceil_div(F.col("alpha") * F.lit(runners), F.col("p")).alias("s"))


def load_bounds(parents: DataFrame, runners: int) -> DataFrame:
    """(p, q, sum_s, lo, hi): loads of a best schedule lie in [q, q + R - 1]; sum_s is a lower bound where R divides P."""
    s = split_factor(parents, runners)
    out = s.agg(F.coalesce(F.sum("alpha"), F.lit(0)).cast("long").alias("p"), F.count(F.lit(1)).alias("q"), F.coalesce(F.sum("s"), F.lit(0)).cast("long").alias("sum_s"))
    return out.select("p", "q", "sum_s", F.col("q").alias("lo"), F.when(F.col("q") > 0, F.col("q") + F.lit(runners - 1)).otherwise(F.lit(0)).cast("long").alias("hi"))


def ordinals(parents: DataFrame, order: str = "id", ranges: int = 1) -> DataFrame:
    """Adds [from, to), the task ordinals of each parent in schedule order: id, or largest (most copies first)."""
    keys = ["parent_id"] if order == "id" else [F.desc("alpha"), "parent_id"]
    if ranges <= 1 or order != "id":
        to = F.sum("alpha").over(Window.orderBy(*keys).rowsBetween(Window.unboundedPreceding, 0))
        return parents.withColumn("to", to.cast("long")).withColumn("from", (F.col("to") - F.col("alpha")).cast("long"))
    span = parents.agg(F.min("parent_id").alias("a"), F.max("parent_id").alias("b"))
    part = F.least(int_div((F.col("parent_id") - F.col("a")) * F.lit(ranges), F.col("b") - F.col("a") + F.lit(1)), F.lit(ranges - 1))
    w = parents.crossJoin(F.broadcast(span)).withColumn("range_no", part).drop("a", "b")
    sums = w.groupBy("range_no").agg(F.sum("alpha").alias("s"))
    offset = F.coalesce(F.sum("s").over(Window.orderBy("range_no").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    inner = F.sum("alpha").over(Window.partitionBy("range_no").orderBy("parent_id").rowsBetween(Window.unboundedPreceding, 0))
    out = w.withColumn("inner", inner).join(F.broadcast(sums.select("range_no", offset.alias("offset"))), "range_no")
    return out.withColumn("to", (F.col("inner") + F.col("offset")).cast("long")).withColumn("from", (F.col("to") - F.col("alpha")).cast("long")).drop("inner", "offset", "range_no")


def static_schedule(parents: DataFrame, runners: int, order: str = "id", ranges: int = 1) -> DataFrame:
    """(runner_id, parent_id, n): tasks of each parent on each runner; one row is one load, at most q + R - 1 rows."""
    o = _with_total(ordinals(parents, order, ranges))
    r = F.lit(runners)
    first, last = int_div(F.col("from") * r, F.col("p")), int_div((F.col("to") - 1) * r, F.col("p"))
    spread = o.select("parent_id", "from", "to", "p", F.explode(F.sequence(first, last)).alias("runner_id"))
    # ordinal i runs on i R div P, so runner k holds ordinals ceil(k P / R) ... ceil((k + 1) P / R) - 1
    begin, stop = ceil_div(F.col("runner_id") * F.col("p"), r), ceil_div((F.col("runner_id") + 1) * F.col("p"), r)
    n = F.least(F.col("to"), stop) - F.greatest(F.col("from"), begin)
    return spread.select("runner_id", "parent_id", n.cast("long").alias("n"))


def schedule_loads(schedule: DataFrame) -> DataFrame:
    """(loads, tasks, busiest): loads are the distinct (runner, parent) pairs."""
    per = schedule.groupBy("runner_id").agg(F.count(F.lit(1)).alias("l"), F.sum("n").alias("t"))
    return per.agg(F.coalesce(F.sum("l"), F.lit(0)).cast("long").alias("loads"), F.coalesce(F.sum("t"), F.lit(0)).cast("long").alias("tasks"), F.coalesce(F.max("t"), F.lit(0)).cast("long").alias("busiest"))


def best_fit_chunks(alpha: dict[int, int], runners: int) -> dict[int, list[tuple[int, int]]]:
    """Cut-avoiding schedule of a small multiset: whole parents by best fit into chunks of P/R, then the rest is cut.

    Returns runner -> [(parent, n)].  Loads stay within q + R - 1: only the
    parents that fit nowhere whole are cut, each along one sweep over open chunks.
    """
    total = sum(alpha.values())
    room = {k: (k + 1) * total // runners - k * total // runners for k in range(runners)}
    plan: dict[int, list[tuple[int, int]]] = {k: [] for k in range(runners)}
    cut = []
    for q, a in sorted(alpha.items(), key=lambda x: (-x[1], x[0])):
        fitting = [k for k in room if room[k] >= a]
        if fitting:
            k = min(fitting, key=lambda k: (room[k], k))
            plan[k].append((q, a))
            room[k] -= a
        else:
            cut.append((q, a))
    open_chunks = sorted((k for k in room if room[k] > 0), key=lambda k: (-room[k], k))
    for q, a in cut:
        while a:
            k = open_chunks[0]
            n = min(a, room[k])
            plan[k].append((q, n))
            room[k] -= n
            a -= n
            if not room[k]:
                open_chunks.pop(0)
    return plan
