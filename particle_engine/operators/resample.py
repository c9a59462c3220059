"""Redraws of an ensemble from integer weights: systematic, stratified, residual, multinomial, and conditional policies.

All schemes work on integer prefix sums in particle order, so the same weights
and key give the same offspring in any partitioning.  Positions are integers in
[0, W), W the total weight.  With ``ranges`` of 1 the prefix sum is one sorted window (a
particle is 16 bytes here, never its state); with more it runs in two phases over ranges of ids, and
positions are looked up in as many ranges of [0, W).  ``run_filter`` takes one range
for every ``ONE_TASK`` particles.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from particle_engine.functions.rng import normal4, unit_int
from particle_engine.functions.scalar import int_div
from particle_engine.operators.schedule import ordinals

SCHEMES = ("systematic", "stratified", "residual", "multinomial")
ONE_TASK = 5_000_000
BIG = "decimal(38,0)"


def prefix_sums(weights: DataFrame, column: str = "w_fix", ranges: int = 1) -> DataFrame:
    """Adds hi, lo = hi - w and total W (decimals). ``ranges`` > 1 sums id ranges apart and adds a small table of offsets."""
    w = weights.withColumn("w_fix", F.col(column).cast(BIG))
    total = w.agg(F.sum("w_fix").cast(BIG).alias("total"))
    if ranges <= 1:
        hi = F.sum("w_fix").over(Window.orderBy("particle_id").rowsBetween(Window.unboundedPreceding, 0)).cast(BIG)
        out = w.withColumn("hi", hi)
    else:
        span = w.agg(F.min("particle_id").alias("a"), F.max("particle_id").alias("b"))
        part = F.least(int_div((F.col("particle_id") - F.col("a")) * F.lit(ranges), F.col("b") - F.col("a") + F.lit(1)), F.lit(ranges - 1))
        w = w.crossJoin(F.broadcast(span)).withColumn("range_no", part).drop("a", "b")
        sums = w.groupBy("range_no").agg(F.sum("w_fix").cast(BIG).alias("s"))
        offset = F.coalesce(F.sum("s").over(Window.orderBy("range_no").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast(BIG)
        sums = sums.select("range_no", offset.alias("offset"))  # one row a range
        inner = F.sum("w_fix").over(Window.partitionBy("range_no").orderBy("particle_id").rowsBetween(Window.unboundedPreceding, 0))
        out = w.withColumn("inner", inner).join(F.broadcast(sums), "range_no").withColumn("hi", (F.col("inner") + F.col("offset")).cast(BIG)).drop("inner", "offset", "range_no")
    return out.withColumn("lo", (F.col("hi") - F.col("w_fix")).cast(BIG)).crossJoin(F.broadcast(total))


def _position(seed: int, cycle: Column | int, draw: Column | int, width: Column) -> Column:
    """Integer position in [0, width) from a 52-bit draw: floor(h * width / 2^52)."""
    return int_div(unit_int(seed, cycle, -1, draw).cast("decimal(20,0)") * width.cast("decimal(18,0)"), F.lit(1 << 52).cast("decimal(20,0)"))


def systematic(weights: DataFrame, n: int, seed: int, cycle: int, ranges: int = 1, offset: int | None = None) -> DataFrame:
    """(parent_id, alpha): n equally spaced positions with one offset; a ceiling difference of scaled prefix sums, no join."""
    p = prefix_sums(weights, ranges=ranges)
    u = _position(seed, cycle, 0, F.col("total")) if offset is None else F.lit(offset)
    p = p.withColumn("u", u.cast(BIG))
    # positions u + k W are hit by particle [lo, hi) scaled by n; the ceiling of a negative numerator is 0
    up = lambda c: F.expr(f"greatest(cast(0 as {BIG}), (cast({n} as {BIG}) * {c} - u + total - 1) div total)")
    return p.select(F.col("particle_id").alias("parent_id"), (up("hi") - up("lo")).cast("long").alias("alpha")).where("alpha > 0")


def _lookup(prefix: DataFrame, draws: DataFrame, ranges: int = 1) -> DataFrame:
    """(slot, parent_id): the particle whose [lo, hi) holds each position - an as-of lookup by one sorted union in each range of positions.

    An interval is listed in every range it reaches into, so there are at most ``ranges`` more rows than particles.
    """
    cell = lambda c: F.expr(f"cast((cast({ranges} as {BIG}) * {c}) div total as int)")
    edges = prefix.where("w_fix > 0").withColumn("range_no", F.explode(F.sequence(cell("lo"), cell("(hi - 1)"))))
    edges = edges.select("range_no", F.col("lo").alias("at"), F.lit(0).alias("kind"), F.col("particle_id").alias("pid"), F.lit(None).cast("long").alias("slot"))
    asks = draws.withColumn("at", F.col("position").cast(BIG)).select(cell("at").alias("range_no"), "at", F.lit(1).alias("kind"), F.lit(None).cast("long").alias("pid"), "slot")
    seen = F.last("pid", ignorenulls=True).over(Window.partitionBy("range_no").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0))
    return edges.unionByName(asks).withColumn("parent_id", seen).where("kind = 1").select("slot", "parent_id")


def _counts(slots: DataFrame) -> DataFrame:
    return slots.groupBy("parent_id").agg(F.count(F.lit(1)).alias("alpha"))


def multinomial(weights: DataFrame, n: int, seed: int, cycle: int, ranges: int = 1) -> DataFrame:
    """n independent draws in proportion to weight."""
    p = prefix_sums(weights, ranges=ranges)
    total = weights.agg(F.sum("w_fix").cast(BIG).alias("total"))
    draws = weights.sparkSession.range(n).crossJoin(F.broadcast(total)).select(F.col("id").alias("slot"), _position(seed, cycle, F.col("id"), F.col("total")).alias("position"), "total")
    return _counts(_lookup(p, draws, ranges))


def stratified(weights: DataFrame, n: int, seed: int, cycle: int, ranges: int = 1) -> DataFrame:
    """One draw in each of n equal strata."""
    p = prefix_sums(weights, ranges=ranges)
    total = weights.agg(F.sum("w_fix").cast(BIG).alias("total"))
    draws = weights.sparkSession.range(n).crossJoin(F.broadcast(total)).withColumn("inside", _position(seed, cycle, F.col("id"), F.col("total")).cast(BIG))
    draws = draws.select(F.col("id").alias("slot"), F.expr(f"(cast(id as {BIG}) * total + inside) div {n}").alias("position"), "total")
    return _counts(_lookup(p, draws, ranges))


def residual(weights: DataFrame, n: int, seed: int, cycle: int, ranges: int = 1) -> DataFrame:
    """floor(n w / W) copies for sure, the rest drawn independently from the remainders (n w) mod W."""
    total = weights.agg(F.sum("w_fix").cast(BIG).alias("total"))
    w = weights.crossJoin(F.broadcast(total)).select("particle_id", F.expr(f"(cast({n} as {BIG}) * w_fix) div total").cast("long").alias("sure"), F.expr(f"cast((cast({n} as {BIG}) * w_fix) % total as {BIG})").alias("w_fix"))
    open_slots = w.agg((F.lit(n) - F.sum("sure")).cast("long").alias("open"), F.sum("w_fix").cast(BIG).alias("total"))
    draws = weights.sparkSession.range(n).crossJoin(F.broadcast(open_slots)).where("id < open").select(F.col("id").alias("slot"), _position(seed, cycle, F.col("id"), F.col("total")).alias("position"), "total")
    drawn = _counts(_lookup(prefix_sums(w.select("particle_id", "w_fix"), ranges=ranges), draws, ranges))
    sure = w.where("sure > 0").select(F.col("particle_id").alias("parent_id"), F.col("sure").alias("alpha"))
    return sure.unionByName(drawn).groupBy("parent_id").agg(F.sum("alpha").cast("long").alias("alpha"))


def resample(weights: DataFrame, n: int, scheme: str = "systematic", seed: int = 42, cycle: int = 0, ranges: int = 1) -> DataFrame:
    """(parent_id, alpha) by one of ``SCHEMES``; sum of alpha is n."""
    if scheme not in SCHEMES:
        raise ValueError(f"unknown scheme {scheme}; one of {SCHEMES}")
    return {"systematic": systematic, "stratified": stratified, "residual": residual, "multinomial": multinomial}[scheme](weights, n, seed, cycle, ranges)


def offspring(parents: DataFrame, ranges: int = 1) -> DataFrame:
    """(slot, parent_id, copy_no): the multiset expanded; slots run in parent order, summed in two phases if ``ranges`` > 1."""
    first = ordinals(parents, "id", ranges)
    copies = first.select("parent_id", "from", F.explode(F.sequence(F.lit(0), F.col("alpha").cast("int") - 1)).alias("copy_no"))
    return copies.select((F.col("from") + F.col("copy_no")).cast("long").alias("slot"), "parent_id", "copy_no")


def parents_of(children: DataFrame) -> DataFrame:
    """(parent_id, alpha) back from offspring."""
    return _counts(children)


def perturb(states: DataFrame, scale: float, seed: int, cycle: int, keep_first: bool = True, fast: bool = False) -> DataFrame:
    """Decorrelate copies of a parent: hashed noise keyed by slot and cell; the first copy may stay as it is."""
    noisy = F.col("x") + F.lit(scale) * normal4(seed, cycle, F.col("particle_id"), F.col("cell_id"), fast=fast)
    return states.withColumn("x", F.when(F.col("copy_no") == 0, F.col("x")).otherwise(noisy) if keep_first else noisy)


def should_redraw(stats: Column | None = None, policy: str = "always", threshold: float = 0.5) -> Column:
    """Flag from columns n, ess, weight_var, cycle: always, ess (ess < threshold n), variance (n^2 var > threshold), every_k."""
    if policy == "always":
        return F.lit(True)
    if policy == "ess":
        return F.col("ess") < F.lit(threshold) * F.col("n")
    if policy == "variance":
        return F.col("weight_var") * F.col("n") * F.col("n") > F.lit(threshold)
    if policy == "every_k":
        return F.pmod(F.col("cycle"), F.lit(int(threshold))) == 0
    raise ValueError(f"unknown policy {policy}")


def draw_bias(weights: DataFrame, n: int, scheme: str, seeds: int, seed: int = 42) -> DataFrame:
    """(particle_id, bias, variance): mean and variance of alpha - n w over seeds."""
    total = weights.agg(F.sum("w_fix").alias("total"))
    runs = None
    for s in range(seeds):
        one = resample(weights, n, scheme, seed + s, 0).withColumn("run", F.lit(s))
        runs = one if runs is None else runs.unionByName(one)
    every = weights.crossJoin(weights.sparkSession.range(seeds).select(F.col("id").cast("int").alias("run"))).crossJoin(F.broadcast(total))
    diff = every.join(runs.withColumnRenamed("parent_id", "particle_id"), ["particle_id", "run"], "left").select("particle_id", (F.coalesce("alpha", F.lit(0)) - F.lit(n) * F.col("w_fix") / F.col("total")).alias("d"))
    return diff.groupBy("particle_id").agg(F.avg("d").alias("bias"), F.var_samp("d").alias("variance"))
