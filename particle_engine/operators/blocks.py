"""Blocked states: one row per (particle, block) with an array of cells, for states of gigabytes.

A block of 1 to 8 MiB keeps sort and aggregate buffers small; likelihoods add over
blocks, so a particle's blocks are scored in parallel and only (particle, log_w)
rows are shuffled.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def pack(states: DataFrame, cells_per_block: int) -> DataFrame:
    """(particle_id, block_id, x array<float>) from long rows; every cell of a block must be present."""
    block = F.floor(F.col("cell_id") / cells_per_block).cast("int")
    cells = F.array_sort(F.collect_list(F.struct("cell_id", "x")))  # bounded by the block
    grouped = states.groupBy("particle_id", block.alias("block_id")).agg(cells.alias("cells"))
    return grouped.select("particle_id", "block_id", F.transform("cells", lambda c: c["x"].cast("float")).alias("x"))


def unpack(blocks: DataFrame, cells_per_block: int) -> DataFrame:
    """Long rows (particle_id, cell_id, x) back."""
    long = blocks.select("particle_id", "block_id", F.posexplode("x").alias("i", "x"))
    return long.select("particle_id", (F.col("block_id") * cells_per_block + F.col("i")).cast("int").alias("cell_id"), F.col("x").cast("double").alias("x"))


def log_likelihood(blocks: DataFrame, obs: DataFrame, scale: float, broadcast_obs: bool = True) -> DataFrame:
    """(particle_id, log_w): Gaussian; ``obs`` has (block_id, y array) with nulls where nothing was observed."""
    y = obs.select("block_id", F.col("y").alias("__y"))
    joined = blocks.join(F.broadcast(y) if broadcast_obs else y, "block_id", "left")
    terms = F.zip_with("x", "__y", lambda a, b: F.when(a.isNotNull() & b.isNotNull(), F.lit(-0.5) * F.pow((b - a) / F.lit(scale), F.lit(2.0))).otherwise(F.lit(0.0)))
    part = F.when(F.col("__y").isNull(), F.lit(0.0)).otherwise(F.aggregate(terms, F.lit(0.0), lambda s, t: s + t))
    return joined.groupBy("particle_id").agg(F.sum(part).alias("log_w"))


def bytes_of(blocks: DataFrame) -> DataFrame:
    """(particles, blocks, state_bytes): what one cycle of states weighs."""
    return blocks.agg(F.countDistinct("particle_id").alias("particles"), F.count(F.lit(1)).alias("blocks"), (F.sum(F.size("x")) * 4).alias("state_bytes"))
