"""Propagation models x <- M(x) + noise on long-form states (cycle, particle_id, cell_id, x).

A model is a column expression of ``x`` and a counter key, so propagation is a
projection without a shuffle.  ``steps`` repeats the inner step through the higher-order
``aggregate``, so the plan does not grow with the number of steps.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from particle_engine.functions.rng import normal4, uniform
from particle_engine.functions.scalar import clamp01

Step = Callable[[Column, Column, dict[str, float], int], Column]


def relax_fraction(x: Column, key: Column, p: dict[str, float], steps: int) -> Column:
    """Relaxation of a fraction to a mean with bounded noise, kept in [0, 1]."""
    noise = F.lit(p["sigma"]) * (F.lit(2.0) * key - F.lit(1.0)) / F.lit(float(steps) ** 0.5)
    return clamp01(x + F.lit(p["kappa"] / steps) * (F.lit(p["mean"]) - x) + noise)


def random_walk(x: Column, key: Column, p: dict[str, float], steps: int) -> Column:
    return x + F.lit(p["sigma"]) * key


def ar1(x: Column, key: Column, p: dict[str, float], steps: int) -> Column:
    return F.lit(p["mean"]) + F.lit(p["phi"]) * (x - F.lit(p["mean"])) + F.lit(p["sigma"]) * key


def identity(x: Column, key: Column, p: dict[str, float], steps: int) -> Column:
    return x


MODELS: dict[str, tuple[Step, str]] = {
    "relax_fraction": (relax_fraction, "uniform"),
    "random_walk": (random_walk, "normal"),
    "ar1": (ar1, "normal"),
    "identity": (identity, "none"),
}


@dataclass(frozen=True)
class Model:
    """A registry entry with its parameters. ``noise``: model (inside M), offspring (copies are perturbed) or none."""

    name: str = "relax_fraction"
    params: dict[str, float] = field(default_factory=lambda: {"kappa": 0.25, "mean": 0.2, "sigma": 0.15})
    noise: str = "model"
    fast: bool = False


def _draw(kind: str, seed: int, cycle: Column | int, model: Model, inner: Column | None = None) -> Column:
    if kind == "none" or model.noise != "model":
        return F.lit(0.5 if kind == "uniform" else 0.0)
    key = [seed, cycle, F.col("particle_id"), F.col("cell_id")] + ([inner] if inner is not None else [])
    return (uniform if kind == "uniform" else normal4)(*key, fast=model.fast)


def propagate(states: DataFrame, model: Model, cycle: Column | int, seed: int, steps: int = 1) -> DataFrame:
    """States one cycle on; ``steps`` inner model steps."""
    step, kind = MODELS[model.name]
    if steps == 1:
        x = step(F.col("x"), _draw(kind, seed, cycle, model), model.params, 1)
    else:
        x = F.aggregate(F.sequence(F.lit(1), F.lit(steps)), F.col("x"), lambda acc, i: step(acc, _draw(kind, seed, cycle, model, i), model.params, steps))
    return states.withColumn("x", x)


def diffuse(states: DataFrame, rate: float) -> DataFrame:
    """Exchange with both neighbour cells of the same particle: a self-join on the neighbour block (halo)."""
    half = states.select("particle_id", "cell_id", "x")
    halo = half.select("particle_id", F.explode(F.array(F.col("cell_id") - 1, F.col("cell_id") + 1)).alias("cell_id"), F.col("x").alias("nx"))
    mean = halo.groupBy("particle_id", "cell_id").agg(F.avg("nx").alias("nx"))
    return states.join(mean, ["particle_id", "cell_id"], "left").withColumn("x", F.col("x") + F.lit(rate) * (F.coalesce("nx", "x") - F.col("x"))).select(*states.columns)


def mean_revert(states: DataFrame, regions: DataFrame, rate: float) -> DataFrame:
    """Pull each cell to its region's mean (static cell attribute joined by broadcast)."""
    tagged = states.join(F.broadcast(regions.select("cell_id", "region_id")), "cell_id")
    mean = tagged.groupBy("particle_id", "region_id").agg(F.avg("x").alias("m"))
    return tagged.join(mean, ["particle_id", "region_id"]).withColumn("x", F.col("x") + F.lit(rate) * (F.col("m") - F.col("x"))).select(*states.columns)


def advance_black_box(states: DataFrame, make: Callable[[], Callable[[pd.DataFrame], pd.DataFrame]]) -> DataFrame:
    """Any Python model: ``make`` starts it once per partition and the warm model serves all batches of the partition."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model = make()
        for pdf in batches:
            yield model(pdf)

    return states.mapInPandas(run, states.schema)


def init_ensemble(grid: DataFrame, particles: int, seed: int, kind: str = "uniform", centre: float = 0.0, spread: float = 1.0, fast: bool = False) -> DataFrame:
    """(particle_id, cell_id, x): hashed start states over the grid, equal weights implied."""
    every = grid.sparkSession.range(particles).select(F.col("id").alias("particle_id")).crossJoin(F.broadcast(grid))
    key = [seed, 0, F.col("particle_id"), F.col("cell_id")]
    draw = uniform(*key, fast=fast) if kind == "uniform" else normal4(*key, fast=fast)
    return every.withColumn("x", F.lit(centre) + F.lit(spread) * draw if (centre, spread) != (0.0, 1.0) else draw)


def state_correction(states: DataFrame) -> DataFrame:
    """Hook for filters that correct states inside a cycle; not part of this engine."""
    raise NotImplementedError("filters that correct states internally are out of scope")
