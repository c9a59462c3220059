"""Baselines: file-based and monolithic ensembles, one runner, one runner per particle, exact and brute-force filters.

The scheduling baselines are settings of the simulator; the engine modes run the
same cycles with the baseline's data movement.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from particle_engine.operators.models import propagate
from particle_engine.operators.resample import offspring, resample
from particle_engine.plans.filter import Spec, score
from particle_engine.plans.simulate import Config
from particle_engine.sources.store import StateStore

#: What each scheduling baseline changes in a configuration.
SIMULATED = {
    "file_based": {"policy": "list", "c": 0, "prefetch": 0, "async_io": False, "startup_us": 3_500_000},
    "monolithic": {"policy": "fixed", "c": 0, "prefetch": 0, "async_io": True},
    "sequential": {"r": 1},
    "static_no_cache": {"policy": "static", "c": 1, "prefetch": 0},
    "sync_io": {"async_io": False, "prefetch": 0},
    "list": {"policy": "list", "prefetch": 0},
}


def baseline(name: str, **base) -> Config:
    return Config(**{**base, "config_id": base.get("config_id", name), **SIMULATED[name]})


def run_file_based(initial: DataFrame, obs: DataFrame, cycles: list[int], spec: Spec, root: str) -> DataFrame:
    """Every cycle writes all particles to files and reads them afresh; copies are written, not referenced."""
    spark = initial.sparkSession
    path = f"{root}/file-based"
    initial.write.mode("overwrite").parquet(f"{path}/start")
    states = spark.read.parquet(f"{path}/start")
    for c in cycles:
        propagate(states, spec.model, c + 1, spec.seed, spec.steps).write.mode("overwrite").parquet(f"{path}/moved-{c}")
        moved = spark.read.parquet(f"{path}/moved-{c}")
        score(moved, obs.where(F.col("cycle") == c).drop("cycle"), spec).write.mode("overwrite").parquet(f"{path}/weights-{c}")
        w = spark.read.parquet(f"{path}/weights-{c}").select("particle_id", "w_fix")
        children = offspring(resample(w, spec.n_particles, spec.scheme, spec.seed, c))
        copies = moved.join(children, moved["particle_id"] == children["parent_id"]).select(F.col("slot").alias("particle_id"), "cell_id", "x")
        copies.write.mode("overwrite").parquet(f"{path}/next-{c}")
        states = spark.read.parquet(f"{path}/next-{c}")
    return states


def run_single_lineage(initial: DataFrame, obs: DataFrame, cycles: list[int], spec: Spec) -> DataFrame:
    """One plan over all cycles, no files and no checkpoint: a failure repeats everything. For a few cycles."""
    states = initial
    for c in cycles:
        moved = propagate(states, spec.model, c + 1, spec.seed, spec.steps)
        w = score(moved, obs.where(F.col("cycle") == c).drop("cycle"), spec).select("particle_id", "w_fix")
        children = offspring(resample(w, spec.n_particles, spec.scheme, spec.seed, c))
        states = moved.join(children, moved["particle_id"] == children["parent_id"]).select(F.col("slot").alias("particle_id"), "cell_id", "x")
    return states


def exact_kalman(level: DataFrame, start_mean: float, start_var: float, noise_var: float, obs_var: float) -> DataFrame:
    """(cycle, mean, var): exact posterior of a scalar random walk seen with variance obs_var / n.

    A fold over the sorted array of hourly values: one array per series, its
    length the number of hours.
    """
    series = level.agg(F.array_sort(F.collect_list(F.struct("cycle", "n", "mean_value"))).alias("s"))
    zero = F.struct(F.lit(start_mean).alias("m"), F.lit(start_var).alias("v"), F.array().cast("array<struct<cycle:int,mean:double,var:double>>").alias("out"))

    def step(a, o):
        pv = a["v"] + F.lit(noise_var)
        gain = pv / (pv + F.lit(obs_var) / o["n"])
        m, v = a["m"] + gain * (o["mean_value"] - a["m"]), pv * (F.lit(1.0) - gain)
        return F.struct(m.alias("m"), v.alias("v"), F.concat(a["out"], F.array(F.struct(o["cycle"].alias("cycle"), m.alias("mean"), v.alias("var")))).alias("out"))

    return series.select(F.explode(F.aggregate("s", zero, step, lambda a: a["out"])).alias("k")).select("k.cycle", F.round("k.mean", 6).alias("mean"), F.round("k.var", 6).alias("var"))


def published_table(spark: SparkSession) -> DataFrame:
    """Printed inputs of the comparison with the file-based mode: particles, cores and seconds of each side."""
    rows = [(128, 384, 1062.0, 1536, 267.0), (256, 768, 1062.0, 3072, 317.0), (512, 1536, 1068.0, 6144, 422.0), (1024, 3072, 1071.0, 12288, 761.0)]
    return spark.createDataFrame(rows, "particles int, cores_a int, time_a double, cores_b int, time_b double")


def store_for(spark: SparkSession) -> StateStore:
    return StateStore(spark)
