"""The experiment workloads on the given tables: assimilation runs, natural multisets, and simulated settings."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from particle_engine.functions.rng import normal4, uniform
from particle_engine.operators import observe, weights
from particle_engine.operators.models import Model, init_ensemble, propagate
from particle_engine.operators.schedule import multiset, ordinals
from particle_engine.plans import metrics
from particle_engine.plans.filter import ensemble_lineages
from particle_engine.plans.simulate import simulate
from particle_engine.sources.tables import table

SEED = 42
K1_PARTICLES = 256
#: Tables whose keys form natural multisets: table, parent key.
NATURAL = {"conversations": "conv_id", "lineitem": "l_orderkey", "orders": "o_custkey", "events": "user_id"}


# K1: hourly mask on a grid of 80 cells.


def k1_states(spark: SparkSession, particles: int = K1_PARTICLES) -> DataFrame:
    return init_ensemble(observe.grid(spark), particles, SEED)


def seen_states(spark: SparkSession, sf_dir: str, particles: int = K1_PARTICLES) -> DataFrame:
    """Start states on the grid of all cells that the events fall into."""
    return init_ensemble(seen_cells(spark, sf_dir), particles, SEED)


def seen_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    cell = observe.cell_of(F.col("user_id"), F.col("event_type"))
    return table(spark, sf_dir, "events").select(cell.alias("cell_id")).where("cell_id is not null").distinct()


def k1_scored(spark: SparkSession, sf_dir: str, particles: int = K1_PARTICLES, steps: int = 1) -> DataFrame:
    """(particle_id, mismatches, w_fix) after the first cycle."""
    mask = observe.mask_grid(table(spark, sf_dir, "events"), 1)
    moved = propagate(k1_states(spark, particles), Model(), 1, SEED, steps)
    return weights.mask_weights(weights.mask_mismatches(moved, mask))


# K1b: scalar hourly level with an exact answer.


def k1b_level(spark: SparkSession, sf_dir: str) -> DataFrame:
    return observe.hourly(table(spark, sf_dir, "events"))


def k1b_filter(level: DataFrame, particles: int, cycles: int | None = None, noise: float = 4.0, obs_sd: float = 49.0, seed: int = SEED) -> DataFrame:
    """(cycle, mean, var, ess) of a scalar Gaussian filter over all hours or the first ``cycles``, one grouped task (a series of hourly numbers)."""
    import numpy as np
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("cycle").head(len(pdf) if cycles is None else cycles)
        rng = np.random.default_rng(seed)
        x = 50.0 + 20.0 * rng.standard_normal(particles)
        out = []
        for c, n, y in pdf[["cycle", "n", "mean_value"]].itertuples(index=False):
            x = x + noise * rng.standard_normal(particles)
            lw = -0.5 * ((y - x) / obs_sd) ** 2 * n
            w = np.exp(lw - lw.max())
            w /= w.sum()
            m = float((w * x).sum())
            out.append((int(c), m, float((w * (x - m) ** 2).sum()), float(1 / (w * w).sum())))
            at = (np.arange(particles) + rng.random()) / particles
            x = x[np.searchsorted(np.cumsum(w), at).clip(0, particles - 1)]
        return pd.DataFrame(out, columns=["cycle", "mean", "var", "ess"])

    return level.withColumn("series", F.lit(0)).groupBy("series").applyInPandas(run, "cycle int, mean double, var double, ess double")


def scalar_cauchy_cycle(states: DataFrame, y: DataFrame, cycle: int, scale: float) -> DataFrame:
    """(particle_id, x, w): scalar states one cycle on, with a rational weight; ``y`` is one row (mean_value)."""
    x = F.col("x") + F.lit(4.0) * normal4(SEED, cycle, F.col("particle_id"), 0)
    moved = states.select("particle_id", x.alias("x")).crossJoin(F.broadcast(y.select(F.col("mean_value").alias("y"))))
    r = (F.col("y") - F.col("x")) / F.lit(scale)
    return moved.select("particle_id", "x", (F.lit(1.0) / (F.lit(1.0) + r * r)).alias("w"))


# K17, K18.


def k17_scores(spark: SparkSession, sf_dir: str, dims: Iterable[int] = (1, 2, 4, 8, 16, 32, 64), kernel: str = "cauchy") -> DataFrame:
    """(d, vec_id, w): every vector scored against the centroid of label 0 over the first d dimensions."""
    emb = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("dim", "v")).withColumn("v", F.col("v").cast("double"))
    centre = emb.where("label = 0").groupBy("dim").agg(F.round(F.avg("v"), 6).alias("c"))
    r = (F.col("v") - F.col("c")) / F.lit(0.125)
    term = -F.log(F.lit(1.0) + r * r) if kernel == "cauchy" else F.lit(-0.5) * r * r
    cells = emb.join(F.broadcast(centre), "dim").select("vec_id", "dim", term.alias("t"))
    spread = cells.select("vec_id", "t", F.explode(F.filter(F.array(*map(F.lit, dims)), lambda d: d > F.col("dim"))).alias("d"))
    return spread.groupBy("d", "vec_id").agg(F.sum("t").alias("log_w"))


def _k18_features(spark: SparkSession, sf_dir: str, batches: int) -> DataFrame:
    """(batch, quality, f1, f2, f3) of every labelled document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text").join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id")
    n = F.greatest(F.char_length("text"), F.lit(1)).cast("double")
    return docs.select(
        F.pmod(F.col("doc_id"), F.lit(batches)).cast("int").alias("batch"), "quality", (F.least(n, F.lit(4000.0)) / F.lit(4000.0)).alias("f1"),
        (F.regexp_count("text", F.lit("[0-9]")) / n).alias("f2"), (F.regexp_count("text", F.lit("[A-Z]")) / n).alias("f3"),
    )


def _k18_wrong(spark: SparkSession, feats: DataFrame, particles: int) -> DataFrame:
    """(batch, particle_id, wrong): every particle's verdict on every document."""
    coef = [normal4(SEED, 0, F.col("id"), j).alias(f"b{j}") for j in range(4)]
    parts = spark.range(particles).select(F.col("id").alias("particle_id"), *[c for c in coef])
    score = F.col("b0") + F.col("b1") * F.col("f1") + F.col("b2") * F.col("f2") + F.col("b3") * F.col("f3")
    joined = feats.crossJoin(F.broadcast(parts))  # a fixed number of particles against every document
    return joined.select("batch", "particle_id", ((score > 0).cast("int") != F.col("quality")).cast("int").alias("wrong"))


def k18_errors(spark: SparkSession, sf_dir: str, particles: int = 64) -> DataFrame:
    """(particle_id, errors, docs): sign classifiers (bias, length, digits, upper-case share) against ``quality`` on all labelled documents as one cycle."""
    wrong = _k18_wrong(spark, _k18_features(spark, sf_dir, 1), particles)
    return wrong.groupBy("particle_id").agg(F.sum("wrong").cast("long").alias("errors"), F.count(F.lit(1)).alias("docs"))


def k18_all_errors(spark: SparkSession, sf_dir: str, particles: int = 64, batches: int = 4) -> DataFrame:
    """(cycle, particle_id, errors, docs, total_errors, total_docs): every batch as a cycle; totals carry on what earlier cycles found."""
    wrong = _k18_wrong(spark, _k18_features(spark, sf_dir, batches), particles)
    each = wrong.groupBy(F.col("batch").alias("cycle"), "particle_id").agg(F.sum("wrong").cast("long").alias("errors"), F.count(F.lit(1)).alias("docs"))
    so_far = Window.partitionBy("particle_id").orderBy("cycle").rowsBetween(Window.unboundedPreceding, 0)  # one row a cycle
    return each.withColumns({"total_errors": F.sum("errors").over(so_far), "total_docs": F.sum("docs").over(so_far)})


# Settings of the simulator.


def settings(spark: SparkSession, rows: list[dict]) -> DataFrame:
    """Configs table from dicts: each has config_id, lineage_id and what differs from the defaults."""
    kinds = {str: "string", int: "long", bool: "boolean", float: "double"}
    names = list(dict.fromkeys(k for r in rows for k in r))
    ddl = ", ".join(f"{n} {kinds[type(next(r[n] for r in rows if n in r))]}" for n in names)
    return spark.createDataFrame([tuple(r.get(n) for n in names) for r in rows], ddl)


def lineages(spark: SparkSession, sf_dir: str, sizes: list[tuple[str, int, int, float | None]], seed: int = SEED) -> DataFrame:
    """Lineages (id, particles, cycles, spread or None for the K1 filter)."""
    runs = spark.createDataFrame([(i, n, t, seed, s) for i, n, t, s in sizes], "lineage_id string, n int, cycles int, seed int, sigma double")
    return ensemble_lineages(runs, observe.mask_grid(table(spark, sf_dir, "events"), 48))


def k4(spark: SparkSession, sf_dir: str, caches: Iterable[int] = (1, 2, 3, 4, 5, 6, 7, 8, 9, 12, 16), cycles: int = 15, sigma: float | None = None) -> tuple[DataFrame, DataFrame]:
    """Cache-size sweep: 128 particles, 32 runners. (configs, trace)."""
    configs = settings(spark, [{"config_id": f"c{c:02d}", "lineage_id": "p128", "r": 32, "c": c} for c in caches])
    return configs, simulate(configs, lineages(spark, sf_dir, [("p128", 128, cycles, sigma)]))


def k5(spark: SparkSession, sf_dir: str, sizes: Iterable[int] = (128, 256, 512, 1024), cycles: int = 5, sigma: float | None = None) -> tuple[DataFrame, DataFrame]:
    """Loads against bounds, four particles per runner, cache of 9."""
    configs = settings(spark, [{"config_id": f"p{p:04d}", "lineage_id": f"l{p}", "r": p // 4, "c": 9} for p in sizes])
    return configs, simulate(configs, lineages(spark, sf_dir, [(f"l{p}", p, cycles, sigma) for p in sizes]))


SCALES = [(315, 63, 2_100_000, 1_400_000, 2_210), (635, 127, 2_100_000, 1_600_000, 4_060), (1275, 255, 2_400_000, 1_800_000, 8_160), (2555, 511, 4_100_000, 2_300_000, 16_370)]


def k6(spark: SparkSession, sf_dir: str, scales=SCALES, cycles: int = 3, sigma: float | None = 0.35) -> tuple[DataFrame, DataFrame]:
    """Weak scaling: five particles per runner, printed load, store and redraw times per scale, one coordinator that answers in turn."""
    configs = settings(spark, [{"config_id": f"p{p:04d}", "lineage_id": f"l{p}", "r": r, "c": 9, "load_us": ld, "store_us": st, "redraw_us": rd, "sequential": True} for p, r, ld, st, rd in scales])
    return configs, simulate(configs, lineages(spark, sf_dir, [(f"l{s[0]}", s[0], cycles, sigma) for s in scales]))


def k7(spark: SparkSession, sf_dir: str, ratios: Iterable[int] = (1, 2, 3, 5, 8, 10, 16, 20), runners: int = 63, cycles: int = 2) -> tuple[DataFrame, DataFrame]:
    """Strong scaling: fixed runners, more particles each; ``one`` is the one-runner reference."""
    rows = [{"config_id": f"x{k:02d}", "lineage_id": f"l{k}", "r": runners, "c": 9} for k in ratios] + [{"config_id": "one", "lineage_id": "l1", "r": 1, "c": 9}]
    configs = settings(spark, rows)
    return configs, simulate(configs, lineages(spark, sf_dir, [(f"l{k}", k * runners, cycles, 0.35) for k in dict.fromkeys([1, *ratios])]))


def k8(spark: SparkSession, sf_dir: str, runners: Iterable[int] = (1, 2, 3, 5, 7, 8, 16, 24, 32, 48, 64, 100, 128), cycles: int = 3) -> tuple[DataFrame, DataFrame]:
    """Whether R divides P = 128."""
    configs = settings(spark, [{"config_id": f"r{r:03d}", "lineage_id": "p128", "r": r, "c": 9} for r in runners])
    return configs, simulate(configs, lineages(spark, sf_dir, [("p128", 128, cycles, 0.35)]))


def k11(spark: SparkSession, sf_dir: str, cycles: int = 8) -> tuple[DataFrame, DataFrame]:
    """Crash test: one crash early in a cycle, one on a cycle's last tasks; timeout 60 s, replacements join."""
    rows = [{"config_id": "calm", "lineage_id": "p315", "r": 63, "c": 9, "crashes": ""}, {"config_id": "faults", "lineage_id": "p315", "r": 63, "c": 9, "crashes": "5:2:1,17:5:-1"}]
    configs = settings(spark, rows)
    return configs, simulate(configs, lineages(spark, sf_dir, [("p315", 315, cycles, 0.35)]))


def k12(spark: SparkSession, sf_dir: str, sizes: Iterable[int] = (128, 256, 512, 1024), cycles: int = 2) -> tuple[DataFrame, DataFrame]:
    """Proposed against file-based and monolithic modes, simulated. File-based storage is shared, so its load and store times grow with P."""
    rows = []
    for p in sizes:
        common = {"lineage_id": f"l{p}"}
        rows.append(common | {"config_id": f"engine-{p:04d}", "r": max(1, p // 13), "c": 9})
        rows.append(common | {"config_id": f"files-{p:04d}", "r": p, "c": 0, "policy": "list", "prefetch": 0, "async_io": False, "startup_us": 3_500_000, "load_us": 2_100_000 * p // 128, "store_us": 1_400_000 * p // 128})
        rows.append(common | {"config_id": f"fixed-{p:04d}", "r": max(1, p // 13), "c": 0, "policy": "fixed", "prefetch": 0})
    configs = settings(spark, rows)
    return configs, simulate(configs, lineages(spark, sf_dir, [(f"l{p}", p, cycles, 0.35) for p in sizes]))


POLICY_ROWS = [
    {"policy": "static", "c": 1, "prefetch": 0}, {"policy": "fixed", "c": 0, "prefetch": 0}, {"policy": "list", "c": 1, "prefetch": 0},
    {"policy": "dynamic", "c": 1, "prefetch": 0}, {"policy": "cache_aware", "c": 9, "prefetch": 1}, {"policy": "cache_aware", "c": 9, "prefetch": 1, "use_rank4": False, "rq_mode": "holding"},
]


def policies(spark: SparkSession, sf_dir: str, runners: int = 32, cycles: int = 4, sigma: float | None = None, **extra) -> tuple[DataFrame, DataFrame]:
    """Every scheduling policy over one lineage."""
    rows = [{"config_id": f"{i}-{r['policy']}", "lineage_id": "p128", "r": runners, "use_rank4": True, "rq_mode": "active"} | r | extra for i, r in enumerate(POLICY_ROWS)]
    configs = settings(spark, rows)
    return configs, simulate(configs, lineages(spark, sf_dir, [("p128", 128, cycles, sigma)]))


def evictions(spark: SparkSession, sf_dir: str, capacity: int = 6, cycles: int = 8) -> tuple[DataFrame, DataFrame]:
    configs = settings(spark, [{"config_id": e, "lineage_id": "p128", "r": 32, "c": capacity, "evict": e} for e in ("ranked", "lru", "fifo", "random")])
    return configs, simulate(configs, lineages(spark, sf_dir, [("p128", 128, cycles, 0.35)]))


def io_modes(spark: SparkSession, sf_dir: str, cycles: int = 4) -> tuple[DataFrame, DataFrame]:
    rows = [{"config_id": "async", "async_io": True, "prefetch": 1, "c": 9}, {"config_id": "no_prefetch", "async_io": True, "prefetch": 0, "c": 9}, {"config_id": "sync", "async_io": False, "prefetch": 0, "c": 9}, {"config_id": "no_cache", "async_io": True, "prefetch": 0, "c": 0}]
    configs = settings(spark, [{"lineage_id": "p128", "r": 32} | r for r in rows])
    return configs, simulate(configs, lineages(spark, sf_dir, [("p128", 128, cycles, 0.35)]))


def table_tasks(rows: DataFrame, parent: str, order: str, cost: str, lineage_id: str) -> DataFrame:
    """Tasks from a table: one per row, parent from a key, duration from a cost column. For simulated studies of the given sizes.

    Numbers are a key's place among the keys (a row a key) and a row's place within its key.
    """
    keys = rows.groupBy(parent).agg(F.count(F.lit(1)).alias("alpha")).withColumnRenamed(parent, "parent_id")
    starts = ordinals(keys).withColumn("key", F.row_number().over(Window.orderBy("parent_id")) - 1).select(F.col("parent_id").alias("__parent"), "key", "from")
    inner = F.row_number().over(Window.partitionBy("__parent").orderBy(order)) - 1
    slot = (F.col("from") + inner).cast("long")
    joined = rows.join(starts, F.col(parent).eqNullSafe(F.col("__parent")))
    return joined.select(F.lit(lineage_id).alias("lineage_id"), F.lit(0).alias("cycle"), slot.alias("slot"), F.col("key").cast("long").alias("parent_slot"), F.lit(1.0).alias("weight"), F.col(cost).cast("long").alias("duration_us"))


def k15(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Very variable durations: a document is a task, its source the parent, its length the cost; some runners three times slower."""
    docs = table(spark, sf_dir, "documents").select("source", "doc_id", (F.col("n_chars") * 1000).alias("cost"))
    rows = [{"config_id": f"{i}-{r['policy']}{'-slow' if s else ''}", "lineage_id": "docs", "r": 16, "load_us": 1_000_000, "slow_every": s} | {k: v for k, v in r.items() if k in ("policy", "c", "prefetch")} for i, r in enumerate(POLICY_ROWS[:5]) for s in (0, 4)]
    configs = settings(spark, rows)
    return configs, simulate(configs, table_tasks(docs, "source", "doc_id", "cost", "docs"))


def k16(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Propagation shorter than a load: short tasks of pages grouped by the page's host."""
    pages = table(spark, sf_dir, "pages").select(F.regexp_extract("url", "//([^/]*)", 1).alias("host"), "page_id", F.char_length("html").alias("cost"))
    configs = settings(spark, [{"config_id": n, "lineage_id": "pages", "r": 8, "c": c, "prefetch": p, "load_us": ld} for n, c, p, ld in (("short-load", 9, 1, 1_000), ("long-load", 9, 1, 60_000), ("long-load-no-cache", 0, 0, 60_000))])
    return configs, simulate(configs, table_tasks(pages, "host", "page_id", "cost", "pages"))


def natural(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return multiset(table(spark, sf_dir, name), NATURAL[name])


def summary(configs: DataFrame, trace: DataFrame) -> DataFrame:
    """(config_id, r, tasks, loads, cycle_us): what most studies report."""
    t = metrics.whole_cycle_time(trace, configs).groupBy("config_id").agg(F.avg("cycle_us").cast("long").alias("cycle_us"))
    n = metrics.loads(trace).groupBy("config_id").agg(F.sum("tasks").alias("tasks"), F.sum("loads").alias("loads"))
    return configs.select("config_id", F.col("r").cast("int").alias("r")).join(n, "config_id").join(t, "config_id")


def duration_of(slot, cycle) -> object:
    """Hashed duration in [24.0, 26.5] s as a column, as the simulator uses it."""
    return F.lit(24_000_000) + F.floor(uniform(SEED, cycle, slot, 0) * F.lit(2_500_001)).cast("long")
