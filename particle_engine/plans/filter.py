"""The filter: one assimilation cycle as a plan, and the loop over cycles.

``run_filter`` is the distributed engine.  Each cycle is one driver round trip (the
one synchronisation point the method has): states are propagated in place,
scored, written and committed; only (particle, weight) rows are normalised and drawn; the
drawn parents' states are shipped to the partitions that need them.  Lineage is cut by the
committed tables, so plans do not grow with cycles and a lost executor repeats tasks
of one cycle.

``ensemble_lineages`` runs many small filters side by side, one in a group of
``applyInPandas``, with the same counter-based numbers and integer weights: it draws the
same offspring as the distributed engine.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from particle_engine.functions.rng import py_int, py_uniforms
from particle_engine.operators import placement, weights
from particle_engine.operators.models import Model, propagate
from particle_engine.operators.resample import ONE_TASK, offspring, perturb, resample, should_redraw
from particle_engine.sources.store import StateStore


@dataclass(frozen=True)
class Spec:
    """All parameters of a run."""

    n_particles: int = 256
    model: Model = field(default_factory=Model)
    kernel: str = "mask"  # mask (integer odds), gaussian or cauchy
    scale: float = 1.0  # spread of the error; for the mask kernel the bits a wrong cell costs (a whole number)
    threshold: float = 0.5
    scheme: str = "systematic"
    policy: str = "always"
    policy_threshold: float = 0.5
    jitter: float = 0.0
    keep_first: bool = True
    steps: int = 1
    seed: int = 42
    partitions: int = 8
    placement: str = "static"  # static, hash, or stay: the first copies stay where their parent lives
    ranges: int = 0  # ranges of two-phase prefix sums; 0: by the number of particles
    keep_cycles: int = 2
    diagnostics: bool = True  # per-cycle figures: two small jobs a cycle
    observation: Column | None = None
    broadcast_obs: bool = True  # run_filter counts a cycle's observations and clears it where they are many

    @property
    def sum_ranges(self) -> int:
        return self.ranges or -(-self.n_particles // ONE_TASK)


def score(states: DataFrame, obs: DataFrame, spec: Spec) -> DataFrame:
    """(particle_id, log_w, w_fix) of one cycle; cells without an observation add nothing."""
    if spec.kernel == "mask":
        odds = int(spec.scale)
        w = weights.mask_weights(weights.mask_mismatches(states, obs, spec.threshold, spec.broadcast_obs), odds=odds)
        return w.select("particle_id", (-F.col("mismatches") * F.log(F.lit(2.0)) * odds).alias("log_w"), "w_fix")
    return weights.fix_weights(weights.log_likelihood(states, obs, spec.kernel, spec.scale, spec.observation, spec.broadcast_obs))


@dataclass
class FilterResult:
    states: DataFrame
    diagnostics: list[dict]
    store: StateStore


def run_cycle(states: DataFrame, obs: DataFrame, cycle: int, spec: Spec, store: StateStore, run_id: str, carried: DataFrame | None = None, homes: DataFrame | None = None) -> tuple[DataFrame, DataFrame | None, dict, DataFrame | None]:
    """One cycle: (next states, carried log weights if no redraw, diagnostics, homes of the next states)."""
    moved = store.write("states", run_id, cycle, propagate(states, spec.model, cycle + 1, spec.seed, spec.steps))
    scored = score(moved, obs, spec)
    if carried is not None:
        scored = weights.fix_weights(weights.update_weights(carried, scored.select("particle_id", "log_w")))
    w = store.write("weights", run_id, cycle, scored)
    row = {"cycle": cycle, "redraw": True}
    if spec.diagnostics or spec.policy != "always":
        stats = weights.summary(w).withColumn("cycle", F.lit(cycle))
        row = stats.withColumn("redraw", should_redraw(None, spec.policy, spec.policy_threshold)).first().asDict()
    if not row["redraw"]:
        store.write("offspring", run_id, cycle, w.select(F.col("particle_id").alias("slot"), F.col("particle_id").alias("parent_id"), F.lit(0).alias("copy_no")), KEPT)
        store.save_coordinator(run_id, cycle, {"redraw": False})
        return moved, w.select("particle_id", "log_w"), row, homes
    parents = resample(w.select("particle_id", "w_fix"), spec.n_particles, spec.scheme, spec.seed, cycle, spec.sum_ranges)
    children = store.write("offspring", run_id, cycle, offspring(parents, spec.sum_ranges))
    drawn = children.groupBy("parent_id").agg(F.count(F.lit(1)).alias("alpha"))
    if spec.diagnostics:
        row |= drawn.agg(F.count(F.lit(1)).alias("q"), F.max("alpha").alias("max_copies")).first().asDict()
    if spec.placement == "stay" and homes is None:
        homes = placement.first_homes(moved, spec.partitions, spec.n_particles)
    plan = placement.with_slots(placement.assign(drawn, spec.partitions, spec.placement, homes, spec.sum_ranges), spec.sum_ranges)
    plan = store.write("plan", run_id, cycle, plan)
    if spec.diagnostics and homes is not None:
        row |= placement.moved_copies(plan, homes).first().asDict()
    shipped = placement.ship(moved.select("particle_id", "cell_id", "x"), plan, spec.partitions, spec.n_particles + spec.partitions)
    if spec.jitter:
        shipped = perturb(shipped, spec.jitter, spec.seed, cycle, spec.keep_first)
    store.save_coordinator(run_id, cycle, {"redraw": True, "placement": spec.placement})
    store.gc(run_id, cycle - spec.keep_cycles + 1)
    return shipped.select("particle_id", "cell_id", "x"), None, row, placement.homes_of(plan) if spec.placement == "stay" else None


#: Bytes of one observed cell where it is broadcast.
OBS_ROW_BYTES = 32
#: Note of offspring slices of cycles without a redraw.
KEPT = "kept"


def run_filter(initial: DataFrame, obs: DataFrame, cycles: list[int], spec: Spec, run_id: str = "run", store: StateStore | None = None) -> FilterResult:
    """Filter over the given cycles; ``obs`` has cycle, cell_id and mask or y. A run found in the store goes on after its last whole cycle."""
    store = store or StateStore(initial.sparkSession)
    states, carried, notes, homes = initial, None, [], None
    done = store.resume_cycle(run_id)
    if done is not None:
        states, carried = restore(store, run_id, done, spec)
        if spec.placement == "stay" and done in store.committed("plan", run_id):
            homes = placement.homes_of(store.read("plan", run_id, done))
        cycles = [c for c in cycles if c > done]
    most = obs.groupBy("cycle").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    if most * OBS_ROW_BYTES > placement.BROADCAST_BYTES:
        spec = replace(spec, broadcast_obs=False)
    for cycle in cycles:
        y = obs.where(F.col("cycle") == cycle).drop("cycle")
        states, carried, row, homes = run_cycle(states, y, cycle, spec, store, run_id, carried, homes)
        notes.append(row)
    return FilterResult(states, notes, store)


def restore(store: StateStore, run_id: str, cycle: int, spec: Spec) -> tuple[DataFrame, DataFrame | None]:
    """States after a committed cycle, rebuilt from its stored states and offspring (and weights where there was no redraw)."""
    moved, children = store.read("states", run_id, cycle), store.read("offspring", run_id, cycle)
    if store.note("offspring", run_id, cycle) == KEPT:
        return moved, store.read("weights", run_id, cycle).select("particle_id", "log_w")
    joined = moved.join(children, moved["particle_id"] == children["parent_id"]).select(F.col("slot").alias("particle_id"), "copy_no", "cell_id", "x")
    if spec.jitter:
        joined = perturb(joined, spec.jitter, spec.seed, cycle, spec.keep_first)
    return joined.select("particle_id", "cell_id", "x"), None


# Small filters, many at once.


def draw_systematic(w: np.ndarray, n: int, seed: int, cycle: int) -> np.ndarray:
    """alpha of each particle: the integer formula of the distributed draw."""
    total = int(w.sum())
    u = py_int(seed, cycle, -1, 0) * total // (1 << 52)
    hi = np.cumsum(w.astype(object))
    up = [max(0, (n * int(h) - u + total - 1) // total) for h in hi]
    return np.diff([max(0, (total - 1 - u) // total), *up]).astype(np.int64)


def mask_filter(mask: np.ndarray, n: int, cycles: int, seed: int, kappa: float = 0.25, mean: float = 0.2, sigma: float = 0.15) -> pd.DataFrame:
    """Lineage (cycle, slot, parent_slot, weight) of the mask filter on a small grid, NumPy only.

    ``slot`` are the tasks of a cycle (one propagation each), ``parent_slot`` the task of
    the cycle before whose state it starts from, ``weight`` its normalised weight.
    """
    cells = mask.shape[1]
    x = py_uniforms((seed, 0), n, cells)
    parent = np.arange(n)
    out = []
    for c in range(cycles):
        noise = sigma * (2.0 * py_uniforms((seed, c + 1), n, cells) - 1.0)
        x = np.clip(x + kappa * (mean - x) + noise, 0.0, 1.0)
        miss = ((x >= 0.5) != mask[c]).sum(1)
        e = 30 - (miss - miss.min())
        w = np.where(e >= 0, np.left_shift(np.int64(1), np.maximum(e, 0)), 0).astype(np.int64)
        out.append(pd.DataFrame({"cycle": c, "slot": np.arange(n), "parent_slot": parent, "weight": w / w.sum()}))
        parent = np.repeat(np.arange(n), draw_systematic(w, n, seed, c))
        x = x[parent]
    return pd.concat(out, ignore_index=True)


def spread_lineage(n: int, cycles: int, seed: int, sigma: float = 0.35) -> pd.DataFrame:
    """Lineage with log-normal weights of a chosen spread and systematic draws (synthetic, for scheduling studies)."""
    rng = np.random.default_rng(seed)
    parent = np.arange(n)
    out = []
    for c in range(cycles):
        w = np.exp(sigma * rng.standard_normal(n))
        out.append(pd.DataFrame({"cycle": c, "slot": np.arange(n), "parent_slot": parent, "weight": w / w.sum()}))
        fixed = np.floor(w / w.max() * (1 << 30)).astype(np.int64)
        parent = np.repeat(np.arange(n), draw_systematic(fixed, n, seed, c))
    return pd.concat(out, ignore_index=True)


LINEAGE = "lineage_id string, cycle int, slot long, parent_slot long, weight double, duration_us long"


def ensemble_lineages(runs: DataFrame, obs: DataFrame) -> DataFrame:
    """Lineages of many runs: ``runs`` (lineage_id, n, cycles, seed, sigma), ``obs`` (cycle, cell_id, mask).

    A run with null ``sigma`` filters the observed mask; else it is synthetic with that spread.  Every
    group holds one small grid (cycles x cells booleans) beside its run.
    """
    grid = obs.select(F.struct("cycle", "cell_id", "mask").alias("o")).agg(F.collect_list("o").alias("obs"))  # the grid's size: hours x 80 cells

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        r = pdf.iloc[0]
        if pd.isna(r["sigma"]):
            rows = [(o["cycle"], o["cell_id"], o["mask"]) for o in r["obs"]]
            mask = np.zeros((max(o[0] for o in rows) + 1, max(o[1] for o in rows) + 1), bool)
            for c, k, m in rows:
                mask[c, k] = m
            out = mask_filter(mask, int(r["n"]), int(r["cycles"]), int(r["seed"]))
        else:
            out = spread_lineage(int(r["n"]), int(r["cycles"]), int(r["seed"]), float(r["sigma"]))
        out.insert(0, "lineage_id", r["lineage_id"])
        out["duration_us"] = np.int64(-1)
        return out

    return runs.crossJoin(F.broadcast(grid)).groupBy("lineage_id").applyInPandas(one, LINEAGE)
