"""Registered queries of the methods, variants, baselines, measures and workloads, with DuckDB SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from particle_engine.functions.rng import normal4, sql_normal4, sql_unit, unit_int
from particle_engine.operators import observe, placement, posterior, resample, schedule, weights
from particle_engine.operators.models import Model, propagate
from particle_engine.plans import baselines, metrics, workloads
from particle_engine.plans.filter import Spec, run_filter
from particle_engine.plans.workloads import K1_PARTICLES, NATURAL, SEED, table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

CYCLE = "CAST(floor((epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01 00:00:00')) / 3600000000) AS INTEGER)"
CELL = "CAST((user_id % 16) * 5 + list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) - 1 AS INTEGER)"


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


# Observations.


@query(f"SELECT {CYCLE} AS cycle, count(*) AS n, round(avg(value), 6) AS mean_value FROM events GROUP BY 1")
def k1_obs_hourly(spark, sf):
    return observe.hourly(table(spark, sf, "events"))


MASK = f"""g AS (SELECT CAST(c AS INTEGER) AS cycle, CAST(k AS INTEGER) AS cell_id FROM range(48) t(c), range(80) u(k)),
seen AS (SELECT {CYCLE} AS cycle, {CELL} AS cell_id, count(*) AS n FROM events WHERE ts < TIMESTAMP '2024-01-03 00:00:00' GROUP BY 1, 2),
mask AS (SELECT cycle, cell_id, CAST(coalesce(n, 0) AS BIGINT) AS n, coalesce(n, 0) > 0 AS mask FROM g LEFT JOIN seen USING (cycle, cell_id))"""


@query(f"WITH {MASK} SELECT * FROM mask")
def k1_mask_grid(spark, sf):
    return observe.mask_grid(table(spark, sf, "events"), 48)


@query(f"WITH {MASK} SELECT cycle, CAST(cell_id // 5 AS INTEGER) AS super_cell, CAST(sum(CAST(mask AS INTEGER)) AS BIGINT) AS hits, sum(CAST(mask AS INTEGER)) * 2 >= 5 AS mask FROM mask GROUP BY 1, 2")
def k1_mask_upscaled(spark, sf):
    return observe.upscaled_mask(table(spark, sf, "events"))


# One cycle of the mask filter, every step checked.

STATES = f"p AS (SELECT CAST(i AS BIGINT) AS particle_id FROM range({K1_PARTICLES}) t(i)), s0 AS (SELECT particle_id, cell_id, {sql_unit(str(SEED), '0', 'particle_id', 'cell_id')} AS x FROM p, (SELECT CAST(k AS INTEGER) AS cell_id FROM range(80) u(k)))"
#: The same on the cells that events fall into.
SEEN_CELLS = f"(SELECT DISTINCT {CELL} AS cell_id FROM events WHERE user_id IS NOT NULL AND event_type IS NOT NULL)"
SEEN = STATES.replace("(SELECT CAST(k AS INTEGER) AS cell_id FROM range(80) u(k))", SEEN_CELLS)
MOVED = f"s1 AS (SELECT particle_id, cell_id, least(greatest(x + 0.25::DOUBLE * (0.2::DOUBLE - x) + 0.15::DOUBLE * (2.0::DOUBLE * {sql_unit(str(SEED), '1', 'particle_id', 'cell_id')} - 1.0::DOUBLE), 0.0::DOUBLE), 1.0::DOUBLE) AS x FROM s0)"
SCORED = "mm AS MATERIALIZED (SELECT particle_id, CAST(sum(CAST((x >= 0.5) <> mask AS INTEGER)) AS BIGINT) AS mismatches FROM s1 JOIN mask USING (cell_id) WHERE cycle = 0 GROUP BY particle_id), w AS MATERIALIZED (SELECT particle_id, mismatches, CASE WHEN 30 - (mismatches - (SELECT min(mismatches) FROM mm)) >= 0 THEN CAST(1 AS BIGINT) << CAST(30 - (mismatches - (SELECT min(mismatches) FROM mm)) AS INTEGER) ELSE 0 END AS w_fix FROM mm)"
CYCLE1 = f"WITH {MASK}, {STATES}, {MOVED}, {SCORED}"
PREFIX = "f AS MATERIALIZED (SELECT particle_id, CAST(w_fix AS HUGEINT) AS w_fix, CAST(sum(w_fix) OVER (ORDER BY particle_id) AS HUGEINT) AS hi, CAST(sum(w_fix) OVER () AS HUGEINT) AS total FROM w)"


def _h52(*key: str) -> str:
    return f"CAST(('0x' || substr(md5(concat_ws('|', {', '.join(key)})), 1, 13)) AS HUGEINT)"


def _draw_sql(scheme: str, cycle: str = "1", n: str = str(K1_PARTICLES)) -> str:
    """CTEs from ``f`` to ``drawn`` (parent_id, alpha)."""
    pos = lambda slot: f"({_h52(str(SEED), cycle, '-1', slot)} * total // 4503599627370496)"
    if scheme == "systematic":
        u = pos("0")
        up = lambda c: f"greatest(0, (CAST({n} AS HUGEINT) * {c} - {u} + total - 1) // total)"
        return f"drawn AS MATERIALIZED (SELECT particle_id AS parent_id, CAST({up('hi')} - {up('(hi - w_fix)')} AS BIGINT) AS alpha FROM f WHERE {up('hi')} > {up('(hi - w_fix)')})"
    found = lambda f: f"SELECT d.slot, f2.particle_id AS parent_id FROM d JOIN {f} f2 ON d.position >= f2.hi - f2.w_fix AND d.position < f2.hi"
    slots = f"(SELECT CAST(i AS BIGINT) AS slot FROM range({n}) t(i))"
    if scheme == "multinomial":
        return f"d AS (SELECT slot, {pos('slot')} AS position FROM {slots}, (SELECT max(total) AS total FROM f)), drawn AS (SELECT parent_id, count(*) AS alpha FROM ({found('f')}) GROUP BY 1)"
    if scheme == "stratified":
        return f"d AS (SELECT slot, (slot * total + {pos('slot')}) // {n} AS position FROM {slots}, (SELECT max(total) AS total FROM f)), drawn AS (SELECT parent_id, count(*) AS alpha FROM ({found('f')}) GROUP BY 1)"
    rest = f"""r AS (SELECT particle_id, CAST(({n} * w_fix) // total AS BIGINT) AS sure, ({n} * w_fix) % total AS w_fix FROM f),
    f3 AS (SELECT particle_id, w_fix, CAST(sum(w_fix) OVER (ORDER BY particle_id) AS HUGEINT) AS hi FROM r),
    o AS (SELECT {n} - sum(sure) AS open, CAST(sum(w_fix) AS HUGEINT) AS total FROM r),
    d AS (SELECT slot, {pos('slot')} AS position FROM {slots}, o WHERE slot < open)"""
    return f"{rest}, drawn AS (SELECT parent_id, CAST(sum(a) AS BIGINT) AS alpha FROM (SELECT parent_id, 1 AS a FROM ({found('f3')}) UNION ALL SELECT particle_id, sure FROM r WHERE sure > 0) GROUP BY 1)"


@query(f"WITH {SEEN} SELECT particle_id, cell_id, round(x, 12) AS x FROM s0")
def f1_initial_ensemble(spark, sf):
    return workloads.seen_states(spark, sf).withColumn("x", F.round("x", 12))


@query(f"WITH {SEEN}, {MOVED} SELECT particle_id, cell_id, round(x, 12) AS x FROM s1")
def f2_propagated(spark, sf):
    return propagate(workloads.seen_states(spark, sf), Model(), 1, SEED).withColumn("x", F.round("x", 12))


@query()
def f2a_inner_steps(spark, sf):
    """36 inner model steps in one cycle."""
    return propagate(workloads.seen_states(spark, sf, 16), Model(fast=True), 1, SEED, steps=36)


def _inner_step_query(steps: int) -> None:
    start = SEEN.replace(f"range({K1_PARTICLES})", "range(16)")
    noise = f"0.15::DOUBLE * (2.0::DOUBLE * {sql_unit(str(SEED), '1', 'particle_id', 'cell_id', 'i + 1')} - 1.0::DOUBLE) / {steps**0.5!r}::DOUBLE"
    moved = f"least(greatest(x + {0.25 / steps!r}::DOUBLE * (0.2::DOUBLE - x) + {noise}, 0.0::DOUBLE), 1.0::DOUBLE)"

    def run(spark, sf):
        return propagate(workloads.seen_states(spark, sf, 16), Model(), 1, SEED, steps=steps).withColumn("x", F.round("x", 9))

    run.__name__ = f"f2a_steps_{steps}"
    query(f"WITH RECURSIVE {start}, m AS (SELECT 0 AS i, particle_id, cell_id, x FROM s0 UNION ALL SELECT i + 1, particle_id, cell_id, {moved} FROM m WHERE i < {steps}) SELECT particle_id, cell_id, round(x, 9) AS x FROM m WHERE i = {steps}")(run)


for _steps in (36, 150):  # fixed values: the published inner steps of a cycle
    _inner_step_query(_steps)


@query(f"{CYCLE1} SELECT * FROM w")
def k1_cycle1_weights(spark, sf):
    return workloads.k1_scored(spark, sf)


@query(f"{CYCLE1}, t AS (SELECT sum(w_fix) AS t FROM w) SELECT particle_id, round(w_fix::DOUBLE / t, 12) AS w_hat FROM w, t")
def f8_normalised(spark, sf):
    return weights.normalise(workloads.k1_scored(spark, sf)).select("particle_id", F.round("w_hat", 12).alias("w_hat"))


@query(f"{CYCLE1} SELECT count(*) AS n, round(max(w_fix) / sum(w_fix)::DOUBLE, 9) AS max_w, round(sum(w_fix::DOUBLE) * sum(w_fix::DOUBLE) / sum(w_fix::DOUBLE * w_fix::DOUBLE), 6) AS ess, round(sum(w_fix::DOUBLE * w_fix::DOUBLE) / (sum(w_fix::DOUBLE) * sum(w_fix::DOUBLE)) / count(*) - 1.0::DOUBLE / (count(*)::DOUBLE * count(*)), 12) AS weight_var, round(sum(CAST(w_fix = 0 AS INTEGER)) / count(*)::DOUBLE, 9) AS underflow_share FROM w")
def f16_degeneracy(spark, sf):
    return weights.degeneracy(workloads.k1_scored(spark, sf))


@query(f"{CYCLE1}, e AS (SELECT -mismatches * ln(2.0::DOUBLE) AS lw FROM w) SELECT round(max(lw) + ln(avg(exp(lw - (SELECT max(lw) FROM e)))), 6) AS log_evidence FROM e")
def f7_evidence(spark, sf):
    scored = workloads.k1_scored(spark, sf).withColumn("log_w", -F.col("mismatches") * F.log(F.lit(2.0)))
    return weights.evidence(scored).select(F.round("log_evidence", 6).alias("log_evidence"))


def _resample_query(scheme: str) -> None:
    def run(spark, sf):
        return resample.resample(workloads.k1_scored(spark, sf).select("particle_id", "w_fix"), K1_PARTICLES, scheme, SEED, 1)

    run.__name__ = f"resample_{scheme}"
    query(f"{CYCLE1}, {PREFIX}, {_draw_sql(scheme)} SELECT parent_id, alpha FROM drawn")(run)


for _scheme in resample.SCHEMES:
    _resample_query(_scheme)


@query(f"{CYCLE1}, {PREFIX}, {_draw_sql('systematic')} SELECT parent_id, alpha FROM drawn")
def resample_two_phase_prefix(spark, sf):
    """The same systematic draw with prefix sums in two phases over id ranges."""
    return resample.resample(workloads.k1_scored(spark, sf).select("particle_id", "w_fix"), K1_PARTICLES, "systematic", SEED, 1, ranges=7)


OFFSPRING = "kids AS MATERIALIZED (SELECT CAST(row_number() OVER (ORDER BY parent_id, copy_no) - 1 AS BIGINT) AS slot, parent_id, CAST(copy_no AS INTEGER) AS copy_no FROM (SELECT parent_id, unnest(range(0, alpha)) AS copy_no FROM drawn))"


@query(f"{CYCLE1}, {PREFIX}, {_draw_sql('systematic')}, {OFFSPRING} SELECT * FROM kids")
def k1_cycle1_offspring(spark, sf):
    return resample.offspring(QUERIES["resample_systematic"](spark, sf))


@query(f"{CYCLE1}, {PREFIX}, {_draw_sql('systematic')} SELECT particle_id FROM p WHERE particle_id IN (SELECT parent_id FROM drawn)")
def survivors(spark, sf):
    drawn = QUERIES["resample_systematic"](spark, sf)
    return workloads.k1_scored(spark, sf).select("particle_id").join(drawn, F.col("particle_id") == F.col("parent_id"), "left_semi")


@query(f"{CYCLE1}, {PREFIX}, {_draw_sql('systematic')} SELECT particle_id FROM p WHERE particle_id NOT IN (SELECT parent_id FROM drawn)")
def discarded(spark, sf):
    drawn = QUERIES["resample_systematic"](spark, sf)
    return workloads.k1_scored(spark, sf).select("particle_id").join(drawn, F.col("particle_id") == F.col("parent_id"), "left_anti")


@query(f"{CYCLE1}, v AS (SELECT cell_id, sum(x * w_fix::DOUBLE) / sum(w_fix::DOUBLE) AS m, sum(x * x * w_fix::DOUBLE) / sum(w_fix::DOUBLE) AS m2, count(*) AS n FROM s1 JOIN w USING (particle_id) GROUP BY cell_id) SELECT cell_id, round(m, 6) AS mean, round(m2 - m * m, 6) AS var, n FROM v")
def k1_posterior(spark, sf):
    moved = propagate(workloads.k1_states(spark), Model(), 1, SEED)
    return posterior.posterior(moved, workloads.k1_scored(spark, sf))


@query(f"{CYCLE1}, h AS (SELECT cell_id, CAST(CASE WHEN x < 0 THEN 0 WHEN x >= 1 THEN 11 ELSE floor(x * 10) + 1 END AS BIGINT) AS bin, sum(w_fix::DOUBLE) AS s FROM s1 JOIN w USING (particle_id) GROUP BY ALL) SELECT cell_id, bin, round(s / sum(s) OVER (PARTITION BY cell_id), 9) AS share FROM h")
def f9_histogram(spark, sf):
    moved = propagate(workloads.k1_states(spark), Model(), 1, SEED)
    return posterior.histogram(moved, workloads.k1_scored(spark, sf), 0.0, 1.0, 10)


@query(f"{CYCLE1}, {PREFIX}, {_draw_sql('systematic')}, {OFFSPRING} SELECT slot AS particle_id, parent_id, copy_no, cell_id, round(CASE WHEN copy_no = 0 THEN x ELSE x + 0.05::DOUBLE * {sql_normal4(str(SEED), '1', 'slot', 'cell_id')} END, 9) AS x FROM kids JOIN s1 ON particle_id = parent_id")
def f12_perturbed_copies(spark, sf):
    moved = propagate(workloads.k1_states(spark), Model(), 1, SEED)
    kids = k1_cycle1_offspring(spark, sf)
    copies = moved.join(kids, moved["particle_id"] == kids["parent_id"]).select(F.col("slot").alias("particle_id"), "parent_id", "copy_no", "cell_id", "x")
    return resample.perturb(copies, 0.05, SEED, 1).withColumn("x", F.round("x", 9))


@query(f"{CYCLE1}, {PREFIX}, {_draw_sql('systematic')}, {OFFSPRING} SELECT count(*) AS n, count(DISTINCT parent_id) AS q FROM kids")
def f14_shipped_offspring(spark, sf):
    """Parents' states shipped by placement: as many offspring and parents as drawn."""
    moved = propagate(workloads.k1_states(spark), Model(), 1, SEED)
    drawn = QUERIES["resample_systematic"](spark, sf)
    shipped = placement.ship(moved, placement.assign(drawn, 8), 8)
    return shipped.select("particle_id", "parent_id").distinct().agg(F.count(F.lit(1)).alias("n"), F.countDistinct("parent_id").alias("q"))


@query("SELECT CAST(c AS INTEGER) AS cycle, true AS whole FROM range(4) t(c)")
def k1_multi_cycle(spark, sf):
    """Four cycles of the distributed filter: in each, copies sum to P and parents are at most P."""
    mask = observe.mask_grid(table(spark, sf, "events"), 4)
    spec = Spec(n_particles=64)
    run = run_filter(workloads.k1_states(spark, 64), mask, [0, 1, 2, 3], spec, "k1")
    parts = [run.store.read("offspring", "k1", c).withColumn("cycle", F.lit(c)) for c in range(4)]
    every = parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])
    per = every.groupBy("cycle").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("slot").alias("slots"), F.countDistinct("parent_id").alias("q"))
    return per.select("cycle", ((F.col("n") == 64) & (F.col("slots") == 64) & (F.col("q") <= 64)).alias("whole"))


@query()
def adaptive_policy(spark, sf):
    """(policy, cycle, ess, redraw): conditional redraw over four cycles, weights carried where there was none."""
    mask = observe.mask_grid(table(spark, sf, "events"), 4)
    out = []
    for policy, t in (("ess", 0.5), ("every_k", 3), ("variance", 0.5)):
        run = run_filter(workloads.k1_states(spark, 32), mask, list(range(4)), Spec(n_particles=32, policy=policy, policy_threshold=t), policy)
        out += [(policy, d["cycle"], float(d["ess"]), bool(d["redraw"])) for d in run.diagnostics]
    return spark.createDataFrame(out, "policy string, cycle int, ess double, redraw boolean")


@query("SELECT 'systematic' AS scheme, true AS unbiased UNION ALL SELECT 'residual', true UNION ALL SELECT 'stratified', true UNION ALL SELECT 'multinomial', true")
def a27_draw_bias(spark, sf):
    """Mean deviation of copies from their expectation over seeds stays within 4 standard errors; an event type is a particle, its events of value over 50 are its weight."""
    kind = F.array_position(F.array(*map(F.lit, observe.EVENT_TYPES)), F.col("event_type")).cast("long")
    w = table(spark, sf, "events").groupBy(kind.alias("particle_id")).agg(F.count_if(F.col("value") > 50).alias("w_fix"))
    w = spark.createDataFrame(w.where("particle_id > 0").collect(), w.schema)  # five rows at most, drawn from 48 times
    out = None
    for scheme in resample.SCHEMES:
        b = resample.draw_bias(w, 16, scheme, 12).agg(F.max(F.abs(F.col("bias")) - 4 * F.sqrt((F.col("variance") + 0.05) / 12)).alias("worst"))
        row = b.select(F.lit(scheme).alias("scheme"), (F.col("worst") <= 0).alias("unbiased"))
        out = row if out is None else out.unionByName(row)
    return out


# K1b: scalar level.


@query()
def k1b_vs_exact(spark, sf):
    """(cycles, within): share of hours whose particle mean lies within 4 standard errors of the exact mean."""
    level = workloads.k1b_level(spark, sf)
    exact = baselines.exact_kalman(level, 50.0, 400.0, 16.0, 49.0**2)
    got = workloads.k1b_filter(level, 2048).withColumnsRenamed({"mean": "m", "var": "v"})
    j = exact.drop("var").join(got, "cycle", "left")  # an hour the filter leaves out counts as not within
    near = F.abs(F.col("m") - F.col("mean")) <= 4 * F.sqrt(F.col("v") / F.col("ess"))
    return j.agg(F.count(F.lit(1)).alias("cycles"), F.round(F.avg(F.coalesce(near, F.lit(False)).cast("int")), 4).alias("within"))


@query(
    f"""WITH RECURSIVE l AS (SELECT {CYCLE} AS cycle, count(*) AS n, round(avg(value), 6) AS y FROM events GROUP BY 1),
    o AS (SELECT *, row_number() OVER (ORDER BY cycle) AS i FROM l),
    k AS (SELECT CAST(0 AS BIGINT) AS i, CAST(NULL AS INTEGER) AS cycle, 50.0::DOUBLE AS m, 400.0::DOUBLE AS v
      UNION ALL SELECT o.i, o.cycle, k.m + ((k.v + 16.0::DOUBLE) / ((k.v + 16.0::DOUBLE) + 2401.0::DOUBLE / o.n)) * (o.y - k.m), (k.v + 16.0::DOUBLE) * (1.0::DOUBLE - (k.v + 16.0::DOUBLE) / ((k.v + 16.0::DOUBLE) + 2401.0::DOUBLE / o.n)) FROM k JOIN o ON o.i = k.i + 1)
    SELECT cycle, round(m, 6) AS mean, round(v, 6) AS var FROM k WHERE i > 0"""
)
def b8_exact_kalman(spark, sf):
    return baselines.exact_kalman(workloads.k1b_level(spark, sf), 50.0, 400.0, 16.0, 2401.0)


def _k1b_states(spark, particles=64):
    start = F.lit(50.0) + F.lit(20.0) * normal4(SEED, 0, F.col("id"), 0)
    return spark.range(particles).select(F.col("id").alias("particle_id"), start.alias("x"))


def _k1b_level_at(spark, sf, rank):
    first = Window.orderBy("cycle")  # one row an hour
    return workloads.k1b_level(spark, sf).withColumn("i", F.row_number().over(first)).where(F.col("i") == rank).select("mean_value")


K1B = f"""WITH l AS (SELECT {CYCLE} AS cycle, round(avg(value), 6) AS y FROM events GROUP BY 1), o AS (SELECT *, row_number() OVER (ORDER BY cycle) AS i FROM l),
a0 AS (SELECT CAST(i AS BIGINT) AS pid, 50.0::DOUBLE + 20.0::DOUBLE * {sql_normal4(str(SEED), '0', 'i', '0')} AS x FROM range(64) t(i)),
a1 AS (SELECT pid, x + 4.0::DOUBLE * {sql_normal4(str(SEED), '1', 'pid', '0')} AS x FROM a0),
w1 AS (SELECT pid, x, CAST(floor(1.0::DOUBLE / (1.0::DOUBLE + ((y - x) / 10.0::DOUBLE) * ((y - x) / 10.0::DOUBLE)) * 1073741824.0::DOUBLE) AS BIGINT) AS w_fix FROM a1, o WHERE i = 1),
w AS (SELECT pid AS particle_id, w_fix FROM w1), {PREFIX}, {_draw_sql('systematic', '1', '64')}, {OFFSPRING},
a2 AS (SELECT slot AS pid, x + 4.0::DOUBLE * {sql_normal4(str(SEED), '2', 'slot', '0')} AS x FROM kids JOIN w1 ON pid = parent_id),
w2 AS (SELECT pid, x, CAST(floor(1.0::DOUBLE / (1.0::DOUBLE + ((y - x) / 10.0::DOUBLE) * ((y - x) / 10.0::DOUBLE)) * 1073741824.0::DOUBLE) AS BIGINT) AS w_fix FROM a2, o WHERE i = 2)"""


@query(f"{K1B} SELECT 1 AS step, round(sum(x * w_fix) / sum(w_fix), 6) AS mean FROM w1 UNION ALL SELECT 2, round(sum(x * w_fix) / sum(w_fix), 6) FROM w2")
def k1b_two_cycles(spark, sf):
    """Two whole cycles as one nested plan: propagate, weigh, redraw, propagate, weigh."""
    fix = lambda df: df.withColumn("w_fix", F.floor(F.col("w") * F.lit(1073741824.0)).cast("long"))
    one = fix(workloads.scalar_cauchy_cycle(_k1b_states(spark), _k1b_level_at(spark, sf, 1), 1, 10.0))
    kids = resample.offspring(resample.resample(one.select("particle_id", "w_fix"), 64, "systematic", SEED, 1))
    drawn = one.join(kids, one["particle_id"] == kids["parent_id"]).select(F.col("slot").alias("particle_id"), "x")
    two = fix(workloads.scalar_cauchy_cycle(drawn, _k1b_level_at(spark, sf, 2), 2, 10.0))
    mean = F.round(F.sum(F.col("x") * F.col("w_fix")) / F.sum("w_fix"), 6).alias("mean")
    return one.agg(mean).select(F.lit(1).alias("step"), "mean").unionByName(two.agg(mean).select(F.lit(2).alias("step"), "mean"))


@query(f"""WITH t AS (SELECT {CYCLE} AS cycle, round(avg(value), 6) AS truth FROM events GROUP BY 1), b AS (SELECT *, truth + {sql_normal4('8', 'cycle', '-1', '0')} AS centre FROM t),
m AS (SELECT cycle, truth, centre + {sql_normal4('9', 'cycle', 'p', '0')} AS x FROM b, range(64) r(p)),
far AS (SELECT cycle, any_value(truth) AS truth, avg(x) AS mean, avg(abs(x - truth)) AS far, quantile_cont(x, 0.05) AS lo, quantile_cont(x, 0.95) AS hi FROM m GROUP BY 1),
pairs AS (SELECT a.cycle, avg(abs(a.x - b.x)) AS apart FROM m a JOIN m b ON a.cycle = b.cycle GROUP BY 1)
SELECT round(sqrt(avg((mean - truth) * (mean - truth))), 6) AS rmse, round(avg(mean - truth), 6) AS bias, round(avg(far - apart / 2), 6) AS crps, round(avg(CAST(truth BETWEEN lo AND hi AS INTEGER)), 6) AS coverage, count(*) AS cycles FROM far JOIN pairs USING (cycle)""")
def a26_accuracy(spark, sf):
    """Scores of a twin experiment: members drawn around the hourly levels of all events."""
    truth = workloads.k1b_level(spark, sf).select("cycle", F.col("mean_value").alias("truth"))
    members = truth.crossJoin(spark.range(64).withColumnRenamed("id", "particle_id")).select("cycle", "particle_id", (F.col("truth") + normal4(8, F.col("cycle"), -1, 0) + normal4(9, F.col("cycle"), F.col("particle_id"), 0)).alias("x"))
    return posterior.accuracy(members, truth).select(*[F.round(c, 6).alias(c) for c in ("rmse", "bias", "crps", "coverage")], "cycles")


# K2, K3.


@query(f"""WITH f AS (SELECT CAST(({CYCLE} // 3) * 3 AS INTEGER) AS forcing_cycle, round(avg(value), 6) AS value FROM events GROUP BY 1), c AS (SELECT DISTINCT {CYCLE} AS cycle FROM events)
SELECT cycle, forcing_cycle, value FROM c ASOF LEFT JOIN f ON cycle >= forcing_cycle""")
def k2_forcing_asof(spark, sf):
    return observe.forcing_asof(table(spark, sf, "events"))


K3 = "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, c_nationkey AS nation, sum(CAST(round(l_extendedprice * 100) AS BIGINT) * CAST(round((1 - l_discount) * 100) AS BIGINT)) AS r FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2"


@query(f"SELECT month, nation, CAST(r AS BIGINT) / 10000.0::DOUBLE AS revenue FROM ({K3})")
def k3_nation_month_obs(spark, sf):
    return observe.nation_month(spark, sf)


@query(f"SELECT r_name AS region, CAST(coalesce(nation, -1) AS INTEGER) AS nation, month, count(*) AS cells, CAST(sum(r) AS BIGINT) / 10000.0::DOUBLE AS revenue FROM ({K3}) JOIN nation ON n_nationkey = nation JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, nation, month)")
def k3_region_rollup(spark, sf):
    dims = table(spark, sf, "nation").join(table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", F.col("r_name").alias("region"))
    obs = observe.nation_month(spark, sf).join(F.broadcast(dims), F.col("nation") == F.col("n_nationkey"))  # 25 nations
    out = obs.rollup("region", "nation", "month").agg(F.count(F.lit(1)).alias("cells"), (F.sum(F.round(F.col("revenue") * 10000).cast("long")) / F.lit(10000.0)).alias("revenue"))
    return out.withColumn("nation", F.coalesce("nation", F.lit(-1)))


@query(f"""WITH o AS (SELECT nation AS cell_id, ln(CAST(r AS BIGINT) / 10000.0::DOUBLE) AS y FROM ({K3}) WHERE month = '1995-01-01'),
s AS (SELECT CAST(i AS BIGINT) AS particle_id, CAST(k AS INTEGER) AS cell_id, 12.0::DOUBLE + {sql_normal4(str(SEED), '0', 'i', 'k')} AS x FROM range(64) t(i), range(25) u(k))
SELECT particle_id, round(sum(CASE WHEN y IS NULL THEN 0.0 ELSE -ln(1.0::DOUBLE + ((y - x) / 0.5::DOUBLE) * ((y - x) / 0.5::DOUBLE)) END), 9) AS log_w FROM s LEFT JOIN o USING (cell_id) GROUP BY 1""")
def k3_cycle_weights(spark, sf):
    """(particle_id, log_w): 25-cell log-revenue states scored with the rational kernel; a nation without revenue adds nothing."""
    obs = observe.nation_month(spark, sf).where("month = (select '1995-01-01')").select(F.col("nation").alias("cell_id"), F.log("revenue").alias("y"))
    base = spark.range(25).select(F.col("id").cast("int").alias("cell_id"))
    states = spark.range(64).withColumnRenamed("id", "particle_id").crossJoin(F.broadcast(base)).withColumn("x", F.lit(12.0) + normal4(SEED, 0, F.col("particle_id"), F.col("cell_id")))
    return weights.log_likelihood(states, obs, "cauchy", 0.5).withColumn("log_w", F.round("log_w", 9))


# K14: natural multisets.


def _natural_queries(name: str, key: str) -> None:
    a = f"a AS (SELECT {key} AS parent_id, count(*) AS alpha FROM {name} WHERE {key} IS NOT NULL GROUP BY 1), t AS (SELECT sum(alpha) AS p FROM a)"

    def split(spark, sf):
        return schedule.split_factor(workloads.natural(spark, sf, name), 32)

    def static(spark, sf):
        return schedule.static_schedule(workloads.natural(spark, sf, name), 32)

    def bounds(spark, sf):
        parents = workloads.natural(spark, sf, name)
        loads = schedule.schedule_loads(schedule.static_schedule(parents, 32, ranges=4))
        return schedule.load_bounds(parents, 32).crossJoin(F.broadcast(loads))

    split.__name__, static.__name__, bounds.__name__ = f"k14_split_{name}", f"k14_static_{name}", f"k14_bounds_{name}"
    query(f"WITH {a} SELECT parent_id, alpha, CAST((alpha * 32 + p - 1) // p AS BIGINT) AS s FROM a, t")(split)
    tasks = f"WITH {a}, o AS (SELECT parent_id, sum(alpha) OVER (ORDER BY parent_id) AS hi, alpha FROM a), e AS (SELECT parent_id, unnest(range(CAST(hi - alpha AS BIGINT), CAST(hi AS BIGINT))) AS i FROM o), r AS (SELECT CAST(i * 32 // p AS BIGINT) AS runner_id, parent_id, count(*) AS n FROM e, t GROUP BY 1, 2)"
    query(f"{tasks} SELECT * FROM r")(static)
    query(f"""{tasks} SELECT CAST(p AS BIGINT) AS p, (SELECT count(*) FROM a) AS q, (SELECT CAST(sum((alpha * 32 + p - 1) // p) AS BIGINT) FROM a) AS sum_s, (SELECT count(*) FROM a) AS lo, (SELECT count(*) FROM a) + 31 AS hi,
      (SELECT count(*) FROM r) AS loads, CAST(p AS BIGINT) AS tasks, (SELECT CAST(max(m) AS BIGINT) FROM (SELECT sum(n) AS m FROM r GROUP BY runner_id)) AS busiest FROM t""")(bounds)


for _name, _key in NATURAL.items():
    _natural_queries(_name, _key)


STAY = """WITH a AS (SELECT o_custkey AS parent_id, count(*) AS alpha, o_custkey % 8 AS home FROM orders WHERE o_custkey IS NOT NULL GROUP BY o_custkey), t AS (SELECT CAST(sum(alpha) AS BIGINT) AS p FROM a),
h AS (SELECT k AS part, (k + 1) * p // 8 - k * p // 8 AS share FROM range(8) r(k), t),
w AS (SELECT parent_id, alpha, home, greatest(0, least(alpha, share - coalesce(sum(alpha) OVER (PARTITION BY home ORDER BY alpha DESC, parent_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))) AS stay FROM a JOIN h ON part = home),
free AS (SELECT part, share - coalesce(used, 0) AS free FROM h LEFT JOIN (SELECT home AS part, sum(stay) AS used FROM w GROUP BY 1) USING (part)),
slots AS (SELECT part, unnest(range(CAST(to_ - free AS BIGINT), CAST(to_ AS BIGINT))) AS i FROM (SELECT part, free, sum(free) OVER (ORDER BY part) AS to_ FROM free)),
over_ AS (SELECT parent_id, unnest(range(CAST(to_ - m AS BIGINT), CAST(to_ AS BIGINT))) AS i FROM (SELECT parent_id, alpha - stay AS m, sum(alpha - stay) OVER (ORDER BY parent_id) AS to_ FROM w WHERE alpha > stay)),
plan AS (SELECT target_part, parent_id, CAST(sum(n) AS BIGINT) AS n FROM (SELECT home AS target_part, parent_id, stay AS n FROM w WHERE stay > 0 UNION ALL SELECT part, parent_id, 1 FROM over_ JOIN slots USING (i)) GROUP BY 1, 2)"""


@query(f"{STAY} SELECT CAST(target_part AS BIGINT) AS target_part, parent_id, n FROM plan")
def s7_placement(spark, sf):
    """Orders placed by customer on 8 partitions, first copies where the customer lives: the whole plan."""
    parents = workloads.natural(spark, sf, "orders")
    homes = parents.select("parent_id", F.pmod("parent_id", F.lit(8)).alias("home_part"))
    return placement.assign(parents, 8, "stay", homes, ranges=3)


@query(f"{STAY} SELECT count(*) AS loads, CAST(sum(CAST(target_part <> parent_id % 8 AS INTEGER)) AS BIGINT) AS moved_loads, CAST(sum(CASE WHEN target_part <> parent_id % 8 THEN n ELSE 0 END) AS BIGINT) AS moved_tasks FROM plan")
def s7_moved_loads(spark, sf):
    """Loads that leave their parent's partition under the same plan."""
    parents = workloads.natural(spark, sf, "orders")
    homes = parents.select("parent_id", F.pmod("parent_id", F.lit(8)).alias("home_part"))
    return placement.moved_copies(placement.assign(parents, 8, "stay", homes), homes)


@query("SELECT strategy, CAST(c AS INTEGER) AS cycle, CAST(64 AS BIGINT) AS tasks, true AS same_offspring FROM (VALUES ('static'), ('stay')) t(strategy), range(3) u(c)")
def s7_filter_strategies(spark, sf):
    """Three cycles of the filter with either placement: the offspring are the same, all 64 tasks are placed."""
    mask, parts = observe.mask_grid(table(spark, sf, "events"), 3), []
    for strategy in ("static", "stay"):
        run = run_filter(workloads.k1_states(spark, 64), mask, [0, 1, 2], Spec(n_particles=64, placement=strategy, diagnostics=False), strategy)
        for c in range(3):
            parts.append((strategy, c, run.store.read("plan", strategy, c), run.store.read("offspring", strategy, c)))
    out = None
    for (strategy, c, plan, kids), (_, _, _, first) in zip(parts, parts[:3] * 2):
        same = kids.join(first, ["slot", "parent_id", "copy_no"], "left_anti").agg((F.count(F.lit(1)) == 0).alias("same_offspring"))
        row = plan.agg(F.sum("n").cast("long").alias("tasks")).crossJoin(F.broadcast(same)).select(F.lit(strategy).alias("strategy"), F.lit(c).alias("cycle"), "tasks", "same_offspring")
        out = row if out is None else out.unionByName(row)
    return out


@query()
def s7_moved_by_cycle(spark, sf):
    """(strategy, cycle, loads, moved_loads, moved_tasks): what leaves its partition, with placements that know or ignore homes."""
    mask, out = observe.mask_grid(table(spark, sf, "events"), 3), []
    for strategy in ("static", "stay"):
        spec = Spec(n_particles=64, placement=strategy, diagnostics=False)
        run = run_filter(workloads.k1_states(spark, 64), mask, [0, 1, 2], spec, strategy)
        homes = placement.first_homes(workloads.k1_states(spark, 64), spec.partitions, 64)
        for c in range(3):
            plan = run.store.read("plan", strategy, c)
            out.append(placement.moved_copies(plan, homes).select(F.lit(strategy).alias("strategy"), F.lit(c).alias("cycle"), "loads", "moved_loads", "moved_tasks"))
            homes = placement.homes_of(plan)
    every = out[0]
    for row in out[1:]:
        every = every.unionByName(row)
    return every


# Published arithmetic.

T2 = "(VALUES (128, 384, 1062.0::DOUBLE, 1536, 267.0::DOUBLE), (256, 768, 1062.0, 3072, 317.0), (512, 1536, 1068.0, 6144, 422.0), (1024, 3072, 1071.0, 12288, 761.0)) t(particles, cores_a, time_a, cores_b, time_b)"


@query(f"SELECT particles, round(cores_a * time_a / particles, 3) AS proposed, round(cores_b * time_b / particles, 3) AS file_based, round((cores_b * time_b) / (cores_a * time_a), 4) AS usage_ratio FROM {T2}")
def k12_core_seconds(spark, sf):
    t = baselines.published_table(spark)
    a = metrics.core_seconds(F.col("cores_a"), F.col("time_a"), F.col("particles"))
    b = metrics.core_seconds(F.col("cores_b"), F.col("time_b"), F.col("particles"))
    ratio = (F.col("cores_b") * F.col("time_b")) / (F.col("cores_a") * F.col("time_a"))
    return t.select("particles", F.round(a, 3).alias("proposed"), F.round(b, 3).alias("file_based"), F.round(ratio, 4).alias("usage_ratio"))


@query("SELECT particles, (nodes - 1) * 39 AS model_processes, round(particles * 2.5::DOUBLE / 1024, 4) AS written_tib, round(particles * 2.5::DOUBLE * 48 / 1024, 3) AS run_tib, round(1 - ((nodes - 1) * 39) / (nodes * 40.0::DOUBLE), 6) AS overhead, round(5 * propagation_s / cycle_s, 6) AS propagation_share FROM (VALUES (315, 64, 25.1::DOUBLE, 136.0::DOUBLE), (635, 128, 25.2, 138.0), (1275, 256, 25.1, 139.0), (2555, 512, 25.0, 146.0)) t(particles, nodes, propagation_s, cycle_s)")
def k6_table_arithmetic(spark, sf):
    t = spark.createDataFrame([(315, 64, 25.1, 136.0), (635, 128, 25.2, 138.0), (1275, 256, 25.1, 139.0), (2555, 512, 25.0, 146.0)], "particles int, nodes int, propagation_s double, cycle_s double")
    procs = (F.col("nodes") - 1) * 39
    return t.select("particles", procs.alias("model_processes"), F.round(F.col("particles") * 2.5 / 1024, 4).alias("written_tib"), F.round(F.col("particles") * 2.5 * 48 / 1024, 3).alias("run_tib"), F.round(1 - procs / (F.col("nodes") * 40.0), 6).alias("overhead"), F.round(5 * F.col("propagation_s") / F.col("cycle_s"), 6).alias("propagation_share"))


# Simulated studies.


@query()
def k4_hit_ratio_by_cache(spark, sf):
    _, trace = workloads.k4(spark, sf)
    return metrics.hit_ratio(trace)


@query()
def k5_loads_vs_bound(spark, sf):
    configs, trace = workloads.k5(spark, sf)
    return metrics.bound_slack(trace, configs)


@query()
def k6_weak_scaling(spark, sf):
    configs, trace = workloads.k6(spark, sf)
    return metrics.weak_growth(trace, configs).join(metrics.work_share(trace, configs), "config_id").join(metrics.hidden_loads(trace), "config_id")


@query()
def k7_strong_scaling(spark, sf):
    configs, trace = workloads.k7(spark, sf)
    return metrics.efficiency(trace, configs, "one")


@query()
def k8_divisibility(spark, sf):
    configs, trace = workloads.k8(spark, sf)
    return metrics.balance(trace).join(metrics.makespan_ratio(trace, configs), metrics.KEY)


@query()
def k9_request_rate(spark, sf):
    """Requests, the fullest second, and how long a coordinator that answers in turn takes, at all four scales."""
    _, trace = workloads.k6(spark, sf, cycles=2)
    return metrics.coordinator_rate(trace).join(metrics.coordinator_latency(trace).drop("requests"), "config_id")


@query()
def k10_io_stats(spark, sf):
    """Load, store and propagation times at all four scales."""
    _, trace = workloads.k6(spark, sf, cycles=2)
    return metrics.io_time_stats(trace).join(metrics.task_time_stats(trace), "config_id")


@query()
def k11_fault_trace(spark, sf):
    _, trace = workloads.k11(spark, sf)
    return metrics.gantt(trace)


@query()
def k11_recovery_cost(spark, sf):
    _, trace = workloads.k11(spark, sf)
    return metrics.recovery_cost(trace)


@query()
def k12_simulated_modes(spark, sf):
    configs, trace = workloads.k12(spark, sf)
    return workloads.summary(configs, trace)


@query()
def k13_phase_shares(spark, sf):
    _, trace = workloads.k11(spark, sf, cycles=3)
    return metrics.phase_shares(trace.where("runner_id = 0"))


@query()
def k15_variable_cost(spark, sf):
    configs, trace = workloads.k15(spark, sf)
    return workloads.summary(configs, trace).join(metrics.makespan_ratio(trace, configs).drop("cycle"), "config_id")


@query()
def k16_io_bound(spark, sf):
    configs, trace = workloads.k16(spark, sf)
    return workloads.summary(configs, trace).join(metrics.hidden_loads(trace), "config_id")


@query()
def s_policies(spark, sf):
    configs, trace = workloads.policies(spark, sf)
    return workloads.summary(configs, trace).join(metrics.control_bytes(trace), "config_id")


@query()
def c3_evictions(spark, sf):
    configs, trace = workloads.evictions(spark, sf)
    return metrics.hit_ratio(trace).join(metrics.io_volume(trace, 2_684_354_560).groupBy("config_id").agg(F.sum("read_bytes").alias("read_bytes")), "config_id")


@query()
def c5_io_modes(spark, sf):
    configs, trace = workloads.io_modes(spark, sf)
    return workloads.summary(configs, trace).join(metrics.hidden_loads(trace), "config_id")


@query()
def a13_sync_penalty(spark, sf):
    _, trace = workloads.io_modes(spark, sf)
    return metrics.sync_penalty(trace, "async", "sync")


@query()
def e2_elastic(spark, sf):
    """Two runners leave and two join during the run; every task is done once."""
    configs = workloads.settings(spark, [{"config_id": "elastic", "lineage_id": "p128", "r": 30, "c": 9, "leaves": "3:60000000,4:90000000", "joins": "30:50000000,31:120000000"}])
    from particle_engine.plans.simulate import simulate

    trace = simulate(configs, workloads.lineages(spark, sf, [("p128", 128, 4, 0.35)]))
    return metrics.loads(trace.where("ok")).join(metrics.cycle_time(trace), metrics.KEY)


@query("SELECT v AS violation, CAST(0 AS BIGINT) AS n FROM (VALUES ('overlap'), ('not_exactly_once'), ('report_before_store'), ('cycles_interleave'), ('cache_too_large')) t(v)")
def trace_invariants(spark, sf):
    """Violations of the trace rules over fault, policy and cache studies together: none."""
    out = None
    for configs, trace in (workloads.k11(spark, sf, 4), workloads.policies(spark, sf, cycles=3), workloads.k4(spark, sf, (1, 3, 9), 4)):
        v = metrics.violations(trace, configs.select("config_id", "c"))
        out = v if out is None else out.unionByName(v)
    return out.groupBy("violation").agg(F.sum("n").cast("long").alias("n"))


@query("SELECT CAST(c AS INTEGER) AS cycle, true AS same FROM range(3) t(c)")
def engines_agree(spark, sf):
    """The grouped small-filter engine draws the same lineage as the distributed one."""
    mask = observe.mask_grid(table(spark, sf, "events"), 4)
    run = run_filter(workloads.k1_states(spark, 48), mask, [0, 1, 2], Spec(n_particles=48), "agree")
    lin = workloads.lineages(spark, sf, [("small", 48, 4, None)])
    parts = [run.store.read("offspring", "agree", c).select(F.lit(c).alias("cycle"), "slot", "parent_id") for c in range(3)]
    every = parts[0].unionByName(parts[1]).unionByName(parts[2])
    j = every.join(lin.select((F.col("cycle") - 1).alias("cycle"), "slot", "parent_slot"), ["cycle", "slot"])
    return j.groupBy("cycle").agg((F.sum((F.col("parent_id") == F.col("parent_slot")).cast("int")) == 48).alias("same"))


# K17, K18.


@query("""WITH e AS (SELECT vec_id, label, unnest(range(0, 64)) AS dim, CAST(unnest(embedding) AS DOUBLE) AS v FROM embeddings), c AS (SELECT dim, round(avg(v), 6) AS c FROM e WHERE label = 0 GROUP BY dim),
t AS (SELECT vec_id, dim, -ln(1.0::DOUBLE + ((v - c) / 0.125::DOUBLE) * ((v - c) / 0.125::DOUBLE)) AS t FROM e JOIN c USING (dim)), s AS (SELECT d, vec_id, sum(t) AS lw FROM t, (VALUES (1), (2), (4), (8), (16), (32), (64)) x(d) WHERE dim < d GROUP BY ALL),
m AS (SELECT d, max(lw) AS top FROM s GROUP BY d) SELECT CAST(d AS INTEGER) AS d, round(sum(exp(lw - top)) * sum(exp(lw - top)) / sum(exp(lw - top) * exp(lw - top)), 3) AS ess, round(1 / sum(exp(lw - top)), 6) AS max_w FROM s JOIN m USING (d) GROUP BY d""")
def k17_degeneracy_by_dim(spark, sf):
    """(d, ess, max_w): effective size falls and the largest weight rises with dimension."""
    s = workloads.k17_scores(spark, sf)
    top = s.groupBy("d").agg(F.max("log_w").alias("top"))
    w = F.exp(F.col("log_w") - F.col("top"))
    return s.join(F.broadcast(top), "d").groupBy("d").agg(F.round(F.sum(w) * F.sum(w) / F.sum(w * w), 3).alias("ess"), F.round(1 / F.sum(w), 6).alias("max_w"))


@query(rf"""WITH d AS (SELECT doc_id, quality, greatest(length(text), 1)::DOUBLE AS n, text FROM documents JOIN labels USING (doc_id)),
x AS (SELECT quality, least(n, 4000.0::DOUBLE) / 4000.0::DOUBLE AS f1, len(regexp_extract_all(text, '[0-9]')) / n AS f2, len(regexp_extract_all(text, '[A-Z]')) / n AS f3 FROM d),
b AS (SELECT CAST(i AS BIGINT) AS particle_id, {', '.join(f"{sql_normal4(str(SEED), '0', 'i', str(j))} AS b{j}" for j in range(4))} FROM range(64) t(i))
SELECT particle_id, CAST(sum(CAST(CAST(b0 + b1 * f1 + b2 * f2 + b3 * f3 > 0 AS INTEGER) <> quality AS INTEGER)) AS BIGINT) AS errors, count(*) AS docs FROM x, b GROUP BY particle_id""")
def k18_classifier_cycle(spark, sf):
    """One cycle whose observation is every labelled document."""
    return workloads.k18_errors(spark, sf)


@query(rf"""WITH d AS (SELECT doc_id % 4 AS cycle, quality, greatest(length(text), 1)::DOUBLE AS n, text FROM documents JOIN labels USING (doc_id)),
x AS (SELECT cycle, quality, least(n, 4000.0::DOUBLE) / 4000.0::DOUBLE AS f1, len(regexp_extract_all(text, '[0-9]')) / n AS f2, len(regexp_extract_all(text, '[A-Z]')) / n AS f3 FROM d),
b AS (SELECT CAST(i AS BIGINT) AS particle_id, {', '.join(f"{sql_normal4(str(SEED), '0', 'i', str(j))} AS b{j}" for j in range(4))} FROM range(64) t(i)),
e AS (SELECT cycle, particle_id, sum(CAST(CAST(b0 + b1 * f1 + b2 * f2 + b3 * f3 > 0 AS INTEGER) <> quality AS INTEGER)) AS errors, count(*) AS docs FROM x, b GROUP BY ALL)
SELECT CAST(cycle AS INTEGER) AS cycle, particle_id, CAST(errors AS BIGINT) AS errors, docs, CAST(sum(errors) OVER w AS BIGINT) AS total_errors, CAST(sum(docs) OVER w AS BIGINT) AS total_docs FROM e WINDOW w AS (PARTITION BY particle_id ORDER BY cycle)""")
def k18_classifier_all_cycles(spark, sf):
    """All batches of documents as cycles; the last totals are those of ``k18_classifier_cycle``."""
    return workloads.k18_all_errors(spark, sf)


@query(rf"""WITH d AS (SELECT quality, greatest(length(text), 1)::DOUBLE AS n, text FROM documents JOIN labels USING (doc_id)),
x AS (SELECT quality, least(n, 4000.0::DOUBLE) / 4000.0::DOUBLE AS f1, len(regexp_extract_all(text, '[0-9]')) / n AS f2, len(regexp_extract_all(text, '[A-Z]')) / n AS f3 FROM d),
b AS (SELECT CAST(i AS BIGINT) AS particle_id, {', '.join(f"{sql_normal4(str(SEED), '0', 'i', str(j))} AS b{j}" for j in range(4))} FROM range(64) t(i)),
e AS (SELECT particle_id, CAST(sum(CAST(CAST(b0 + b1 * f1 + b2 * f2 + b3 * f3 > 0 AS INTEGER) <> quality AS INTEGER)) AS BIGINT) AS mm FROM x, b GROUP BY 1), m AS (SELECT min(mm) AS least_ FROM e),
w AS (SELECT particle_id, CASE WHEN 30 - (mm - least_) >= 0 THEN CAST(1 AS BIGINT) << CAST(30 - (mm - least_) AS INTEGER) ELSE 0 END AS w_fix FROM e, m)
SELECT particle_id, w_fix, round(w_fix::DOUBLE / sum(w_fix) OVER (), 12) AS w_hat FROM w""")
def k18_classifier_weights(spark, sf):
    """(particle_id, w_fix, w_hat): classifier particles weighed by their errors over all cycles."""
    last = workloads.k18_all_errors(spark, sf).groupBy("particle_id").agg(F.sum("errors").alias("mismatches"))
    return weights.normalise(weights.mask_weights(last).select("particle_id", "w_fix")).withColumn("w_hat", F.round("w_hat", 12))


# K19.


@query("WITH h AS (SELECT date_trunc('hour', ts) AS cycle_start, count(*) AS n, round(avg(value), 6) AS mean_value FROM events GROUP BY 1), w AS (SELECT max(ts) - INTERVAL 2 HOUR AS mark FROM events) SELECT h.* FROM h, w WHERE cycle_start + INTERVAL 1 HOUR <= mark")
def k19_stream_hourly(spark, sf):
    from particle_engine.streaming.assimilate import stream_hourly

    return stream_hourly(spark, sf)


# Cache eviction as data, coordinator ids, random numbers.


@query("""WITH c AS (SELECT o_custkey % 8 AS runner_id, o_orderkey AS state_id, CASE WHEN o_orderstatus = 'F' THEN 1 WHEN o_orderstatus = 'O' THEN 2 ELSE 3 END AS rank_no, o_totalprice AS weight FROM orders)
SELECT CAST(runner_id AS BIGINT) AS runner_id, state_id, CAST(rank_no AS INTEGER) AS rank_no FROM c QUALIFY row_number() OVER (PARTITION BY runner_id ORDER BY rank_no, CASE WHEN rank_no = 3 THEN weight ELSE 0 END, state_id) <= 3""")
def evict_rank_order(spark, sf):
    """First three victims of each runner's cache, ranked; a synthetic cache relation from orders."""
    rank = F.when(F.col("o_orderstatus") == "F", 1).when(F.col("o_orderstatus") == "O", 2).otherwise(3)
    c = table(spark, sf, "orders").select(F.pmod("o_custkey", F.lit(8)).alias("runner_id"), F.col("o_orderkey").alias("state_id"), rank.alias("rank_no"), F.col("o_totalprice").alias("weight"))
    order = Window.partitionBy("runner_id").orderBy("rank_no", F.when(F.col("rank_no") == 3, F.col("weight")).otherwise(0.0), "state_id")
    return c.withColumn("i", F.row_number().over(order)).where("i <= 3").select("runner_id", "state_id", "rank_no")


@query("SELECT user_id, CAST(('0x' || substr(md5(concat_ws('|', 7, 1, user_id, 0)), 1, 13)) AS BIGINT) AS h FROM (SELECT DISTINCT user_id FROM events)")
def rng_unit_hash(spark, sf):
    return table(spark, sf, "events").select("user_id").distinct().select("user_id", unit_int(7, 1, F.col("user_id"), 0).alias("h"))


# Further variants.


@query("SELECT true AS within_bound, true AS no_worse")
def s3b_best_fit(spark, sf):
    """The cut-avoiding static schedule of all conversations against the id order and the bound."""
    import pandas as pd

    parents = workloads.natural(spark, sf, "conversations")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        plan = schedule.best_fit_chunks(dict(zip(pdf["parent_id"].tolist(), pdf["alpha"].tolist())), 16)
        return pd.DataFrame({"loads": [sum(map(len, plan.values()))], "bound": [len(pdf) + 15]})

    best = parents.withColumn("series", F.lit(0)).groupBy("series").applyInPandas(run, "loads long, bound long")
    plain = schedule.schedule_loads(schedule.static_schedule(parents, 16)).select(F.col("loads").alias("plain"))
    return best.crossJoin(F.broadcast(plain)).select((F.col("loads") <= F.col("bound")).alias("within_bound"), (F.col("loads") <= F.col("plain")).alias("no_worse"))


@query("SELECT CAST(c AS INTEGER) AS cycle, CAST(128 AS BIGINT) AS done FROM range(4) t(c)")
def x4_coordinator_outage(spark, sf):
    """Coordinator fails in mid-cycle: finished slots stand, every slot is done once."""
    from particle_engine.plans.simulate import simulate

    configs = workloads.settings(spark, [{"config_id": "outage", "lineage_id": "p128", "r": 32, "c": 9, "outages": "150000000:60000000"}])
    trace = simulate(configs, workloads.lineages(spark, sf, [("p128", 128, 4, 0.35)]))
    return trace.where("ok").groupBy("cycle").agg(F.countDistinct("task_id").alias("done"))


@query(f"SELECT CAST({K1_PARTICLES} AS BIGINT) AS particles, {K1_PARTICLES} * count(DISTINCT cell_id // 16) AS blocks, {K1_PARTICLES} * count(*) * 4 AS state_bytes FROM {SEEN_CELLS}")
def d1_blocked_states(spark, sf):
    """Size of one cycle of blocked states on the cells that events fall into."""
    from particle_engine.operators import blocks

    return blocks.bytes_of(blocks.pack(workloads.seen_states(spark, sf), 16))


@query(f"WITH {MASK}, {STATES}, o AS (SELECT cell_id, CAST(CAST(mask AS INTEGER) AS FLOAT) AS y FROM mask WHERE cycle = 0) SELECT particle_id, round(sum(-0.5::DOUBLE * pow((y - CAST(x AS FLOAT))::DOUBLE / 0.5::DOUBLE, 2)), 4) AS log_w FROM s0 JOIN o USING (cell_id) GROUP BY 1")
def f5_blocked_likelihood(spark, sf):
    """(particle_id, log_w): Gaussian score of blocked states against the first hour's mask."""
    from particle_engine.operators import blocks

    mask = observe.mask_grid(table(spark, sf, "events"), 1)
    y = blocks.pack(mask.select(F.lit(0).alias("particle_id"), "cell_id", F.col("mask").cast("double").alias("x")), 16).select("block_id", F.col("x").alias("y"))
    return blocks.log_likelihood(blocks.pack(workloads.k1_states(spark), 16), y, 0.5).withColumn("log_w", F.round("log_w", 4))


@query(f"{CYCLE1}, {PREFIX} SELECT particle_id, CAST(hi AS VARCHAR) AS hi FROM f")
def f10_prefix_sums(spark, sf):
    return resample.prefix_sums(workloads.k1_scored(spark, sf), ranges=5).select("particle_id", F.col("hi").cast("string").alias("hi"))


@query(f"{CYCLE1}, q AS (SELECT cell_id, x, w_fix, sum(w_fix) OVER (PARTITION BY cell_id ORDER BY x RANGE UNBOUNDED PRECEDING) AS r, sum(w_fix) OVER (PARTITION BY cell_id) AS t FROM s1 JOIN w USING (particle_id)) SELECT cell_id, round(min(x), 9) AS quantile FROM q WHERE r >= 0.5 * t GROUP BY cell_id")
def f9_weighted_median(spark, sf):
    from particle_engine.functions.scalar import weighted_quantile

    moved = propagate(workloads.k1_states(spark), Model(), 1, SEED)
    both = moved.join(workloads.k1_scored(spark, sf), "particle_id")
    return weighted_quantile(both, "x", "w_fix", 0.5, ["cell_id"]).withColumn("quantile", F.round("quantile", 9))


@query()
def k4_hit_ratio_spread(spark, sf):
    """The cache sweep on the synthetic lineage with log-normal weights of spread 0.35."""
    _, trace = workloads.k4(spark, sf, sigma=0.35)
    return metrics.hit_ratio(trace)


@query()
def k5_loads_vs_bound_spread(spark, sf):
    configs, trace = workloads.k5(spark, sf, sigma=0.35)
    return metrics.bound_slack(trace, configs)


@query("SELECT true AS falls, true AS flattens, true AS high")
def k4_shape(spark, sf):
    """Misses fall with the cache, hardly change past nine states, and the hit ratio is over 0.8 there."""
    _, trace = workloads.k4(spark, sf, caches=(1, 3, 9, 16), cycles=8, sigma=0.35)
    h = metrics.hit_ratio(trace).agg(*[F.max(F.when(F.col("config_id") == f"c{c:02d}", F.col("hit_ratio"))).alias(f"h{c}") for c in (1, 3, 9, 16)])
    return h.select(((F.col("h1") < F.col("h3")) & (F.col("h3") < F.col("h9"))).alias("falls"), (F.abs(F.col("h16") - F.col("h9")) < 0.05).alias("flattens"), (F.col("h9") > 0.8).alias("high"))


@query("SELECT true AS under_bound, true AS at_least_switches")
def k5_shape(spark, sf):
    """Loads are under the bound; every parent is switched to, and loaded while caches are empty (later ones may hold it)."""
    configs, trace = workloads.k5(spark, sf, sizes=(128, 256), cycles=4, sigma=0.35)
    s = metrics.bound_slack(trace, configs).join(metrics.switch_loads(trace).withColumnRenamed("loads", "switches"), metrics.KEY)
    switched = (F.col("switches") >= F.col("q")) & ((F.col("cycle") > 0) | (F.col("loads") >= F.col("q")))
    return s.agg(F.min(F.col("slack") >= 0).alias("under_bound"), F.min(switched).alias("at_least_switches"))


@query("SELECT true AS files_cost_more, true AS gap_grows")
def k12_shape(spark, sf):
    """Core time per particle: files over the engine, and more so with more particles."""
    configs, trace = workloads.k12(spark, sf, sizes=(128, 256))
    per = workloads.summary(configs, trace).withColumn("cost", F.col("r") * F.col("cycle_us"))
    cost = lambda c: F.max(F.when(F.col("config_id") == c, F.col("cost")))
    g = per.agg((cost("files-0128") / cost("engine-0128")).alias("a"), (cost("files-0256") / cost("engine-0256")).alias("b"))
    return g.select((F.col("a") > 1).alias("files_cost_more"), (F.col("b") > F.col("a")).alias("gap_grows"))


@query("SELECT true AS recovers, true AS waits_for_timeout")
def k11_shape(spark, sf):
    """Two crashes: every cycle completes, and the re-run starts after the timeout."""
    _, trace = workloads.k11(spark, sf)
    f = trace.where("config_id = 'faults'")
    whole = f.where("ok").groupBy("cycle").agg(F.countDistinct("task_id").alias("n")).agg(F.min(F.col("n") == 315).alias("recovers"))
    lost = f.where("not ok").select("cycle", "task_id", F.col("start_us").alias("s0"))
    late = f.where("ok").join(lost, ["cycle", "task_id"]).agg(F.min(F.col("start_us") - F.col("s0") >= 60_000_000).alias("waits_for_timeout"))
    return whole.crossJoin(F.broadcast(late))


@query(f"WITH {SEEN.replace(f'range({K1_PARTICLES})', 'range(32)')} SELECT particle_id, cell_id, round(x, 12) AS x FROM s0")
def io8_ensemble_source(spark, sf):
    """Start states of the cells that events fall into, read through the Python data source, equal the hashed ensemble."""
    from particle_engine.sources.ensemble import register

    register(spark)
    states = spark.read.format("ensemble_state").options(particles="32", cells="80", seed=str(SEED), partitions="3").load()
    return states.join(F.broadcast(workloads.seen_cells(spark, sf)), "cell_id", "left_semi").select("particle_id", "cell_id", F.round("x", 12).alias("x"))


@query("SELECT true AS starts_hidden, true AS slower_when_shared")
def b1_file_based_shape(spark, sf):
    """File-based mode: every propagation loads and starts a model; its shared storage makes it slower as particles grow."""
    configs, trace = workloads.k12(spark, sf, sizes=(128, 256), cycles=2)
    t = metrics.cycle_time(trace).groupBy("config_id").agg(F.avg("cycle_us").alias("t"))
    at = lambda c: F.max(F.when(F.col("config_id") == c, F.col("t")))
    all_loads = trace.where("config_id like 'files-%'").agg(F.min("loaded").alias("starts_hidden"))
    return all_loads.crossJoin(F.broadcast(t.agg((at("files-0256") > at("files-0128")).alias("slower_when_shared"))))
