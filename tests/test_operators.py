import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from particle_engine.functions import rng, scalar
from particle_engine.operators import models, observe, placement, posterior, resample, schedule, weights


def multiset(spark, alpha):
    return spark.createDataFrame(list(enumerate(alpha)), "parent_id long, alpha long")


def weights_df(spark, w):
    return spark.createDataFrame(list(enumerate(w)), "particle_id long, w_fix long")


def test_portable_random_numbers(spark):
    assert rng.py_int(7, 1, 42) == 3258855730030263
    assert spark.range(1).select(rng.unit_int(7, 1, 42)).first()[0] == 3258855730030263
    x = spark.range(4000).select(rng.normal4(1, 0, F.col("id"), 0).alias("x")).agg(F.avg("x"), F.stddev("x")).first()
    assert abs(x[0]) < 0.08 and abs(x[1] - 1) < 0.05


def test_systematic_gold(spark):
    got = {r["parent_id"]: r["alpha"] for r in resample.systematic(weights_df(spark, [5, 1, 0, 10]), 4, 1, 0, offset=3).collect()}
    assert got == {0: 2, 3: 2}


@pytest.mark.parametrize("scheme", resample.SCHEMES)
def test_schemes_sum_to_n_and_are_stable(spark, scheme):
    rand = random.Random(4)
    w = [rand.randrange(0, 1 << 30) for _ in range(50)]
    df = weights_df(spark, w)
    one = {r["parent_id"]: r["alpha"] for r in resample.resample(df, 64, scheme, 3, 1).collect()}
    two = {r["parent_id"]: r["alpha"] for r in resample.resample(df.repartition(7), 64, scheme, 3, 1, ranges=5).collect()}
    assert one == two and sum(one.values()) == 64
    expect = [64 * x / sum(w) for x in w]
    if scheme == "systematic":
        assert all(abs(one.get(i, 0) - e) < 1 for i, e in enumerate(expect))
    if scheme == "residual":
        assert all(one.get(i, 0) >= math.floor(e) for i, e in enumerate(expect))


def test_redraw_edges(spark):
    equal = weights_df(spark, [7] * 8)
    assert {r["alpha"] for r in resample.systematic(equal, 8, 1, 0, offset=0).collect()} == {1}
    assert [tuple(r) for r in resample.resample(weights_df(spark, [0, 9, 0]), 5).collect()] == [(1, 5)]
    assert [tuple(r) for r in resample.resample(weights_df(spark, [3]), 1).collect()] == [(0, 1)]
    kids = resample.offspring(spark.createDataFrame([(3, 2), (1, 1)], "parent_id long, alpha long")).orderBy("slot").collect()
    assert [tuple(r) for r in kids] == [(0, 1, 0), (1, 3, 0), (2, 3, 1)]
    many = spark.range(1, 40).selectExpr("id as parent_id", "id % 4 + 1 as alpha")
    assert sorted(map(tuple, resample.offspring(many, 5).collect())) == sorted(map(tuple, resample.offspring(many).collect()))
    with pytest.raises(ValueError):
        resample.resample(equal, 8, "other")


def test_weights_and_evidence(spark):
    scores = spark.createDataFrame([(0, -1.0), (1, -1000.0), (2, None), (3, float("nan"))], "particle_id long, log_w double")
    fix = {r["particle_id"]: r["w_fix"] for r in weights.fix_weights(scores).collect()}
    assert fix == {0: 1 << 30, 1: 0, 2: 0, 3: 0}
    two = spark.createDataFrame([(0, math.log(0.2)), (1, math.log(0.6))], "particle_id long, log_w double")
    assert abs(weights.evidence(two).first()[0] - math.log(0.4)) < 1e-12
    hat = {r["particle_id"]: r["w_hat"] for r in weights.normalise(weights_df(spark, [1, 3])).collect()}
    assert hat == {0: 0.25, 1: 0.75}
    d = weights.degeneracy(weights_df(spark, [1, 1, 1, 1])).first()
    assert d["ess"] == 4 and d["max_w"] == 0.25 and d["weight_var"] == 0
    both = weights.summary(weights.fix_weights(two)).first()
    assert abs(both["log_evidence"] - math.log(0.4)) < 1e-6 and abs(both["ess"] - 1.6) < 1e-6
    again = weights.update_weights(two, two).collect()
    assert abs(again[0]["log_w"] - 2 * math.log(0.2)) < 1e-12 or abs(again[1]["log_w"] - 2 * math.log(0.2)) < 1e-12


@pytest.mark.parametrize("kernel, want", [("gaussian", -0.5 * 4), ("cauchy", -math.log(5)), ("mask", 0.0)])
def test_kernels_skip_missing_cells(spark, kernel, want):
    states = spark.createDataFrame([(0, 0, 1.0), (0, 1, 9.0)], "particle_id long, cell_id int, x double")
    obs = spark.createDataFrame([(0, 3.0 if kernel != "mask" else 1.0)], "cell_id int, y double")
    assert abs(weights.log_likelihood(states, obs, kernel, 1.0 if kernel != "mask" else 0.2).first()["log_w"] - want) < 1e-12


def test_static_schedule_random_cases(spark):
    rand = random.Random(1)
    for _ in range(12):
        alpha = [rand.randrange(1, 10) for _ in range(rand.randrange(1, 13))]
        r = rand.randrange(1, 9)
        parents = multiset(spark, alpha)
        rows = schedule.static_schedule(parents, r, ranges=rand.choice([1, 3])).collect()
        p, brute = sum(alpha), {}
        for i, q in enumerate(q for q, a in enumerate(alpha) for _ in range(a)):
            brute[(i * r // p, q)] = brute.get((i * r // p, q), 0) + 1
        assert {(x["runner_id"], x["parent_id"]): x["n"] for x in rows} == brute
        b = schedule.load_bounds(parents, r).first()
        assert b["lo"] <= len(rows) <= b["hi"] and b["sum_s"] <= b["hi"]
        if p % r == 0:
            assert len(rows) >= b["sum_s"]


@pytest.mark.parametrize("alpha, r, loads, hi, sum_s", [((7, 4, 3, 3, 2, 2, 1, 1, 1), 4, 12, 12, 10), ((12,), 4, 4, 4, 4), ((1,) * 12, 4, 12, 15, 12), ((2, 2, 2), 2, 4, 4, 3)])
def test_worked_schedules(spark, alpha, r, loads, hi, sum_s):
    parents = multiset(spark, alpha)
    assert schedule.schedule_loads(schedule.static_schedule(parents, r)).first()["loads"] == loads
    b = schedule.load_bounds(parents, r).first()
    assert (b["hi"], b["sum_s"]) == (hi, sum_s)


def test_best_fit_chunks_within_bound():
    rand = random.Random(9)
    for _ in range(300):
        alpha = {q: rand.randrange(1, 10) for q in range(rand.randrange(1, 13))}
        r = rand.randrange(1, 9)
        plan = schedule.best_fit_chunks(alpha, r)
        done = {}
        for k, rows in plan.items():
            assert sum(n for _, n in rows) == (k + 1) * sum(alpha.values()) // r - k * sum(alpha.values()) // r
            for q, n in rows:
                done[q] = done.get(q, 0) + n
        assert done == alpha and sum(map(len, plan.values())) <= len(alpha) + r - 1
    assert sum(map(len, schedule.best_fit_chunks(dict(enumerate((7, 4, 3, 3, 2, 2, 1, 1, 1))), 4).values())) == 10


@pytest.mark.parametrize("strategy", ["static", "stay", "hash"])
def test_placement_ships_every_copy_once(spark, strategy):
    alpha = [7, 1, 1, 3, 12, 0, 8]
    parents = multiset(spark, alpha).where("alpha > 0")
    homes = parents.select("parent_id", (F.col("parent_id") % 4).alias("home_part"))
    plan = placement.assign(parents, 4, strategy, homes)
    states = spark.range(7).select(F.col("id").alias("particle_id"), F.lit(0).alias("cell_id"), F.col("id").cast("double").alias("x"))
    out = placement.ship(states, plan, 4).withColumn("at", F.spark_partition_id()).collect()
    assert sorted(r["particle_id"] for r in out) == list(range(32))
    assert all(r["x"] == r["parent_id"] and r["at"] == r["target_part"] for r in out)
    per = {}
    for r in out:
        per.setdefault(r["parent_id"], []).append(r["copy_no"])
    assert {q: sorted(c) for q, c in per.items()} == {q: list(range(a)) for q, a in enumerate(alpha) if a}
    if strategy != "hash":
        assert max(sum(r["target_part"] == k for r in out) for k in range(4)) == 8
    if strategy == "stay":
        moved = placement.moved_copies(plan, homes).first()
        assert moved["moved_tasks"] < placement.moved_copies(placement.assign(parents, 4, "static"), homes).first()["moved_tasks"]


def test_models(spark):
    grid = observe.grid(spark, 4)
    states = models.init_ensemble(grid, 3, 42)
    rows = {(r["particle_id"], r["cell_id"]): r["x"] for r in states.collect()}
    assert rows[(2, 3)] == rng.py_uniform(42, 0, 2, 3)
    still = models.propagate(states, models.Model("identity"), 1, 42)
    assert {(r["particle_id"], r["cell_id"]): r["x"] for r in still.collect()} == rows
    steps = models.propagate(states, models.Model(), 1, 42, steps=5)
    assert all(0 <= r["x"] <= 1 for r in steps.collect())
    flat = models.diffuse(states.withColumn("x", F.lit(2.0)), 0.5)
    assert {r["x"] for r in flat.collect()} == {2.0}
    box = models.advance_black_box(states, lambda: lambda pdf: pdf.assign(x=pdf["x"] + 1))
    assert {(r["particle_id"], r["cell_id"]): r["x"] for r in box.collect()} == {k: v + 1 for k, v in rows.items()}
    regions = grid.withColumn("region_id", F.lit(0))
    mean = models.mean_revert(states, regions, 1.0).groupBy("particle_id").agg(F.countDistinct(F.round("x", 9)).alias("n")).collect()
    assert {r["n"] for r in mean} == {1}
    with pytest.raises(NotImplementedError):
        models.state_correction(states)


def test_accuracy_scores(spark):
    members = spark.createDataFrame([(0, i, float(i)) for i in range(5)], "cycle int, particle_id long, x double")
    truth = spark.createDataFrame([(0, 2.0)], "cycle int, truth double")
    got = posterior.accuracy(members, truth).first()
    x = np.arange(5.0)
    crps = np.abs(x - 2).mean() - np.abs(x[:, None] - x[None, :]).mean() / 2
    assert abs(got["crps"] - crps) < 1e-12 and got["bias"] == 0 and got["coverage"] == 1
    assert posterior.rank_histogram(members, truth).first()["rank"] == 2


def test_scalar_helpers(spark):
    df = spark.createDataFrame([("a", 1.0, 1.0), ("a", 2.0, 3.0), ("b", 5.0, 1.0)], "k string, x double, w double")
    lse = {r["k"]: r["lse"] for r in scalar.log_sum_exp(df, "x", ["k"]).collect()}
    assert abs(lse["a"] - math.log(math.e + math.e**2)) < 1e-12
    assert {r["k"]: r["quantile"] for r in scalar.weighted_quantile(df, "x", "w", 0.5, ["k"]).collect()} == {"a": 2.0, "b": 5.0}
    assert df.groupBy("k").agg(scalar.weighted_quantile_udf(0.2)("x", "w").alias("q")).where("k = 'a'").first()["q"] == 1.0
    assert abs(df.where("k = 'a'").agg(scalar.log_sum_exp_udf()("x").alias("l")).first()["l"] - lse["a"]) < 1e-12


def test_observation_gold(spark, sf):
    from particle_engine.sources.tables import table

    mask = observe.mask_grid(table(spark, sf, "events"), 48).where("mask").agg(F.count("*"), F.sum("n"), F.max("n")).first()
    assert tuple(mask) == (72, 72, 1)
    hourly = observe.hourly(table(spark, sf, "events"))
    assert hourly.count() == 531
    assert [(r["n"], r["mean_value"]) for r in hourly.orderBy("cycle").limit(3).collect()] == [(3, 100.296667), (1, 40.34), (1, 29.61)]
    k3 = observe.nation_month(spark, sf).agg(F.count("*"), F.countDistinct("month"), F.round(F.sum("revenue"), 0)).first()
    assert (k3[0], k3[1], k3[2]) == (1000, 80, 301270840.0)


def test_ranged_lookups_draw_the_same(spark):
    """Any number of ranges gives the same offspring in every scheme."""
    from particle_engine.operators import resample

    w = spark.createDataFrame([(i * i, (i * 7919) % 50) for i in range(60)] + [(10_000_000, 900)], "particle_id long, w_fix long")
    for scheme in resample.SCHEMES:
        draws = [sorted(map(tuple, resample.resample(w, 100, scheme, 5, 1, ranges).collect())) for ranges in (1, 4, 13)]
        assert draws[0] == draws[1] == draws[2] and sum(a for _, a in draws[0]) == 100


def test_coordinator_queue_equals_a_walk(spark):
    from particle_engine.plans import metrics

    rng = random.Random(3)
    arrivals = sorted(rng.randrange(20_000) for _ in range(60))
    trace = spark.createDataFrame([("a", 0, i, t) for i, t in enumerate(arrivals)], "config_id string, cycle int, task_id long, report_us long")
    free, waits = 0, []
    for t in arrivals:
        free = max(free, t) + 300
        waits.append(free - t)
    got = metrics.coordinator_latency(trace, 300).first()
    assert (got["requests"], got["max_us"]) == (60, max(waits)) and abs(got["mean_us"] - sum(waits) / 60) < 0.01
