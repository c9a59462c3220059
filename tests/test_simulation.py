import itertools
import random

import numpy as np
import pytest

from particle_engine.plans import baselines, metrics
from particle_engine.plans.cache import Cache
from particle_engine.plans.coordinator import Desk, Rules
from particle_engine.plans.filter import draw_systematic, mask_filter, spread_lineage
from particle_engine.plans.simulate import Config, run

FREE = {"load_us": 0, "store_us": 0, "weigh_us": 0, "response_us": 0, "redraw_us": 0, "prefetch": 0}


def one_cycle(alpha, duration=10):
    parents = np.repeat(np.arange(len(alpha)), alpha)
    n = len(parents)
    return [(parents, np.full(n, 1 / n), np.full(n, duration) if np.isscalar(duration) else np.asarray(duration))]


def as_cycles(df):
    return [(g["parent_slot"].to_numpy(), g["weight"].to_numpy(), np.full(len(g), -1)) for _, g in df.groupby("cycle")]


def loads(rows):
    return sum(r[9] for r in rows)


@pytest.mark.parametrize("pick", ["id", "fresh", "largest", "fresh_largest"])
def test_dynamic_bound_counterexample(pick):
    rows = run(Config(policy="dynamic", pick=pick, r=3, c=1, **FREE), one_cycle([6, 6]))
    assert loads(rows) == 5 and max(r[7] for r in rows) == 40


def test_worked_dynamic_case():
    rows = run(Config(policy="dynamic", r=4, c=1, **FREE), one_cycle([7, 4, 3, 3, 2, 2, 1, 1, 1]))
    assert loads(rows) == 10 and max(r[7] for r in rows) == 60


@pytest.mark.parametrize("policy", ["list", "dynamic", "cache_aware", "static", "fixed"])
def test_every_task_once_and_makespan(policy):
    rand = random.Random(3)
    for case in range(40):
        alpha = [rand.randrange(1, 10) for _ in range(rand.randrange(1, 13))]
        r = rand.randrange(1, 9)
        d = np.array([rand.randrange(1, 31) for _ in range(sum(alpha))])
        rows = run(Config(policy=policy, r=r, c=rand.choice([0, 1, 3]), **FREE), one_cycle(alpha, d))
        assert sorted(x[3] for x in rows) == list(range(sum(alpha)))
        span = max(x[7] for x in rows)
        if policy in ("list", "dynamic", "cache_aware"):
            assert span <= (2 - 1 / r) * max(d.sum() / r, d.max()) + 1e-9, case
        if r == 1:
            assert span == d.sum()


def test_one_runner_per_task():
    rows = run(Config(policy="list", r=6, c=1, **FREE), one_cycle([1] * 6, [3, 9, 4, 1, 2, 8]))
    assert max(x[7] for x in rows) == 9


def test_static_matches_closed_form():
    alpha, r = [7, 4, 3, 3, 2, 2, 1, 1, 1], 4
    rows = run(Config(policy="static", r=r, c=1, **FREE), one_cycle(alpha))
    got = {(x[2], x[4]) for x in rows}
    want = {(i * r // 24, q) for i, q in enumerate(np.repeat(np.arange(9), alpha).tolist())}
    assert got == want and loads(rows) == len(want)


def test_optimal_loads_are_within_reach():
    """Exhaustive optimum of small cases against the dynamic schedule and the lower bound."""
    for alpha, r in (((3, 2, 1), 2), ((4, 1, 1), 3), ((2, 2, 2), 3), ((5, 3), 2)):
        tasks = [q for q, a in enumerate(alpha) for _ in range(a)]
        size = -(-len(tasks) // r)
        best = min(len({(k, q) for k, q in zip(c, tasks)}) for c in itertools.product(range(r), repeat=len(tasks)) if max(c.count(k) for k in range(r)) <= size)
        assert len(alpha) <= best <= len(alpha) + r - 1
        assert loads(run(Config(policy="dynamic", r=r, c=1, **FREE), one_cycle(alpha))) >= best or r * size > len(tasks)


def test_eviction_ranks_in_order():
    cache = Cache(5)
    for state, role, w in (((0, 1), "child", 0.0), ((0, 2), "parent", 0.0), ((1, 3), "child", 0.1), ((1, 4), "child", 0.4), ((0, 5), "parent", 0.0)):
        cache.insert(state, role, 0, set(), w)
    cache.entries[(0, 1)].role = "stale"
    unfinished = {(0, 5)}
    seen = []
    while (v := cache.victim(10, unfinished)) is not None:
        seen.append((v[0].state, v[1]))
        del cache.entries[v[0].state]
    assert seen == [((0, 1), 1), ((0, 2), 2), ((1, 3), 3), ((1, 4), 3), ((0, 5), 4)]


def test_pinned_and_unstored_states_stay():
    cache = Cache(2)
    cache.insert((0, 1), "parent", 0, set())
    cache.insert((1, 2), "child", 0, set(), 0.1, persisted_at=50)
    cache.pin((0, 1))
    assert cache.victim(10, set()) is None and cache.victim(60, set())[0].state == (1, 2)
    assert cache.insert((0, 9), "parent", 10, set()) == (False, 0)
    with pytest.raises(ValueError):
        Cache(2, "other")


def test_more_cache_fewer_misses_and_prefetch_hides_loads():
    lin = as_cycles(spread_lineage(128, 6, 1))
    miss = {c: 1 - np.mean([x[8] for x in run(Config(r=32, c=c), lin) if 0 < x[1] < 5]) for c in (0, 1, 2, 4, 9)}
    assert miss[0] > 0.9 and miss[9] < 0.2 and miss[9] <= miss[4] + 0.02 <= miss[2] + 0.04 <= miss[1] + 0.06
    wait = {p: sum(x[10] for x in run(Config(r=32, c=9, prefetch=p), lin)) for p in (0, 1)}
    assert wait[1] <= wait[0]
    sync = max(x[7] for x in run(Config(r=32, c=9, prefetch=0, async_io=False), lin))
    assert sync > max(x[7] for x in run(Config(r=32, c=9), lin))


def test_cache_aware_beats_blind_list():
    lin = as_cycles(spread_lineage(128, 4, 2))
    assert loads(run(Config(r=32, c=9), lin)) < loads(run(Config(r=32, c=9, policy="list"), lin))


@pytest.mark.parametrize("release", [False, True])
def test_crashes_lose_nothing(release):
    lin = as_cycles(spread_lineage(64, 4, 3))
    rows = run(Config(r=13, c=9, crashes="5:1:1,2:2:-1", release_on_crash=release), lin)
    lost = [x for x in rows if not x[17]]
    assert 1 <= len(lost) <= 4
    for c in range(4):
        assert sorted(x[3] for x in rows if x[1] == c and x[17]) == list(range(64))
    again = next(x for x in rows if x[17] and (x[1], x[3]) == (lost[0][1], lost[0][3]))
    assert release or again[5] >= lost[0][5] + 60_000_000


def test_coordinator_outage_keeps_finished_slots():
    lin = as_cycles(spread_lineage(64, 3, 3))
    rows = run(Config(r=8, c=9, outages="150000000:40000000", crashes="5:0:1"), lin)
    done = [x for x in rows if x[17]]
    for c in range(3):
        assert sorted(x[3] for x in done if x[1] == c) == list(range(64))
    lost = [x for x in rows if not x[17] and x[6] == 150_000_000]
    assert 1 <= len(lost) <= 8 and not any(150_000_000 < x[5] < 190_000_000 for x in rows)
    assert all(x[7] <= 150_000_000 or x[5] >= 190_000_000 for x in done)


def test_leave_and_join():
    lin = as_cycles(spread_lineage(64, 3, 3))
    rows = run(Config(r=8, c=9, leaves="1:60000000", joins="8:90000000"), lin)
    assert sorted(x[3] for x in rows if x[1] == 2) == list(range(64))
    assert any(x[2] == 8 for x in rows) and all(x[5] <= 60_000_000 + 30_000_000 for x in rows if x[2] == 1)


def test_baseline_settings():
    lin = as_cycles(spread_lineage(32, 2, 3))
    files = run(baselines.baseline("file_based", r=32), lin)
    assert all(x[9] for x in files)
    mine = run(Config(r=8, c=9), lin)
    assert sum(x[6] - x[5] for x in mine) < sum(x[7] - x[5] + x[10] + 3_500_000 for x in files)


def test_desk_split_factor_and_loss():
    desk = Desk({(0, 0): [0, 1, 2, 3], (0, 1): [4]}, 3, Rules(policy="dynamic"))
    assert desk.split((0, 0)) == 3
    slot = desk.take((0, 0))
    desk.lost((0, 0), slot)
    assert desk.total_left == 5 and desk.left[(0, 0)] == [0, 1, 2, 3] and desk.active[(0, 0)] == 0


def test_draw_of_small_filter():
    assert draw_systematic(np.array([0, 0, 9]), 5, 1, 1).tolist() == [0, 0, 5]
    rng = np.random.default_rng(1)
    w = rng.integers(0, 1 << 30, 40)
    a = draw_systematic(w, 100, 7, 3)
    assert a.sum() == 100 and np.abs(a - 100 * w / w.sum()).max() < 1
    lin = mask_filter(np.zeros((3, 10), bool), 16, 3, 42)
    assert len(lin) == 48 and lin["parent_slot"].between(0, 15).all()


def test_published_arithmetic(spark):
    from particle_engine.plans.catalogue import QUERIES

    got = [tuple(r) for r in QUERIES["k12_core_seconds"](spark, "").orderBy("particles").collect()]
    assert [(r[1], r[2], round(r[3], 2)) for r in got] == [(3186, 3204, 1.01), (3186, 3804, 1.19), (3204, 5064, 1.58), (3213, 9132, 2.84)]
    assert round(metrics.overhead_share(512, 40, 19929), 3) == 0.027
    assert round(metrics.run_volume(2555, 2.5 / 1024, 48), 1) == 299.4
    assert metrics.startup_cost(100, 5, 10) == (50, 1000)


def test_classifier_cycles_score_every_labelled_document(spark, sf):
    from particle_engine.plans.catalogue import QUERIES

    labelled = spark.read.parquet(f"{sf}/documents.parquet").join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").count()
    got = QUERIES["k18_classifier_all_cycles"](spark, sf).collect()
    assert {r["cycle"] for r in got} == {0, 1, 2, 3} and {r["total_docs"] for r in got if r["cycle"] == 3} == {labelled}
    errors = {r["particle_id"]: r["total_errors"] for r in got if r["cycle"] == 3}
    w = {r["particle_id"]: r["w_fix"] for r in QUERIES["k18_classifier_weights"](spark, sf).collect()}
    assert len(w) == 64 and all(w[a] >= w[b] for a in w for b in w if errors[a] < errors[b])
    one = {r["particle_id"]: (r["errors"], r["docs"]) for r in QUERIES["k18_classifier_cycle"](spark, sf).collect()}
    assert one == {r["particle_id"]: (r["total_errors"], labelled) for r in got if r["cycle"] == 3}


def test_registered_studies_use_all_rows_and_sizes(spark, sf, monkeypatch):
    from particle_engine.operators import schedule
    from particle_engine.plans import workloads
    from particle_engine.plans.catalogue import QUERIES

    large, seen = sf.replace("0.001", "0.1"), []
    plain = schedule.static_schedule
    monkeypatch.setattr(schedule, "static_schedule", lambda parents, *a: (seen.append(parents.count()), plain(parents, *a))[1])
    assert tuple(QUERIES["s3b_best_fit"](spark, large).first()) == (True, True)
    assert seen == [spark.read.parquet(f"{large}/conversations.parquet").select("conv_id").distinct().count()]
    assert QUERIES["k1b_vs_exact"](spark, sf).first()["cycles"] == workloads.k1b_level(spark, sf).count()
    assert {r["config_id"][-4:] for r in workloads.k12(spark, sf)[0].collect()} == {"0128", "0256", "0512", "1024"}


def test_traces_in_closed_form_are_the_simulators(spark, sf):
    """Static, fixed and list traces of all orders, computed without the event simulator, are its own; no Python task holds them all."""
    from particle_engine.plans import catalogue, measure_queries as m

    for name, policy, cost in (("s3_static_trace", "static", m.PARENT_COST), ("b2_fixed_trace", "fixed", m.PARENT_COST), ("s4a_list_trace", "list", "o_orderkey")):
        got = catalogue.QUERIES[name](spark, sf)
        plan = got._jdf.queryExecution().executedPlan().toString()
        assert "FlatMapGroupsInPandas" not in plan
        want = m.orders_trace(spark, sf, policy, cost).select(*got.columns)
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
