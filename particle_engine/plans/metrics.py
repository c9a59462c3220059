"""Cost measures over traces, as plain aggregations: one row per (config_id, cycle) or per config_id."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

KEY = ["config_id", "cycle"]


def _ok(trace: DataFrame) -> DataFrame:
    return trace.where("ok")


def loads(trace: DataFrame) -> DataFrame:
    """(config_id, cycle, loads, tasks): transfers from the global store."""
    return trace.groupBy(*KEY).agg(F.sum(F.col("loaded").cast("long")).alias("loads"), F.count(F.lit(1)).alias("tasks"))


def switch_loads(trace: DataFrame) -> DataFrame:
    """Loads inferred without a hit flag: the parent differs from the runner's previous one."""
    prev = F.lag("parent_id").over(Window.partitionBy(*KEY, "runner_id").orderBy("start_us", "task_id", "parent_id"))
    return trace.withColumn("sw", (~prev.eqNullSafe(F.col("parent_id"))).cast("long")).groupBy(*KEY).agg(F.sum("sw").alias("loads"))


def trimmed(trace: DataFrame, trim: int = 1) -> DataFrame:
    """Without the first and last ``trim`` cycles of each configuration."""
    ends = trace.groupBy("config_id").agg(F.min("cycle").alias("__a"), F.max("cycle").alias("__b"))
    return trace.join(F.broadcast(ends), "config_id").where((F.col("cycle") >= F.col("__a") + trim) & (F.col("cycle") <= F.col("__b") - trim)).drop("__a", "__b")


def hit_ratio(trace: DataFrame, trim: int = 1) -> DataFrame:
    """(config_id, hit_ratio, miss_ratio): hits over state requests."""
    return trimmed(_ok(trace), trim).groupBy("config_id").agg(F.round(F.avg(F.col("hit").cast("int")), 6).alias("hit_ratio"), F.round(F.avg((~F.col("hit")).cast("int")), 6).alias("miss_ratio"))


def parent_stats(trace: DataFrame) -> DataFrame:
    """(config_id, cycle, q, max_copies)."""
    per = _ok(trace).groupBy(*KEY, "parent_id").agg(F.count(F.lit(1)).alias("a"))
    return per.groupBy(*KEY).agg(F.count(F.lit(1)).alias("q"), F.max("a").alias("max_copies"))


def bound_slack(trace: DataFrame, configs: DataFrame) -> DataFrame:
    """(config_id, cycle, q, loads, bound, slack): slack = q + R - 1 - loads."""
    j = loads(trace).join(parent_stats(trace), KEY).join(configs.select("config_id", "r"), "config_id")
    bound = F.col("q") + F.col("r") - 1
    return j.select(*KEY, "q", "max_copies", "loads", bound.alias("bound"), (bound - F.col("loads")).alias("slack"))


def io_volume(trace: DataFrame, state_bytes: int) -> DataFrame:
    """(config_id, cycle, read_bytes, written_bytes)."""
    return trace.groupBy(*KEY).agg((F.sum(F.col("loaded").cast("long")) * F.lit(state_bytes)).alias("read_bytes"), (F.sum(F.col("ok").cast("long")) * F.lit(state_bytes)).alias("written_bytes"))


def task_time_stats(trace: DataFrame) -> DataFrame:
    """(config_id, mean_us, min_us, max_us, spread): propagation times."""
    d = F.col("end_us") - F.col("start_us") - F.col("weigh_us")
    g = _ok(trace).groupBy("config_id").agg(F.avg(d).alias("mean_us"), F.min(d).alias("min_us"), F.max(d).alias("max_us"))
    return g.withColumn("spread", F.round((F.col("max_us") - F.col("min_us")) / F.col("mean_us"), 6))


def cycle_time(trace: DataFrame, redraw_us: int = 0) -> DataFrame:
    """(config_id, cycle, cycle_us): first start to the end of the redraw."""
    first = F.min(F.col("start_us") - F.col("load_wait_us"))
    return trace.groupBy(*KEY).agg((F.max("report_us") - first + F.lit(redraw_us)).alias("cycle_us"))


def whole_cycle_time(trace: DataFrame, configs: DataFrame, redraw_us: int = 2_210) -> DataFrame:
    """(config_id, cycle, cycle_us) with the redraw of each configuration, ``redraw_us`` where it names none."""
    own = F.coalesce(F.col("redraw_us"), F.lit(redraw_us)) if "redraw_us" in configs.columns else F.lit(redraw_us)
    return cycle_time(trace).join(configs.select("config_id", own.cast("long").alias("redraw")), "config_id").select(*KEY, (F.col("cycle_us") + F.col("redraw")).alias("cycle_us"))


def efficiency(trace: DataFrame, configs: DataFrame, reference: str) -> DataFrame:
    """(config_id, efficiency): reference one-runner time per task, times tasks, over R times cycle time."""
    per = cycle_time(trace).join(loads(trace), KEY).groupBy("config_id").agg(F.sum("cycle_us").alias("t"), F.sum("tasks").alias("n"))
    ref = per.where(F.col("config_id") == reference).select((F.col("t") / F.col("n")).alias("t1"))
    return per.crossJoin(F.broadcast(ref)).join(configs.select("config_id", "r"), "config_id").select("config_id", "r", F.round(F.col("t1") * F.col("n") / (F.col("r") * F.col("t")), 6).alias("efficiency"))


def work_share(trace: DataFrame, configs: DataFrame) -> DataFrame:
    """(config_id, propagation, weighing, waiting, coordination): shares of runner time."""
    d = F.col("end_us") - F.col("start_us") - F.col("weigh_us")
    s = trace.groupBy("config_id").agg(F.sum(d).alias("p"), F.sum("weigh_us").alias("w"), F.sum("load_wait_us").alias("l"))
    t = cycle_time(trace).groupBy("config_id").agg(F.sum("cycle_us").alias("t"))
    j = s.join(t, "config_id").join(configs.select("config_id", "r"), "config_id").withColumn("all", F.col("t") * F.col("r"))
    share = lambda c: F.round(F.col(c) / F.col("all"), 6)
    return j.select("config_id", share("p").alias("propagation"), share("w").alias("weighing"), share("l").alias("waiting"), F.round(1 - (F.col("p") + F.col("w") + F.col("l")) / F.col("all"), 6).alias("coordination"))


def phase_shares(trace: DataFrame) -> DataFrame:
    """(config_id, cycle, runner_id, propagate, weigh, load_wait): time per phase at every level of a rollup."""
    d = F.col("end_us") - F.col("start_us") - F.col("weigh_us")
    phases = trace.select(*KEY, "runner_id", F.explode(F.array(F.struct(F.lit("propagate").alias("phase"), d.alias("us")), F.struct(F.lit("weigh").alias("phase"), F.col("weigh_us").alias("us")), F.struct(F.lit("load_wait").alias("phase"), F.col("load_wait_us").alias("us")))).alias("x"))
    flat = phases.select(*KEY, "runner_id", "x.phase", "x.us").rollup(*KEY, "runner_id", "phase").agg(F.sum("us").alias("us")).where("phase is not null")
    return flat.groupBy(*KEY, "runner_id").pivot("phase", ["propagate", "weigh", "load_wait"]).agg(F.sum("us"))


def weak_growth(trace: DataFrame, configs: DataFrame) -> DataFrame:
    """(config_id, r, cycle_us, growth): mean cycle time against that of the fewest runners."""
    t = whole_cycle_time(trace, configs).groupBy("config_id").agg(F.avg("cycle_us").alias("cycle_us")).join(configs.select("config_id", "r"), "config_id")
    base = t.agg(F.min_by("cycle_us", "r").alias("base"))
    return t.crossJoin(F.broadcast(base)).select("config_id", "r", "cycle_us", F.round(F.col("cycle_us") / F.col("base") - 1, 6).alias("growth"))


def hidden_loads(trace: DataFrame, long_wait_us: int = 100_000) -> DataFrame:
    """(config_id, hidden_share, long_wait_share): loads the model never waited for; tasks that waited long."""
    return _ok(trace).groupBy("config_id").agg(
        F.round(F.sum((F.col("loaded") & (F.col("load_wait_us") == 0)).cast("int")) / F.sum(F.col("loaded").cast("int")), 6).alias("hidden_share"),
        F.round(F.avg((F.col("load_wait_us") > long_wait_us).cast("int")), 6).alias("long_wait_share"),
    )


def sync_penalty(trace: DataFrame, asynchronous: str, synchronous: str) -> DataFrame:
    """(async_us, sync_us, penalty): cycle time with input/output on the critical path against beside it."""
    t = cycle_time(trace).groupBy("config_id").agg(F.avg("cycle_us").alias("t"))
    a, s = t.where(F.col("config_id") == asynchronous).select(F.col("t").alias("async_us")), t.where(F.col("config_id") == synchronous).select(F.col("t").alias("sync_us"))
    return a.crossJoin(F.broadcast(s)).withColumn("penalty", F.round(F.col("sync_us") / F.col("async_us") - 1, 6))


def io_time_stats(trace: DataFrame) -> DataFrame:
    """(config_id, loads, load_mean_us, load_q25_us, load_q50_us, load_q75_us, load_max_us, stores, store_mean_us, store_max_us, local_hits): transfers as the lanes see them; states found in the cache move nothing."""
    loaded, stored = F.col("loaded"), F.col("ok")
    load, store = F.when(loaded, F.col("load_us")), F.when(stored, F.col("store_us"))
    quartile = lambda q: F.percentile(load, F.lit(q))
    return trace.groupBy("config_id").agg(
        F.sum(loaded.cast("long")).alias("loads"), F.round(F.avg(load), 3).alias("load_mean_us"), quartile(0.25).alias("load_q25_us"), quartile(0.5).alias("load_q50_us"), quartile(0.75).alias("load_q75_us"), F.max(load).alias("load_max_us"),
        F.sum(stored.cast("long")).alias("stores"), F.round(F.avg(store), 3).alias("store_mean_us"), F.max(store).alias("store_max_us"), F.sum(F.col("hit").cast("long")).alias("local_hits"),
    )


def coordinator_rate(trace: DataFrame) -> DataFrame:
    """(config_id, requests, peak_per_second): requests and the fullest second."""
    per = trace.groupBy("config_id", F.floor(F.col("report_us") / 1_000_000).alias("second")).agg(F.count(F.lit(1)).alias("n"))
    return per.groupBy("config_id").agg(F.sum("n").alias("requests"), F.max("n").alias("peak_per_second"))


def coordinator_latency(trace: DataFrame, service_us: int = 300) -> DataFrame:
    """(config_id, requests, mean_us, p50_us, p90_us, p99_us, max_us): from a report's arrival to its answer, where one coordinator answers one after the other.

    The queue has a closed form: answer i ends i + 1 services after the latest of the
    arrivals so far, each less the services before it.  One window over a cycle's reports.
    """
    order = Window.partitionBy(*KEY).orderBy("report_us", "task_id")
    i = F.row_number().over(order) - 1
    q = trace.select(*KEY, "task_id", "report_us", i.cast("long").alias("i"))
    latest = F.max(F.col("report_us") - F.col("i") * service_us).over(order.rowsBetween(Window.unboundedPreceding, 0))
    waits = q.select("config_id", (latest + (F.col("i") + 1) * service_us - F.col("report_us")).alias("us"))
    part = lambda p: F.round(F.percentile("us", F.lit(p)), 3)
    return waits.groupBy("config_id").agg(F.count(F.lit(1)).alias("requests"), F.round(F.avg("us"), 3).alias("mean_us"), part(0.5).alias("p50_us"), part(0.9).alias("p90_us"), part(0.99).alias("p99_us"), F.max("us").alias("max_us"))


def recovery_cost(trace: DataFrame) -> DataFrame:
    """(config_id, cycle, lost_tasks, lost_us, idle_us): work lost, and time other runners waited for the re-run."""
    lost = trace.where("not ok").groupBy(*KEY).agg(F.count(F.lit(1)).alias("lost_tasks"), F.sum(F.col("end_us") - F.col("start_us")).alias("lost_us"))
    ends = _ok(trace).groupBy(*KEY, "runner_id").agg(F.max("report_us").alias("e"))
    idle = ends.groupBy(*KEY).agg((F.max("e") * F.count(F.lit(1)) - F.sum("e")).alias("idle_us"))
    return lost.join(idle, KEY)


def detection_delay(trace: DataFrame) -> DataFrame:
    """(config_id, cycle, task_id, delay_us): from the end of a lost attempt to the start of the task's next one."""
    lost = trace.where("not ok").groupBy(*KEY, "task_id").agg(F.max("end_us").alias("lost_us"))
    again = _ok(trace).join(lost, [*KEY, "task_id"]).where("start_us >= lost_us")
    return again.groupBy(*KEY, "task_id").agg((F.min("start_us") - F.max("lost_us")).alias("delay_us"))


def makespan_ratio(trace: DataFrame, configs: DataFrame) -> DataFrame:
    """(config_id, cycle, ratio): makespan over max(total work / R, longest task)."""
    d = F.col("end_us") - F.col("start_us")
    g = _ok(trace).groupBy(*KEY).agg(F.sum(d).alias("w"), F.max(d).alias("m")).join(cycle_time(trace), KEY).join(configs.select("config_id", "r"), "config_id")
    return g.select(*KEY, F.round(F.col("cycle_us") / F.greatest(F.col("w") / F.col("r"), F.col("m").cast("double")), 6).alias("ratio"))


def balance(trace: DataFrame) -> DataFrame:
    """(config_id, cycle, task_gap, busy_gap_us): most less least over runners."""
    per = _ok(trace).groupBy(*KEY, "runner_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("end_us") - F.col("start_us")).alias("b"))
    return per.groupBy(*KEY).agg((F.max("n") - F.min("n")).alias("task_gap"), (F.max("b") - F.min("b")).alias("busy_gap_us"))


def control_bytes(trace: DataFrame, id_bytes: int = 8, weight_bytes: int = 8) -> DataFrame:
    """(config_id, control_bytes): an id and a weight up, an id down, per task."""
    return trace.groupBy("config_id").agg((F.count(F.lit(1)) * F.lit(2 * id_bytes + weight_bytes)).alias("control_bytes"))


def violations(trace: DataFrame, configs: DataFrame) -> DataFrame:
    """(violation, n): invariants of a trace; every n is 0 on a correct one."""
    by_runner = Window.partitionBy("config_id", "runner_id").orderBy("start_us", "end_us")
    overlap = trace.withColumn("p", F.lag("end_us").over(by_runner)).where("p > start_us").agg(F.count(F.lit(1)).alias("n")).select(F.lit("overlap").alias("violation"), "n")
    twice = _ok(trace).groupBy(*KEY, "task_id").agg(F.count(F.lit(1)).alias("k")).where("k <> 1").agg(F.count(F.lit(1)).alias("n")).select(F.lit("not_exactly_once").alias("violation"), "n")
    early = _ok(trace).where("report_us < end_us").agg(F.count(F.lit(1)).alias("n")).select(F.lit("report_before_store").alias("violation"), "n")
    span = trace.groupBy(*KEY).agg(F.min("start_us").alias("a"), F.max("report_us").alias("b"))
    inter = span.withColumn("p", F.lag("b").over(Window.partitionBy("config_id").orderBy("cycle"))).where("p > a").agg(F.count(F.lit(1)).alias("n")).select(F.lit("cycles_interleave").alias("violation"), "n")
    size = trace.join(F.broadcast(configs.select("config_id", "c")), "config_id").where("cache_size > c").agg(F.count(F.lit(1)).alias("n")).select(F.lit("cache_too_large").alias("violation"), "n")
    return overlap.unionByName(twice).unionByName(early).unionByName(inter).unionByName(size)


def gantt(trace: DataFrame) -> DataFrame:
    """Rows for a Gantt chart in seconds."""
    return trace.select(*KEY, "runner_id", "task_id", "parent_id", (F.col("start_us") / 1e6).alias("start_s"), (F.col("end_us") / 1e6).alias("end_s"), "hit", "ok")


# Arithmetic measures.


def core_seconds(cores: Column, seconds: Column, particles: Column) -> Column:
    return cores * seconds / particles


def run_volume(particles: int, state_bytes: float, cycles: int) -> float:
    return particles * state_bytes * cycles


def overhead_share(nodes: int, cores_per_node: int, model_processes: int) -> float:
    return 1 - model_processes / (nodes * cores_per_node)


def startup_cost(tasks: int, runners: int, startup_us: int) -> tuple[int, int]:
    """(once per runner, once per task)."""
    return runners * startup_us, tasks * startup_us


def cpu_hours(runs: DataFrame) -> DataFrame:
    """(cpu_hours) of runs (cores, seconds)."""
    return runs.agg(F.round(F.sum(F.col("cores") * F.col("seconds")) / 3600, 6).alias("cpu_hours"))
