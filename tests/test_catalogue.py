"""Every registered query outside the training-data operators: equal to its SQL on the smallest tables, or rows with a stable schema."""

import duckdb
import pytest

from particle_engine.operators import relational
from particle_engine.plans import catalogue, measure_queries  # noqa: F401
from particle_engine.sources.tables import SCHEMAS

QUERIES = {**catalogue.QUERIES, **relational.QUERIES}
SQL = {**catalogue.SQL, **relational.SQL}
#: Slow loops of whole filters, covered in test_filter.
ELSEWHERE = {"adaptive_policy", "k1_multi_cycle", "engines_agree"}


@pytest.fixture(scope="module")
def con(sf):
    con = duckdb.connect()
    for t in SCHEMAS:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def rows(df):
    text = lambda v: str(round(float(v), 9)) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)
    return sorted(tuple(map(text, r)) for r in df[sorted(df.columns)].astype(object).where(df.notna(), None).values.tolist())


@pytest.mark.parametrize("name", sorted(set(SQL) - ELSEWHERE))
def test_equal_to_sql(spark, sf, con, name):
    got, want = QUERIES[name](spark, sf).toPandas(), con.execute(SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(SQL) - ELSEWHERE - {"k6_weak_scaling", "k7_strong_scaling"}))
def test_gives_rows(spark, sf, name, tmp_path):
    """Every column of every row is computed and written, as a reader of the result would have it."""
    path = str(tmp_path / "out")
    QUERIES[name](spark, sf).write.parquet(path)
    assert spark.read.parquet(path).count() > 0


def test_filters_reach_the_scan(spark, sf):
    plan = relational.op_time_slice(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(ts), LessThan(ts" in plan and "ReadSchema: struct<event_id:bigint,ts:timestamp,value:double>" in plan


def test_redraw_never_reads_states(spark, tmp_path):
    from particle_engine.operators import resample

    spark.range(10).selectExpr("id as particle_id", "cast(1 as bigint) as w_fix", "array(1.0, 2.0) as x").write.parquet(str(tmp_path / "w"))
    plan = resample.systematic(spark.read.parquet(str(tmp_path / "w")), 10, 1, 0)._jdf.queryExecution().executedPlan().toString()
    assert "x:array" not in plan


def test_lateral_rank_has_an_order(spark, sf):
    plan = relational.op_lateral_top2(spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "o_totalprice" in plan.split("row_number()")[1].split(" AS ")[0]


def test_dearest_of_a_tie_is_the_first_order(spark, tmp_path):
    rows = [(k, 1, "O", 10.0) for k in (7, 9, 3, 8, 5)] + [(2, 1, "O", 5.0), (4, 2, "F", 1.0)]
    for at, part in enumerate((rows, rows[::-1])):
        spark.createDataFrame(part, "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double").selectExpr("*", "timestamp '2024-01-01' AS o_orderdate", "'' AS o_orderpriority").write.parquet(f"{tmp_path}/{at}/orders.parquet")
        assert {r["o_custkey"]: r["dearest"] for r in relational.op_collect(spark, f"{tmp_path}/{at}").collect()} == {1: 3, 2: 4}


READ = {"a16_overhead": "orders", "a28_cpu_hours": "lineitem"} | dict.fromkeys(
    ("a20_volume", "a26_accuracy", "d1_blocked_states", "f1_initial_ensemble", "f2_propagated", "f2a_inner_steps", "f2a_steps_36", "f2a_steps_150", "io8_ensemble_source"), "events")


@pytest.mark.parametrize("name", sorted(READ))
def test_reads_its_table(spark, sf, name):
    assert f"{sf}/{READ[name]}.parquet" in " ".join(QUERIES[name](spark, sf).inputFiles())


def test_draw_bias_reads_events(spark, tmp_path):
    with pytest.raises(Exception, match="events.parquet"):
        QUERIES["a27_draw_bias"](spark, str(tmp_path))
