"""Relational operators around the filter, each as a query on the given tables with the same result in DuckDB."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from particle_engine.sources.tables import table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def operator(sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


@operator("SELECT ts, value FROM events")
def op_projection(spark, sf):
    return table(spark, sf, "events").select("ts", "value")


@operator("SELECT event_id, date_trunc('hour', ts) AS hour, CAST(user_id % 16 AS BIGINT) AS group_no, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def op_computed_columns(spark, sf):
    return table(spark, sf, "events").select("event_id", F.date_trunc("hour", "ts").alias("hour"), F.pmod("user_id", F.lit(16)).alias("group_no"), F.get_json_object("props", "$.k").cast("int").alias("k"))


@operator("SELECT event_id, value FROM events WHERE ts < TIMESTAMP '2024-01-03 00:00:00'")
def op_time_slice(spark, sf):
    return table(spark, sf, "events").where("ts < timestamp '2024-01-03 00:00:00'").select("event_id", "value")


@operator("SELECT p_partkey, p_brand, p_size FROM part WHERE (p_size BETWEEN 10 AND 20 OR p_size IN (1, 2)) AND p_brand LIKE 'Brand#%' AND regexp_matches(p_type, '[A-Z]') AND p_name IS DISTINCT FROM 'x'")
def op_filter_mix(spark, sf):
    p = table(spark, sf, "part")
    keep = (F.col("p_size").between(10, 20) | F.col("p_size").isin(1, 2)) & F.col("p_brand").like("Brand#%") & F.col("p_type").rlike("[A-Z]") & ~F.col("p_name").eqNullSafe(F.lit("x"))
    return p.where(keep).select("p_partkey", "p_brand", "p_size")


@operator("SELECT p_brand, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def op_broadcast_join(spark, sf):
    """The smaller side is aggregated per key first; Spark broadcasts the dimension while its size allows."""
    per = table(spark, sf, "lineitem").groupBy("l_partkey").agg(F.sum("l_extendedprice").alias("s"))
    return per.join(table(spark, sf, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.round(F.sum("s"), 2).alias("price"))


@operator("SELECT o_orderpriority, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def op_merge_join(spark, sf):
    o = table(spark, sf, "orders").select("o_orderkey", "o_orderpriority").hint("merge")
    return o.join(table(spark, sf, "lineitem").select("l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@operator("SELECT o_orderstatus, round(sum(l_quantity), 2) AS qty FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def op_shuffle_hash_join(spark, sf):
    o = table(spark, sf, "orders").select("o_orderkey", "o_orderstatus").hint("shuffle_hash")
    return table(spark, sf, "lineitem").select("l_orderkey", "l_quantity").join(o, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty"))


@operator("SELECT n_name, CAST(m AS BIGINT) AS month_no FROM nation, range(1, 13) t(m)")
def op_grid_product(spark, sf):
    return table(spark, sf, "nation").select("n_name").crossJoin(F.broadcast(spark.range(1, 13).withColumnRenamed("id", "month_no")))


@operator("WITH e AS (SELECT DISTINCT user_id, ts FROM events WHERE event_type = 'error') SELECT e.user_id, count(*) AS near FROM e JOIN events v ON v.user_id = e.user_id AND v.ts BETWEEN e.ts - INTERVAL 5 MINUTE AND e.ts + INTERVAL 5 MINUTE GROUP BY 1")
def op_interval_join(spark, sf):
    """Events within five minutes of an error of the same user: equi-join on user and time bucket, then the exact test."""
    ev = table(spark, sf, "events").select("user_id", F.unix_micros("ts").alias("t"), "event_type")
    five = 300_000_000
    err = ev.where("event_type = 'error'").select("user_id", F.col("t").alias("te")).distinct()
    err = err.withColumn("slot", F.explode(F.sequence(F.floor((F.col("te") - five) / five), F.floor((F.col("te") + five) / five))))
    near = ev.withColumn("slot", F.floor(F.col("t") / five)).join(err, ["user_id", "slot"]).where(F.abs(F.col("t") - F.col("te")) <= five)
    return near.groupBy("user_id").agg(F.count(F.lit(1)).alias("near"))


@operator("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def op_semi_join(spark, sf):
    return table(spark, sf, "customer").select("c_custkey").join(table(spark, sf, "orders").select("o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@operator("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")
def op_anti_join(spark, sf):
    big = table(spark, sf, "orders").where("o_totalprice > 300000").select("o_custkey")
    return table(spark, sf, "customer").select("c_custkey").join(big, F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@operator("SELECT coalesce(s_nationkey, -1) AS s_nationkey, coalesce(c_nationkey, -1) AS c_nationkey, coalesce(s, 0) AS suppliers, coalesce(c, 0) AS customers FROM (SELECT s_nationkey, count(*) AS s FROM supplier WHERE s_acctbal > 0 GROUP BY 1) FULL OUTER JOIN (SELECT c_nationkey, count(*) AS c FROM customer WHERE c_acctbal > 5000 GROUP BY 1) ON s_nationkey = c_nationkey")
def op_full_outer(spark, sf):
    s = table(spark, sf, "supplier").where("s_acctbal > 0").groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("s"))
    c = table(spark, sf, "customer").where("c_acctbal > 5000").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("c"))
    return s.join(c, F.col("s_nationkey") == F.col("c_nationkey"), "full_outer").select(F.coalesce("s_nationkey", F.lit(-1)).alias("s_nationkey"), F.coalesce("c_nationkey", F.lit(-1)).alias("c_nationkey"), F.coalesce("s", F.lit(0)).alias("suppliers"), F.coalesce("c", F.lit(0)).alias("customers"))


@operator("SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def op_lateral_top2(spark, sf):
    """Two dearest orders of each customer: per-parent expansion by a correlated lateral subquery (decorrelated to a ranked window).

    The rank is written out: Spark turns ORDER BY and LIMIT of a lateral subquery into a window without an order.
    """
    table(spark, sf, "orders").createOrReplaceTempView("orders")
    return spark.sql("SELECT c.o_custkey, t.o_orderkey FROM (SELECT DISTINCT o_custkey FROM orders) c, LATERAL (SELECT r.o_orderkey FROM (SELECT o.o_orderkey, row_number() OVER (ORDER BY o.o_totalprice DESC, o.o_orderkey) AS i FROM orders o WHERE o.o_custkey <=> c.o_custkey) r WHERE r.i <= 2) t")


@operator("SELECT a.n_nationkey AS a_key, count(*) AS below FROM nation a JOIN nation b ON a.n_nationkey > b.n_nationkey AND a.n_regionkey <> b.n_regionkey GROUP BY 1")
def op_theta_join(spark, sf):
    n = table(spark, sf, "nation").select("n_nationkey", "n_regionkey")  # 25 rows
    a, b = n.alias("a"), F.broadcast(n).alias("b")
    j = a.join(b, (F.col("a.n_nationkey") > F.col("b.n_nationkey")) & (F.col("a.n_regionkey") != F.col("b.n_regionkey")))
    return j.groupBy(F.col("a.n_nationkey").alias("a_key")).agg(F.count(F.lit(1)).alias("below"))


@operator("WITH l AS (SELECT l_orderkey, l_linenumber, sum(l_quantity) AS q FROM lineitem GROUP BY 1, 2) SELECT a.l_orderkey, a.l_linenumber, round(b.q - a.q, 2) AS step FROM l a JOIN l b ON a.l_orderkey = b.l_orderkey AND b.l_linenumber = a.l_linenumber + 1")
def op_neighbour_join(spark, sf):
    """Self-join on the next block (halo exchange)."""
    q = table(spark, sf, "lineitem").groupBy("l_orderkey", "l_linenumber").agg(F.sum("l_quantity").alias("q"))
    nxt = q.select("l_orderkey", (F.col("l_linenumber") - 1).alias("l_linenumber"), F.col("q").alias("q2"))
    return q.join(nxt, ["l_orderkey", "l_linenumber"]).select("l_orderkey", "l_linenumber", F.round(F.col("q2") - F.col("q"), 2).alias("step"))


@operator("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc FROM lineitem GROUP BY 1, 2")
def op_hash_aggregate(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"))


@operator("SELECT o_custkey, len(list(o_orderkey)) AS n_keys, len(list(DISTINCT o_orderstatus)) AS n_status, max_by(o_orderkey, o_totalprice) AS dearest FROM orders GROUP BY 1")
def op_collect(spark, sf):
    return table(spark, sf, "orders").groupBy("o_custkey").agg(F.size(F.collect_list("o_orderkey")).cast("long").alias("n_keys"), F.size(F.collect_set("o_orderstatus")).cast("long").alias("n_status"), F.max_by("o_orderkey", F.struct("o_totalprice", -F.col("o_orderkey"))).alias("dearest"))


@operator("SELECT count(DISTINCT user_id) AS users, count(DISTINCT event_type) AS types, (SELECT count(*) FROM (SELECT DISTINCT user_id, event_type FROM events)) AS pairs FROM events")
def op_count_distinct(spark, sf):
    return table(spark, sf, "events").agg(F.countDistinct("user_id").alias("users"), F.countDistinct("event_type").alias("types"), F.countDistinct("user_id", "event_type").alias("pairs"))


@operator("SELECT true AS users_close, true AS median_close")
def op_approximate(spark, sf):
    """Approximate distinct count and quantile stay close to the exact ones."""
    e = table(spark, sf, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.countDistinct("user_id").alias("b"), F.percentile_approx("value", 0.5, 1000).alias("m"), F.percentile("value", F.lit(0.5)).alias("x"))
    return e.select((F.abs(F.col("a") - F.col("b")) <= 0.1 * F.col("b")).alias("users_close"), (F.abs(F.col("m") - F.col("x")) <= 2.0).alias("median_close"))


@operator("SELECT r_name, n_name, count(*) AS n, CAST(grouping(r_name) * 2 + grouping(n_name) AS BIGINT) AS gid FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (r_name, n_name)")
def op_cube(spark, sf):
    d = table(spark, sf, "nation").join(table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    c = table(spark, sf, "customer").select("c_nationkey").join(F.broadcast(d), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 nations
    return c.cube("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("gid"))


@operator("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def op_grouping_sets(spark, sf):
    o = table(spark, sf, "orders")
    return o.groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


PIVOTED = "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS day, " + ", ".join(f"count(*) FILTER (event_type = '{t}') AS n_{t}" for t in ("click", "error", "view")) + " FROM events GROUP BY 1"


@operator(PIVOTED)
def op_pivot(spark, sf):
    p = table(spark, sf, "events").withColumn("day", F.date_trunc("day", "ts")).groupBy("day").pivot("event_type", ["click", "error", "view"]).agg(F.count(F.lit(1)))
    return p.select("day", *[F.coalesce(t, F.lit(0)).alias(f"n_{t}") for t in ("click", "error", "view")])


@operator(f"WITH p AS ({PIVOTED}) SELECT day, kind, n FROM (SELECT day, 'n_click' AS kind, n_click AS n FROM p UNION ALL SELECT day, 'n_error', n_error FROM p UNION ALL SELECT day, 'n_view', n_view FROM p)")
def op_unpivot(spark, sf):
    return op_pivot(spark, sf).unpivot("day", ["n_click", "n_error", "n_view"], "kind", "n")


@operator("SELECT event_type, round(var_samp(value), 6) AS v, round(stddev_pop(value), 6) AS s, round(corr(value, user_id), 6) AS r, round(covar_pop(value, user_id), 4) AS c, count(*) FILTER (value > 50) AS high, bool_and(value > 0) AS positive FROM events GROUP BY 1")
def op_moments(spark, sf):
    u = F.col("user_id").cast("double")
    return table(spark, sf, "events").groupBy("event_type").agg(
        F.round(F.var_samp("value"), 6).alias("v"), F.round(F.stddev_pop("value"), 6).alias("s"), F.round(F.corr("value", u), 6).alias("r"),
        F.round(F.covar_pop("value", u), 4).alias("c"), F.count_if(F.col("value") > 50).alias("high"), F.bool_and(F.col("value") > 0).alias("positive"),
    )


@operator("SELECT l_returnflag, round(sum(l_extendedprice * l_quantity) / sum(l_quantity), 4) AS mean, round(ln(sum(exp(l_discount))), 6) AS lse FROM lineitem GROUP BY 1")
def op_weighted(spark, sf):
    from particle_engine.functions.scalar import weighted_mean

    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.round(weighted_mean(F.col("l_extendedprice"), F.col("l_quantity")), 4).alias("mean"), F.round(F.log(F.sum(F.exp("l_discount"))), 6).alias("lse"))


@operator("SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS running FROM orders")
def op_running_sum(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return table(spark, sf, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("running"))


@operator("SELECT p_partkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey), v AS (PARTITION BY p_brand ORDER BY p_size)")
def op_ranks(spark, sf):
    w, v = Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    return table(spark, sf, "part").select(
        "p_partkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(v).cast("long").alias("rk"), F.dense_rank().over(v).cast("long").alias("dr"),
        F.ntile(4).over(w).cast("long").alias("nt"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"),
    )


@operator("SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before, coalesce(lead(event_id) OVER w, -1) AS after, first_value(event_id) OVER w AS first, coalesce(nth_value(event_id, 2) OVER w, -1) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_neighbours(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf, "events").select("event_id", F.lag("event_id", 1, -1).over(w).alias("before"), F.lead("event_id", 1, -1).over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.coalesce(F.nth_value("event_id", 2).over(w), F.lit(-1)).alias("second"))


@operator("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM (SELECT event_id, user_id, date_trunc('second', ts) AS ts FROM events)")
def op_range_window(spark, sf):
    w = Window.partitionBy("user_id").orderBy(F.unix_seconds("ts")).rangeBetween(-3600, 0)
    return table(spark, sf, "events").select("event_id", F.count(F.lit(1)).over(w).alias("last_hour"))


@operator("WITH d AS (SELECT event_type, CAST(date_trunc('day', ts) AS TIMESTAMP) AS day, avg(value) AS v FROM events GROUP BY 1, 2) SELECT event_type, day, round(avg(v) OVER (PARTITION BY event_type ORDER BY day ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING), 6) AS smooth FROM d")
def op_smoothing(spark, sf):
    d = table(spark, sf, "events").groupBy("event_type", F.date_trunc("day", "ts").alias("day")).agg(F.avg("value").alias("v"))
    return d.select("event_type", "day", F.round(F.avg("v").over(Window.partitionBy("event_type").orderBy("day").rowsBetween(-3, 3)), 6).alias("smooth"))


@operator("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def op_top_k(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@operator("SELECT l_orderkey, l_extendedprice FROM (SELECT l_orderkey, l_extendedprice, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_extendedprice DESC, l_partkey) AS i FROM lineitem) WHERE i <= 3")
def op_top_k_per_group(spark, sf):
    w = Window.partitionBy("l_orderkey").orderBy(F.desc("l_extendedprice"), "l_partkey")
    return table(spark, sf, "lineitem").withColumn("i", F.row_number().over(w)).where("i <= 3").select("l_orderkey", "l_extendedprice")


@operator("SELECT true AS sorted_apart")
def op_range_partition(spark, sf):
    """Range partitioning with local sorting: partitions hold disjoint, ordered key ranges."""
    part = table(spark, sf, "lineitem").select("l_shipdate").repartitionByRange(8, "l_shipdate").sortWithinPartitions("l_shipdate").withColumn("p", F.spark_partition_id())
    spans = part.groupBy("p").agg(F.min("l_shipdate").alias("a"), F.max("l_shipdate").alias("b"))
    return spans.withColumn("prev", F.lag("b").over(Window.orderBy("p"))).agg(F.bool_and(F.col("prev").isNull() | (F.col("prev") <= F.col("a"))).alias("sorted_apart"))  # a row a partition


@operator("SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 20 OFFSET 40")
def op_page(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey").orderBy("o_orderkey").offset(40).limit(20)


@operator("SELECT CAST(ts AS TIMESTAMP) AS t, 'event' AS kind FROM events UNION ALL SELECT o_orderdate, 'order' FROM orders")
def op_union_by_name(spark, sf):
    a = table(spark, sf, "events").select(F.col("ts").alias("t"), F.lit("event").alias("kind"))
    return a.unionByName(table(spark, sf, "orders").select(F.lit("order").alias("kind"), F.col("o_orderdate").alias("t")))


DAYS = [f"(SELECT user_id FROM events WHERE ts >= TIMESTAMP '2024-01-0{d} 00:00:00' AND ts < TIMESTAMP '2024-01-0{d + 1} 00:00:00')" for d in (2, 3)]


def _day(spark, sf, d):
    return table(spark, sf, "events").where(f"ts >= timestamp '2024-01-0{d} 00:00:00' and ts < timestamp '2024-01-0{d + 1} 00:00:00'").select("user_id")


@operator(f"{DAYS[0]} INTERSECT ALL {DAYS[1]}")
def op_intersect_all(spark, sf):
    return _day(spark, sf, 2).intersectAll(_day(spark, sf, 3))


@operator(f"{DAYS[0]} EXCEPT ALL {DAYS[1]}")
def op_except_all(spark, sf):
    return _day(spark, sf, 2).exceptAll(_day(spark, sf, 3))


@operator("SELECT DISTINCT c_mktsegment, c_nationkey FROM customer")
def op_distinct(spark, sf):
    return table(spark, sf, "customer").select("c_mktsegment", "c_nationkey").dropDuplicates()


@operator("SELECT p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY md5('42|' || p_partkey)) <= 2")
def op_stratified_sample(spark, sf):
    """Two parts per brand by hash rank: the same sample in any partitioning."""
    w = Window.partitionBy("p_brand").orderBy(F.md5(F.concat(F.lit("42|"), F.col("p_partkey").cast("string"))))
    return table(spark, sf, "part").withColumn("i", F.row_number().over(w)).where("i <= 2").select("p_partkey")


@operator("SELECT p_partkey FROM part ORDER BY md5('7|' || p_partkey) LIMIT 64")
def op_hash_sample(spark, sf):
    return table(spark, sf, "part").orderBy(F.md5(F.concat(F.lit("7|"), F.col("p_partkey").cast("string")))).limit(64).select("p_partkey")


CORRELATED = "SELECT o_orderkey FROM orders o WHERE o_totalprice > 1.5 * (SELECT avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey) AND EXISTS (SELECT 1 FROM customer WHERE c_custkey = o.o_custkey AND c_acctbal > 0) AND o.o_totalprice < (SELECT max(o_totalprice) FROM orders)"


@operator(CORRELATED)
def op_subqueries(spark, sf):
    for t in ("orders", "customer"):
        table(spark, sf, t).createOrReplaceTempView(t)
    return spark.sql(CORRELATED)


@operator("WITH RECURSIVE t(i, v) AS (SELECT 0, CAST(1 AS BIGINT) UNION ALL SELECT i + 1, v * 2 FROM t WHERE i < 10) SELECT i, v FROM t")
def op_recursive_cte(spark, sf):
    return spark.sql("WITH RECURSIVE t(i, v) AS (SELECT 0, CAST(1 AS BIGINT) UNION ALL SELECT i + 1, v * 2 FROM t WHERE i < 10) SELECT i, v FROM t")


@operator("SELECT s_suppkey, round(sqrt(abs(s_acctbal)), 6) AS r, CAST(floor(s_acctbal) AS BIGINT) AS f, CAST(sign(s_acctbal) AS DOUBLE) AS g, upper(s_name) AS u, substr(s_name, 1, 4) AS p, lpad(CAST(s_suppkey AS VARCHAR), 6, '0') AS k, greatest(s_acctbal, 0.0) AS m FROM supplier")
def op_scalar_functions(spark, sf):
    return table(spark, sf, "supplier").select(
        "s_suppkey", F.round(F.sqrt(F.abs("s_acctbal")), 6).alias("r"), F.floor("s_acctbal").alias("f"), F.signum("s_acctbal").alias("g"), F.upper("s_name").alias("u"),
        F.substring("s_name", 1, 4).alias("p"), F.lpad(F.col("s_suppkey").cast("string"), 6, "0").alias("k"), F.greatest("s_acctbal", F.lit(0.0)).alias("m"),
    )


@operator("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS norm2, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, embedding[3] AS third FROM embeddings")
def op_array_functions(spark, sf):
    e = F.col("embedding")
    return table(spark, sf, "embeddings").select("vec_id", F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 4).alias("norm2"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"), F.element_at(e, 3).alias("third"))


@operator("SELECT user_id, CAST(count(*) AS BIGINT) AS copies FROM events GROUP BY user_id")
def op_table_function(spark, sf):
    """Copies expanded by the table function and counted again."""
    from particle_engine.functions.scalar import register_sql

    register_sql(spark)
    table(spark, sf, "events").groupBy("user_id").agg(F.count(F.lit(1)).cast("int").alias("alpha")).createOrReplaceTempView("op_parents")
    return spark.sql("SELECT p.user_id, count(*) AS copies FROM op_parents p, LATERAL offspring_slots(p.alpha) GROUP BY p.user_id")


@operator("SELECT event_id, CAST(('0x' || substr(md5(concat_ws('|', 1, 2, event_id, 3)), 1, 13)) AS BIGINT) AS h FROM events")
def op_sql_macro(spark, sf):
    from particle_engine.functions.scalar import register_sql

    register_sql(spark)
    return table(spark, sf, "events").selectExpr("event_id", "unit_hash(1, 2, event_id, 3) AS h")
