"""Operators around the methods: formats, joins, aggregates, windows, sets, functions, subqueries, UDFs."""

from __future__ import annotations

import uuid

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators import bottomk as B
from ..operators import relational as RO
from ..operators.exact import frequencies, histogram, self_join_count
from ..operators.wr import cumulated
from ..plans.lineage import checkpoint_folder
from ..plans.registry import query
from ..sources.tables import HOST, TOKEN, load, read, to_elements, write
from .advice import END, NOW, PAST, between, cust_parts
from .sql import f_sql, freq, s, sig, u_sql


def _path(spark, name):
    return f"{checkpoint_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


# -- sources and sinks -------------------------------------------------------------------------


@query("src_parquet", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus = 'F' AND o_totalprice > 100000")
def src_parquet(spark, d):
    return load(spark, d, "orders").where("o_orderstatus = 'F' and o_totalprice > 100000").select("o_orderkey", "o_custkey")


def _round_trip(form, **options):
    @query(f"src_{form}_roundtrip", "SELECT c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment FROM customer")
    def run(spark, d):
        rows = load(spark, d, "customer").select("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment")
        path = write(rows, _path(spark, form), form, **options)
        return read(spark, path, form, schema=rows.schema, **options)

    run.__name__ = f"src_{form}_roundtrip"


_round_trip("csv", header="true")
_round_trip("json")
_round_trip("orc")


@query("src_text", "SELECT CAST(count(*) AS BIGINT) AS n, CAST(sum(length(l)) AS BIGINT) AS chars FROM (SELECT unnest(string_split(text, chr(10))) AS l FROM documents) x")
def src_text(spark, d):
    rows = load(spark, d, "documents").select(F.explode(F.split("text", "\n")).alias("value"))
    return read(spark, write(rows, _path(spark, "text"), "text"), "text").agg(F.count("*").alias("n"), F.sum(F.length("value")).alias("chars"))


@query("src_partitioned", "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(count(*) AS BIGINT) AS n FROM orders WHERE year(o_orderdate) IN (1997, 1998) GROUP BY 1")
def src_partitioned(spark, d):
    path = write(load(spark, d, "orders").withColumn("y", F.year("o_orderdate")), _path(spark, "by-year"), by=["y"])
    return read(spark, path).where(F.col("y").isin(1997, 1998)).groupBy(F.col("y").cast("int").alias("y")).agg(F.count("*").alias("n"))


@query("sink_sketch_roundtrip", f"SELECT key, {s('w')} AS w, {s('seed')} AS seed FROM (SELECT key, w, {u_sql()} / w AS seed FROM {f_sql('cust_out')} a ORDER BY seed, key LIMIT 50) x")
def sink_sketch_roundtrip(spark, d):
    sk = B.bottom_k(B.seeded(freq(spark, d, "cust_out"), F.col("w"), scheme="priority"), 50)
    path = RO.store_sketch(sk, "cust", _path(spark, "sketches"), {"k": 50, "scheme": "priority", "salt": "s"})
    return RO.stored_rows(spark, path, "cust").select("key", sig("w").alias("w"), sig("seed").alias("seed"))


# -- projection and filters -------------------------------------------------------------------------


@query("proj_basic", "SELECT c_custkey AS id, coalesce(c_mktsegment, '?') AS seg, CASE WHEN c_acctbal < 0 THEN 'debt' ELSE 'ok' END AS state, least(c_acctbal, 5000.0) AS capped, CAST(c_nationkey AS BIGINT) AS nation FROM customer")
def proj_basic(spark, d):
    return load(spark, d, "customer").select(
        F.col("c_custkey").alias("id"), F.coalesce("c_mktsegment", F.lit("?")).alias("seg"), F.when(F.col("c_acctbal") < 0, "debt").otherwise("ok").alias("state"),
        F.least("c_acctbal", F.lit(5000.0)).alias("capped"), F.col("c_nationkey").cast("bigint").alias("nation"),
    )


@query("filter_label", "SELECT CAST(count(*) AS BIGINT) AS n FROM lineitem WHERE l_returnflag <> 'R' AND l_quantity BETWEEN 5 AND 20 AND l_linestatus IN ('O', 'F')")
def filter_label(spark, d):
    return load(spark, d, "lineitem").where((F.col("l_returnflag") != "R") & F.col("l_quantity").between(5, 20) & F.col("l_linestatus").isin("O", "F")).agg(F.count("*").alias("n"))


@query("filter_period", f"SELECT o_orderkey FROM orders WHERE o_orderdate >= TIMESTAMP '{PAST} 00:00:00' AND o_orderdate < TIMESTAMP '{NOW} 00:00:00'")
def filter_period(spark, d):
    return load(spark, d, "orders").where(between("o_orderdate", PAST, NOW)).select("o_orderkey")


@query("filter_domain", "SELECT p_partkey FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_type, '^[A-Z]+$') AND p_size IS NOT NULL AND NOT (p_size > 40 OR p_brand = 'Brand#11')")
def filter_domain(spark, d):
    return load(spark, d, "part").where(F.col("p_name").like("%a%") & F.col("p_type").rlike("^[A-Z]+$") & F.col("p_size").isNotNull() & ~((F.col("p_size") > 40) | (F.col("p_brand") == "Brand#11"))).select("p_partkey")


# -- joins ----------------------------------------------------------------------------------------------

_JOIN = "SELECT n_name, CAST(count(*) AS BIGINT) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"


def _join(name, hint):
    @query(name, _JOIN)
    def run(spark, d):
        c = load(spark, d, "customer").select("c_custkey", "c_nationkey")
        o = load(spark, d, "orders").select("o_custkey")
        c = c.hint(hint) if hint else c
        rows = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(load(spark, d, "nation").select("n_nationkey", "n_name"), F.col("c_nationkey") == F.col("n_nationkey"))
        return rows.groupBy("n_name").agg(F.count("*").alias("n"))

    run.__name__ = name


_join("join_inner", None)
_join("join_broadcast", "broadcast")
_join("join_merge", "merge")
_join("join_shuffle_hash", "shuffle_hash")


def _period_sql(a, b):
    return f"(SELECT CAST(o_custkey AS VARCHAR) AS key, count(*) AS w FROM orders WHERE o_orderdate >= TIMESTAMP '{a} 00:00:00' AND o_orderdate < TIMESTAMP '{b} 00:00:00' GROUP BY 1)"


@query("join_left_advice", f"SELECT n.key, CAST(n.w AS BIGINT) AS w, CAST(coalesce(p.w, 0) AS BIGINT) AS advice FROM {_period_sql(NOW, END)} n LEFT JOIN {_period_sql(PAST, NOW)} p ON p.key = n.key")
def join_left_advice(spark, d):
    past, now = (frequencies(x) for x in cust_parts(spark, d))
    return now.join(past.withColumnRenamed("w", "advice"), "key", "left").select("key", F.col("w").cast("bigint").alias("w"), F.coalesce("advice", F.lit(0)).cast("bigint").alias("advice"))


@query("join_full_periods", f"SELECT coalesce(n.key, p.key) AS key, CAST(coalesce(n.w, 0) AS BIGINT) - CAST(coalesce(p.w, 0) AS BIGINT) AS change FROM {_period_sql(NOW, END)} n FULL OUTER JOIN {_period_sql(PAST, NOW)} p ON p.key = n.key")
def join_full_periods(spark, d):
    past, now = (frequencies(x) for x in cust_parts(spark, d))
    rows = now.join(past.withColumnRenamed("w", "v"), "key", "full")
    return rows.select("key", (F.coalesce("w", F.lit(0)).cast("bigint") - F.coalesce("v", F.lit(0)).cast("bigint")).alias("change"))


@query("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def join_semi(spark, d):
    o = load(spark, d, "orders").where("o_totalprice > 400000").select("o_custkey")
    return load(spark, d, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def join_anti(spark, d):
    o = load(spark, d, "orders").where("o_totalprice > 400000").select("o_custkey")
    return load(spark, d, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("join_range_draws", f"SELECT CAST(count(*) AS BIGINT) AS n, {s('max(hi)')} AS top, CAST(count(DISTINCT key) AS BIGINT) AS keys FROM (SELECT key, sum(w) OVER (ORDER BY key) / sum(w) OVER () AS hi FROM {f_sql('cust_out')} a) b")
def join_range_draws(spark, d):
    from ..functions.frequency import moment

    rows = cumulated(freq(spark, d, "cust_out"), moment(1))
    return rows.agg(F.count("*").alias("n"), sig(F.max("hi")).alias("top"), F.count_distinct("key").alias("keys"))


@query("join_cross_grid", f"SELECT CAST(p AS DOUBLE) AS p, {s('sum(pow(w, p))')} AS value FROM {f_sql('cust_out')} a, (SELECT unnest([0.5, 1.0, 2.0, 3.0]) AS p) g GROUP BY p")
def join_cross_grid(spark, d):
    grid = spark.createDataFrame([(x,) for x in (0.5, 1.0, 2.0, 3.0)], "p double")
    rows = freq(spark, d, "cust_out").crossJoin(F.broadcast(grid))
    return rows.groupBy("p").agg(F.sum(F.pow("w", "p")).alias("value")).select("p", sig("value").alias("value"))


@query("join_asof_advice", "SELECT e.event_id, (SELECT max(x.day) FROM (SELECT DISTINCT user_id, date_trunc('day', ts) AS day FROM events WHERE value > 90) x WHERE x.user_id = e.user_id AND x.day <= e.ts) AS version FROM events e WHERE e.event_type = (SELECT min(event_type) FROM events)")
def join_asof_advice(spark, d):
    e = load(spark, d, "events")
    kind = e.agg(F.min("event_type").alias("k"))
    left = e.join(F.broadcast(kind), F.col("event_type") == F.col("k"), "left_semi").select("event_id", "user_id", "ts")
    right = e.where("value > 90").select("user_id", F.date_trunc("day", "ts").cast("timestamp_ntz").alias("ts")).distinct().withColumn("version", F.col("ts"))
    return RO.asof_join(left, right, "user_id", "ts", ["version"]).select("event_id", "version")


@query("self_join_brute", "SELECT CAST(count(*) AS BIGINT) AS pairs FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey")
def self_join_brute(spark, d):
    return self_join_count(to_elements(load(spark, d, "orders"), ["o_custkey"]), 2).select(F.col("value").cast("bigint").alias("pairs"))


# -- aggregates -----------------------------------------------------------------------------------------


@query("agg_basic", f"SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n, {s('sum(l_quantity)')} AS qty, {s('avg(l_extendedprice)')} AS price, min(l_discount) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY 1, 2")
def agg_basic(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), sig(F.sum("l_quantity")).alias("qty"), sig(F.avg("l_extendedprice")).alias("price"), F.min("l_discount").alias("lo"), F.max("l_tax").alias("hi")
    )


@query("agg_distinct", "SELECT o_orderstatus, CAST(count(DISTINCT o_custkey) AS BIGINT) AS customers, CAST(count(DISTINCT o_orderpriority) AS BIGINT) AS priorities, CAST(count(*) FILTER (o_totalprice > 200000) AS BIGINT) AS large FROM orders GROUP BY 1")
def agg_distinct(spark, d):
    return load(spark, d, "orders").groupBy("o_orderstatus").agg(F.count_distinct("o_custkey").alias("customers"), F.count_distinct("o_orderpriority").alias("priorities"), F.count_if(F.col("o_totalprice") > 200000).alias("large"))


@query("agg_stats", f"SELECT event_type, {s('stddev_samp(value)')} AS sd, {s('var_pop(value)')} AS var, {s('corr(value, user_id)')} AS cor FROM events GROUP BY 1")
def agg_stats(spark, d):
    return load(spark, d, "events").groupBy("event_type").agg(sig(F.stddev_samp("value")).alias("sd"), sig(F.var_pop("value")).alias("var"), sig(F.corr("value", "user_id")).alias("cor"))


@query("agg_maxby", "SELECT c_mktsegment, arg_max(c_custkey, c_acctbal) AS richest, arg_min(c_custkey, c_acctbal) AS poorest FROM customer GROUP BY 1")
def agg_maxby(spark, d):
    """Of equal balances the smallest key: what SQL finds that reads the rows in order of their keys."""
    some = F.col("c_custkey").isNotNull() & F.col("c_acctbal").isNotNull()
    rows = load(spark, d, "customer").select("c_mktsegment", "c_custkey", F.when(some, F.struct("c_acctbal", F.bitwise_not("c_custkey"))).alias("high"), F.when(some, F.struct("c_acctbal", "c_custkey")).alias("low"))
    return rows.groupBy("c_mktsegment").agg(F.max_by("c_custkey", "high").alias("richest"), F.min_by("c_custkey", "low").alias("poorest"))


@query("agg_percentile", f"SELECT l_returnflag, {s('quantile_cont(l_extendedprice, 0.5)')} AS mid, {s('quantile_cont(l_extendedprice, 0.9)')} AS high FROM lineitem GROUP BY 1")
def agg_percentile(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(sig(F.percentile("l_extendedprice", 0.5)).alias("mid"), sig(F.percentile("l_extendedprice", 0.9)).alias("high"))


@query("agg_collect", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def agg_collect(spark, d):
    return load(spark, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_set("n_name")), ",").alias("names"))


_SETS = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
_SETS_COLS = f"r_name, c_mktsegment, CAST(grouping(r_name) * 2 + grouping(c_mktsegment) AS BIGINT) AS gid, {s('sum(c_acctbal)')} AS bal, CAST(count(*) AS BIGINT) AS n"


def _domains(spark, d):
    c, n, r = load(spark, d, "customer"), load(spark, d, "nation"), load(spark, d, "region")
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).select("r_name", "c_mktsegment", "c_acctbal")


def _sets(name, sql, make):
    @query(name, f"SELECT {_SETS_COLS} {_SETS} GROUP BY {sql}")
    def run(spark, d):
        return make(_domains(spark, d)).agg(F.grouping_id().cast("bigint").alias("gid"), sig(F.sum("c_acctbal")).alias("bal"), F.count("*").alias("n"))

    run.__name__ = name


_sets("agg_rollup", "ROLLUP (r_name, c_mktsegment)", lambda x: x.rollup("r_name", "c_mktsegment"))
_sets("agg_cube", "CUBE (r_name, c_mktsegment)", lambda x: x.cube("r_name", "c_mktsegment"))
_sets("agg_gsets", "GROUPING SETS ((r_name, c_mktsegment), (r_name), ())", lambda x: x.groupingSets([[F.col("r_name"), F.col("c_mktsegment")], [F.col("r_name")], []], "r_name", "c_mktsegment"))


@query("agg_pivot", "SELECT l_returnflag, CAST(count(*) FILTER (l_linestatus = 'F') AS BIGINT) AS f, CAST(count(*) FILTER (l_linestatus = 'O') AS BIGINT) AS o FROM lineitem GROUP BY 1")
def agg_pivot(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count().na.fill(0).withColumnsRenamed({"F": "f", "O": "o"})


@query("unpivot_stats", f"SELECT 'm1' AS name, {s('sum(w)')} AS value FROM {f_sql('cust_out')} a UNION ALL SELECT 'm2', {s('sum(w*w)')} FROM {f_sql('cust_out')} a")
def unpivot_stats(spark, d):
    one = freq(spark, d, "cust_out").agg(F.sum("w").alias("m1"), F.sum(F.col("w") * F.col("w")).alias("m2"))
    return one.unpivot([], ["m1", "m2"], "name", "value").select("name", sig("value").alias("value"))


@query("approx_distinct")
def approx_distinct(spark, d):
    e = load(spark, d, "documents").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(TOKEN), F.lit(0))).alias("key"))
    return e.agg(F.approx_count_distinct("key", 0.02).alias("hll"), F.hll_sketch_estimate(F.hll_sketch_agg("key")).alias("sketch"), F.count_distinct("key").alias("exact"))


@query("approx_topk")
def approx_topk(spark, d):
    load(spark, d, "lineitem").createOrReplaceTempView("_topk_rows")
    return spark.sql("SELECT inline(approx_top_k(l_suppkey, 10)) FROM _topk_rows")


@query("kll_quantiles")
def kll_quantiles(spark, d):
    load(spark, d, "lineitem").createOrReplaceTempView("_kll_rows")
    return spark.sql("SELECT kll_sketch_get_quantile_double(kll_sketch_agg_double(l_extendedprice), 0.5D) AS mid, percentile(l_extendedprice, 0.5) AS exact FROM _kll_rows")


@query("count_min")
def count_min(spark, d):
    rows = load(spark, d, "lineitem").select(F.col("l_suppkey").cast("string").alias("key"))
    return rows.agg(F.length(F.count_min_sketch("key", F.lit(0.01), F.lit(0.95), F.lit(7))).alias("bytes"), F.count("*").alias("n"))


@query("theta_overlap")
def theta_overlap(spark, d):
    past, now = cust_parts(spark, d)
    past.createOrReplaceTempView("_theta_a")
    now.createOrReplaceTempView("_theta_b")
    return spark.sql("SELECT theta_sketch_estimate(theta_intersection((SELECT theta_sketch_agg(key) FROM _theta_a), (SELECT theta_sketch_agg(key) FROM _theta_b))) AS overlap")


# -- windows, sorts, sets -------------------------------------------------------------------------------

_WIN = "OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey)"


@query("win_rank", f"SELECT c_custkey, CAST(row_number() {_WIN} AS BIGINT) AS rn, CAST(rank() {_WIN} AS BIGINT) AS rk, CAST(dense_rank() {_WIN} AS BIGINT) AS dr, CAST(ntile(4) {_WIN} AS BIGINT) AS nt, {s(f'percent_rank() {_WIN}')} AS pr, {s(f'cume_dist() {_WIN}')} AS cd FROM customer")
def win_rank(spark, d):
    w = W.partitionBy("c_mktsegment").orderBy(F.col("c_acctbal").desc(), "c_custkey")
    big = lambda c: c.cast("bigint")
    return load(spark, d, "customer").select("c_custkey", big(F.row_number().over(w)).alias("rn"), big(F.rank().over(w)).alias("rk"), big(F.dense_rank().over(w)).alias("dr"), big(F.ntile(4).over(w)).alias("nt"), sig(F.percent_rank().over(w)).alias("pr"), sig(F.cume_dist().over(w)).alias("cd"))


@query("win_lag", "SELECT event_id, value - lag(value) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS back, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS following FROM events")
def win_lag(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events").select("event_id", (F.col("value") - F.lag("value").over(w)).alias("back"), F.lead("event_id").over(w).alias("following"))


_ALL = "OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"


@query("win_firstlast", f"SELECT event_id, first_value(event_id) {_ALL} AS f, last_value(event_id) {_ALL} AS l, nth_value(event_id, 2) {_ALL} AS n2 FROM events")
def win_firstlast(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return load(spark, d, "events").select("event_id", F.first("event_id").over(w).alias("f"), F.last("event_id").over(w).alias("l"), F.nth_value("event_id", 2).over(w).alias("n2"))


@query("win_rows", f"SELECT event_id, {s('avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW)')} AS moving FROM events")
def win_rows(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)
    return load(spark, d, "events").select("event_id", sig(F.avg("value").over(w)).alias("moving"))


@query("win_range", "SELECT o_orderkey, CAST(count(*) OVER (PARTITION BY o_orderstatus ORDER BY CAST(o_totalprice AS BIGINT) RANGE BETWEEN 1000 PRECEDING AND 1000 FOLLOWING) AS BIGINT) AS near FROM orders")
def win_range(spark, d):
    return RO.count_near(load(spark, d, "orders"), "o_orderstatus", F.rint("o_totalprice").cast("bigint"), 1000).select("o_orderkey", "near")


@query("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk_global(spark, d):
    return load(spark, d, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


@query("topk_group", "SELECT o_orderpriority, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) x WHERE rn <= 10")
def topk_group(spark, d):
    w = W.partitionBy("o_orderpriority").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return load(spark, d, "orders").withColumn("rn", F.row_number().over(w)).where("rn <= 10").select("o_orderpriority", "o_orderkey")


@query("sort_multi", "SELECT CAST(row_number() OVER (ORDER BY c_mktsegment NULLS LAST, c_acctbal DESC, c_custkey) AS BIGINT) AS i, c_custkey FROM customer")
def sort_multi(spark, d):
    w = W.orderBy(F.col("c_mktsegment").asc_nulls_last(), F.col("c_acctbal").desc(), "c_custkey")
    return load(spark, d, "customer").select(F.row_number().over(w).cast("bigint").alias("i"), "c_custkey")


@query("limit_offset", "SELECT p_partkey FROM part ORDER BY p_retailprice, p_partkey LIMIT 20 OFFSET 30")
def limit_offset(spark, d):
    return load(spark, d, "part").orderBy("p_retailprice", "p_partkey").offset(30).limit(20).select("p_partkey")


_PA, _PB = _period_sql(PAST, NOW), _period_sql(NOW, END)


def _sets_of(name, op, make):
    @query(name, f"SELECT key FROM {_PA} a {op} SELECT key FROM {_PB} b")
    def run(spark, d):
        a, b = (frequencies(x).select("key") for x in cust_parts(spark, d))
        return make(a, b)

    run.__name__ = name


_sets_of("set_union_all", "UNION ALL", lambda a, b: a.unionByName(b))
_sets_of("set_union", "UNION", lambda a, b: a.union(b).distinct())
_sets_of("set_intersect", "INTERSECT", lambda a, b: a.intersect(b))
_sets_of("set_except", "EXCEPT", lambda a, b: a.subtract(b))


@query("set_except_all", "SELECT o_orderpriority FROM orders WHERE o_orderkey % 3 = 0 EXCEPT ALL SELECT o_orderpriority FROM orders WHERE o_orderkey % 3 = 1")
def set_except_all(spark, d):
    o = load(spark, d, "orders")
    return o.where("o_orderkey % 3 = 0").select("o_orderpriority").exceptAll(o.where("o_orderkey % 3 = 1").select("o_orderpriority"))


@query("set_intersect_all", "SELECT o_orderpriority FROM orders WHERE o_orderkey % 3 = 0 INTERSECT ALL SELECT o_orderpriority FROM orders WHERE o_orderkey % 3 = 1")
def set_intersect_all(spark, d):
    o = load(spark, d, "orders")
    return o.where("o_orderkey % 3 = 0").select("o_orderpriority").intersectAll(o.where("o_orderkey % 3 = 1").select("o_orderpriority"))


@query("dedupe_clicks", "SELECT CAST(count(*) AS BIGINT) AS n FROM (SELECT DISTINCT user_id, event_type, date_trunc('hour', ts) AS h FROM events) x")
def dedupe_clicks(spark, d):
    return load(spark, d, "events").withColumn("h", F.date_trunc("hour", "ts")).dropDuplicates(["user_id", "event_type", "h"]).agg(F.count("*").alias("n"))


# -- functions --------------------------------------------------------------------------------------------


@query("fn_string", "SELECT p_partkey, lower(trim(p_name)) AS name, substr(p_brand, 7, 2) AS brand, string_split(p_type, ' ')[1] AS first, regexp_replace(p_type, '[AEIOU]', '', 'g') AS bare, CAST(length(p_name) AS BIGINT) AS n, md5(p_name) AS h, sha256(p_name) AS h2, concat_ws('-', p_brand, p_size) AS tag FROM part")
def fn_string(spark, d):
    return load(spark, d, "part").select(
        "p_partkey", F.lower(F.trim("p_name")).alias("name"), F.substring("p_brand", 7, 2).alias("brand"), F.split("p_type", " ")[0].alias("first"), F.regexp_replace("p_type", "[AEIOU]", "").alias("bare"),
        F.length("p_name").cast("bigint").alias("n"), F.md5(F.col("p_name").cast("binary")).alias("h"), F.sha2(F.col("p_name").cast("binary"), 256).alias("h2"), F.concat_ws("-", "p_brand", F.col("p_size").cast("string")).alias("tag"),
    )


@query("tokens", "SELECT doc_id, CAST(len(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+')) AS BIGINT) AS n FROM documents")
def tokens(spark, d):
    return load(spark, d, "documents").select("doc_id", F.size(F.regexp_extract_all(F.lower("text"), F.lit(TOKEN), F.lit(0))).cast("bigint").alias("n"))


@query("page_hosts", "SELECT regexp_extract(url, '^[a-zA-Z]+://([^/:?#]+)', 1) AS host, CAST(count(*) AS BIGINT) AS n FROM pages GROUP BY 1")
def page_hosts(spark, d):
    return load(spark, d, "pages").groupBy(F.regexp_extract("url", HOST, 1).alias("host")).agg(F.count("*").alias("n"))


@query("fn_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(datediff('day', TIMESTAMP '1995-01-01 00:00:00', o_orderdate) AS INTEGER) AS days, CAST(date_trunc('month', o_orderdate) AS DATE) AS month_start FROM orders")
def fn_date(spark, d):
    day = F.col("o_orderdate").cast("date")
    return load(spark, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.datediff(day, F.lit("1995-01-01").cast("date")).alias("days"), F.trunc(day, "month").alias("month_start"))


@query("fn_math", f"SELECT l_orderkey, l_linenumber, {s('pow(l_quantity, 1.5)')} AS p, {s('ln(l_quantity)')} AS l, {s('ln(1 + l_discount)')} AS l1, {s('exp(-l_tax)')} AS e, {s('sqrt(l_extendedprice)')} AS r, CAST(floor(l_extendedprice / 7) AS BIGINT) AS f, CAST(ceil(l_extendedprice / 7) AS BIGINT) AS c, greatest(l_discount, l_tax) AS g, CAST(l_orderkey % 7 AS BIGINT) AS m FROM lineitem")
def fn_math(spark, d):
    return load(spark, d, "lineitem").select(
        "l_orderkey", "l_linenumber", sig(F.pow("l_quantity", F.lit(1.5))).alias("p"), sig(F.log("l_quantity")).alias("l"), sig(F.log1p("l_discount")).alias("l1"), sig(F.exp(-F.col("l_tax"))).alias("e"), sig(F.sqrt("l_extendedprice")).alias("r"),
        F.floor(F.col("l_extendedprice") / 7).alias("f"), F.ceil(F.col("l_extendedprice") / 7).alias("c"), F.greatest("l_discount", "l_tax").alias("g"), F.pmod("l_orderkey", F.lit(7)).cast("bigint").alias("m"),
    )


@query("fn_array", "SELECT p_partkey, CAST(list_sum(list_transform(range(1, p_size % 5 + 2), lambda x: x * x)) AS BIGINT) AS squares, CAST(len(list_filter(range(1, p_size + 1), lambda x: x % 3 = 0)) AS BIGINT) AS thirds, list_contains(string_split(p_type, ' '), 'STEEL') AS steel FROM part")
def fn_array(spark, d):
    up = F.sequence(F.lit(1), F.col("p_size") % 5 + 1)
    return load(spark, d, "part").select(
        "p_partkey", F.aggregate(F.transform(up, lambda x: (x * x).cast("bigint")), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("squares"),
        F.size(F.filter(F.sequence(F.lit(1), "p_size"), lambda x: x % 3 == 0)).cast("bigint").alias("thirds"), F.array_contains(F.split("p_type", " "), "STEEL").alias("steel"),
    )


@query("fn_map", f"SELECT 'm' || p AS name, {s('sum(pow(w, p))')} AS value FROM {f_sql('cust_out')} a, (SELECT unnest([1, 2, 3]) AS p) g GROUP BY p")
def fn_map(spark, d):
    one = freq(spark, d, "cust_out").agg(*[F.sum(F.pow("w", F.lit(float(p)))).alias(f"m{p}") for p in (1, 2, 3)])
    pairs = F.map_from_arrays(F.array(*[F.lit(f"m{p}") for p in (1, 2, 3)]), F.array("m1", "m2", "m3"))
    return one.select(F.explode(pairs).alias("name", "value")).select("name", sig("value").alias("value"))


@query("fn_struct", "SELECT c_custkey, c_mktsegment || ':' || CAST(c_nationkey AS VARCHAR) AS tag FROM customer WHERE c_nationkey < 5")
def fn_struct(spark, d):
    rows = load(spark, d, "customer").select("c_custkey", F.struct(F.col("c_mktsegment").alias("a"), F.col("c_nationkey").alias("b")).alias("x"))
    return rows.where("x.b < 5").select("c_custkey", F.concat("x.a", F.lit(":"), F.col("x.b").cast("string")).alias("tag"))


@query("fn_json", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")
def fn_json(spark, d):
    return load(spark, d, "events").select(F.from_json("props", "k bigint").alias("j")).groupBy(F.col("j.k").alias("k")).agg(F.count("*").alias("n"))


@query("fn_json_out", "SELECT CAST(json_extract(props, '$.k') AS VARCHAR) AS k FROM events")
def fn_json_out(spark, d):
    rows = load(spark, d, "events").select(F.to_json(F.from_json("props", "k bigint")).alias("j"))
    return rows.select(F.get_json_object("j", "$.k").alias("k"))


# -- subqueries, SQL surface, UDFs ---------------------------------------------------------------------


@query("subq_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
def subq_scalar(spark, d):
    o = load(spark, d, "orders")
    mean = o.agg((F.avg("o_totalprice") * 1.5).alias("m"))
    return o.where(F.col("o_totalprice") > mean.scalar()).select("o_orderkey")


@query("subq_exists", "SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_suppkey = s_suppkey AND l_quantity = 50 AND l_discount = 0)")
def subq_exists(spark, d):
    s_ = load(spark, d, "supplier")
    li = load(spark, d, "lineitem").where("l_quantity = 50 and l_discount = 0")
    return s_.where(li.where(F.col("l_suppkey") == F.col("s_suppkey").outer()).exists()).select("s_suppkey")


@query("lateral_topk", "SELECT n_name, c_custkey FROM (SELECT n_name, c_custkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn FROM nation JOIN customer ON c_nationkey = n_nationkey) x WHERE rn <= 3")
def lateral_topk(spark, d):
    load(spark, d, "nation").createOrReplaceTempView("_lat_n")
    load(spark, d, "customer").createOrReplaceTempView("_lat_c")
    return spark.sql("SELECT n_name, c_custkey FROM _lat_n, LATERAL (SELECT c_custkey FROM _lat_c WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3)")


@query("sql_surface", f"SELECT key, {u_sql()} AS u FROM {f_sql('cust_out')} a WHERE w >= 10")
def sql_surface(spark, d):
    RO.register_functions(spark)
    freq(spark, d, "cust_out").createOrReplaceTempView("_surface")
    return spark.sql("SELECT key, unit_seed(key, 's') AS u FROM _surface WHERE w >= :least", args={"least": 10})


@query("udf_scalar", f"SELECT key, CAST(length(key) AS BIGINT) AS n FROM {f_sql('page_hosts')} a")
def udf_scalar(spark, d):
    return freq(spark, d, "page_hosts").select("key", RO.code_points("key").alias("n"))


@query("udaf_bottomk", f"SELECT c_mktsegment AS segment, string_agg(key, ',' ORDER BY u, key) AS keys FROM (SELECT c_mktsegment, key, u, row_number() OVER (PARTITION BY c_mktsegment ORDER BY u, key) AS rn FROM (SELECT c_mktsegment, CAST(c_custkey AS VARCHAR) AS key, {u_sql(key='CAST(c_custkey AS VARCHAR)')} AS u FROM customer) a) b WHERE rn <= 8 GROUP BY 1")
def udaf_bottomk(spark, d):
    rows = load(spark, d, "customer").select(F.col("c_mktsegment").alias("segment"), F.col("c_custkey").cast("string").alias("key"))
    return RO.bottom_k_by_group(rows, "segment", 8)


@query("udaf_bottomk_pandas", f"SELECT c_mktsegment AS segment, string_agg(key, ',' ORDER BY u, key) AS keys FROM (SELECT c_mktsegment, key, u, row_number() OVER (PARTITION BY c_mktsegment ORDER BY u, key) AS rn FROM (SELECT c_mktsegment, CAST(c_custkey AS VARCHAR) AS key, {u_sql(key='CAST(c_custkey AS VARCHAR)')} AS u FROM customer) a) b WHERE rn <= 8 GROUP BY 1")
def udaf_bottomk_pandas(spark, d):
    rows = load(spark, d, "customer").select(F.col("c_mktsegment").alias("segment"), F.col("c_custkey").cast("string").alias("key"))
    return RO.bottom_k_by_group_pandas(rows, "segment", 8)


@query("udtf_zipf", f"SELECT user_id, CAST(i AS VARCHAR) AS key, {s('w1 * pow(i, -1.5)')} AS w FROM (SELECT user_id, w1, unnest(range(1, n + 1)) AS i FROM (SELECT user_id, count(DISTINCT date_trunc('day', ts)) AS n, max(value) AS w1 FROM events WHERE value > 0 GROUP BY 1) u) a")
def udtf_zipf(spark, d):
    """For each user a vector of as many keys as days with events, the first with the largest value."""
    users = load(spark, d, "events").where("value > 0").groupBy("user_id").agg(F.countDistinct(F.date_trunc("day", "ts")).alias("n"), F.max("value").alias("w1"))
    return RO.zipf_rows(users, "n", 1.5, "w1").select("user_id", "key", sig("w").alias("w"))


@query("hist_reuse", f"SELECT CAST(count(*) AS BIGINT) AS d, CAST(sum(m) AS BIGINT) AS n FROM (SELECT w, count(*) AS m FROM {f_sql('cust_out')} a GROUP BY w) b")
def hist_reuse(spark, d):
    return histogram(freq(spark, d, "cust_out")).agg(F.count("*").alias("d"), F.sum("m").alias("n"))
