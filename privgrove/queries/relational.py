"""Queries of the surrounding operators: sources, filters, joins, aggregates, windows, sets, functions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from privgrove.functions.noise import uniform, uniform_sql
from privgrove.operators.schema import static_bin
from privgrove.queries.base import KEY, both, query
from privgrove.sources import io
from privgrove.sources.io import load


def counted():
    """The number of rows, as n."""
    return F.count(F.lit(1)).alias("n")


# ---- sources and sinks


@query("s01_scan_parquet", "SELECT l_returnflag, sum(l_quantity) AS quantity FROM lineitem WHERE l_quantity > 45 GROUP BY 1")
def s01(spark, d):
    return load(spark, d, "lineitem").select("l_returnflag", "l_quantity").where("l_quantity > 45").groupBy("l_returnflag").agg(F.sum("l_quantity").alias("quantity"))


for _fmt, _options in (("csv", {"header": "true"}), ("json", {}), ("orc", {}), ("parquet", {})):

    @query(f"s02_{_fmt}_round_trip", "SELECT p_partkey, p_name, p_size, p_retailprice FROM part")
    def s02(spark, d, fmt=_fmt, options=_options):
        return io.round_trip(load(spark, d, "part").select("p_partkey", "p_name", "p_size", "p_retailprice"), fmt, **options)


@query("s02_text_round_trip", "SELECT p_name AS value FROM part")
def s02_text(spark, d):
    return io.round_trip(load(spark, d, "part").select(F.col("p_name").alias("value")), "text")


@query("s03_explicit_schema", "SELECT o_orderkey, o_totalprice FROM orders")
def s03(spark, d):
    return spark.read.schema("o_orderkey bigint, o_totalprice double").parquet(f"{d}/orders.parquet")


@query("s04_partitioned_pruned_read", "SELECT p_partkey, p_size FROM part WHERE p_size = 7")
def s04(spark, d):
    path = io.shared_dir(spark, "parts")
    load(spark, d, "part").select("p_partkey", "p_size").write.partitionBy("p_size").parquet(path)
    return spark.read.parquet(path).where("p_size = 7").select("p_partkey", "p_size")


@query("s05_bucketed_table", "SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1")
def s05(spark, d):
    path, name = io.shared_dir(spark, "buckets"), "grove_buckets"
    spark.sql(f"DROP TABLE IF EXISTS {name}")
    load(spark, d, "lineitem").select("l_orderkey", "l_quantity").write.mode("overwrite").option("path", path).bucketBy(8, "l_orderkey").sortBy("l_orderkey").saveAsTable(name)
    return spark.table(name).groupBy("l_orderkey").agg(counted())


both("s06_sql_front", "SELECT r_name, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")


@query("s10_inline_rows", "SELECT * FROM (VALUES (1, 'a'), (2, 'b')) t(k, v)")
def s10(spark, d):
    return spark.createDataFrame([(1, "a"), (2, "b")], "k int, v string")


@query("s11_sparse_text", "SELECT l_linestatus, round(sum(l_discount), 6) AS discount, count(*) AS n FROM lineitem WHERE l_discount <> 0 GROUP BY 1")
def s11(spark, d):
    lines = load(spark, d, "lineitem").withColumn("label", (F.col("l_linestatus") == "O").cast("int"))
    back = io.from_libsvm(io.round_trip(io.to_libsvm(lines, "label", ["l_tax", "l_discount"]), "text"))
    own = back.select(F.when(F.col("label") == 1, "O").otherwise("F").alias("l_linestatus"), F.try_element_at("features", F.lit(1)).alias("x")).where("x IS NOT NULL")
    return own.groupBy("l_linestatus").agg(F.round(F.sum("x"), 6).alias("discount"), counted())


# ---- projections and predicates

both("p01_projection_cast", "SELECT CAST(l_quantity AS INT) AS q, CAST(l_linenumber AS STRING) AS line, l_extendedprice * (1 - l_discount) AS net FROM lineitem")
both("p02_predicates", "SELECT count(*) AS n FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#1', 'Brand#12', 'Brand#23') OR p_name LIKE '%a%' AND p_type IS NOT NULL")
both("p02_null_safe", "SELECT count(*) AS n FROM orders WHERE nullif(o_orderstatus, 'F') <=> NULL", "SELECT count(*) AS n FROM orders WHERE nullif(o_orderstatus, 'F') IS NOT DISTINCT FROM NULL")
both("p03_case_routing", "SELECT CASE WHEN l_quantity <= 10 THEN 1 WHEN l_discount <= 0.05 THEN 2 ELSE 3 END AS leaf, count(*) AS n FROM lineitem GROUP BY 1")
both("p04_rescale", "SELECT p_partkey, round(greatest(-1.0, least(1.0, 2 * (p_retailprice - 900) / 100 - 1)), 9) AS y, CAST(sign(p_retailprice - 950) AS DOUBLE) AS side FROM part")


@query("p05_static_bins", "SELECT CAST(least(greatest(ceil((l_quantity - 1) / 49.0 * 16) - 1, 0), 15) AS INTEGER) AS b, count(*) AS n FROM lineitem GROUP BY 1")
def p05(spark, d):
    return load(spark, d, "lineitem").groupBy(static_bin(F.col("l_quantity"), 1, 50, 16).cast("int").alias("b")).agg(counted())


@query("p05_left_closed_bins", "SELECT CAST(CASE WHEN l_quantity < 1 THEN 0 WHEN l_quantity >= 50 THEN 17 ELSE floor((l_quantity - 1) / 49.0 * 16) + 1 END AS BIGINT) AS b, count(*) AS n FROM lineitem GROUP BY 1")
def p05_left(spark, d):
    return load(spark, d, "lineitem").groupBy(F.expr("width_bucket(l_quantity, 1, 50, 16)").alias("b")).agg(counted())


@query("p06_hash_split", f"SELECT {uniform_sql(f"'{KEY}|' || o_orderkey")} < 0.2 AS test, count(*) AS n FROM orders GROUP BY 1")
def p06(spark, d):
    return load(spark, d, "orders").groupBy((uniform(KEY, "o_orderkey") < 0.2).alias("test")).agg(counted())


@query("p06_random_split")
def p06_random(spark, d):
    a, b = load(spark, d, "orders").select("o_orderkey").randomSplit([0.8, 0.2], seed=7)
    return a.agg(counted()).unionByName(b.agg(counted())).agg(F.sum("n").alias("n"))


@query("p06_sample_by")
def p06_by(spark, d):
    return load(spark, d, "lineitem").sampleBy("l_returnflag", {"R": 0.5, "A": 0.1}, seed=3).groupBy("l_returnflag").agg(counted())


@query("p07_wide_to_long", "SELECT feature, round(sum(value), 4) AS total FROM (SELECT 'tax' AS feature, l_tax AS value FROM lineitem UNION ALL SELECT 'discount', l_discount FROM lineitem) GROUP BY 1")
def p07(spark, d):
    wide = load(spark, d, "lineitem").select("l_orderkey", F.col("l_tax").alias("tax"), F.col("l_discount").alias("discount"))
    return wide.unpivot(["l_orderkey"], ["tax", "discount"], "feature", "value").groupBy("feature").agg(F.round(F.sum("value"), 4).alias("total"))


@query("p08_long_to_wide", "SELECT l_returnflag, count_if(l_linestatus = 'F') AS F, count_if(l_linestatus = 'O') AS O FROM lineitem GROUP BY 1")
def p08(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count().na.fill(0)


@query("p09_distinct", "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")
def p09(spark, d):
    return load(spark, d, "lineitem").select("l_returnflag", "l_linestatus").dropDuplicates()


@query("p10_one_hot", "SELECT sum(CAST(c_mktsegment = 'BUILDING' AS INTEGER)) AS building, sum(CAST(c_mktsegment = 'MACHINERY' AS INTEGER)) AS machinery FROM customer")
def p10(spark, d):
    return load(spark, d, "customer").agg(*[F.sum((F.col("c_mktsegment") == v).cast("int")).alias(v.lower()) for v in ("BUILDING", "MACHINERY")])


@query("p10_ordinal", "SELECT c_custkey, CAST(coalesce(list_position(['AUTOMOBILE', 'BUILDING'], c_mktsegment), 0) AS BIGINT) AS code FROM customer")
def p10_ordinal(spark, d):
    return load(spark, d, "customer").select("c_custkey", F.array_position(F.array(F.lit("AUTOMOBILE"), F.lit("BUILDING")), F.col("c_mktsegment")).alias("code"))


both("p11_missing", "SELECT count(x) AS present, count(*) AS n, round(sum(coalesce(x, -1.0)), 4) AS filled FROM (SELECT nullif(l_discount, 0) AS x FROM lineitem)")

# ---- joins


@query("j01_broadcast_join", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def j01(spark, d):
    n = load(spark, d, "nation").select("n_nationkey", "n_name")  # one row per nation: a size that data does not change
    return load(spark, d, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(counted())


for _hint in ("merge", "shuffle_hash"):

    @query(f"j02_{_hint}_join", "SELECT o_orderpriority, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
    def j02(spark, d, hint=_hint):
        o = load(spark, d, "orders").select("o_orderkey", "o_orderpriority").hint(hint)
        joined = load(spark, d, "lineitem").select("l_orderkey", "l_quantity").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
        return joined.groupBy("o_orderpriority").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"))


for _how in ("left", "right", "full"):
    both(f"j03_{_how}_outer", f"SELECT c_custkey, o_orderkey FROM customer {_how.upper()} JOIN orders ON c_custkey = o_custkey AND o_totalprice > 300000")
both("j04_semi_join", "SELECT c_custkey FROM customer LEFT SEMI JOIN (SELECT * FROM orders WHERE o_totalprice > 300000) ON c_custkey = o_custkey", "SELECT c_custkey FROM customer SEMI JOIN (SELECT * FROM orders WHERE o_totalprice > 300000) ON c_custkey = o_custkey")
both("j04_anti_join", "SELECT c_custkey FROM customer LEFT ANTI JOIN (SELECT * FROM orders WHERE o_totalprice > 300000) ON c_custkey = o_custkey", "SELECT c_custkey FROM customer ANTI JOIN (SELECT * FROM orders WHERE o_totalprice > 300000) ON c_custkey = o_custkey")
both("j05_cross_grid", "SELECT r_regionkey, n_nationkey FROM region CROSS JOIN nation")


@query("j06_range_join", "WITH c(lo, hi, slot) AS (VALUES (0, 10, 0), (10, 25, 1), (25, 40, 2), (40, 1000, 3)) SELECT slot, count(*) AS n FROM lineitem JOIN c ON l_quantity > lo AND l_quantity <= hi GROUP BY 1")
def j06(spark, d):
    cuts = spark.createDataFrame([(0, 10, 0), (10, 25, 1), (25, 40, 2), (40, 1000, 3)], "lo int, hi int, slot int")  # public cuts
    return load(spark, d, "lineitem").join(F.broadcast(cuts), (F.col("l_quantity") > F.col("lo")) & (F.col("l_quantity") <= F.col("hi"))).groupBy("slot").agg(counted())


both(
    "j07_interval_join",
    "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
)


@query("j08_as_of_join", "SELECT event_id, (SELECT max(o_orderdate) FROM orders WHERE o_custkey = user_id AND o_orderdate <= ts) AS last_order FROM events")
def j08(spark, d):
    events = load(spark, d, "events").select("event_id", F.col("user_id").alias("k"), "ts", F.lit(None).cast("timestamp_ntz").alias("o"))
    orders = load(spark, d, "orders").select(F.lit(None).cast("long").alias("event_id"), F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts"), F.col("o_orderdate").alias("o"))
    w = Window.partitionBy("k").orderBy("ts", F.col("event_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    return events.unionByName(orders).withColumn("last_order", F.last("o", ignorenulls=True).over(w)).where("event_id IS NOT NULL").select("event_id", "last_order")


@query("j09_neighbour", "SELECT count(*) AS n FROM nation WHERE n_nationkey <> 3")
def j09(spark, d):
    n = load(spark, d, "nation")
    return n.exceptAll(n.where("n_nationkey = 3")).agg(counted())


@query("j10_lateral", "SELECT n_nationkey, unnest([true, false]) AS default_left FROM nation")
def j10(spark, d):
    sides = spark.range(1).select(F.explode(F.array(F.lit(True), F.lit(False))).alias("default_left"))
    return load(spark, d, "nation").select("n_nationkey").lateralJoin(sides)


@query("j11_salted_aggregate", "SELECT event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
def j11(spark, d):
    salted = load(spark, d, "events").groupBy("event_type", F.pmod(F.xxhash64("event_id"), F.lit(16)).alias("salt")).agg(counted(), F.sum("value").alias("total"))
    return salted.groupBy("event_type").agg(F.sum("n").alias("n"), F.round(F.sum("total"), 4).alias("total"))


# ---- aggregates

both("g01_hash_aggregate", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY l_returnflag, l_linestatus")
both("g02_min_by", "SELECT l_returnflag, min_by(l_orderkey, l_extendedprice * 100000 + l_linenumber) AS cheapest FROM lineitem GROUP BY l_returnflag", "SELECT l_returnflag, arg_min(l_orderkey, l_extendedprice * 100000 + l_linenumber) AS cheapest FROM lineitem GROUP BY l_returnflag")
both("g03_distinct_aggregate", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag")
both("g05_exact_quantiles", "SELECT round(percentile(l_extendedprice, 0.25), 4) AS q1, round(median(l_extendedprice), 4) AS q2 FROM lineitem", "SELECT round(quantile_cont(l_extendedprice, 0.25), 4) AS q1, round(median(l_extendedprice), 4) AS q2 FROM lineitem")


@query("g04_approx_distinct")
def g04(spark, d):
    return load(spark, d, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("hll"), F.countDistinct("user_id").alias("exact"))


@query("g05_approx_quantiles")
def g05(spark, d):
    return load(spark, d, "lineitem").agg(F.percentile_approx("l_extendedprice", [0.25, 0.5, 0.75], 10000).alias("q"))


@query("g06_kll_quantiles")
def g06(spark, d):
    return load(spark, d, "lineitem").selectExpr("kll_sketch_get_quantile_double(kll_sketch_agg_double(l_extendedprice), 0.5D) AS median")


for _kind, _sql in (("rollup", "ROLLUP (l_returnflag, l_linestatus)"), ("cube", "CUBE (l_returnflag, l_linestatus)"), ("sets", "GROUPING SETS ((l_returnflag), (l_linestatus), ())")):
    both(f"g07_{_kind}", f"SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY {_sql}")
both("g08_filtered", "SELECT count(*) FILTER (WHERE l_discount > 0.05) AS high, count_if(l_tax > 0.04) AS taxed, sum(CASE WHEN l_quantity > 25 THEN 1 ELSE 0 END) AS bulk FROM lineitem")
both("g09_moments", "SELECT round(stddev(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_samp(l_discount, l_tax), 9) AS c FROM lineitem")
both("g10_array_agg", "SELECT n_regionkey, array_join(array_sort(array_agg(n_name)), ',') AS names FROM nation GROUP BY n_regionkey", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")


@query("g11_pivot_sums", "SELECT o_orderstatus, round(sum(o_totalprice) FILTER (WHERE o_orderpriority = '1-URGENT'), 2) AS urgent, round(sum(o_totalprice) FILTER (WHERE o_orderpriority = '5-LOW'), 2) AS low FROM orders GROUP BY 1")
def g11(spark, d):
    p = load(spark, d, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).agg(F.round(F.sum("o_totalprice"), 2))
    return p.withColumnsRenamed({"1-URGENT": "urgent", "5-LOW": "low"})


both("g12_having", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey HAVING count(*) >= 500")


@query("g16_histogram_numeric")
def g16(spark, d):
    return load(spark, d, "lineitem").selectExpr("inline(histogram_numeric(l_quantity, 10))")


# ---- windows, sorts, sets

both("w_1_running_sum", "SELECT o_orderkey, sum(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto FROM orders")
both("w_2_partition_total", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey) AS n FROM orders")
both("w_3_ranks", "SELECT n_nationkey, row_number() OVER w AS a, rank() OVER v AS b, dense_rank() OVER v AS c, round(percent_rank() OVER v, 6) AS p, ntile(3) OVER w AS t, round(cume_dist() OVER v, 6) AS u FROM nation WINDOW w AS (ORDER BY n_nationkey), v AS (ORDER BY n_regionkey)")
both("w_4_neighbours", "SELECT n_nationkey, lag(n_name) OVER w AS before, lead(n_name) OVER w AS after, first_value(n_name) OVER w AS first, nth_value(n_name, 2) OVER w AS second FROM nation WINDOW w AS (PARTITION BY n_regionkey ORDER BY n_nationkey)")
both("w_5_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY unix_seconds(CAST(ts AS TIMESTAMP)) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS recent FROM events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS recent FROM (SELECT event_id, user_id, date_trunc('second', ts) AS ts FROM events)")
both("w_6_moving_average", "SELECT n_nationkey, round(avg(n_nationkey * 1.5D) OVER (ORDER BY n_nationkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS smooth FROM nation", "SELECT n_nationkey, round(avg(n_nationkey * 1.5) OVER (ORDER BY n_nationkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS smooth FROM nation")
both("o_1_sort_nulls", "SELECT row_number() OVER (ORDER BY nullif(n_regionkey, 2) ASC NULLS LAST, n_name DESC) AS place, n_name FROM nation")


@query("o_2_top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def o_2(spark, d):
    return load(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


both("o_3_top_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")


@query("o_4_layout", "SELECT count(*) AS n, sum(o_orderkey) AS keys FROM orders")
def o_4(spark, d):
    laid = load(spark, d, "orders").repartitionByRange(8, "o_orderkey").sortWithinPartitions("o_orderkey")
    return laid.agg(counted(), F.sum("o_orderkey").alias("keys"))


@query("x_1_union_missing", "SELECT n_name AS name, n_nationkey AS k FROM nation UNION ALL SELECT r_name, NULL FROM region")
def x_1(spark, d):
    a = load(spark, d, "nation").select(F.col("n_name").alias("name"), F.col("n_nationkey").alias("k"))
    return a.unionByName(load(spark, d, "region").select(F.col("r_name").alias("name")), allowMissingColumns=True)


for _op in ("INTERSECT", "INTERSECT ALL", "EXCEPT", "EXCEPT ALL"):
    both(f"x_2_{_op.lower().replace(' ', '_')}", f"SELECT l_linenumber, l_returnflag FROM lineitem WHERE l_quantity > 10 {_op} SELECT l_linenumber, l_returnflag FROM lineitem WHERE l_quantity <= 30 AND l_linenumber < 5")

# ---- functions

both("f01_math", "SELECT n_nationkey AS k, round(ln(n_nationkey + 1) + exp(-n_nationkey) + sqrt(n_nationkey) + pow(n_nationkey, 1.5) + abs(5 - n_nationkey) + floor(n_nationkey / 3.0) + ceil(n_nationkey / 7.0), 6) AS x FROM nation")
both("f01_expm1", "SELECT n_nationkey AS k, round(log1p(n_nationkey) + expm1(n_nationkey / 10.0D), 9) AS x, pmod(n_nationkey - 10, 7) AS m, try_divide(1.0D, n_nationkey) AS q FROM nation", "SELECT n_nationkey AS k, round(ln(1.0 + n_nationkey) + exp(n_nationkey / 10.0) - 1, 9) AS x, ((n_nationkey - 10) % 7 + 7) % 7 AS m, 1.0 / nullif(n_nationkey, 0) AS q FROM nation")
both("f02_hash", "SELECT n_nationkey AS k, sha2(n_name, 256) AS s, md5(n_name) AS m, CAST(conv(substr(sha2(n_name, 256), 1, 13), 16, 10) AS BIGINT) AS u FROM nation", "SELECT n_nationkey AS k, sha256(n_name) AS s, md5(n_name) AS m, CAST('0x' || substr(sha256(n_name), 1, 13) AS BIGINT) AS u FROM nation")
both("f02_bits", "SELECT n_nationkey AS k, shiftright(n_nationkey * 37, 2) AS r, (n_nationkey * 37) & 15 AS a FROM nation", "SELECT n_nationkey AS k, (n_nationkey * 37) >> 2 AS r, (n_nationkey * 37) & 15 AS a FROM nation")
both("f03_strings", "SELECT p_partkey, length(p_name) AS n, upper(p_name) AS u, regexp_replace(p_brand, '[^0-9]', '') AS b, concat_ws('-', substr(p_name, 1, 3), trim(p_type)) AS c, levenshtein(p_brand, 'Brand#11') AS e, translate(p_name, 'abc', 'xyz') AS t FROM part", "SELECT p_partkey, length(p_name) AS n, upper(p_name) AS u, regexp_replace(p_brand, '[^0-9]', '', 'g') AS b, concat_ws('-', substr(p_name, 1, 3), trim(p_type)) AS c, levenshtein(p_brand, 'Brand#11') AS e, translate(p_name, 'abc', 'xyz') AS t FROM part")
both("f04_dates", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofweek(o_orderdate) AS w, datediff(o_orderdate, DATE '1995-01-01') AS n FROM orders", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofweek(o_orderdate) + 1 AS w, date_diff('day', DATE '1995-01-01', o_orderdate) AS n FROM orders")


@query("f05_arrays", "SELECT vec_id, round(CAST(list_sum(embedding) AS DOUBLE), 3) AS total, round(CAST(list_max(embedding) AS DOUBLE), 6) AS top, round(CAST(embedding[3] AS DOUBLE), 6) AS third FROM embeddings")
def f05(spark, d):
    e = F.col("embedding")
    total = F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double"))
    return load(spark, d, "embeddings").select("vec_id", F.round(total, 3).alias("total"), F.round(F.array_max(e).cast("double"), 6).alias("top"), F.round(F.element_at(e, 3).cast("double"), 6).alias("third"))


@query("f05_dot_product", "SELECT vec_id, round(list_sum([CAST(a AS DOUBLE) * a FOR a IN embedding]), 5) AS norm FROM embeddings")
def f05_dot(spark, d):
    squares = F.zip_with("embedding", "embedding", lambda a, b: a.cast("double") * b)
    return load(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(squares, F.lit(0.0), lambda a, x: a + x), 5).alias("norm"))


@query("f06_maps", "SELECT l_orderkey, l_linenumber, l_tax + l_discount AS total FROM lineitem WHERE l_linenumber = 1")
def f06(spark, d):
    m = F.map_filter(F.map_from_arrays(F.array(F.lit(0), F.lit(1), F.lit(2)), F.array("l_tax", "l_discount", "l_quantity")), lambda k, v: k < 2)
    total = F.aggregate(F.map_values(m), F.lit(0.0), lambda a, x: a + x)
    return load(spark, d, "lineitem").where("l_linenumber = 1").select("l_orderkey", "l_linenumber", total.alias("total"))


both("f07_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS a, from_json(props, 'k INT').k AS b FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS a, CAST(json_extract_string(props, '$.k') AS INT) AS b FROM events")
both("f07_variant", "SELECT event_id, variant_get(try_parse_json(props), '$.k', 'int') AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
both("f08_conditionals", "SELECT n_nationkey, coalesce(nullif(n_regionkey, 1), -1) AS a, ifnull(nullif(n_regionkey, 2), 9) AS b FROM nation")


def text_sql(kind: str) -> str:
    return f"length(regexp_replace(text, '[^{kind}]', '', 'g')) / greatest(length(text), 1)"


@query("f03_text_features", f"SELECT doc_id, round({text_sql('A-Z')}, 9) AS upper, round({text_sql('0-9')}, 9) AS digits FROM documents")
def f03_text(spark, d):
    share = lambda kind: F.round(F.length(F.regexp_replace("text", f"[^{kind}]", "")) / F.greatest(F.length("text"), F.lit(1)), 9)
    return load(spark, d, "documents").select("doc_id", share("A-Z").alias("upper"), share("0-9").alias("digits"))


