"""Queries of workloads, whole trainings, baselines, studies, audits, streams and the UDF surface."""

from __future__ import annotations

from pyspark.sql import functions as F

from privgrove.functions import sqlfront
from privgrove.functions.noise import laplace_sql, uniform_sql

from privgrove.plans import audit, experiments, metrics
from privgrove.plans.boost import BoostParams, fit
from privgrove.plans.workloads import LINE_KEY as LINE_ID
from privgrove.plans.workloads import for_tables
from privgrove.queries import methods as m
from privgrove.queries.base import KEY, query
from privgrove.sources.io import load
from privgrove.streaming import streams

#: Registered trainings and studies have their full settings: 20 trees of depth 6, all budgets, sizes and bins, and five
#: trials in the studies; a workload's own fit has one trial of each budget. Models of a study are trained in step.
STUDIED = ("w01", "w02", "w03", "w04", "w05", "w06")
LINE = m.LINE_KEY


def plant_sql(rule: str, flips: float, key: str) -> str:
    draw = uniform_sql(f"'plant|' || {key}")
    return f"CASE WHEN ({rule}) <> ({draw} <= {flips}) THEN 1.0 ELSE -1.0 END"


def summary_sql(source: str, y: str, x: str) -> str:
    return f"SELECT count(*) AS n, round(avg({y}), 6) AS mean_y, round(sum({x}), 3) AS sum_x0 FROM {source}"


K = "CAST(json_extract_string(props, '$.k') AS DOUBLE)"
W01 = "(CASE WHEN l_quantity > 20 AND l_discount > 0.025 THEN 1.2 ELSE -0.8 END) + (CASE WHEN l_shipdate < TIMESTAMP '1998-06-01' THEN 0.6 ELSE -0.6 END) + (CASE WHEN l_extendedprice > 60000 THEN 0.5 ELSE -0.3 END) > 0"
W02 = "CAST(o_totalprice > 250000 AS INT) + CAST(o_orderpriority IN ('1-URGENT', '2-HIGH') AS INT) + CAST(c_mktsegment IN ('BUILDING', 'MACHINERY') AS INT) + CAST(c_acctbal > 5000 AS INT) >= 2"
W03 = f"least(value, 200) / 100 + (CASE WHEN hour(ts) >= 12 THEN 0.5 ELSE -0.5 END) + ({K} - 50) / 50 > 0.5"
ROWS_SQL = {
    "w01": summary_sql("lineitem JOIN orders ON l_orderkey = o_orderkey", plant_sql(W01, 0.08, LINE), "l_quantity"),
    "w02": summary_sql("orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey", plant_sql(W02, 0.12, "o_orderkey"), "o_totalprice"),
    "w03": summary_sql("events", plant_sql(W03, 0.05, "event_id"), "value"),
    "w04": summary_sql("lineitem", "2 * l_extendedprice * (1 - l_discount) * (1 + l_tax) / 115500 - 1", "l_extendedprice"),
    "w05": summary_sql("part", "2 * (p_retailprice - 900) / 100 - 1", "p_partkey"),
    "w06": summary_sql("labels JOIN documents USING (doc_id)", "2.0 * quality - 1", "len(list_distinct(string_split_regex(text, '[ \\n]+'))) / len(string_split_regex(text, '[ \\n]+'))"),
    "w11a": summary_sql("lineitem JOIN orders ON l_orderkey = o_orderkey", "CASE WHEN l_returnflag = 'R' THEN 1.0 ELSE -1.0 END", "l_quantity"),
    "w12": summary_sql("embeddings", "CASE WHEN label < 5 THEN 1.0 ELSE -1.0 END", "CAST(embedding[1] AS DOUBLE)"),
}

for _name, _sql in ROWS_SQL.items():

    @query(f"{_name}_rows", _sql)
    def rows(spark, d, name=_name):
        return for_tables(d)[name].rows(spark, d).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("y"), 6).alias("mean_y"), F.round(F.sum("x_0"), 3).alias("sum_x0"))

    @query(f"{_name}_fit")
    def fitted(spark, d, name=_name):
        return experiments.sweep(spark, d, name, trials=1)


STUMP_SQL = f"""WITH {m.HIST_SQL}, {m.grid_sql()}, {m.dp_sql(1 / 3)}, {m.cuts_sql("dp")},
  gb AS (SELECT feature, bin, sum(CASE WHEN y > 0 THEN -1 ELSE 1 END) AS g, count(*) AS n FROM (SELECT 0 AS feature, b_0 AS bin, y FROM binned UNION ALL SELECT 1, b_1, y FROM binned UNION ALL SELECT 2, b_2, y FROM binned) GROUP BY ALL),
  tot AS (SELECT sum(g) AS gt, sum(n) AS nt FROM gb WHERE feature = 0), mis AS (SELECT feature, coalesce(sum(g) FILTER (WHERE bin < 0), 0) AS gm, coalesce(sum(n) FILTER (WHERE bin < 0), 0) AS nm FROM gb GROUP BY 1),
  base AS (SELECT c.feature, c.slot, c.cut_bin, sum(b.g) AS g0, sum(b.n) AS n0 FROM cuts c JOIN gb b ON b.feature = c.feature AND b.bin >= 0 AND b.bin <= c.cut_bin GROUP BY ALL),
  dirs AS (SELECT *, unnest([true, false]) AS default_left FROM base JOIN mis USING (feature)),
  side AS (SELECT feature, slot, cut_bin, default_left, CAST(g0 + CASE WHEN default_left THEN gm ELSE 0 END AS DOUBLE) AS gl, CAST(n0 + CASE WHEN default_left THEN nm ELSE 0 END AS DOUBLE) AS nl FROM dirs WHERE default_left OR nm > 0),
  gains AS (SELECT *, gt - gl AS gr, nt - nl AS nr, gl * gl / (nl + 0.1) + (gt - gl) * (gt - gl) / (nt - nl + 0.1) AS gain FROM side, tot),
  raced AS (SELECT *, ln(-ln({uniform_sql(f"'{KEY}|split|0|0|' || feature || '|' || slot || '|' || CAST(default_left AS INTEGER)")})) - gain * {1 / 3 / 6} AS race FROM gains WHERE nl >= 100 AND nr >= 100),
  best AS (SELECT * FROM raced ORDER BY race, feature, slot LIMIT 1)
  SELECT feature, cut_bin, default_left, round(0.3 * (-gl / (nl + 0.1) + {laplace_sql(uniform_sql(f"'{KEY}|leaf|0|1'"), str(2 / 101.1 * 3))}), 8) AS left_value,
    round(0.3 * (-gr / (nr + 0.1) + {laplace_sql(uniform_sql(f"'{KEY}|leaf|0|2'"), str(2 / 101.1 * 3))}), 8) AS right_value FROM best"""


@query("m30_seeded_private_stump", STUMP_SQL)
def m30(spark, d):
    p = BoostParams(epsilon_total=1.0, trees=1, max_depth=1, subsample=1.0, max_cuts=m.CUTS, bins=m.BINS, min_child=100, noise_key=KEY)
    model, _, _ = fit(m.binned(spark, d), m.SPEC, p)
    x = model.trees[0].nodes
    return spark.createDataFrame([(x[0].feature, x[0].cut_bin, x[0].default_left, round(x[1].value, 8), round(x[2].value, 8))], "feature int, cut_bin int, default_left boolean, left_value double, right_value double")


LEDGER_SQL = """WITH t AS (SELECT unnest(range(20)) AS tree), e AS (SELECT ln(1 + (exp(2.0 / 20) - 1) / 0.1) / 3 AS third),
  c AS (SELECT tree, 'sketch' AS mechanism, -1 AS level, 'feature ' || k AS scope, third / 3 AS epsilon, 'parallel over bins' AS composition FROM t, e, (SELECT unnest(range(3)) AS k)
    UNION ALL SELECT tree, 'split', k, 'level ' || k, third / 6, 'parallel over nodes' FROM t, e, (SELECT unnest(range(6)) AS k)
    UNION ALL SELECT tree, 'leaf', 6, 'leaves', third, 'parallel over leaves' FROM t, e)
  SELECT CAST(tree AS INTEGER) AS tree, mechanism, CAST(level AS INTEGER) AS level, scope, round(epsilon, 9) AS epsilon, composition FROM c"""


@query("m30_ledger", LEDGER_SQL)
def m30_ledger(spark, d):
    """What twenty trees of depth 6 are charged: three features, six levels and the leaves of each, amplified in the total."""
    p = BoostParams(epsilon_total=2.0, bins=m.BINS, min_child=50, noise_key=KEY)
    _, ledger, _ = fit(m.binned(spark, d), m.SPEC, p)
    return ledger.to_df(spark).select("tree", "mechanism", "level", "scope", F.round("epsilon", 9).alias("epsilon"), "composition")


def variant(name: str, **changes):
    @query(name)
    def run(spark, d):
        bench = experiments.Bench(spark, d, "w01")
        p = bench.params(**({"epsilon_total": 10.0} | changes))
        out = experiments.table(spark, [bench.run(name, p)])
        bench.close()
        return out


variant("m19b_local_proposals", proposal="local")
variant("m32_joint_proposals", proposal="joint")
variant("m25_noisy_average_fit", leaf_mode="noisy_average")
variant("m25_strict_fit", leaf_mode="noisy_average", strict=True)
variant("m23_worst_case_fit", leaf_mode="worst_case")
variant("m31_uneven_fit", tree_weights=tuple(float(k) for k in range(20, 0, -1)), early_leaf_bonus=True)


@query("b01_open_model")
def b01(spark, d):
    return experiments.open_models(spark, d, "w01", ways=("even", "sketch"))


@query("b07_exact_greedy_model")
def b07(spark, d):
    return experiments.open_models(spark, d, "w06", ways=("even", "exact"))


@query("b03_precursor")
def b03(spark, d):
    return experiments.against_precursor(spark, d, ("w01", "w03"), experiments.EPSILONS, experiments.TRIALS)


@query("w07_leaf_study")
def w07(spark, d):
    return experiments.leaf_study(spark, d)


@query("w08_bin_study")
def w08(spark, d):
    return experiments.bin_study(spark, d)


@query("w09_result_table")
def w09(spark, d):
    return experiments.means(experiments.sweeps(spark, d, STUDIED))


@query("w10_runtime")
def w10(spark, d):
    return experiments.runtime(spark, d)


@query("a10_engine_cost")
def a10(spark, d):
    return experiments.engine_cost(spark, d)


@query("a11_trial_summary", "SELECT l_returnflag AS variant, round(avg(v), 6) AS mean, round(stddev_samp(v), 6) AS stddev, count(*) AS trials FROM (SELECT l_returnflag, l_linenumber, avg(l_discount) AS v FROM lineitem GROUP BY ALL) GROUP BY 1")
def a11(spark, d):
    trials = load(spark, d, "lineitem").groupBy(F.col("l_returnflag").alias("variant"), "l_linenumber").agg(F.avg("l_discount").alias("v"))
    return metrics.trial_summary(trials, ["variant"], "v")


# ---- audits


def line_runs(spark, d):
    """A run of an audit for every line item, keyed by the row."""
    return load(spark, d, "lineitem").select(F.expr(LINE_ID).alias("id"))


@query("m01_audit_laplace")
def m01_laplace(spark, d):
    return audit.empirical_epsilon(spark, audit.laplace_count(0.5), 10, 11, line_runs(spark, d))


@query("m01_audit_exponential")
def m01_race(spark, d):
    return audit.empirical_epsilon(spark, audit.exponential_of(1.0, 3.0), [0.0, 3.0, 1.0], [3.0, 0.0, 1.0], line_runs(spark, d))


@query("m01_audit_noisy_average")
def m01_average(spark, d):
    return audit.empirical_epsilon(spark, audit.noisy_average(0.5), [10.0, 10], [11.0, 11], 50_000)


# ---- streams and their batch forms



def events(spark, d):
    return load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def window_sql(step: str, size: str) -> str:
    start = f"strftime(w, '%Y-%m-%d %H:%M:%S')"
    return f"SELECT {start} AS start, round(n + {laplace_sql(uniform_sql(f"'{KEY}|' || {start}"), '1.0')}, 6) AS n FROM (SELECT w, count(*) AS n FROM ({step}) GROUP BY 1)"


DAY = "SELECT date_trunc('day', ts) AS w FROM events"
SLIDE = "SELECT date_trunc('day', ts) - to_days(k) AS w FROM events, (VALUES (0), (1)) t(k)"


@query("t02_daily_counts", window_sql(DAY, "1 day"))
def t02(spark, d):
    return streams.dp_window_counts(events(spark, d), 1.0, KEY).select("start", F.round("n", 6).alias("n"))


@query("t02_daily_counts_stream", window_sql(DAY, "1 day"))
def t02_stream(spark, d):
    out = streams.drained(streams.dp_window_counts(streams.events_stream(spark, d), 1.0, KEY), "daily", "complete")
    return out.select("start", F.round("n", 6).alias("n"))


@query("t03_sliding_counts", window_sql(SLIDE, "2 days"))
def t03(spark, d):
    return streams.dp_window_counts(events(spark, d), 1.0, KEY, "2 days", "1 day").select("start", F.round("n", 6).alias("n"))


@query(
    "t04_sessions",
    """WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM e) SELECT n, count(*) AS sessions FROM (SELECT user_id, k, count(*) AS n FROM s GROUP BY ALL) GROUP BY n""",
)
def t04(spark, d):
    return streams.session_counts(events(spark, d)).groupBy("n").agg(F.count(F.lit(1)).alias("sessions"))


@query("t01_scored_stream", f"SELECT CAST(event_id AS VARCHAR) AS row_key, CAST(CASE WHEN value <= 100 THEN -0.5 ELSE 0.5 END AS DOUBLE) AS margin FROM events")
def t01(spark, d):
    from privgrove.plans.tree import Tree, TreeModel

    tree = Tree()
    left, right = tree.split(0, 0, 31, True)
    left.value, right.value = -0.5, 0.5
    model = TreeModel(for_tables(d)["w03"].spec, 64, [tree])
    return streams.drained(streams.scored(streams.events_stream(spark, d), model), "scored")


FIRST, LATE = "('view', 'click')", "('purchase', 'error')"


@query("t05_late_rows", f"SELECT event_id FROM events WHERE event_type NOT IN {LATE} OR ts > (SELECT date_trunc('milliseconds', max(ts)) - INTERVAL 1 HOUR FROM events WHERE event_type IN {FIRST})")
def t05(spark, d):
    """Three batches by type. The first one's latest time sets a watermark that the second advances to and the third is
    held against: rows of the third that are behind it are dropped."""
    rows = events(spark, d).select("event_id", "ts", "event_type")
    parts = [rows.where(f"event_type IN {FIRST}"), rows.where(f"event_type NOT IN {FIRST} AND event_type NOT IN {LATE}"), rows.where(f"event_type IN {LATE}")]
    return streams.drained(streams.on_time(streams.arriving(parts, "late").select("event_id", "ts"), "event_id"), "late").select("event_id")


@query("t06_deduplicated", "SELECT count(*) AS n FROM events")
def t06(spark, d):
    stream = streams.events_stream(spark, d).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return streams.drained(stream.select("event_id"), "dedup").agg(F.count(F.lit(1)).alias("n"))


@query("t08_incremental_histogram", "SELECT CAST(least(greatest(ceil(value / 200 * 16) - 1, 0), 15) AS INTEGER) AS bin, count(*) AS n FROM events GROUP BY 1")
def t08(spark, d):
    return streams.incremental_histogram(streams.events_stream(spark, d), 0.0, 200.0, 16)


@query("t09_stream_static_join", "SELECT event_id, t.cut FROM events JOIN (VALUES ('click', 1.0), ('view', 2.0)) t(event_type, cut) USING (event_type)")
def t09(spark, d):
    cuts = spark.createDataFrame([("click", 1.0), ("view", 2.0)], "event_type string, cut double")
    return streams.drained(streams.events_stream(spark, d).join(F.broadcast(cuts), "event_type").select("event_id", "cut"), "static")


@query("t07_budget_meter", "SELECT user_id, least(n, 10) AS allowed, n - least(n, 10) AS refused, round(CAST(1.0 - least(n, 10) * 0.1 AS DOUBLE), 6) AS remaining FROM (SELECT user_id, count(*) AS n FROM events GROUP BY 1)")
def t07(spark, d):
    """Two batches meet one state: what the first leaves is what the second can spend."""
    own = streams.with_rocksdb(spark)
    rows = events(own, d).select("user_id", "event_type")
    stream = streams.arriving([rows.where(f"event_type NOT IN {LATE}"), rows.where(f"event_type IN {LATE}")], "meter")
    spent = streams.drained(streams.budget_meter(stream), "meter", "update")
    return spent.groupBy("user_id").agg(F.sum("allowed").alias("allowed"), F.sum("refused").alias("refused"), F.round(F.min("remaining"), 6).alias("remaining"))


# ---- UDFs and SQL functions


@query("u01_pandas_scoring", f"WITH {m.MARGIN_SQL} SELECT row_key, CAST(margin AS DOUBLE) AS margin FROM pred")
def u01(spark, d):
    score = sqlfront.tree_predict(m.two_trees())
    return m.binned(spark, d).select("row_key", score(F.struct("b_0", "b_1", "b_2")).alias("margin"))


@query("u02_weighted_quartiles")
def u02(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(sqlfront.weighted_quartiles("l_quantity", "l_extendedprice").alias("q"))


@query("u03_table_function", "SELECT CAST(k AS INT) AS slot, 10.0 + (k + 1) * 10.0 AS cut FROM (SELECT unnest(range(4)) AS k)")
def u03(spark, d):
    sqlfront.registered(spark)
    return spark.sql("SELECT slot, cut FROM propose_cuts(10.0D, 60.0D, 4)")


@query("u03_explained_tree")
def u03_explained(spark, d):
    return sqlfront.explained(spark, m.two_trees())


@query("u06_sql_functions", f"SELECT l_returnflag, round(count(*) + {laplace_sql(uniform_sql("'k|' || l_returnflag"), '2.0')}, 6) AS n, round(2.0 * 2.0 / 10.1 + 9.0 / 20.1, 6) AS gain, round(ln(1 + 0.1 * (exp(1.0) - 1)), 6) AS eps FROM lineitem GROUP BY 1")
def u06(spark, d):
    sqlfront.registered(spark)
    load(spark, d, "lineitem").createOrReplaceTempView("lineitem")
    return spark.sql("SELECT l_returnflag, round(dp_laplace(n, 2.0D, concat('k|', l_returnflag)), 6) AS n, round(split_gain(2D, 10D, -3D, 20D, 0.1D), 6) AS gain, round(amplify_epsilon(1D, 0.1D), 6) AS eps FROM (SELECT l_returnflag, CAST(count(*) AS DOUBLE) AS n FROM lineitem GROUP BY l_returnflag)")


