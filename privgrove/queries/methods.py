"""Queries of the methods: mechanisms, cuts, histograms, splits, leaves, budgets, and whole trees."""

from __future__ import annotations



from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privgrove.functions import closed
from privgrove.functions.noise import laplace_sql, race_key, uniform, uniform_sql
from privgrove.operators import gradient, histogram, leaves, mechanisms, proposals, sampling, sketch, splits
from privgrove.operators.schema import DatasetSpec, FeatureSpec, TargetSpec
from privgrove.plans import ledger, metrics
from privgrove.plans.tree import Tree, TreeModel
from privgrove.queries.base import KEY, query
from privgrove.sources.io import ReleaseCache, load

LINE_KEY = "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT))"
BINS, CUTS, LAM, EPS = 16, 8, 0.1, 1.0

SPEC = DatasetSpec(
    LINE_KEY,
    (FeatureSpec("quantity", "l_quantity", 1, 50), FeatureSpec("price", "l_extendedprice", 900, 105000), FeatureSpec("discount", "CASE WHEN l_linenumber <> 3 THEN l_discount END", 0, 0.1)),
    TargetSpec("CASE WHEN l_quantity > 20 AND l_discount > 0.025D THEN 1.0D ELSE -1.0D END", kind="class"),
)

# ---- the same rows in DuckDB: static bins of three features, one of them with missing values


def bin_sql(x: str, lo: float, hi: float, bins: int = BINS) -> str:
    return f"CAST(coalesce(least(greatest(ceil(({x} - {lo}) / ({hi} - {lo}) * {bins}) - 1, 0), {bins - 1}), -1) AS INTEGER)"


BINNED_SQL = f"""binned AS (SELECT {LINE_KEY} AS row_key, {bin_sql("l_quantity", 1.0, 50.0)} AS b_0, {bin_sql("l_extendedprice", 900.0, 105000.0)} AS b_1,
  {bin_sql("CASE WHEN l_linenumber <> 3 THEN l_discount END", 0.0, 0.1)} AS b_2, CASE WHEN l_quantity > 20 AND l_discount > 0.025 THEN 1.0 ELSE -1.0 END AS y FROM lineitem)"""
LONG_SQL = "long AS (SELECT 0 AS feature, b_0 AS bin FROM binned UNION ALL SELECT 1, b_1 FROM binned UNION ALL SELECT 2, b_2 FROM binned)"
HIST_SQL = f"{BINNED_SQL}, {LONG_SQL}, hist AS (SELECT feature, bin, CAST(count(*) AS DOUBLE) AS weight FROM long WHERE bin >= 0 GROUP BY ALL)"
BOUNDS_SQL = "bounds(feature, lo, hi) AS (VALUES (0, 1.0, 50.0), (1, 900.0, 105000.0), (2, 0.0, 0.1))"


def grid_sql(bins: int = BINS, point: float = 1.0) -> str:
    return f"""{BOUNDS_SQL}, grid AS (SELECT feature, bin, CAST(lo AS DOUBLE) + (bin + {point}) * (CAST(hi AS DOUBLE) - lo) / {bins} AS edge FROM bounds, (SELECT unnest(range({bins})) AS bin)),
  cells AS (SELECT feature, bin, edge, coalesce(weight, 0.0) AS weight FROM grid LEFT JOIN hist USING (feature, bin))"""


def dp_sql(eps: float, tree: int = 0) -> str:
    u = uniform_sql(f"'{KEY}|sketch|{tree}|' || feature || '|' || bin")
    return f"dp AS (SELECT feature, bin, edge, greatest(0.0, weight + {laplace_sql(u, str(3 / eps))}) AS weight FROM cells)"


def cuts_sql(source: str, cuts: int = CUTS, bins: int = BINS) -> str:
    return f"""t AS (SELECT *, sum(weight) OVER (PARTITION BY feature) AS total, sum(weight) OVER (PARTITION BY feature ORDER BY bin) AS upto FROM {source}),
  marks AS (SELECT *, least(floor(round(upto / (total / {cuts + 1}), 9)), {cuts}) AS mark FROM t),
  steps AS (SELECT *, coalesce(lag(mark) OVER (PARTITION BY feature ORDER BY bin), 0) AS before FROM marks),
  cuts AS (SELECT feature, CAST(row_number() OVER (PARTITION BY feature ORDER BY bin) - 1 AS INTEGER) AS slot, CAST(bin AS INTEGER) AS cut_bin, edge AS cut FROM steps WHERE mark > before AND bin < {bins - 1})"""


CUT_BINS = {0: [2, 6, 10], 1: [3, 7, 11], 2: [1, 4, 8, 12]}
FIX = "CAST(trunc(CASE WHEN y > 0 THEN -0.75 ELSE 0.5 END * 1048576) AS BIGINT)"


def slot_sql(b: str, cuts: list[int]) -> str:
    return f"CASE WHEN {b} < 0 THEN -1 ELSE {' + '.join(f'CAST({b} > {c} AS INTEGER)' for c in cuts)} END"


LEVEL_SQL = f"""{BINNED_SQL}, work AS (SELECT CASE WHEN b_0 <= 6 THEN 1 ELSE 2 END AS node, {FIX} AS g, b_0, b_1, b_2 FROM binned),
  lh AS (SELECT node, feature, slot, CAST(sum(g) AS BIGINT) AS sg, CAST(count(*) AS DOUBLE) AS sh, count(*) AS n FROM (
    {" UNION ALL ".join(f"SELECT node, g, {k} AS feature, {slot_sql(f'b_{k}', c)} AS slot FROM work" for k, c in CUT_BINS.items())}) GROUP BY ALL)"""
CAND_SQL = f"""{LEVEL_SQL}, g AS (SELECT v.node, f.feature, s.slot FROM (SELECT unnest([1, 2]) AS node) v, (VALUES (0, 3), (1, 3), (2, 4)) f(feature, k), (SELECT unnest(range(-1, 5)) AS slot) s WHERE slot <= k),
  full_ AS (SELECT g.*, coalesce(sg, 0) AS sg, coalesce(n, 0) AS n FROM g LEFT JOIN lh USING (node, feature, slot)),
  pre AS (SELECT node, feature, slot, sum(CASE WHEN slot >= 0 THEN sg ELSE 0 END) OVER w AS gl0, sum(CASE WHEN slot >= 0 THEN n ELSE 0 END) OVER w AS nl0,
     sum(CASE WHEN slot = -1 THEN sg ELSE 0 END) OVER p AS gm, sum(CASE WHEN slot = -1 THEN n ELSE 0 END) OVER p AS nm, sum(sg) OVER p AS gt, sum(n) OVER p AS nt, max(slot) OVER p AS last
     FROM full_ WINDOW w AS (PARTITION BY node, feature ORDER BY slot), p AS (PARTITION BY node, feature)),
  c0 AS (SELECT *, unnest([true, false]) AS default_left FROM pre WHERE slot >= 0 AND slot < last),
  c1 AS (SELECT node, feature, slot, default_left, CAST(gl0 + CASE WHEN default_left THEN gm ELSE 0 END AS BIGINT) AS gl, CAST(nl0 + CASE WHEN default_left THEN nm ELSE 0 END AS BIGINT) AS nl, gt, nt, nm FROM c0 WHERE default_left OR nm > 0),
  cand AS (SELECT node, feature, slot, default_left, gl, nl, CAST(gt - gl AS BIGINT) AS gr, CAST(nt - nl AS BIGINT) AS nr,
     (gl / 1048576.0) * (gl / 1048576.0) / (nl + {LAM}) + ((gt - gl) / 1048576.0) * ((gt - gl) / 1048576.0) / (nt - nl + {LAM}) AS gain FROM c1)"""
CAND_COLS = "node, feature, slot, default_left, gl, nl, gr, nr, round(gain, 4) AS gain"


def binned(spark: SparkSession, d: str, bins: int = BINS) -> DataFrame:
    return SPEC.binned(SPEC.encode(load(spark, d, "lineitem")), bins)


def work(spark: SparkSession, d: str) -> DataFrame:
    g = F.when(F.col("y") > 0, -0.75).otherwise(0.5)
    node = F.when(F.col("b_0") <= 6, 1).otherwise(2)
    return binned(spark, d).select(node.alias("node"), gradient.fixed(g).alias("g"), F.lit(1.0).alias("h"), "b_0", "b_1", "b_2")


def cands(spark: SparkSession, d: str) -> DataFrame:
    full = splits.complete_slots(splits.level_histogram(work(spark, d), CUT_BINS), [1, 2], CUT_BINS)
    return splits.candidates(full, CUT_BINS, LAM)


def shown(c: DataFrame) -> DataFrame:
    return c.select("node", "feature", "slot", "default_left", "gl", "nl", "gr", "nr", F.round("gain", 4).alias("gain"))


def one(spark: SparkSession, **values) -> DataFrame:
    return spark.range(1).select(*[F.round(F.lit(float(v)), 6).alias(k) for k, v in values.items()])


# ---- closed forms, budgets


@query("m02_sensitivities", "SELECT 1.0 AS histogram, 3.0 AS gain, round(1 / 1.1, 6) AS worst_case, round(2 / 501.1, 6) AS min_child, round((2 * 10 + 0.1) / ((10 + 0.1) * (11 + 0.1)), 6) AS at_n, 2.0 AS leaf_sum")
def m02(spark, d):
    s = closed.sensitivity
    return one(spark, histogram=s("histogram"), gain=s("gain"), worst_case=s("leaf_worst_case"), min_child=s("leaf_min_child", min_child=500), at_n=s("leaf_at_n", n=10), leaf_sum=s("leaf_sum"))


@query("m03_laplace_release", f"WITH c AS (SELECT CAST(l_shipdate::DATE AS VARCHAR) AS day, count(*) AS n FROM lineitem GROUP BY 1) SELECT day, round(n + {laplace_sql(uniform_sql(f"'{KEY}|' || day"), '2.0')}, 6) AS n FROM c")
def m03(spark, d):
    counts = load(spark, d, "lineitem").groupBy(F.to_date("l_shipdate").cast("string").alias("day")).agg(F.count(F.lit(1)).alias("n"))
    return mechanisms.laplace_release(counts, "n", 1.0, 0.5, KEY, ["day"]).select("day", F.round("n", 6).alias("n"))


def race_sql(factor: float) -> str:
    u = uniform_sql(f"'{KEY}|' || l_returnflag || '|' || l_linenumber")
    return f"""WITH c AS (SELECT l_returnflag, l_linenumber, CAST(count(*) AS DOUBLE) / 1000 AS utility FROM lineitem GROUP BY ALL),
      k AS (SELECT *, ln(-ln({u})) - utility * {1 / factor} AS race FROM c)
      SELECT l_returnflag, l_linenumber, round(utility, 6) AS utility FROM (SELECT *, row_number() OVER (PARTITION BY l_returnflag ORDER BY race, l_linenumber) AS r FROM k) WHERE r = 1"""


def exponential(spark, d, factor):
    c = load(spark, d, "lineitem").groupBy("l_returnflag", "l_linenumber").agg((F.count(F.lit(1)) / 1000.0).alias("utility"))
    best = mechanisms.exponential_choice(c, ["l_returnflag"], F.col("utility"), 1.0, 1.0, KEY, ["l_linenumber"], factor)
    return best.select("l_returnflag", "l_linenumber", F.round("utility", 6).alias("utility"))


@query("m04_exponential_mechanism", race_sql(2.0))
def m04(spark, d):
    return exponential(spark, d, 2.0)


@query("m05_exponential_without_half", race_sql(1.0))
def m05(spark, d):
    return exponential(spark, d, 1.0)


@query("m06_race_frequencies", f"""WITH k AS (SELECT o_orderkey, w, ln(-ln({uniform_sql(f"'{KEY}|' || o_orderkey || '|' || w")})) - ln(w) AS race FROM orders, (VALUES (1), (2), (3), (4)) t(w))
  SELECT w, count(*) AS wins FROM (SELECT o_orderkey, arg_min(w, race) AS w FROM k GROUP BY 1) GROUP BY 1""")
def m06(spark, d):
    c = load(spark, d, "orders").select("o_orderkey", F.explode(F.array(*[F.lit(k) for k in (1, 2, 3, 4)])).alias("w"))
    won = c.groupBy("o_orderkey").agg(F.min_by("w", race_key(F.ln(F.col("w").cast("double")), uniform(KEY, "o_orderkey", "w"))).alias("w"))
    return won.groupBy("w").agg(F.count(F.lit(1)).alias("wins"))


PLAN_SQL = "e AS (SELECT unnest([1.0, 2.0, 4.0, 6.0, 8.0, 10.0])::DOUBLE AS epsilon), p AS (SELECT epsilon, ln(1 + (exp(epsilon / 20) - 1) / 0.1) AS t FROM e)"


@query("m07_sequential_composition", "SELECT count(*) AS mechanisms, round(sum(0.1 * k), 6) AS epsilon FROM (SELECT unnest(range(1, 11)) AS k)")
def m07(spark, d):
    return spark.range(1, 11).agg(F.count(F.lit(1)).alias("mechanisms"), F.round(F.sum(F.col("id") * 0.1), 6).alias("epsilon"))


@query("m08_parallel_composition", "SELECT round(sum(e), 6) AS epsilon FROM (SELECT n_regionkey, max(0.01 * n_nationkey) AS e FROM nation GROUP BY 1)")
def m08(spark, d):
    scopes = load(spark, d, "nation").groupBy("n_regionkey").agg(F.max(F.col("n_nationkey") * 0.01).alias("e"))
    return scopes.agg(F.round(F.sum("e"), 6).alias("epsilon"))


@query("m09_amplification", f"WITH {PLAN_SQL} SELECT epsilon, round(t, 6) AS mechanism, round(ln(1 + 0.1 * (exp(t) - 1)), 6) AS back FROM p")
def m09(spark, d):
    rows = [(e, closed.before_sampling(e / 20, 0.1)) for e in (1.0, 2.0, 4.0, 6.0, 8.0, 10.0)]
    return spark.createDataFrame([(e, round(t, 6), round(closed.amplified(t, 0.1), 6)) for e, t in rows], "epsilon double, mechanism double, back double")


@query("m10_advanced_composition", "SELECT k, round(sqrt(2 * k * ln(1e6)) * 0.1 + k * 0.1 * (exp(0.1) - 1), 6) AS advanced, round(k * 0.1, 6) AS basic FROM (SELECT unnest([10, 100, 1000]) AS k)")
def m10(spark, d):
    return spark.createDataFrame([(k, round(closed.advanced(0.1, k, 1e-6), 6), round(0.1 * k, 6)) for k in (10, 100, 1000)], "k int, advanced double, basic double")


@query("m27_budget_in_a_tree", f"WITH {PLAN_SQL} SELECT epsilon, round(t / 3, 6) AS sketch, round(t / 24, 6) AS per_feature, round(t / 3, 6) AS leaf, round(t / 18, 6) AS per_level FROM p")
def m27(spark, d):
    rows = [(e, ledger.plan_ensemble(e, 20, 0.1, 8, 6)[0]) for e in (1.0, 2.0, 4.0, 6.0, 8.0, 10.0)]
    return spark.createDataFrame([(e, *(round(x, 6) for x in (p.sketch, p.sketch_feature, p.leaf(), p.level))) for e, p in rows], "epsilon double, sketch double, per_feature double, leaf double, per_level double")


@query("m28_budget_over_trees", "SELECT 1.0 AS epsilon, 20 AS trees")
def m28(spark, d):
    book = ledger.Ledger(1.0, 0.1)
    for t, p in enumerate(ledger.plan_ensemble(1.0, 20, 0.1, 8, 6)):
        book.charge(p.charges(t))
    return ledger.total_of(book.to_df(spark), 0.1)


@query("m31_uneven_budgets", "SELECT tree, round(ln(1 + (exp(4.0 * w / 10) - 1) / 0.1), 6) AS mechanism, round(ln(1 + (exp(4.0 * w / 10) - 1) / 0.1) * 0.5 / 6 * 4 + ln(1 + (exp(4.0 * w / 10) - 1) / 0.1) * 0.3, 6) AS leaf_at_depth_2 FROM (VALUES (0, 1), (1, 2), (2, 3), (3, 4)) t(tree, w)")
def m31(spark, d):
    plans = ledger.plan_ensemble(4.0, 4, 0.1, 8, 6, (0.2, 0.3, 0.5), (1, 2, 3, 4), True)
    return spark.createDataFrame([(t, round(p.eps_tree, 6), round(p.leaf(2), 6)) for t, p in enumerate(plans)], "tree int, mechanism double, leaf_at_depth_2 double")


@query("a08_noise_variance", "SELECT l_suppkey, n, round(2 * pow(2 / (n + 1.1) / 0.13797, 2), 9) AS variance FROM (SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1)")
def a08(spark, d):
    """The variance of a leaf's noise where the least child is as large as each supplier's group of line items."""
    groups = load(spark, d, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"))
    return groups.select("l_suppkey", "n", F.round(metrics.noise_variance(2 / (F.col("n") + 1.1) / 0.13797), 9).alias("variance"))


# ---- losses, filters, samples

U_LINE = uniform_sql(f"'{KEY}|' || {LINE_KEY}")


@query("m12_squared_loss", "SELECT count(*) AS n, round(avg(0.5 * (l_discount * 10 - l_tax * 10) ** 2), 6) AS loss, round(avg(l_discount * 10 - l_tax * 10), 6) AS gradient, 1.0 AS hessian FROM lineitem")
def m12(spark, d):
    loss, g, h = gradient.squared(F.col("l_discount") * 10, F.col("l_tax") * 10)
    return load(spark, d, "lineitem").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(loss), 6).alias("loss"), F.round(F.avg(g), 6).alias("gradient"), F.avg(h).alias("hessian"))


@query("m17_gradient_filter", "SELECT count(*) AS n, max(g) <= 0.5 AS upper, min(g) >= -0.5 AS lower FROM (SELECT l_discount * 10 - l_tax * 10 AS g FROM lineitem) WHERE abs(g) <= 0.5")
def m17(spark, d):
    g = load(spark, d, "lineitem").select((F.col("l_discount") * 10 - F.col("l_tax") * 10).alias("g"))
    return gradient.filter_bounded(g, 0.5).agg(F.count(F.lit(1)).alias("n"), (F.max("g") <= 0.5).alias("upper"), (F.min("g") >= -0.5).alias("lower"))


@query("g15_fixed_point_sum", "SELECT CAST(sum(CAST(trunc((l_discount - l_tax) * 1048576) AS BIGINT)) AS BIGINT) AS units FROM lineitem")
def g15(spark, d):
    return load(spark, d, "lineitem").agg(F.sum(gradient.fixed(F.col("l_discount") - F.col("l_tax"))).alias("units"))


def sample_sql(tree: int) -> str:
    return uniform_sql(f"'{KEY}|sample|{tree}|' || row_key")


KEYED_SQL = f"keyed AS (SELECT {LINE_KEY} AS row_key, l_quantity FROM lineitem)"


def keyed(spark, d):
    return load(spark, d, "lineitem").select(F.expr(LINE_KEY).alias("row_key"), "l_quantity")


@query("m29_bernoulli_sample", f"WITH {KEYED_SQL} SELECT row_key, l_quantity FROM keyed WHERE {sample_sql(3)} < 0.1")
def m29(spark, d):
    return sampling.bernoulli(keyed(spark, d), 0.1, 3, KEY)


@query("m29_exact_fraction", f"WITH {KEYED_SQL} SELECT row_key, l_quantity FROM keyed ORDER BY {sample_sql(3)}, row_key LIMIT (SELECT CAST(floor(count(*) * 0.05) AS BIGINT) FROM lineitem)")
def m29_exact(spark, d):
    return sampling.exact_fraction(keyed(spark, d), 0.05, 3, KEY)


@query("m29_materialized_samples", f"WITH {KEYED_SQL}, s AS ({' UNION ALL '.join(f'SELECT {t} AS tree_id, l_quantity FROM keyed WHERE {sample_sql(t)} < 0.1' for t in range(4))}) SELECT tree_id, count(*) AS n, sum(l_quantity) AS quantity FROM s GROUP BY 1")
def m29_mat(spark, d):
    from privgrove.sources.io import shared_dir

    drawn = sampling.materialize(keyed(spark, d), shared_dir(spark, "samples"), 4, 0.1, KEY)
    return drawn.groupBy("tree_id").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"))


@query("b05_disjoint_parts", f"WITH {KEYED_SQL}, p AS (SELECT {uniform_sql(f"'{KEY}|part|' || row_key")} AS u FROM keyed) SELECT CAST(CAST(u >= 0.5 AS INTEGER) + CAST(u >= 0.75 AS INTEGER) AS INTEGER) AS tree_id, count(*) AS n FROM p GROUP BY 1")
def b05(spark, d):
    return sampling.disjoint(keyed(spark, d), [2, 1, 1], KEY).groupBy("tree_id").agg(F.count(F.lit(1)).alias("n"))


@query("bound_contribution", f"""SELECT o_orderkey, o_custkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY {uniform_sql(f"'{KEY}|' || o_orderkey")}, o_orderkey) AS n FROM orders) WHERE n <= 5""")
def contribution(spark, d):
    return mechanisms.bound_contribution(load(spark, d, "orders").select("o_orderkey", "o_custkey"), "o_custkey", 5, KEY, ["o_orderkey"])


# ---- histograms and cuts


@query("m18_dp_histogram", f"WITH {HIST_SQL}, {grid_sql()}, {dp_sql(EPS)} SELECT feature, bin, round(edge, 6) AS edge, round(weight, 6) AS weight FROM dp")
def m18(spark, d):
    h = histogram.dp_feature_histogram(binned(spark, d), SPEC, BINS, EPS, KEY)
    return h.select("feature", "bin", F.round("edge", 6).alias("edge"), F.round("weight", 6).alias("weight"))


def sized(bins: int):
    sql = HIST_SQL
    for x, lo, hi in (("l_quantity", 1.0, 50.0), ("l_extendedprice", 900.0, 105000.0), ("CASE WHEN l_linenumber <> 3 THEN l_discount END", 0.0, 0.1)):
        sql = sql.replace(bin_sql(x, lo, hi), bin_sql(x, lo, hi, bins))

    @query(f"m18a_bins_{bins}", f"WITH {sql}, {grid_sql(bins)}, {dp_sql(EPS)}, {cuts_sql('dp', CUTS, bins)} SELECT feature, slot, cut_bin, round(cut, 6) AS cut FROM cuts")
    def run(spark, d):
        h = histogram.dp_feature_histogram(binned(spark, d, bins), SPEC, bins, EPS, KEY)
        return proposals.from_weighted_bins(h, CUTS).withColumn("cut", F.round("cut", 6))


for _bins in (8, 32, 64, 128, 256, 512):
    sized(_bins)


@query("m18b_weighted_bins", f"WITH {BINNED_SQL} SELECT 0 AS feature, b_0 AS bin, CAST(sum(0.25 + 0.5 * CAST(y > 0 AS INTEGER)) AS DOUBLE) AS weight FROM binned GROUP BY b_0")
def m18b(spark, d):
    b = binned(spark, d).withColumn("h", 0.25 + 0.5 * (F.col("y") > 0).cast("int"))
    return histogram.raw_histogram(b, 1, "h").select("feature", F.col("bin").cast("int").alias("bin"), "weight")


@query("m18c_midpoints", f"WITH {HIST_SQL}, {grid_sql(point=0.5)} SELECT feature, bin, round(edge, 6) AS edge, weight FROM cells")
def m18c(spark, d):
    return histogram.complete_grid(histogram.raw_histogram(binned(spark, d), 3), SPEC, BINS, "mid").withColumn("edge", F.round("edge", 6))


@query("m18_arrow_histogram", f"WITH {HIST_SQL} SELECT feature, bin, weight FROM hist")
def m18_arrow(spark, d):
    return histogram.raw_histogram_arrow(binned(spark, d), 3, BINS)


@query("m18_grouping_sets_histogram", f"WITH {HIST_SQL} SELECT feature, bin, weight FROM hist")
def m18_sets(spark, d):
    return histogram.raw_histogram_sets(binned(spark, d), 3)


@query("m19_private_cuts", f"WITH {HIST_SQL}, {grid_sql()}, {dp_sql(EPS)}, {cuts_sql('dp')} SELECT feature, slot, cut_bin, round(cut, 6) AS cut FROM cuts")
def m19(spark, d):
    h = histogram.dp_feature_histogram(binned(spark, d), SPEC, BINS, EPS, KEY)
    return proposals.from_weighted_bins(h, CUTS).withColumn("cut", F.round("cut", 6))


@query("b02_open_cuts", f"WITH {HIST_SQL}, {grid_sql()}, {cuts_sql('cells')} SELECT feature, slot, cut_bin, round(cut, 6) AS cut FROM cuts")
def b02(spark, d):
    h = histogram.complete_grid(histogram.raw_histogram(binned(spark, d), 3), SPEC, BINS)
    return proposals.from_weighted_bins(h, CUTS).withColumn("cut", F.round("cut", 6))


@query("m19c_fifty_cuts", f"WITH {HIST_SQL}, {grid_sql()}, {dp_sql(EPS)}, {cuts_sql('dp', 50)} SELECT feature, count(*) AS cuts FROM cuts GROUP BY 1")
def m19c(spark, d):
    h = histogram.dp_feature_histogram(binned(spark, d), SPEC, BINS, EPS, KEY)
    return proposals.from_weighted_bins(h, 50).groupBy("feature").agg(F.count(F.lit(1)).alias("cuts"))


@query("a09_rank_error", f"WITH {HIST_SQL}, {grid_sql()}, {cuts_sql('cells')}, s AS (SELECT c.feature, c.bin, any_value(c.weight) AS weight, count_if(k.cut_bin < c.bin) AS slot FROM cells c JOIN cuts k USING (feature) GROUP BY 1, 2), e AS (SELECT feature, slot, sum(weight) AS w FROM s GROUP BY ALL) SELECT feature, round(max(w) / sum(w) * {CUTS + 1}, 6) AS worst_share FROM e GROUP BY 1")
def a09(spark, d):
    h = histogram.complete_grid(histogram.raw_histogram(binned(spark, d), 3), SPEC, BINS)
    return metrics.rank_error(h, proposals.from_weighted_bins(h, CUTS), CUTS)


@query("m19a_percentile_cuts")
def m19a(spark, d):
    return proposals.from_percentiles(SPEC.encode(load(spark, d, "lineitem")), 3, CUTS)


@query("m19b_sketch_cuts")
def m19b(spark, d):
    return sketch.propose(SPEC.encode(load(spark, d, "lineitem")), 3, CUTS)


@query("m32_joint_quantiles")
def m32(spark, d):
    h = histogram.raw_histogram(binned(spark, d), 3).toPandas()
    rows = []
    for k in range(3):
        w = h[h.feature == k].set_index("bin").weight.reindex(range(BINS), fill_value=0.0).to_numpy()
        rows += [(k, s, int(b)) for s, b in enumerate(proposals.joint_quantiles(w, 4, EPS / 3, KEY, k))]
    return spark.createDataFrame(rows, "feature int, slot int, cut_bin int")


@query("m33_dp_bounds", f"""WITH e(cell, lo, hi) AS (VALUES (0, 0.0, 10.0), (1, 10.0, 100.0), (2, 100.0, 1000.0), (3, 1000.0, 10000.0), (4, 10000.0, 100000.0), (5, 100000.0, 1000000.0), (6, 1000000.0, 10000000.0)),
  c AS (SELECT CAST(l_extendedprice > 10 AS INT) + CAST(l_extendedprice > 100 AS INT) + CAST(l_extendedprice > 1000 AS INT) + CAST(l_extendedprice > 10000 AS INT) + CAST(l_extendedprice > 100000 AS INT) + CAST(l_extendedprice > 1000000 AS INT) AS cell, count(*) AS n FROM lineitem GROUP BY 1),
  f AS (SELECT cell, lo, hi, coalesce(n, 0) AS n FROM e LEFT JOIN c USING (cell))
  SELECT CAST(min(lo) AS DOUBLE) AS lo, CAST(max(hi) AS DOUBLE) AS hi FROM f WHERE n + {laplace_sql(uniform_sql(f"'{KEY}|' || cell"), '1.0')} > 20""")
def m33(spark, d):
    return histogram.dp_range(load(spark, d, "lineitem"), "l_extendedprice", [0, 10, 100, 1e3, 1e4, 1e5, 1e6, 1e7], 1.0, 20.0, KEY)


@query("m34_answer_reuse", f"WITH {HIST_SQL}, {grid_sql()}, {dp_sql(EPS)} SELECT feature, round(sum(weight), 4) AS weight, 1 AS charges FROM dp GROUP BY 1")
def m34(spark, d):
    cache, charges = ReleaseCache(spark), 0
    for _ in range(3):
        answer, new = cache.get_or_release("hist", lambda: histogram.dp_feature_histogram(binned(spark, d), SPEC, BINS, EPS, KEY))
        charges += new
    return answer.groupBy("feature").agg(F.round(F.sum("weight"), 4).alias("weight")).withColumn("charges", F.lit(charges))


# ---- splits

LH_COLS = "node, feature, slot, sg, sh, n"


@query("m20_level_histogram", f"WITH {LEVEL_SQL} SELECT {LH_COLS} FROM lh")
def m20(spark, d):
    return splits.level_histogram(work(spark, d), CUT_BINS)


@query("g14_arrow_level_histogram", f"WITH {LEVEL_SQL} SELECT {LH_COLS} FROM lh")
def g14(spark, d):
    return splits.level_histogram_arrow(work(spark, d), CUT_BINS)


@query("g07_grouping_sets_level", f"WITH {LEVEL_SQL} SELECT {LH_COLS} FROM lh")
def g07_level(spark, d):
    return splits.level_histogram_sets(work(spark, d), CUT_BINS)


@query("h08_sibling_subtraction", f"WITH {LEVEL_SQL} SELECT {LH_COLS} FROM lh WHERE node = 2")
def h08(spark, d):
    w = work(spark, d)
    parent = splits.level_histogram(w.withColumn("node", F.lit(0)), CUT_BINS)
    return splits.subtract_sibling(parent, splits.level_histogram(w.where("node = 1"), CUT_BINS), 2)


@query("m21_candidates", f"WITH {CAND_SQL} SELECT {CAND_COLS} FROM cand")
def m21(spark, d):
    return shown(cands(spark, d))


@query("m15_gain_gates", f"WITH {CAND_SQL} SELECT {CAND_COLS} FROM cand WHERE nl >= 500 AND nr >= 500 AND gain - ((gl + gr) / 1048576.0) ** 2 / (nl + nr + {LAM}) > 1.0")
def m15(spark, d):
    return shown(splits.admissible(cands(spark, d), 500, 1.0, LAM))


@query("m22_dp_split", f"""WITH {CAND_SQL}, r AS (SELECT *, ln(-ln({uniform_sql(f"'{KEY}|split|0|' || node || '|' || feature || '|' || slot || '|' || CAST(default_left AS INTEGER)")})) - gain * {0.02299 / 6} AS k FROM cand)
  SELECT {CAND_COLS} FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY k, feature, slot, default_left) AS i FROM r) WHERE i = 1""")
def m22(spark, d):
    return shown(splits.choose_dp(cands(spark, d), 0.02299, 1.0, KEY))


@query("m26_greedy_split", f"WITH {CAND_SQL} SELECT {CAND_COLS} FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY round(gain, 6) DESC, feature, slot, default_left DESC) AS i FROM cand) WHERE i = 1")
def m26(spark, d):
    return shown(splits.choose_greedy(cands(spark, d)))


@query("b07_exact_greedy", f"""WITH {LINE_KEY and 'w AS (SELECT l_quantity AS x, CAST(trunc(CASE WHEN l_quantity > 20 AND l_discount > 0.025 THEN -0.75 ELSE 0.5 END * 1048576) AS BIGINT) AS g FROM lineitem)'},
  v AS (SELECT x, sum(g) AS g, count(*) AS n FROM w GROUP BY x), p AS (SELECT x, sum(g) OVER o / 1048576.0 AS gl, sum(n) OVER o AS nl, sum(g) OVER () / 1048576.0 AS gt, sum(n) OVER () AS nt FROM v WINDOW o AS (ORDER BY x))
  SELECT x AS cut, round(gl * gl / (nl + {LAM}) + (gt - gl) * (gt - gl) / (nt - nl + {LAM}), 4) AS gain FROM p WHERE nl < nt""")
def b07(spark, d):
    from privgrove.plans.baselines import exact_greedy

    y = F.when((F.col("l_quantity") > 20) & (F.col("l_discount") > 0.025), -0.75).otherwise(0.5)
    w = load(spark, d, "lineitem").select(F.col("l_quantity").alias("x"), gradient.fixed(y).alias("g"))
    return exact_greedy(w, LAM).select(F.col("x").alias("cut"), F.round("gain", 4).alias("gain"))


# ---- leaves

LEAF_SQL = f"{LEVEL_SQL}, leaf AS (SELECT node, sum(g) / 1048576.0 AS g, count(*) AS n FROM work GROUP BY node)"
U_LEAF = uniform_sql(f"'{KEY}|leaf|2|' || node")


def leaf_rows(spark, d):
    return work(spark, d).groupBy("node").agg((F.sum("g") / gradient.UNIT).alias("g"), F.count(F.lit(1)).alias("n"))


def leaf_query(name: str, mode: str, value: str, min_child: int = 500, strict: bool = False) -> None:
    @query(name, f"WITH {LEAF_SQL} SELECT node, round({value}, 8) AS value FROM leaf")
    def run(spark, d):
        r = leaves.released(leaf_rows(spark, d), mode, 0.138, KEY, 1.0, LAM, min_child, 2, 0.3, strict)
        return r.select("node", F.round("value", 8).alias("value"))


PLAIN = f"-g / (n + {LAM})"
leaf_query("m16_exact_leaves", "exact", PLAIN)
leaf_query("m23_worst_case_leaves", "worst_case", f"{PLAIN} + {laplace_sql(U_LEAF, f'{1 / 1.1 / 0.138}')}")
leaf_query("m24_min_child_leaves", "min_child", f"{PLAIN} + {laplace_sql(U_LEAF, f'{2 / 501.1 / 0.138}')}")
for _n in (10, 50, 200, 600):
    leaf_query(f"m24a_min_child_{_n}", "min_child", f"{PLAIN} + {laplace_sql(U_LEAF, f'{2 / (_n + 1.1) / 0.138}')}", _n)
leaf_query("m24_strict_leaves", "min_child", f"-g / (greatest(n, 100000) + {LAM}) + {laplace_sql(U_LEAF, f'{2 / 100001.1 / 0.138}')}", 100000, True)
leaf_query("m25_noisy_average", "noisy_average", f"-greatest(-1.0, least(1.0, (g + {laplace_sql(U_LEAF, f'{2 / 0.138}')}) / (n + {LAM})))")
leaf_query("b04_geometric_leaves", "geometric", f"greatest(-{0.7**2}, least({0.7**2}, {PLAIN})) + {laplace_sql(U_LEAF, f'{min(1 / 1.1, 2 * 0.7**2) / 0.138}')}")


@query("m14_structure_score", f"WITH {LEAF_SQL} SELECT round(-0.5 * sum(g * g / (n + {LAM})), 6) AS structure_score FROM leaf")
def m14(spark, d):
    return metrics.structure_score(leaf_rows(spark, d).withColumn("h", F.col("n").cast("double")), LAM)


# ---- scoring


def two_trees() -> TreeModel:
    """A fixed ensemble for scoring tests."""
    first, second = Tree(), Tree()
    first.split(0, 0, 6, True)
    first.split(2, 2, 3, False)
    for node, value in ((1, -0.5), (5, -0.25), (6, 0.75)):
        first.nodes[node].value = value
    second.split(0, 1, 8, True)
    for node, value in ((1, 0.125), (2, -0.125)):
        second.nodes[node].value = value
    return TreeModel(SPEC, BINS, [first, second])


MARGIN_SQL = f"{BINNED_SQL}, pred AS (SELECT row_key, y, CASE WHEN b_0 <= 6 THEN -0.5 WHEN b_2 >= 0 AND b_2 <= 3 THEN -0.25 ELSE 0.75 END + CASE WHEN b_1 <= 8 THEN 0.125 ELSE -0.125 END AS margin FROM binned)"


def scored(spark, d, path="expression"):
    return two_trees().predict_binned(binned(spark, d), path)


for _path in ("expression", "arrow"):

    @query(f"m11_ensemble_{_path}", f"WITH {MARGIN_SQL} SELECT row_key, CAST(margin AS DOUBLE) AS margin FROM pred")
    def m11(spark, d, path=_path):
        return scored(spark, d, path).select("row_key", "margin")


@query("a01_error", f"WITH {MARGIN_SQL} SELECT round(100 * avg(CAST((margin >= 0) <> (y > 0) AS INTEGER)), 6) AS error_pct, count(*) AS n FROM pred")
def a01(spark, d):
    return metrics.error_pct(scored(spark, d))


@query("a02_rmse", f"WITH {MARGIN_SQL} SELECT round(sqrt(avg((greatest(-1.0, least(1.0, margin)) - y) ** 2)), 6) AS rmse, count(*) AS n FROM pred")
def a02(spark, d):
    return metrics.rmse(scored(spark, d), SPEC.target)


@query("g08_confusion", f"WITH {MARGIN_SQL} SELECT count_if(margin >= 0 AND y > 0) AS tp, count_if(margin >= 0 AND y <= 0) AS fp, count_if(margin < 0 AND y > 0) AS fn, count_if(margin < 0 AND y <= 0) AS tn FROM pred")
def g08(spark, d):
    return metrics.confusion(scored(spark, d))


@query("m13_objective", f"WITH {MARGIN_SQL} SELECT round(sum(0.5 * (margin - y) ** 2) + 0.05 * {0.5**2 + 0.25**2 + 0.75**2 + 2 * 0.125**2}, 6) AS objective FROM pred")
def m13(spark, d):
    model = two_trees()
    return metrics.objective(scored(spark, d), sum(x.value**2 for t in model.trees for x in t.leaves()), LAM)


@query("b08_constant", f"WITH {BINNED_SQL}, s AS (SELECT y, {uniform_sql("'split|' || row_key")} < 0.2 AS test FROM binned), m AS (SELECT CASE WHEN avg(y) >= 0 THEN 1.0 ELSE -1.0 END AS margin FROM s WHERE NOT test) SELECT round(100 * avg(CAST(margin <> y AS INTEGER)), 6) AS error_pct, count(*) AS n FROM s, m WHERE test")
def b08(spark, d):
    train, test = sampling.split(binned(spark, d))
    return metrics.error_pct(metrics.constant_baseline(train, test, True))


@query("s07_model_round_trip", f"WITH {MARGIN_SQL} SELECT round(sum(margin), 6) AS margins, count(*) AS n FROM pred")
def s07(spark, d):
    from privgrove.sources.io import shared_dir

    path = shared_dir(spark, "model")
    two_trees().save(spark, path)
    back = TreeModel.load(spark, path, SPEC)
    return back.predict_binned(binned(spark, d)).agg(F.round(F.sum("margin"), 6).alias("margins"), F.count(F.lit(1)).alias("n"))


@query("s08_ledger_round_trip", "SELECT 'leaf' AS mechanism, 2 AS n, 0.2 AS epsilon UNION ALL SELECT 'sketch', 6, 0.2 UNION ALL SELECT 'split', 8, 0.2")
def s08(spark, d):
    from privgrove.sources.io import round_trip

    book = ledger.Ledger()
    for t in range(2):
        book.charge(ledger.BudgetPlan(0.3, 3, 4).charges(t))
    back = round_trip(book.to_df(spark), "parquet")
    return back.groupBy("mechanism").agg(F.count(F.lit(1)).cast("int").alias("n"), F.round(F.sum("epsilon"), 6).alias("epsilon"))


# ---- private aggregates for users


@query("g13_dp_count", f"SELECT round(count(*) + {laplace_sql(uniform_sql(f"'{KEY}|count'"), '2.0')}, 6) AS n FROM events")
def g13c(spark, d):
    return mechanisms.dp_count(load(spark, d, "events"), 0.5, KEY).select(F.round("n", 6).alias("n"))


@query("g13_dp_sum", f"SELECT round(sum(least(greatest(value, 0.0), 100.0)) + {laplace_sql(uniform_sql(f"'{KEY}|sum'"), '200.0')}, 4) AS s FROM events")
def g13s(spark, d):
    return mechanisms.dp_sum(load(spark, d, "events"), "value", 0.0, 100.0, 0.5, KEY).select(F.round("s", 4).alias("s"))


@query("g13_dp_mean", f"SELECT round(greatest(0.0, least(100.0, (sum(least(greatest(value, 0.0), 100.0)) + {laplace_sql(uniform_sql(f"'{KEY}|sum'"), '200.0')}) / (count(value) + {laplace_sql(uniform_sql(f"'{KEY}|count'"), '2.0')}))), 6) AS mean FROM events")
def g13m(spark, d):
    return mechanisms.dp_mean(load(spark, d, "events"), "value", 0.0, 100.0, 1.0, KEY).select(F.round("mean", 6).alias("mean"))


@query("g13_dp_group_count", f"WITH k AS (SELECT unnest(['click', 'purchase', 'refund', 'signup', 'view', 'never']) AS event_type) SELECT event_type, round(coalesce(n, 0) + {laplace_sql(uniform_sql(f"'{KEY}|' || event_type"), '2.0')}, 6) AS n FROM k LEFT JOIN (SELECT event_type, count(*) AS n FROM events GROUP BY 1) USING (event_type)")
def g13g(spark, d):
    keys = ["click", "purchase", "refund", "signup", "view", "never"]
    return mechanisms.dp_group_count(load(spark, d, "events"), "event_type", keys, 0.5, KEY).select("event_type", F.round("n", 6).alias("n"))




@query("m35_accountants", """WITH e AS (SELECT 0.05 AS e, 0.000001 AS d, 200 AS k), s AS (SELECT *, e * k AS plain, k * e * (exp(e) - 1) + sqrt(2 * ln(1 / d) * k * e * e) AS adv, k * e * e / 2 AS rho FROM e)
  SELECT round(plain, 6) AS pure, round(least(plain, adv), 6) AS advanced, round(least(plain, rho + 2 * sqrt(rho * ln(1 / d))), 6) AS concentrated FROM s""")
def m35(spark, d):
    """Two hundred equal charges under three accountants."""
    e = [0.05] * 200
    return one(spark, pure=ledger.PureAccountant().total(e)[0], advanced=ledger.AdvancedAccountant(1e-6).total(e)[0], concentrated=ledger.ConcentratedAccountant(1e-6).total(e)[0])
