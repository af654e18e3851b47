"""Training: invariants of the loop, of samples and of the histograms."""

import math
from collections import Counter
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from privgrove.functions.noise import uniform_of
from privgrove.operators import leaves, sampling, sketch, splits
from privgrove.operators.gradient import UNIT
from privgrove.plans import audit, experiments, ledger
from privgrove.plans.boost import BoostParams, fit, fit_many
from privgrove.queries import methods as m
from privgrove.queries import registry

SMALL = BoostParams(epsilon_total=2.0, trees=2, max_depth=3, subsample=0.5, bins=m.BINS, min_child=20, noise_key="k0")


def test_model_does_not_depend_on_partitioning(spark, sf_dir):
    b = m.binned(spark, sf_dir)
    one, ledger, _ = fit(b, m.SPEC, SMALL)
    other, _, _ = fit(b.repartition(7), m.SPEC, SMALL, materialized=False)
    assert one.nodes(spark).collect() == other.nodes(spark).collect()
    assert ledger.total() == pytest.approx(2.0)


def test_budget_is_kept_and_counts_are_not_released(spark, sf_dir):
    model, ledger, _ = fit(m.binned(spark, sf_dir), m.SPEC, SMALL)
    assert all(x.n == 0 for t in model.trees for x in t.nodes.values())
    assert {c.mechanism for c in ledger.charges} == {"sketch", "split", "leaf"}


def test_models_trained_in_step_equal_those_trained_alone(spark, sf_dir):
    b = m.binned(spark, sf_dir)
    runs = [SMALL, replace(SMALL, epsilon_total=9.0, trees=3), replace(SMALL, noise_key="k1", max_depth=2), replace(SMALL, disjoint=True), SMALL.open()]
    for params, (model, ledger, _) in zip(runs, fit_many(b, m.SPEC, runs)):
        alone, own, _ = fit(b, m.SPEC, params)
        assert model.nodes(spark).collect() == alone.nodes(spark).collect() and ledger.charges == own.charges
    with pytest.raises(ValueError):
        fit_many(b, m.SPEC, [SMALL, replace(SMALL, bins=8)])


def test_strict_mode_stays_within_its_budget(spark, sf_dir):
    params = replace(SMALL, strict=True, leaf_mode="noisy_average")
    _, ledger, _ = fit(m.binned(spark, sf_dir), m.SPEC, params)
    assert ledger.limit == 2.0 and 1.99 < ledger.total() <= 2.0 * (1 + 1e-9) and "leaf count" in {c.mechanism for c in ledger.charges}


def test_children_have_the_least_hessian_weight(spark, sf_dir):
    b = m.binned(spark, sf_dir)
    model, _, _ = fit(b, m.SPEC, replace(SMALL.open(), trees=1, subsample=1.0, min_child=1, min_hessian=300.0))
    tree = model.trees[0]
    leaf = tree.expression(lambda x: F.lit(x.node))
    assert len(tree.leaves()) > 2 and min(r["count"] for r in b.groupBy(leaf.alias("leaf")).count().collect()) >= 300


def test_scoring_paths_agree(spark, sf_dir):
    b = m.binned(spark, sf_dir)
    model = m.two_trees()
    pairs = model.predict_binned(b, "expression").join(model.predict_binned(b, "arrow").select("row_key", F.col("margin").alias("m2")), "row_key")
    assert pairs.where("abs(margin - m2) > 1e-12").count() == 0


def test_level_histograms_agree_and_add_up(spark, sf_dir):
    w = m.work(spark, sf_dir)
    a, b, c = (sorted(map(tuple, f(w, m.CUT_BINS).select("node", "feature", "slot", "sg", "sh", "n").collect())) for f in (splits.level_histogram, splits.level_histogram_arrow, splits.level_histogram_sets))
    assert a == b == c
    n = w.count()
    assert all(sum(r[5] for r in a if r[1] == k) == n for k in m.CUT_BINS)


def test_driver_choice_equals_dataframe_choice(spark, sf_dir):
    w = m.work(spark, sf_dir)
    chosen = {r["node"]: r for r in splits.choose_dp(m.cands(spark, sf_dir), 0.5, 1.0, "k0").collect()}
    for node, row in chosen.items():
        sub = w.where(F.col("node") == node).toPandas()
        sg, n = np.zeros((3, m.BINS + 1), np.int64), np.zeros((3, m.BINS + 1), np.int64)
        for k in range(3):
            np.add.at(sg[k], sub[f"b_{k}"].to_numpy() + 1, sub.g.to_numpy())
            np.add.at(n[k], sub[f"b_{k}"].to_numpy() + 1, 1)
        best = splits.best_split(sg, n, [np.array(m.CUT_BINS[k]) for k in range(3)], m.LAM, 0, None, False, 0.5, 1.0, ("k0|split|0", node))
        assert (best.feature, best.cut_bin) == (row["feature"], m.CUT_BINS[row["feature"]][row["slot"]])
        assert best.gl == pytest.approx(row["gl"] / UNIT) and best.nl == row["nl"]


def test_materialized_samples_are_the_bernoulli_samples(spark, sf_dir):
    rows = m.keyed(spark, sf_dir)
    both = sampling.with_trees(rows, 3, 0.2, "k").where("tree_id = 1").select("row_key")
    assert sorted(both.collect()) == sorted(sampling.bernoulli(rows, 0.2, 1, "k").select("row_key").collect())


def test_all_gradients_filtered_gives_a_bare_leaf(spark, sf_dir):
    params = BoostParams(epsilon_total=1.0, trees=1, max_depth=2, subsample=1.0, bins=m.BINS, g_star=1e-6, min_child=5)
    model, ledger, _ = fit(m.binned(spark, sf_dir), m.SPEC, params)
    assert len(model.trees[0].nodes) == 1 and ledger.total() == pytest.approx(1.0)


def test_open_model_beats_private_beats_constant(spark):
    bench = experiments.Bench(spark, "/root/testdata/sf0.01", "w01")
    p = bench.params(trees=8, max_depth=4, epsilon_total=20.0)
    open_, private, floor = bench.run("open", p.open()).value, bench.run("private", p).value, bench.floor().value
    bench.close()
    assert open_ <= private + 0.5 < floor


@pytest.mark.parametrize("name", ["w11a", "w12"])
def test_negative_controls_stay_at_the_constant(spark, name):
    """Targets that do not depend on the features: no model may seem to learn, with or without privacy."""
    bench = experiments.Bench(spark, "/root/testdata/sf0.01", name)
    p = bench.params(trees=4, max_depth=3, subsample=0.5, epsilon_total=10.0)
    floor, (open_, private) = bench.floor(), bench.run_many([("open", p.open(), 0), ("private", p, 0)])
    bench.close()
    band = 300 * math.sqrt(0.25 / floor.n_test)  # three standard errors, in percent
    assert open_.value > floor.value - band and private.value > floor.value - band


def test_registered_studies_run_in_full(spark, sf_dir, monkeypatch):
    """What each query asks to be trained; the training itself is replaced."""
    asked = []

    class Asked(experiments.Bench):
        def __init__(self, spark, sf_dir, name, bins=None, bins_by="even"):
            self.work, self.bins, self.settings = experiments.for_tables(sf_dir)[name], bins or 64, {"min_child": 500}

        def run_many(self, runs):
            asked.extend((self.work.name, *r) for r in runs)
            return [experiments.Run(self.work.name, variant, params.epsilon_total, trial, "error_pct", 1.0, 1, 1.0, 1.0) for variant, params, trial in runs]

        def floor(self):
            return experiments.Run(self.work.name, "constant", 0.0, 0, "error_pct", 1.0, 1, 0.0, 0.0)

        def close(self):
            pass

    def of(name):
        asked.clear()
        registry.QUERIES[name](spark, sf_dir)
        assert all((p.trees, p.max_depth) == (20, 6) for _, v, p, _ in asked if v != "warm-up")
        return list(asked)

    monkeypatch.setattr(experiments, "Bench", Asked)
    private = {(w, p.epsilon_total, t) for w, v, p, t in of("w09_result_table") if v == "private"}
    assert private == {(f"w0{k}", eps, t) for k in range(1, 7) for eps in experiments.EPSILONS for t in range(experiments.TRIALS)}
    assert {v for _, v, _, _ in of("w07_leaf_study")} == {"clipped", "noisy_average", "min_child_200", "min_child_600"}
    assert {p.bins for _, _, p, _ in of("w08_bin_study")} == {8, 16, 32, 64, 128, 256, 512}
    assert {(w, p.epsilon_total, t) for w, _, p, t in of("b03_precursor")} == {(w, eps, t) for w in ("w01", "w03") for eps in experiments.EPSILONS for t in range(experiments.TRIALS)}
    for name in ("b01_open_model", "w10_runtime", "w04_fit", *(n for n in registry.QUERIES if n.startswith("m") and n.endswith("_fit"))):
        assert of(name), name


def test_sketch_keeps_its_rank_error_over_many_batches(spark):
    rng, eps = np.random.default_rng(1), 0.02
    size = sketch.entries_for(eps)
    parts = [np.round(np.arange(400) * 0.01 + k * 0.37 + rng.random(400), 3) for k in range(1000)]
    whole, exact = sketch.Stack(size), sketch.build(np.concatenate(parts), np.ones(400_000))
    small = sketch.Stack(64)
    for x in parts:
        whole.push(sketch.build(x, np.ones(400)))
        small.push(sketch.build(x, np.ones(400)))
    ranks = np.linspace(0, exact.total, 200)
    for s, bound in ((whole.whole(), eps), (small.whole(), 12 / 60)):
        assert len(s.value) <= size + 2
        low, high, _ = sketch.bounds_at(exact, sketch.query(s, ranks))
        assert (np.maximum(low - ranks, ranks - high).max() / exact.total) <= bound
    rows = spark.createDataFrame([(float(v),) for v in rng.exponential(1, 20_000)], "x_0 double").repartition(23)
    got = [r["cut"] for r in sketch.propose(rows, 1, 9, sketch_eps=0.01).orderBy("slot").collect()]
    x = np.sort(np.array([r[0] for r in rows.collect()]))
    assert np.abs(np.searchsorted(x, got) / len(x) - np.arange(1, 10) / 10).max() <= 0.01
    assert sketch.propose(rows.where("x_0 < 0"), 1, 9).count() == 0


def test_open_models_over_the_datas_own_bins(spark, sf_dir):
    for way in ("sketch", "exact"):
        bench = experiments.Bench(spark, sf_dir, "w06", bins_by=way)
        p = bench.params(trees=4, max_depth=3, subsample=1.0, min_child=5).open()
        cuts = bench.bins if way == "exact" else 50
        assert bench.run("open", replace(p, max_cuts=cuts)).value < bench.floor().value
        with pytest.raises(ValueError):
            bench.run("private", bench.params())
        bench.close()
    rows = experiments.for_tables(sf_dir)["w01"].rows(spark, sf_dir)
    with pytest.raises(ValueError):
        experiments.all_cuts(rows, 2, 10)


def test_exact_greedy_tree_takes_the_best_of_all_cuts(spark):
    rng = np.random.default_rng(8)
    x, y = rng.integers(0, 40, 400) / 7, rng.choice([-1.0, 1.0], 400)
    rows = spark.createDataFrame([(str(k), float(a), float(b)) for k, (a, b) in enumerate(zip(x, y))], "row_key string, x_0 double, y double")
    spec = m.DatasetSpec("row_key", (m.FeatureSpec("x", "x_0", 0, 6),), m.TargetSpec("y", kind="class"))
    cuts = experiments.all_cuts(rows, 1)
    p = replace(SMALL.open(), trees=1, max_depth=1, subsample=1.0, min_child=1, bins=len(cuts[0]) + 1, max_cuts=len(cuts[0]) + 1)
    model, _, _ = fit(spec.binned_at(rows, cuts), spec, p)
    gains = {c: (-y[x <= c].sum()) ** 2 / ((x <= c).sum() + 0.1) + (-y[x > c].sum()) ** 2 / ((x > c).sum() + 0.1) for c in cuts[0][:-1]}
    assert cuts[0][model.trees[0].nodes[0].cut_bin] == max(gains, key=gains.get)


def test_audits_stay_below_their_epsilon(spark):
    for mechanism, one, other, eps in ((audit.laplace_count(0.5), 10, 11, 0.5), (audit.exponential_of(1.0, 3.0), [0.0, 3.0, 1.0], [3.0, 0.0, 1.0], 1.0)):
        rows = audit.empirical_epsilon(spark, mechanism, one, other, 40_000).collect()
        assert rows and all(r["log_ratio"] - 1.5 * r["error"] <= eps for r in rows)


def audited(release, one, other, runs):
    """Largest log ratio of outcome shares on two inputs, less three standard errors; release(input, key) -> bucket."""
    counts = [Counter(release(x, f"{tag}{k}") for k in range(runs)) for tag, x in (("a", one), ("b", other))]
    return max(abs(math.log(counts[0][o] / counts[1][o])) - 3 * math.sqrt(1 / counts[0][o] + 1 / counts[1][o]) for o in counts[0] if min(counts[0][o], counts[1][o]) >= 50)


def test_a_seeded_split_and_a_leaf_stay_below_their_epsilon():
    rng = np.random.default_rng(2)
    n, g = rng.integers(1, 6, (2, 9)), rng.integers(-UNIT, UNIT, (2, 9))
    n[1], g[1] = n[0][::-1], g[0][::-1]
    n[:, 0] = g[:, 0] = 0
    more_n, more_g = n.copy(), g.copy()
    more_n[0, 1] += 1
    more_n[1, 8] += 1
    more_g[0, 1] += UNIT
    more_g[1, 8] += UNIT
    eps, cuts = 1.0, [np.arange(7)] * 2

    def split(tables, key):
        s = splits.best_split(*tables, cuts, 0.1, 0, None, True, eps, 1.0, (key, 0))
        return s.feature, s.cut_bin

    assert audited(split, (g, n), (more_g, more_n), 3000) <= eps
    for mode in ("min_child", "worst_case"):
        leaf = lambda sums, key, mode=mode: math.floor(leaves.leaf_value(mode, *sums, eps, 1.0, 0.1, 20, uniform_of(key, "leaf")) / 0.05)
        assert audited(leaf, (-20.0, 20), (-19.0, 21), 20_000) <= eps


def test_accountants():
    assert ledger.PureAccountant().total([0.1, 0.2]) == (pytest.approx(0.3), 0.0)
    few, many = [0.5, 0.5], [0.01] * 1000
    for a in (ledger.AdvancedAccountant(1e-6), ledger.ConcentratedAccountant(1e-6)):
        assert a.total(few) == (1.0, 0.0) and a.total(many)[0] < 10 and a.total(many)[1] == 1e-6


def test_training_shuffles_cells_not_rows(spark, sf_dir):
    rows = {r["variant"]: r for r in experiments.engine_cost(spark, sf_dir, trees=2, together=4, max_depth=3).collect()}
    assert all(0 < r["shuffle_records"] <= r["most_records"] for r in rows.values())
    assert rows["private_x4"]["jobs"] <= rows["private"]["jobs"] + 8  # four models in the jobs of one


def test_plans_push_filters_and_keep_rows_in_place(spark, sf_dir):
    plan = m.m18(spark, sf_dir)._jdf.queryExecution().toString()
    assert "PushedFilters" in plan and "SortMergeJoin" not in plan
