"""Studies in full: few jobs, the same models by every way of training, any number of values and of bins."""

from dataclasses import replace
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from privgrove.functions.noise import below, in_race, race_keys, uniform
from privgrove.operators import sampling
from privgrove.plans import boost, cost, experiments, workloads
from privgrove.plans.tree import Codes, Router, Tree, routed
from privgrove.queries import methods as m

SMALL = boost.BoostParams(epsilon_total=2.0, trees=3, max_depth=3, subsample=0.5, bins=m.BINS, min_child=20, noise_key="k0")


def nodes(spark, fitted):
    return [model.nodes(spark).collect() for model, _, _ in fitted]


def test_samples_by_digits_are_those_by_numbers(spark):
    rows = spark.range(20_000).select(F.when(F.col("id") % 1000 > 0, F.col("id").cast("string")).alias("row_key"))
    for share in (0.0, 2**-52, 0.1, 0.2, 1 / 3, 1.0):
        assert rows.where(below(share, "k", "row_key") != (uniform("k", "row_key") < share)).count() == 0


@pytest.mark.parametrize("bins", [12, 9000])
def test_router_reaches_the_leaves_of_a_walk(bins):
    rng = np.random.default_rng(bins)
    for depth in range(8):
        tree, open_nodes = Tree(), [0]
        for _ in range(depth):
            kept = [v for v in open_nodes if v == 0 or depth > 6 or rng.random() < 0.8]
            open_nodes = [x.node for v in kept for x in tree.split(v, int(rng.integers(3)), int(rng.integers(bins - 1)), bool(rng.integers(2)))]
        router, places = Router(tree, 3, bins), rng.integers(0, bins + 1, (3, 500))
        assert (router.order[router.place(places)] == routed(tree.arrays(), places.T - 1, tree.depth())).all()


def test_a_study_takes_few_jobs_and_gives_the_trees_of_level_jobs(spark, sf_dir, monkeypatch):
    b = m.binned(spark, sf_dir).persist()
    runs = [SMALL, replace(SMALL, noise_key="k1", trees=2), replace(SMALL, disjoint=True), SMALL.open(), replace(SMALL, strict=True), replace(SMALL, proposal="local"), replace(SMALL, max_depth=0)]
    got = {}
    used = cost.measured(spark, lambda: got.update(whole=boost.fit_many(b, m.SPEC, runs)))
    assert used["jobs"] <= 12
    monkeypatch.setattr(boost, "IN_A_TASK", 0)
    assert nodes(spark, got["whole"]) == nodes(spark, boost.fit_many(b, m.SPEC, runs))
    monkeypatch.setattr(boost, "DENSE", 1)
    monkeypatch.setattr(boost, "CHUNK", 300)
    assert nodes(spark, got["whole"]) == nodes(spark, boost.fit_many(b, m.SPEC, runs))
    b.unpersist()


def test_exact_greedy_takes_any_number_of_values(spark):
    rng = np.random.default_rng(3)
    x = rng.permutation(40_000) / 8
    y = np.where((x > 1234.5) != (rng.random(len(x)) < 0.1), 1.0, -1.0)
    rows = spark.createDataFrame([(str(k), float(a), float(k % 5), float(b)) for k, (a, b) in enumerate(zip(x, y))], "row_key string, x_0 double, x_1 double, y double")
    spec = m.DatasetSpec("row_key", tuple(m.FeatureSpec(f"x{k}", f"x_{k}", 0, 5000) for k in range(2)), m.TargetSpec("y", kind="class"))
    cuts = experiments.all_cuts(rows, 2)
    assert list(map(len, cuts.values())) == [40_000, 5]
    p = boost.BoostParams(trees=1, max_depth=2, subsample=1.0, min_child=1, bins=40_001, max_cuts=80_000).open()
    model, _, _ = boost.fit(spec.binned_at(rows, cuts), spec, p)
    order = np.argsort(x)
    left, size = np.cumsum(-y[order])[:-1], np.arange(1, len(x))
    gains = left**2 / (size + 0.1) + (-y.sum() - left) ** 2 / (len(x) - size + 0.1)
    root = model.trees[0].nodes[0]
    assert root.feature == 0 and cuts[0][root.cut_bin] == x[order][np.argmax(np.round(gains, 6))]


def test_rare_values_have_cuts_in_exact_greedy_search(spark, sf_dir, monkeypatch):
    asked = []
    monkeypatch.setattr(experiments.Bench, "run_many", lambda self, runs: asked.extend((self.n, p) for _, p, _ in runs) or [])
    experiments.open_models(spark, sf_dir, "w06", 1, ("exact",))
    (n, p), = asked
    assert p.max_cuts >= n and len(boost.cuts_for(np.array([[0, 1, 10_000, 1, 10_000, 1, 5]]), None, replace(p, max_cuts=20_008), ())[0]) == 5


def test_coarser_bins_share_the_finest_rows(spark, sf_dir):
    sizes = (4, 6, 8, 16)
    runs = experiments.bin_study(spark, sf_dir, bins=sizes, trials=1, trees=2, max_depth=2, subsample=0.5).collect()
    assert len(runs) == 2 * len(sizes)
    for b in sizes:
        bench = experiments.Bench(spark, sf_dir, "w01", b)
        alone = bench.run("alone", bench.params(epsilon_total=1.0, trees=2, max_depth=2, subsample=0.5))
        bench.close()
        assert [alone.value] == [r["value"] for r in runs if r["variant"] == f"noised_{b}"]
    with pytest.raises(ValueError):
        boost.fit_many(m.binned(spark, sf_dir), m.SPEC, [replace(SMALL, bins=6)], bins=m.BINS)


def test_workloads_side_by_side_are_as_one_by_one(spark, sf_dir):
    few = {"trees": 2, "max_depth": 2}
    both = experiments.against_precursor(spark, sf_dir, ("w05", "w03"), (1.0,), 1, **few).drop("seconds_per_tree").collect()
    alone = [r for w in ("w05", "w03") for r in experiments.against_precursor(spark, sf_dir, w, (1.0,), 1, **few).drop("seconds_per_tree").collect()]
    assert both == alone


def test_samples_of_all_trees_take_one_condition(spark):
    rows = spark.range(3000).select(F.when(F.col("id") % 1000 > 0, F.col("id").cast("string")).alias("row_key"))
    drawn = sampling.with_trees(rows, 20, 0.1, "k")
    assert drawn._jdf.queryExecution().optimizedPlan().toString().count("sha2(") == 1
    by_tree = [sampling.bernoulli(rows, 0.1, t, "k").withColumn("tree_id", F.lit(t)) for t in range(20)]
    assert sorted(map(str, drawn.collect())) == sorted(str(r) for x in by_tree for r in x.collect())


def test_exact_and_even_bins_share_the_features(spark, sf_dir, monkeypatch):
    made, levels = [], []
    rows, cuts = experiments.Workload.rows, experiments.all_cuts
    monkeypatch.setattr(experiments.Workload, "rows", lambda self, *a: made.append(rows(self, *a)) or made[-1])
    monkeypatch.setattr(experiments, "all_cuts", lambda found, m: levels.append(made[0].storageLevel.useMemory) or cuts(found, m))
    experiments.open_models(spark, sf_dir, "w06", 1, ("even", "exact"), trees=1, max_depth=1)
    assert len(made) == 1 and levels == [True] and not made[0].storageLevel.useMemory


def test_shares_of_characters_count_each(spark):
    share = {f.name: f.expr for f in workloads.text_features()}
    text = spark.createDataFrame([("Aé,,b\n12 ZZ😀.", 13), ("", 0), ("xyz", 3)], "text string, n int")
    found = text.selectExpr(*[f"{share[k]} * greatest(n, 1) AS {k}" for k in ("upper_case", "digits", "punctuation")]).collect()
    assert [tuple(round(x) for x in r) for r in found] == [(3, 2, 3), (0, 0, 0), (0, 0, 0)]
    assert not any("]', ''" in share[k] for k in ("upper_case", "digits", "punctuation"))  # runs go at once


@pytest.mark.parametrize("bins", [5, 64])
def test_a_task_sums_up_the_smaller_part_of_a_node(bins, monkeypatch):
    rng, n = np.random.default_rng(bins), 40_000
    places = rng.integers(0, bins + 1, (4, n)).astype(np.uint8)
    places[1] //= bins
    g = rng.integers(-boost.UNIT, boost.UNIT, n)
    g[rng.random(n) < 0.1] = boost.LEFT_OUT
    codes, summed = Codes(places, bins + 1), []
    sums = boost.HeldRows.sums
    monkeypatch.setattr(boost.HeldRows, "sums", lambda self, rows: summed.append(len(rows)) or sums(self, rows))
    assert len(codes.groups) < 4
    held, tree, nodes = boost.HeldRows(codes, g), Tree(), [0]
    for level in range(4):
        before, router = len(summed), Router(tree, 4, bins)
        at = np.where(g == boost.LEFT_OUT, -1, router.ids[router.order][router.place(places.astype(np.intp))])
        for node, found, counts in held.level(tree, nodes):
            own = at == node
            for k in range(4):
                assert (counts[k] == np.bincount(places[k][own], minlength=bins + 1)).all()
                assert (found[k] == [g[own & (places[k] == b)].sum() for b in range(bins + 1)]).all()
        assert level == 0 or sum(summed[before:]) <= (g != boost.LEFT_OUT).sum() / 2
        nodes = [x.node for v in nodes for x in tree.split(v, level, int(rng.integers(bins - 1)) if level != 1 else 0, bool(rng.integers(2)))]
    routers = [Router(tree, 4, bins)] * 3
    assert (codes.margins(routers, 1000) == sum(r.values(places.astype(np.intp)) for r in routers)).all()


def test_workloads_over_the_same_lines_draw_once(spark, sf_dir, tmp_path, monkeypatch):
    small = {"epsilons": (1.0,), "trials": 2, "trees": 2, "max_depth": 2}
    for name in ("lineitem", "orders"):
        spark.read.parquet(f"{sf_dir}/{name}.parquet").where("o_orderkey % 5 > 0" if name == "orders" else "true").write.parquet(f"{tmp_path}/sf0.001/{name}.parquet")
    path, drawn = f"{tmp_path}/sf0.001", []  # some lines are without an order
    draw = boost.drawn_for
    monkeypatch.setattr(boost, "drawn_for", lambda *a: drawn.append(1) or draw(*a))
    both = experiments.sweeps(spark, path, ("w04", "w01"), **small).drop("seconds_per_tree").collect()
    assert len(drawn) == 1
    alone = [r for w in ("w04", "w01") for r in experiments.sweep(spark, path, w, **small).drop("seconds_per_tree").collect()]
    assert both == alone and len({r["n_test"] for r in alone}) == 2
    spark.read.parquet(f"{sf_dir}/orders.parquet").where("o_orderkey % 5 = 1").write.mode("append").parquet(f"{path}/orders.parquet")
    assert experiments.sweeps(spark, path, ("w01", "w04"), **small).count() == len(alone) and len(drawn) == 5


def test_draws_of_one_share_are_from_one_pass(spark):
    rows = spark.range(2000).select(F.col("id").cast("string").alias("row_key"))
    runs = [boost.BoostParams(trees=3 + k % 2, noise_key=f"k{k}", disjoint=k == 2) for k in range(4)]
    drawn = boost.drawn_for(rows, runs)
    assert drawn._jdf.queryExecution().optimizedPlan().toString().count("Range") == 2  # that of the disjoint one is another
    alone = [sampling.with_trees(rows, p.trees, p.subsample, p.noise_key) for p in runs if not p.disjoint]
    alone.insert(2, boost.drawn_for(rows, runs[2:3]).drop("draw"))
    each = [sorted(map(str, drawn.where(F.col("draw") == k).select("row_key", "tree_id").collect())) for k in range(4)]
    assert each == [sorted(map(str, x.select("row_key", "tree_id").collect())) for x in alone]


def test_trees_share_the_hashes_of_a_row(spark, monkeypatch):
    rows = spark.range(4000).select(F.when(F.col("id") % 1000 > 0, F.col("id").cast("string")).alias("row_key")).orderBy("row_key")
    ids, hashed = [r[0] and r[0].encode() for r in rows.collect()], []
    digests = sampling.digests_of
    monkeypatch.setattr(sampling, "digests_of", lambda key, ids: hashed.append(key) or digests(key, ids))
    key = lambda r: (str(r["row_key"]), r["tree_id"])
    for trees, share in ((20, 0.1), (45, 1 / 3), (3, 1.0), (3, 0.0)):
        at, tree = sampling.shared_rows(ids, trees, share, "k")
        drawn = sampling.with_draws(rows, [(0, trees, "k")], share, shared=True)
        assert sorted((str(ids[i] and ids[i].decode()), t) for i, t in zip(at, tree)) == sorted(map(key, drawn.collect()))
        assert (np.diff(tree) >= 0).all() and (trees > 20 or abs(len(at) / len(ids) / trees - share) < 0.01)
    assert hashed == ["k|samples|0", *(f"k|samples|{b}" for b in range(3)), "k|samples|0"]
    place, part = sampling.disjoint_rows(ids, [2, 1, 1], "k")
    assert sorted((str(ids[i] and ids[i].decode()), t) for i, t in zip(place, part)) == sorted(map(key, sampling.disjoint(rows, [2, 1, 1], "k").collect()))


def test_samples_that_tasks_draw_are_those_of_the_rows(spark, sf_dir):
    b = m.binned(spark, sf_dir).persist()
    runs = [replace(SMALL, shared_draws=True), replace(SMALL, disjoint=True), SMALL, replace(SMALL, shared_draws=True, noise_key="k1", subsample=0.3)]
    later = {k: p for k, p in enumerate(runs) if k != 2}
    assert boost.drawn_for(b, runs, later).count() == b.count() + boost.drawn_for(b, runs[2:3]).count()  # a pass for three draws
    assert nodes(spark, boost.fit_many(b, m.SPEC, runs)) == nodes(spark, boost.fit_many(b, m.SPEC, runs, materialized=False))
    b.unpersist()


def test_only_those_that_can_win_a_race_draw():
    rng = np.random.default_rng(4)
    for spread in (1, 30, 3000):
        weight, least = rng.random(300) * spread, 2.0**-53
        kept = in_race(weight)
        keys = race_keys(weight, np.full(300, 1 - least))  # the best that the others can draw
        keys[kept] = race_keys(weight[kept], np.full(len(kept), least))  # the worst
        assert len(kept) == 300 or np.delete(keys, kept).min() > keys[np.argmax(weight)]
    assert len(kept) < 20 and in_race(np.array([np.nan, 1.0])).tolist() == [0, 1]


def test_a_bench_computes_its_rows_once(spark, sf_dir):
    rows, read = experiments.for_tables(sf_dir)["w03"].rows(spark, sf_dir), spark.sparkContext.accumulator(0)

    def counted(batches):
        for batch in batches:
            read.add(batch.num_rows)
            yield batch

    few = experiments.Bench(spark, sf_dir, "w03", rows=rows)
    assert few.bins == 16 and few.n == rows.count() and few.binned.selectExpr("max(b_0)").first()[0] < 16
    few.close()
    many = rows.crossJoin(spark.range(120).select()).coalesce(1).mapInArrow(counted, rows.schema)
    bench = experiments.Bench(spark, sf_dir, "w03", rows=many)
    assert bench.bins == 64 and bench.binned.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism
    assert read.value == bench.n == bench.binned.count() == 120 * few.n >= 100_000
    bench.close()


def test_chunks_keep_targets_whole_and_classes_small():
    for y in (np.array([1.0, -1.0, 1.0]), np.array([0.25, -1.0, 1.0]), np.array([1.0, np.nan]), np.zeros(0)):
        packed = boost.packed_targets(y)
        assert np.array_equal(boost.targets_of(packed, len(y)), y, equal_nan=True) and (len(packed) == len(y)) == (np.abs(y) == 1).all()


def test_samples_are_bits_beside_rows_that_are_stored_once(spark, sf_dir):
    """160 samples of half of the rows are 80 times the rows; on disk they are a bit each beside them."""
    b, found = m.binned(spark, sf_dir), lambda: {x: x.stat().st_size for x in Path("/tmp/checkpoints").glob("grove-samples-*/**/*.parquet")}
    n, runs, before = b.count(), [replace(SMALL, trees=20, max_depth=1, shared_draws=True, noise_key=f"k{k}") for k in range(8)], found()
    fitted = boost.fit_many(b, m.SPEC, runs)
    assert len(fitted) == 8 and all(len(model.trees) == 20 for model, _, _ in fitted)
    assert 0 < sum(size for x, size in found().items() if x not in before) < 20 * n + n * (m.SPEC.m + 1) + 200_000 < 80 * n


def test_trees_of_a_job_are_those_of_few_rows(spark, sf_dir, monkeypatch):
    assert list(boost.windows([5, 5, 5, 20, 1, 9], 10)) == [range(2), range(2, 3), range(3, 4), range(4, 6)]
    assert boost.ways_to_part(5, 6) == 1 and boost.ways_to_part(1, 6) == 6 and boost.ways_to_part(10, 6) == 1 and boost.ways_to_part(4, 6) == 3
    b = m.binned(spark, sf_dir).persist()
    runs = [SMALL, replace(SMALL, noise_key="k1", trees=2), replace(SMALL, disjoint=True), replace(SMALL, shared_draws=True, trees=5), replace(SMALL, subsample=1e-9)]
    whole = nodes(spark, boost.fit_many(b, m.SPEC, runs))
    for most in (1, 3 * b.count()):
        monkeypatch.setattr(boost, "DEALT", most)
        used = cost.measured(spark, lambda: nodes(spark, boost.fit_many(b, m.SPEC, runs)) == whole or pytest.fail("other trees"))
        assert used["jobs"] > 5
    b.unpersist()
