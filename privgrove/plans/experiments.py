"""Experiments: fit a workload's model in its variants and measure them on the held-out rows."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import asdict, dataclass, replace
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privgrove.operators import sketch
from privgrove.operators.sampling import is_test
from privgrove.plans import cost, metrics
from privgrove.plans.boost import BoostParams, Target, coarser, fit_many, fit_targets
from privgrove.plans.tree import Router, TreeModel, places_of
from privgrove.plans.workloads import Workload, for_tables
from privgrove.sources.io import freed, load, stored

#: Budgets of the result table, and how often a trial is repeated with another key.
EPSILONS, TRIALS = (1.0, 2.0, 4.0, 6.0, 8.0, 10.0), 5


@dataclass
class Run:
    """One fitted model with its measures."""

    workload: str
    variant: str
    epsilon: float
    trial: int
    measure: str
    value: float
    n_test: int
    spent: float
    seconds_per_tree: float


class Bench:
    """A workload's train and test rows in static bins, stored for all runs over it."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, bins: int | None = None, bins_by: str = "even", rows: DataFrame | None = None):
        """Bins are even over the public bounds, or lie between the data's quantiles (`sketch`) or between all of its
        values (`exact`, for small tables); only a model without privacy may use the data's. `rows` are the workload's,
        where benches share them."""
        self.work: Workload = for_tables(sf_dir)[name]
        rows = self.work.rows(spark, sf_dir) if rows is None else rows
        spec = self.work.spec
        self.bins_by = bins_by
        if bins_by == "even":  # rows are counted in the bins of a large table, which stay if it is one
            self.bins = bins or self.work.bins[1]
            self.binned, self.n = held(spec.binned(rows, self.bins))
            self.settings = self.work.settings(self.n)
            if not bins and self.bins != self.settings["bins"]:
                self.bins = self.settings["bins"]
                self.binned, _ = held(spec.binned(rows, self.bins))
        else:
            self.n = rows.count()
            self.settings = self.work.settings(self.n)
            cuts = sketched_cuts(rows.where(~is_test()), spec.m, (bins or self.settings["bins"]) - 1) if bins_by == "sketch" else all_cuts(rows.where(~is_test()), spec.m)
            self.bins = 1 + max(map(len, cuts.values()), default=0)
            self.binned, _ = held(spec.binned_at(rows, cuts))
        self.train = self.binned.where("NOT test").drop("test")
        self.test = self.binned.where("test").drop("test")

    @classmethod
    def of(cls, work: Workload, binned: DataFrame, n: int, bins: int, fitted: Callable[[list[BoostParams]], list]) -> Bench:
        """Of rows in even bins with `test`, that another holds, and fits."""
        self = cls.__new__(cls)
        self.fitted = fitted
        self.work, self.n, self.settings, self.bins, self.bins_by, self.binned = work, n, work.settings(n), bins, "even", binned
        self.train, self.test = binned.where("NOT test").drop("test"), binned.where("test").drop("test")
        return self

    def params(self, **changes) -> BoostParams:
        return BoostParams(**({"min_child": self.settings["min_child"], "bins": self.bins, "shared_draws": True} | changes))

    def measure(self, scored: DataFrame) -> tuple[str, float, int]:
        if self.work.classes:
            value, n = metrics.error_pct(scored).first()
            return "error_pct", value, n
        value, n = metrics.rmse(scored, self.work.spec.target).first()
        return "rmse", value, n

    def measures(self, models: list[TreeModel]) -> list[tuple[str, float, int]]:
        """The same measure of every model, from one pass over the test rows."""
        m, classes, target = self.work.spec.m, self.work.classes, self.work.spec.target
        packed = self.test.sparkSession.sparkContext.broadcast([[Router(t, m, x.bins) for t in x.trees] for x in models])
        shifts = [(self.bins // x.bins).bit_length() - 1 for x in models]
        half = (target.hi - target.lo) / 2

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            scored = packed.value
            loss, n = np.zeros(len(scored)), 0
            for batch in batches:
                whole, y = places_of(batch, m), batch.column("y").to_numpy()
                n += len(y)
                by_shift = {x: coarser(whole, x) for x in set(shifts)}
                for k, trees in enumerate(scored):
                    margin = sum((r.values(by_shift[shifts[k]]) for r in trees), np.zeros(len(y)))
                    loss[k] += (np.where(margin >= 0, 1.0, -1.0) != y).sum() if classes else (((np.clip(margin, -1, 1) - y) * half) ** 2).sum()
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(scored))), pa.array(loss), pa.array(np.full(len(scored), n))], names=["k", "loss", "n"])

        sums = {r["k"]: (r["loss"], r["n"]) for r in self.test.mapInArrow(run, "k long, loss double, n long").groupBy("k").agg(F.sum("loss").alias("loss"), F.sum("n").alias("n")).collect()}
        packed.destroy()
        mean = [sums[k][0] / max(sums[k][1], 1) for k in range(len(models))]
        return [("error_pct", round(100 * x, 6), sums[k][1]) if classes else ("rmse", round(x**0.5, 6), sums[k][1]) for k, x in enumerate(mean)]

    def run_many(self, asked: list[tuple[str, BoostParams, int]]) -> list[Run]:
        """Fit and measure (variant, params, trial), all in step."""
        if self.bins_by != "even" and any(p.private for _, p, _ in asked):
            raise ValueError("bins that come from the data are not private")
        fitted = self.fitted([p for _, p, _ in asked])
        found = self.measures([model for model, _, _ in fitted])
        free = float("inf")
        return [
            Run(self.work.name, variant, p.epsilon_total if p.private else free, trial, measure, value, n, ledger.total() if p.private else free, sum(seconds) / len(seconds))
            for (variant, p, trial), (_, ledger, seconds), (measure, value, n) in zip(asked, fitted, found)
        ]

    def fitted(self, runs: list[BoostParams]) -> list:
        return fit_many(self.train, self.work.spec, runs, bins=self.bins)

    def run(self, variant: str, params: BoostParams, trial: int = 0) -> Run:
        return self.run_many([(variant, params, trial)])[0]

    def floor(self) -> Run:
        """The constant predictor."""
        measure, value, n = self.measure(metrics.constant_baseline(self.train, self.test, self.work.classes))
        return Run(self.work.name, "constant", 0.0, 0, measure, value, n, 0.0, 0.0)

    def close(self) -> None:
        self.binned.unpersist()


def held(binned: DataFrame) -> tuple[DataFrame, int]:
    """(BINNED rows with `test`, stored in as many parts as there are cores at least, their number)."""
    spark = binned.sparkSession
    ways, kept = spark.sparkContext.defaultParallelism, stored(binned.withColumn("test", is_test()), "rows")
    n = kept.count()
    if len(kept.inputFiles()) < ways:
        kept = stored(kept.repartition(ways), "rows")
    freed(spark)
    return kept, n


def precursor(params: BoostParams) -> BoostParams:
    """The earlier private trees: cuts from the data itself, half of the budget to the leaves and half to the splits,
    geometric leaf clipping, trees on disjoint rows, no minimum child."""
    return replace(params, proposal_noise=False, shares=(0.0, 0.5, 0.5), leaf_mode="geometric", min_child=1, disjoint=True)


def by_feature(cuts: DataFrame) -> dict[int, list[float]]:
    part = cuts.select(F.col("feature").cast("int").alias("feature"), "cut").toArrow()  # bounded by features times bins
    feature, cut = part["feature"].to_numpy(), part["cut"].to_numpy()
    return {int(k): np.sort(cut[feature == k]).tolist() for k in np.unique(feature)}


def sketched_cuts(rows: DataFrame, m: int, cuts: int) -> dict[int, list[float]]:
    """Cuts per feature at even shares of its values."""
    return by_feature(sketch.propose(rows, m, cuts).select("feature", "cut"))


def all_cuts(rows: DataFrame, m: int, most: int | None = None) -> dict[int, list[float]]:
    """Every value of each feature as a cut, as exact greedy search tries them; refuses features with more than `most`, where
    that is given. All values meet on the driver, eight bytes each."""
    pairs = ", ".join(f"{k}, x_{k}" for k in range(m))
    values = rows.select(F.expr(f"stack({m}, {pairs}) AS (feature, cut)")).where("cut IS NOT NULL").distinct()
    if most is not None and values.groupBy("feature").count().where(F.col("count") > most).count():
        raise ValueError(f"exact greedy search is for features of at most {most} values")
    return by_feature(values)


def table(spark: SparkSession, runs: list[Run]) -> DataFrame:
    schema = "workload string, variant string, epsilon double, trial int, measure string, value double, n_test long, spent double, seconds_per_tree double"
    return spark.createDataFrame([tuple(asdict(r).values()) for r in runs], schema)


#: Benches of a study that are at work at a time: the jobs of one fill the cores that another's leave idle.
AT_ONCE = 3


def side_by_side(parts: list[Callable[[], list[Run]]]) -> list[Run]:
    """The runs of all parts, in their order."""
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return [run for runs in pool.map(lambda part: part(), parts) for run in runs]


def sweep_runs(spark: SparkSession, sf_dir: str, name: str, epsilons=EPSILONS, trials: int = TRIALS, **changes) -> list[Run]:
    bench = Bench(spark, sf_dir, name)
    runs = [bench.floor(), *bench.run_many(swept(bench, epsilons, trials, **changes))]
    bench.close()
    return runs


def swept(bench: Bench, epsilons=EPSILONS, trials: int = TRIALS, **changes) -> list[tuple[str, BoostParams, int]]:
    asked = [("open", bench.params(noise_key=f"k{t}", **changes).open(), t) for t in range(trials)]
    return asked + [("private", bench.params(epsilon_total=eps, noise_key=f"k{t}", **changes), t) for eps in epsilons for t in range(trials)]


#: Two workloads over the same lines; the first has all features of the second, and only lines with an order.
SAME_LINES = ("w01", "w04")


def same_lines_runs(spark: SparkSession, sf_dir: str, **changes) -> list[Run]:
    """The sweeps of both, whose equal samples are drawn once: from lines with the targets of both, where the first's is
    null without an order. Where orders repeat or the two sizes have other bins, each has its own."""
    works = [for_tables(sf_dir)[name] for name in SAME_LINES]
    wide, narrow = (work.spec for work in works)
    lines, orders = (load(spark, sf_dir, t) for t in works[0].tables)
    o = orders.select("o_orderkey", "o_totalprice", "o_orderdate")
    both = lines.join(o, lines.l_orderkey == o.o_orderkey, "left")
    ys = {"y_0": F.when(F.col("o_orderkey").isNotNull(), wide.target.column()), "y_1": narrow.target.column()}
    rows = both.select(F.expr(wide.row_key).cast("string").alias("row_key"), *[f.column().alias(f"x_{k}") for k, f in enumerate(wide.features)], F.struct(*[y.alias(k) for k, y in ys.items()]).alias("y"))
    kept = lambda bins: held(wide.binned(rows, bins).select("*", "y.*").drop("y"))
    bins = works[0].bins[1]
    binned, n = kept(bins)  # rows are counted in the bins of a large table, which stay if it is one
    sizes = list(binned.agg(*[F.count(k) for k in ys]).first())
    settings = [work.settings(k) for work, k in zip(works, sizes)]
    if n != lines.count() or settings[1]["bins"] != settings[0]["bins"]:
        return [run for name in SAME_LINES for run in sweep_runs(spark, sf_dir, name, **changes)]
    if bins != settings[0]["bins"]:
        bins = settings[0]["bins"]
        binned, _ = kept(bins)
    features = [list(range(wide.m)), [wide.features.index(f) for f in narrow.features]]
    asked, models = [], []

    def fitted(i: int, runs: list[BoostParams]) -> list:
        """One's models, with those of the other."""
        if not models:
            targets = [Target(work.spec, [p for _, p, _ in each], own, y) for work, each, own, y in zip(works, asked, features, ys)]
            models.extend(fit_targets(binned.where("NOT test").drop("test"), targets, bins=bins))
        return models[i]

    benches = [
        Bench.of(work, binned.select("row_key", *[F.col(f"b_{k}").alias(f"b_{i}") for i, k in enumerate(own)], F.col(y).alias("y"), "test").where("y IS NOT NULL"), size, bins, partial(fitted, i))
        for i, (work, own, y, size) in enumerate(zip(works, features, ys, sizes))
    ]
    asked.extend(swept(bench, **changes) for bench in benches)
    return [run for bench, each in zip(benches, asked) for run in (bench.floor(), *bench.run_many(each))]


def sweep(spark: SparkSession, sf_dir: str, name: str, epsilons=EPSILONS, trials: int = TRIALS, **changes) -> DataFrame:
    """Error of the private model by budget and trial, with the open model and the constant."""
    return table(spark, sweep_runs(spark, sf_dir, name, epsilons, trials, **changes))


def sweeps(spark: SparkSession, sf_dir: str, names: tuple[str, ...], **changes) -> DataFrame:
    """The sweeps of several workloads."""
    alone = [name for name in names if not set(SAME_LINES) <= set(names) or name not in SAME_LINES]
    together = [partial(same_lines_runs, spark, sf_dir, **changes)] if len(alone) < len(names) else []
    runs = side_by_side([*together, *[partial(sweep_runs, spark, sf_dir, name, **changes) for name in alone]])
    return table(spark, sorted(runs, key=lambda run: names.index(run.workload)))


def open_models(spark: SparkSession, sf_dir: str, name: str, trials: int = TRIALS, ways: tuple[str, ...] = ("even", "sketch", "exact"), **changes) -> DataFrame:
    """The model without privacy over even bins, over the data's quantiles, and by exact greedy search over all values."""
    shared = None
    if "exact" in ways:  # a small table; its features may be long to compute
        shared = for_tables(sf_dir)[name].rows(spark, sf_dir).persist(StorageLevel.MEMORY_AND_DISK)
        shared.count()

    def part(way: str) -> list[Run]:
        bench = Bench(spark, sf_dir, name, bins_by=way) if shared is None else Bench(spark, sf_dir, name, bins_by=way, rows=shared)
        each = [bench.params(noise_key=f"k{t}", **changes).open() for t in range(trials)]
        every = max(bench.bins, getattr(bench, "n", 0))  # so many even shares that no value in a sample is without a cut
        runs = bench.run_many([(f"open_{way}", replace(p, max_cuts=every) if way == "exact" else p, t) for t, p in enumerate(each)])
        bench.close()
        return runs

    runs = side_by_side([partial(part, way) for way in ways])
    if shared is not None:
        shared.unpersist()
    return table(spark, runs)


def against_precursor(spark: SparkSession, sf_dir: str, names: str | tuple[str, ...], epsilons=(1.0, 10.0), trials: int = 1, **changes) -> DataFrame:
    def part(name: str) -> list[Run]:
        bench = Bench(spark, sf_dir, name)
        each = [(t, bench.params(epsilon_total=eps, noise_key=f"k{t}", **changes)) for eps in epsilons for t in range(trials)]
        runs = bench.run_many([x for t, p in each for x in (("private", p, t), ("precursor", precursor(p), t))])
        bench.close()
        return runs

    return table(spark, side_by_side([partial(part, name) for name in ([names] if isinstance(names, str) else names)]))


def leaf_study(spark: SparkSession, sf_dir: str, name: str = "w01", epsilon: float = 1.0, children: tuple[int, int] = (200, 600), trials: int = TRIALS, **changes) -> DataFrame:
    """Leaf-noise strategies: clipped baseline, two minimum child sizes, noisy average."""
    bench = Bench(spark, sf_dir, name)
    asked = []
    for t in range(trials):
        p = bench.params(epsilon_total=epsilon, noise_key=f"k{t}", **changes)
        asked += [("clipped", replace(p, leaf_mode="geometric", min_child=1), t), ("noisy_average", replace(p, leaf_mode="noisy_average"), t)]
        asked += [(f"min_child_{c}", replace(p, leaf_mode="min_child", min_child=c), t) for c in children]
    runs = bench.run_many(asked)
    bench.close()
    return table(spark, runs)


def bin_study(spark: SparkSession, sf_dir: str, name: str = "w01", epsilon: float = 1.0, bins=(8, 16, 32, 64, 128, 256, 512), trials: int = TRIALS, **changes) -> DataFrame:
    """Private against data-exact cuts at several bin counts, everything else equal."""

    groups: list[list[int]] = []
    for b in sorted(bins, reverse=True):  # rows in the finest even bins serve those that are a power of two wider
        group = next((x for x in groups if x[0] % b == 0 and (x[0] // b).bit_count() == 1), None)
        group.append(b) if group else groups.append([b])

    def part(group: list[int]) -> list[Run]:
        bench = Bench(spark, sf_dir, name, group[0])
        asked = []
        for b in sorted(group):
            for t in range(trials):
                p = bench.params(epsilon_total=epsilon, noise_key=f"k{t}", **{**changes, "bins": b})
                asked += [(f"noised_{b}", p, t), (f"exact_{b}", replace(p, proposal_noise=False), t)]
        runs = bench.run_many(asked)
        bench.close()
        return runs

    return table(spark, side_by_side([partial(part, group) for group in groups]))


def runtime(spark: SparkSession, sf_dir: str, name: str = "w01", **changes) -> DataFrame:
    """Seconds per tree of the private and the open model."""
    bench = Bench(spark, sf_dir, name)
    p = bench.params(**changes)
    runs = [bench.run("warm-up", replace(p, trees=2)), bench.run("private", p), bench.run("open", p.open())]
    bench.close()
    return table(spark, runs[1:])


def engine_cost(spark: SparkSession, sf_dir: str, name: str = "w01", trees: int = 4, together: int = 8, **changes) -> DataFrame:
    """What training costs the engine: jobs, tasks, bytes and shuffled rows of a private and an open model, and of several
    in step; with the most rows that its tasks may shuffle, the cells of a level each."""
    bench = Bench(spark, sf_dir, name)
    p = bench.params(trees=trees, **changes)
    runs = {"private": [p], "open": [p.open()], f"private_x{together}": [replace(p, noise_key=f"k{k}") for k in range(together)]}
    rows = [(k, trees, len(v), *cost.measured(spark, lambda v=v: fit_many(bench.train, bench.work.spec, v)).values()) for k, v in runs.items()]
    cells = bench.work.spec.m * (bench.bins + 1) * 2 ** max(0, p.max_depth - 1)  # of the last level: of two children one is summed
    bench.close()
    out = spark.createDataFrame(rows, "variant string, trees int, models int, jobs long, tasks long, input_bytes long, shuffle_records long, shuffle_bytes long, seconds double")
    return out.withColumn("most_records", F.col("tasks") * F.col("models") * F.lit(cells))


def means(runs: DataFrame) -> DataFrame:
    """The result table: mean and standard deviation over trials by workload, variant and budget."""
    return metrics.trial_summary(runs, ["workload", "variant", "epsilon", "measure"], "value")
