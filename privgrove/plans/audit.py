"""Empirical privacy: how far a mechanism's outcomes on two neighbouring tables are apart, over many keys."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from privgrove.functions.noise import laplace, race_key, uniform


def empirical_epsilon(spark: SparkSession, mechanism, one: float | list[float], other: float | list[float], runs: int | DataFrame = 200_000, least: int = 100) -> DataFrame:
    """(bucket, n_one, n_other, log_ratio, error): outcomes of mechanism(value, key) -> Column on two inputs.

    Every run has a key of its own, so the two sides draw independently; a table of `runs` has them in its column id. Only buckets with `least` outcomes on either
    side count; error is two standard errors of the log ratio.
    """
    base = spark.range(runs) if isinstance(runs, int) else runs
    sides = [base.select(mechanism(v, F.concat_ws("|", F.lit(tag), F.col("id").cast("string"))).alias("bucket")).groupBy("bucket").agg(F.count(F.lit(1)).alias(f"n_{tag}")) for tag, v in (("one", one), ("other", other))]
    both = sides[0].join(sides[1], "bucket").where((F.col("n_one") >= least) & (F.col("n_other") >= least))
    ratio = F.ln(F.col("n_one") / F.col("n_other"))
    return both.select("bucket", "n_one", "n_other", F.abs(ratio).alias("log_ratio"), (2 * F.sqrt(1 / F.col("n_one") + 1 / F.col("n_other"))).alias("error"))


def laplace_count(epsilon: float, width: float = 1.0):
    """A noisy count, in buckets."""
    return lambda value, key: F.floor((F.lit(float(value)) + laplace(uniform("audit", key), 1 / epsilon)) / width)


def exponential_of(epsilon: float, sensitivity: float):
    """The candidate that wins a race over given utilities."""

    def run(utilities: list[float], key: Column) -> Column:
        keys = [race_key(F.lit(u * epsilon / (2 * sensitivity)), uniform("audit", key, F.lit(str(k)))) for k, u in enumerate(utilities)]
        best = F.least(*keys)
        return F.coalesce(*[F.when(k == best, F.lit(i)) for i, k in enumerate(keys)])

    return run


def noisy_average(epsilon: float, lam: float = 0.1, g_star: float = 1.0, width: float = 0.05):
    """The noisy average with an exact count, for (sum, count) inputs."""
    return lambda sn, key: F.floor(F.greatest(F.least((F.lit(float(sn[0])) + laplace(uniform("audit", key), 2 * g_star / epsilon)) / (sn[1] + lam), F.lit(g_star)), F.lit(-g_star)) / width)


def average_charge_bound(epsilon: float, n: int, lam: float) -> float:
    """What a noisy average over n rows can cost at most: the exact count adds to the sum's epsilon."""
    return epsilon + math.log((n + 1 + lam) / (n + lam))
