"""Laplace and exponential mechanisms on DataFrames, and private aggregates for users."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from privgrove.functions.noise import laplace, race_key, uniform


def laplace_release(df: DataFrame, col: str, sensitivity: float, epsilon: float, key: str, ids: Sequence[str], out: str | None = None) -> DataFrame:
    """Add keyed Laplace noise of scale sensitivity / epsilon to a column; ids name each row's draw."""
    scale = sensitivity / epsilon if epsilon != float("inf") else 0.0
    noised = F.col(col).cast("double") + (laplace(uniform(key, *ids), scale) if scale else F.lit(0.0))
    return df.withColumn(out or col, noised)


def exponential_choice(df: DataFrame, group: Sequence[str], utility: Column, sensitivity: float, epsilon: float, key: str, ids: Sequence[str], factor: float = 2.0) -> DataFrame:
    """One row per group, chosen with probability in proportion to exp(epsilon * utility / (factor * sensitivity)).

    A race of keyed draws with min_by: one aggregation that combines before its shuffle, no normaliser. factor=1 is the
    form without the half in the exponent, which costs twice epsilon unless the utility is monotone.
    """
    raced = df.withColumn("_race", race_key(utility * (epsilon / (factor * sensitivity)), uniform(key, *group, *ids)))
    row = F.struct(*[F.col(c) for c in df.columns if c not in group])
    best = raced.groupBy(*group).agg(F.min_by(row, F.struct("_race", *ids)).alias("_row"))
    return best.select(*group, "_row.*")


def bound_contribution(df: DataFrame, unit: str, cap: int, key: str, ids: Sequence[str]) -> DataFrame:
    """At most `cap` rows of each unit, the ones with the smallest keyed draws."""
    order = Window.partitionBy(unit).orderBy(uniform(key, *ids), *ids)
    return df.withColumn("_n", F.row_number().over(order)).where(F.col("_n") <= cap).drop("_n")


def dp_count(df: DataFrame, epsilon: float, key: str) -> DataFrame:
    one = df.agg(F.count(F.lit(1)).alias("n")).withColumn("q", F.lit("count"))
    return laplace_release(one, "n", 1.0, epsilon, key, ["q"]).select("n")


def dp_sum(df: DataFrame, col: str, lo: float, hi: float, epsilon: float, key: str) -> DataFrame:
    """A sum of values clipped to the public bounds."""
    clipped = F.least(F.greatest(F.col(col).cast("double"), F.lit(lo)), F.lit(hi))
    one = df.agg(F.coalesce(F.sum(clipped), F.lit(0.0)).alias("s")).withColumn("q", F.lit("sum"))
    return laplace_release(one, "s", max(abs(lo), abs(hi)), epsilon, key, ["q"]).select("s")


def dp_mean(df: DataFrame, col: str, lo: float, hi: float, epsilon: float, key: str) -> DataFrame:
    """Noisy sum over noisy count, half of epsilon each, limited to the bounds."""
    s = dp_sum(df, col, lo, hi, epsilon / 2, key)
    n = dp_count(df.where(F.col(col).isNotNull()), epsilon / 2, key)
    mean = F.col("s") / F.greatest(F.col("n"), F.lit(1.0))
    return s.crossJoin(n).select(F.least(F.greatest(mean, F.lit(lo)), F.lit(hi)).alias("mean"))


def dp_group_count(df: DataFrame, by: str, keys: Sequence[object], epsilon: float, key: str) -> DataFrame:
    """Noisy counts over a public list of keys; absent keys get noise as well."""
    public = df.sparkSession.createDataFrame([(k,) for k in keys], f"{by} {df.schema[by].dataType.simpleString()}")
    counts = df.groupBy(by).agg(F.count(F.lit(1)).alias("n"))
    full = F.broadcast(public).join(counts, by, "left").withColumn("n", F.coalesce("n", F.lit(0)))
    return laplace_release(full, "n", 1.0, epsilon, key, [by])
