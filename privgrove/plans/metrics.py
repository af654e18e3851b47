"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privgrove.operators.schema import TargetSpec


def error_pct(pred: DataFrame) -> DataFrame:
    """Share of rows, in percent, whose margin's sign is not the class."""
    wrong = (F.when(F.col("margin") >= 0, 1.0).otherwise(-1.0) != F.col("y")).cast("double")
    return pred.agg(F.round(100 * F.avg(wrong), 6).alias("error_pct"), F.count(F.lit(1)).alias("n"))


def rmse(pred: DataFrame, target: TargetSpec) -> DataFrame:
    """Root mean squared error in the target's own units."""
    half = (target.hi - target.lo) / 2
    limited = F.least(F.greatest(F.col("margin"), F.lit(-1.0)), F.lit(1.0))
    return pred.agg(F.round(F.sqrt(F.avg(((limited - F.col("y")) * half) ** 2)), 6).alias("rmse"), F.count(F.lit(1)).alias("n"))


def confusion(pred: DataFrame) -> DataFrame:
    """Counts of hits and misses per class."""
    up, yes = F.col("margin") >= 0, F.col("y") > 0
    return pred.agg(F.count_if(up & yes).alias("tp"), F.count_if(up & ~yes).alias("fp"), F.count_if(~up & yes).alias("fn"), F.count_if(~up & ~yes).alias("tn"))


def constant_baseline(train: DataFrame, test: DataFrame, classes: bool) -> DataFrame:
    """The floor: the majority class or the mean of the training rows as margin of every test row."""
    mean = train.agg(F.avg("y").alias("mean")).select((F.when(F.col("mean") >= 0, 1.0).otherwise(-1.0) if classes else F.col("mean")).alias("margin"))
    return test.crossJoin(F.broadcast(mean))


def noise_variance(scale: Column) -> Column:
    """Variance of Laplace noise."""
    return 2 * scale**2


def structure_score(stats: DataFrame, lam: float) -> DataFrame:
    """Minus half the sum over leaves (g, h) of squared gradient sums over regularised hessian sums."""
    return stats.agg(F.round(-0.5 * F.sum(F.col("g") ** 2 / (F.col("h") + lam)), 6).alias("structure_score"))


def objective(pred: DataFrame, leaf_squares: float, lam: float) -> DataFrame:
    """Regularised loss: half squared errors plus half lam times the squared leaf values."""
    return pred.agg(F.round(F.sum(0.5 * (F.col("margin") - F.col("y")) ** 2) + 0.5 * lam * leaf_squares, 6).alias("objective"))


def rank_error(hist: DataFrame, cuts: DataFrame, max_cuts: int) -> DataFrame:
    """Per feature: the largest weight between neighbouring cuts over an even share of it."""
    cut = cuts.select(F.col("feature"), F.col("cut_bin"))
    slot = hist.join(F.broadcast(cut), "feature", "left").groupBy("feature", "bin", "weight").agg(F.count_if(F.col("cut_bin") < F.col("bin")).alias("slot"))
    each = slot.groupBy("feature", "slot").agg(F.sum("weight").alias("w"))
    return each.groupBy("feature").agg(F.round(F.max("w") / F.sum("w") * (max_cuts + 1), 6).alias("worst_share"))


def trial_summary(trials: DataFrame, by: list[str], value: str) -> DataFrame:
    """Mean and standard deviation over trials."""
    return trials.groupBy(*by).agg(F.round(F.avg(value), 6).alias("mean"), F.round(F.coalesce(F.stddev(value), F.lit(0.0)), 6).alias("stddev"), F.count(F.lit(1)).alias("trials"))
