"""Baselines beside the switches of BoostParams: exact greedy search over all values."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from privgrove.operators.gradient import UNIT
from privgrove.operators.splits import gain


def exact_greedy(work: DataFrame, lam: float) -> DataFrame:
    """Every distinct value x of a feature as a cut, with the gain of x <= cut, for rows (x, g in fixed point).

    Values are summed before the running sums; those still go through one task per feature, which is why this search is a
    baseline for small tables.
    """
    values = work.where("x IS NOT NULL").groupBy("x").agg(F.sum("g").alias("g"), F.count(F.lit(1)).alias("n"))
    upto, whole = Window.orderBy("x"), Window.partitionBy()
    v = values.select("x", (F.sum("g").over(upto) / UNIT).alias("gl"), F.sum("n").over(upto).alias("nl"), (F.sum("g").over(whole) / UNIT).alias("gt"), F.sum("n").over(whole).alias("nt"))
    cuts = v.where(F.col("nl") < F.col("nt"))
    return cuts.withColumn("gain", gain(F.col("gl"), F.col("nl"), F.col("gt") - F.col("gl"), F.col("nt") - F.col("nl"), lam))
