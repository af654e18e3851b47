"""Candidate cuts: from weighted bins, from raw values, and by a joint private choice."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from privgrove.functions.noise import race_keys, uniform_of


def from_weighted_bins(hist: DataFrame, max_cuts: int) -> DataFrame:
    """CUTS (feature, slot, cut_bin, cut): for each of max_cuts even shares of a feature's weight, the first edge whose
    running weight reaches it; equal ones once, the last edge never. A feature without weight gets even edges."""
    running = Window.partitionBy("feature").orderBy("bin")
    whole = Window.partitionBy("feature")
    h = hist.withColumn("total", F.sum("weight").over(whole)).withColumn("bins", F.count(F.lit(1)).over(whole))
    h = h.withColumn("w", F.when(F.col("total") > 0, F.col("weight")).otherwise(F.lit(1.0)))
    h = h.withColumn("total", F.when(F.col("total") > 0, F.col("total")).otherwise(F.col("bins").cast("double")))
    step = F.col("total") / (max_cuts + 1)
    reached = lambda c: F.floor(F.round(c / step, 9))
    h = h.withColumn("upto", F.sum("w").over(running)).withColumn("mark", F.least(reached(F.col("upto")), F.lit(max_cuts)))
    h = h.withColumn("before", F.coalesce(F.lag("mark").over(running), F.lit(0)))
    picked = h.where((F.col("mark") > F.col("before")) & (F.col("bin") < F.col("bins") - 1))
    slot = F.row_number().over(running) - 1
    return picked.select("feature", slot.cast("int").alias("slot"), F.col("bin").cast("int").alias("cut_bin"), F.col("edge").alias("cut"))


def cuts_of(weights: np.ndarray, max_cuts: int) -> np.ndarray:
    """The same choice for one feature's bin weights on the driver."""
    w = weights if weights.sum() > 0 else np.ones_like(weights)
    mark = np.minimum(np.floor(np.round(np.cumsum(w) / (w.sum() / (max_cuts + 1)), 9)), max_cuts)
    picked = np.flatnonzero(mark > np.concatenate(([0], mark[:-1])))
    return picked[picked < len(w) - 1]


def from_percentiles(rows: DataFrame, m: int, max_cuts: int, accuracy: int = 10_000) -> DataFrame:
    """Cuts from values by Spark's mergeable percentile summary; for the non-private model."""
    shares = [k / (max_cuts + 1) for k in range(1, max_cuts + 1)]
    row = rows.agg(*[F.percentile_approx(f"x_{k}", shares, accuracy).alias(f"q_{k}") for k in range(m)])
    pairs = ", ".join(f"{k}, q_{k}" for k in range(m))
    long = row.select(F.expr(f"stack({m}, {pairs}) AS (feature, q)")).select("feature", F.explode(F.array_sort(F.array_distinct("q"))).alias("cut"))
    return long.select("feature", (F.row_number().over(Window.partitionBy("feature").orderBy("cut")) - 1).cast("int").alias("slot"), "cut")


def joint_quantiles(weights: np.ndarray, count: int, epsilon: float, key: str, feature: int = 0) -> list[int]:
    """`count` cut bins of one feature chosen together by an exponential mechanism on a static grid.

    The utility is minus the sum of the gaps between the rows in each stretch and an even share; one record more or less
    changes it by 2 at most. Forward sums over grid places and backward draws sample from all increasing tuples.
    """
    bins = len(weights)
    upto = np.concatenate(([0.0], np.cumsum(weights)))
    share = upto[-1] / (count + 1)
    if count > bins - 1:
        raise ValueError("more cuts than edges")

    def step(a: np.ndarray, b: int) -> np.ndarray:
        return -epsilon / 4 * np.abs(upto[b + 1] - upto[a + 1] - share)

    level = np.array([step(np.array([-1]), b)[0] for b in range(bins - 1)])
    levels = [level]
    for _ in range(count - 1):
        nxt = np.full(bins - 1, -np.inf)
        for b in range(1, bins - 1):
            x = level[:b] + step(np.arange(b), b)
            top = x.max()
            nxt[b] = top + math.log(np.exp(x - top).sum()) if np.isfinite(top) else -np.inf
        level = nxt
        levels.append(level)
    out, last = [], bins - 1
    for k in range(count - 1, -1, -1):
        end = step(np.arange(min(last, bins - 1)), last)
        log = levels[k][: len(end)] + end
        u = np.array([uniform_of(key, "joint", feature, k, b) for b in range(len(log))])
        last = int(np.argmin(race_keys(log, u)))
        out.append(last)
    return out[::-1]
