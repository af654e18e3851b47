"""Static-bin histograms and their private release."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from privgrove.operators.mechanisms import laplace_release
from privgrove.operators.schema import DatasetSpec


def raw_histogram(binned: DataFrame, m: int, weight: str | None = None) -> DataFrame:
    """(feature, bin, weight) of present values: rows stay where they are, only counts are shuffled."""
    pairs = ", ".join(f"{k}, b_{k}" for k in range(m))
    w = f"CAST({weight} AS DOUBLE)" if weight else "CAST(1 AS DOUBLE)"
    long = binned.select(F.expr(f"stack({m}, {pairs}) AS (feature, bin)"), F.expr(f"{w} AS w"))
    return long.where("bin >= 0").groupBy("feature", "bin").agg(F.sum("w").alias("weight"))


def raw_histogram_sets(binned: DataFrame, m: int) -> DataFrame:
    """The same counts by one aggregation over grouping sets."""
    sets = ", ".join(f"(b_{k})" for k in range(m))
    names = ", ".join(f"b_{k}" for k in range(m))
    binned.createOrReplaceTempView("_grove_binned")
    one = binned.sparkSession.sql(f"SELECT {names}, grouping_id() AS gid, CAST(count(*) AS DOUBLE) AS weight FROM _grove_binned GROUP BY GROUPING SETS ({sets})")
    ids = {k: ((1 << m) - 1) ^ (1 << (m - 1 - k)) for k in range(m)}
    feature = F.coalesce(*[F.when(F.col("gid") == i, F.lit(k)) for k, i in ids.items()])
    bin_ = F.coalesce(*[F.when(F.col("gid") == i, F.col(f"b_{k}")) for k, i in ids.items()])
    return one.select(feature.alias("feature"), bin_.alias("bin"), "weight").where("bin >= 0")


def arrow_counts(m: int, bins: int, columns: Sequence[str]):
    """A mapInArrow function: one (feature, bin, weight) row per occupied cell and task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((m, bins + 1), np.int64)
        for batch in batches:
            for k, name in enumerate(columns):
                counts[k] += np.bincount(batch.column(name).to_numpy(zero_copy_only=False) + 1, minlength=bins + 1)
        feature, place = np.nonzero(counts[:, 1:])
        yield pa.RecordBatch.from_arrays([pa.array(feature.astype(np.int32)), pa.array(place.astype(np.int16)), pa.array(counts[feature, place + 1].astype(np.float64))], names=["feature", "bin", "weight"])

    return run


def raw_histogram_arrow(binned: DataFrame, m: int, bins: int) -> DataFrame:
    """The same counts with numpy partials: better for many features, as no row is multiplied."""
    cols = [f"b_{k}" for k in range(m)]
    part = binned.select(*cols).mapInArrow(arrow_counts(m, bins, cols), "feature int, bin smallint, weight double")
    return part.groupBy("feature", "bin").agg(F.sum("weight").alias("weight"))


def complete_grid(hist: DataFrame, spec: DatasetSpec, bins: int, point: str = "edge") -> DataFrame:
    """Every cell of the public grid, weight 0 where no row is, with its representative value."""
    spark = hist.sparkSession
    place = {"edge": 1.0, "mid": 0.5}[point]
    bounds = spark.createDataFrame([(k, float(f.lo), float(f.hi)) for k, f in enumerate(spec.features)], "feature int, lo double, hi double")
    grid = bounds.select("feature", "lo", "hi", F.explode(F.sequence(F.lit(0), F.lit(bins - 1))).alias("bin"))
    grid = grid.select("feature", "bin", (F.col("lo") + (F.col("bin") + place) * (F.col("hi") - F.col("lo")) / bins).alias("edge"))
    cells = hist.select(F.col("feature").cast("int"), F.col("bin").cast("int"), "weight")
    return grid.join(cells, ["feature", "bin"], "left").withColumn("weight", F.coalesce("weight", F.lit(0.0)))


def dp_feature_histogram(binned: DataFrame, spec: DatasetSpec, bins: int, epsilon: float, key: str, tree: int = 0, h_max: float = 1.0, point: str = "edge", weight: str | None = None) -> DataFrame:
    """DP_HIST: noised, clamped weight of every grid cell. epsilon is shared by all features, one share each."""
    grid = complete_grid(raw_histogram(binned, spec.m, weight), spec, bins, point)
    noised = laplace_release(grid, "weight", spec.m * h_max, epsilon, f"{key}|sketch|{tree}", ["feature", "bin"])
    return noised.withColumn("weight", F.greatest(F.col("weight"), F.lit(0.0)))


def dp_range(df: DataFrame, col: str, grid: Sequence[float], epsilon: float, threshold: float, key: str) -> DataFrame:
    """Private bounds: noised counts on a public grid of edges; the outermost cells above the threshold."""
    edges = [float(g) for g in grid]
    cell = sum(((F.col(col) > e).cast("int") for e in edges[1:-1]), F.lit(0))
    counts = df.where(F.col(col).isNotNull()).groupBy(cell.alias("cell")).agg(F.count(F.lit(1)).alias("n"))
    cells = df.sparkSession.createDataFrame([(k, edges[k], edges[k + 1]) for k in range(len(edges) - 1)], "cell int, lo double, hi double")
    full = cells.join(counts, "cell", "left").withColumn("n", F.coalesce("n", F.lit(0)).cast("double"))
    noised = laplace_release(full, "n", 1.0, epsilon, key, ["cell"])
    return noised.where(F.col("n") > threshold).agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))


