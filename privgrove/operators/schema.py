"""Declared datasets: features with public bounds, a target with a public range, a row key."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class FeatureSpec:
    """A numeric feature; lo and hi are public, or a private release of their own."""

    name: str
    expr: str
    lo: float
    hi: float
    nullable: bool = True
    sparse_zero: bool = False

    def column(self) -> Column:
        value = F.expr(self.expr).cast("double")
        value = F.when(~F.isnan(value), value)
        return F.when(value != 0, value) if self.sparse_zero else value


@dataclass(frozen=True)
class TargetSpec:
    """The target; [lo, hi] goes to [-1, 1]. Classes are -1 and 1 already."""

    expr: str
    lo: float = -1.0
    hi: float = 1.0
    kind: str = "regression"

    def column(self) -> Column:
        y = F.expr(self.expr).cast("double")
        return F.least(F.greatest(2 * (y - self.lo) / (self.hi - self.lo) - 1, F.lit(-1.0)), F.lit(1.0))


@dataclass(frozen=True)
class DatasetSpec:
    row_key: str
    features: tuple[FeatureSpec, ...]
    target: TargetSpec

    @property
    def m(self) -> int:
        return len(self.features)

    def encode(self, df: DataFrame) -> DataFrame:
        """ROWS: row_key, x_0.., y. Everything else is pruned at the scan."""
        xs = [f.column().alias(f"x_{k}") for k, f in enumerate(self.features)]
        return df.select(F.expr(self.row_key).cast("string").alias("row_key"), *xs, self.target.column().alias("y")).where("y IS NOT NULL")

    def binned(self, rows: DataFrame, bins: int) -> DataFrame:
        """BINNED: static bins that depend on public bounds only, so one pass serves all trees."""
        cols = [static_bin(F.col(f"x_{k}"), f.lo, f.hi, bins).alias(f"b_{k}") for k, f in enumerate(self.features)]
        return rows.select("row_key", *cols, "y")

    def binned_at(self, rows: DataFrame, cuts: dict[int, list[float]]) -> DataFrame:
        """Bins between cuts that come from the data, for a model that is not private: right-closed, -1 where x is missing."""
        m, edges = self.m, [np.array(sorted(cuts.get(k, []))) for k in range(self.m)]
        kind, name = (np.int16, "smallint") if max(map(len, edges), default=0) < 1 << 15 else (np.int32, "int")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                xs = [batch.column(f"x_{k}").to_numpy(zero_copy_only=False).astype(np.float64) for k in range(m)]
                bins = [np.where(np.isnan(x), -1, np.searchsorted(e, x, "left")).astype(kind) for x, e in zip(xs, edges)]
                yield pa.RecordBatch.from_arrays([batch.column("row_key"), *map(pa.array, bins), batch.column("y")], names=["row_key", *(f"b_{k}" for k in range(m)), "y"])

        columns = [F.col(f"x_{k}").cast("double").alias(f"x_{k}") for k in range(m)]
        return rows.select("row_key", *columns, F.col("y").cast("double").alias("y")).mapInArrow(run, ", ".join(["row_key string", *(f"b_{k} {name}" for k in range(m)), "y double"]))

    def edge(self, feature: int, b: int, bins: int) -> float:
        f = self.features[feature]
        return f.lo + (b + 1) * (f.hi - f.lo) / bins


def static_bin(x: Column, lo: float, hi: float, bins: int) -> Column:
    """Right-closed equal-width bin of x, limited to the ends; -1 where x is missing."""
    place = F.ceil((x - lo) / (hi - lo) * bins) - 1
    return F.coalesce(F.least(F.greatest(place, F.lit(0)), F.lit(bins - 1)), F.lit(-1)).cast("smallint")


def onehot(col: str, values: list[str], lo: float = 0.0, hi: float = 1.0) -> list[FeatureSpec]:
    """One feature per value of a public dictionary."""
    quoted = [v.replace("'", "''") for v in values]
    return [FeatureSpec(f"{col}={v}", f"CASE WHEN {col} = '{q}' THEN 1 ELSE 0 END", lo, hi) for v, q in zip(values, quoted)]
