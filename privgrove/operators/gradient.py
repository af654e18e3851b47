"""Losses, gradient filtering and fixed-point gradients."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UNIT = 1 << 20


def squared(margin: Column, y: Column) -> tuple[Column, Column, Column]:
    """(loss, gradient, hessian) of half the squared error."""
    return 0.5 * (margin - y) ** 2, margin - y, F.lit(1.0)


def fixed(g: Column) -> Column:
    """Whole units of 2**-20, towards zero: sums of these do not depend on their order."""
    return (g * UNIT).cast("bigint")


def filter_bounded(df: DataFrame, g_star: float, col: str = "g") -> DataFrame:
    """Rows whose gradient is at most g_star in size; the bound depends on the loss alone."""
    return df.where(F.abs(F.col(col)) <= g_star)
