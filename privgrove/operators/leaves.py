"""Leaf values: exact, with Laplace noise of three scales, by a noisy average, or clipped geometrically."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privgrove.functions.closed import sensitivity
from privgrove.functions.noise import laplace, laplace_of, uniform

MODES = ("exact", "worst_case", "min_child", "noisy_average", "geometric")


def exact(g: Column | float, n: Column | float, lam: float):
    """Minus the gradient sum over the regularised count."""
    return -g / (n + lam)


def scale_of(mode: str, eps: float, g_star: float, lam: float, min_child: int, tree: int = 0, eta: float = 0.3) -> float:
    """Noise scale of a leaf value, or of the sum for the noisy average."""
    kind = {"worst_case": "leaf_worst_case", "min_child": "leaf_min_child", "noisy_average": "leaf_sum", "geometric": "leaf_geometric"}[mode]
    return sensitivity(kind, g_star, lam, min_child, tree=tree, eta=eta) / eps


def leaf_value(mode: str, g: float, n: int, eps: float, g_star: float, lam: float, min_child: int, u: float, tree: int = 0, eta: float = 0.3, strict: bool = False) -> float:
    """One leaf's released value; strict mode floors the count, so that the scale holds without any gate."""
    n = max(n, min_child) if strict else n
    if mode == "exact" or eps == float("inf"):
        value = exact(g, n, lam)
        return max(-g_star, min(g_star, value)) if mode == "noisy_average" else value
    noise = laplace_of(u, scale_of(mode, eps, g_star, lam, min_child, tree, eta))
    if mode == "noisy_average":
        return -max(-g_star, min(g_star, (g + noise) / (n + lam)))
    value = exact(g, n, lam)
    if mode == "geometric":
        bound = g_star * (1 - eta) ** tree
        value = max(-bound, min(bound, value))
    return value + noise


def released(nodes: DataFrame, mode: str, eps: float, key: str, g_star: float = 1.0, lam: float = 0.1, min_child: int = 1, tree: int = 0, eta: float = 0.3, strict: bool = False, ids: tuple[str, ...] = ("node",)) -> DataFrame:
    """Leaf rows (ids.., g, n) with their released value."""
    n = F.greatest(F.col("n"), F.lit(min_child)) if strict else F.col("n")
    plain = exact(F.col("g"), n, lam)
    if mode == "exact":
        return nodes.withColumn("value", plain)
    noise = laplace(uniform(f"{key}|leaf|{tree}", *ids), scale_of(mode, eps, g_star, lam, min_child, tree, eta))
    if mode == "noisy_average":
        noisy = (F.col("g") + noise) / (n + lam)
        return nodes.withColumn("value", -F.greatest(F.least(noisy, F.lit(g_star)), F.lit(-g_star)))
    if mode == "geometric":
        bound = g_star * (1 - eta) ** tree
        plain = F.greatest(F.least(plain, F.lit(bound)), F.lit(-bound))
    return nodes.withColumn("value", plain + noise)
