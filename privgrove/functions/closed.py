"""Closed forms: sensitivities, budgets and composition."""

from __future__ import annotations

import math


def sensitivity(kind: str, g_star: float = 1.0, lam: float = 0.1, min_child: int = 1, n: int = 0, adjacency: str = "add_remove", tree: int = 0, eta: float = 0.3) -> float:
    """The worst change of a release when one record is added or removed (or, on request, replaced).

    count, histogram: of one feature. gain: of a split candidate. leaf_worst_case, leaf_min_child, leaf_at_n: of a leaf
    value. leaf_sum: of a noisy average's sum. leaf_geometric: of a leaf clipped for tree number `tree`.
    """
    twice = 2.0 if adjacency == "replace_one" else 1.0
    if kind in ("count", "histogram"):
        return twice
    if kind == "gain":
        return 3 * g_star**2 * twice
    if kind == "leaf_worst_case":
        return g_star / (1 + lam)
    if kind == "leaf_min_child":
        return 2 * g_star / (min_child + 1 + lam)
    if kind == "leaf_at_n":
        return (2 * n + lam) * g_star / ((n + lam) * (n + 1 + lam))
    if kind == "leaf_sum":
        return 2 * g_star
    if kind == "leaf_geometric":
        return min(g_star / (1 + lam), 2 * g_star * (1 - eta) ** tree)
    raise ValueError(f"unknown release {kind}")


def amplified(eps: float, gamma: float) -> float:
    """Privacy of an eps mechanism that sees a random fraction gamma."""
    return math.log1p(gamma * math.expm1(eps))


def before_sampling(target: float, gamma: float) -> float:
    """The mechanism's eps that sampling at gamma brings down to target."""
    return math.log1p(math.expm1(target) / gamma)


def advanced(eps: float, k: int, slack: float) -> float:
    """(eps, slack) privacy of k mechanisms in sequence, growing with the root of k."""
    return math.sqrt(2 * k * math.log(1 / slack)) * eps + k * eps * math.expm1(eps)


def strict_average_charge(eps: float, min_child: int, lam: float) -> float:
    """What a noisy average with an exact count costs at most, for leaves floored at min_child rows."""
    return eps + math.log1p(1 / (min_child + lam))
