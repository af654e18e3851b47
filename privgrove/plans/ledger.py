"""Privacy accounting: budget plans, composition rules and the ledger."""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, field, replace
from typing import Protocol

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privgrove.functions.closed import amplified, before_sampling

SCHEMA = "tree int, mechanism string, level int, scope string, epsilon double, delta double, composition string, note string"


@dataclass(frozen=True)
class Charge:
    """One release. Charges that share a scope act on disjoint rows; scopes follow one another."""

    tree: int
    mechanism: str
    level: int
    scope: str
    epsilon: float
    delta: float = 0.0
    composition: str = "parallel"
    note: str = ""


def sequential(values: Sequence[float]) -> float:
    """Mechanisms on the same rows add up."""
    return math.fsum(values)


def parallel(values: Sequence[float]) -> float:
    """Mechanisms on disjoint rows cost the largest."""
    return max(values, default=0.0)


@dataclass(frozen=True)
class BudgetPlan:
    """How one tree's eps is spent: shares for sketch, leaves and splits; m features, h levels."""

    eps_tree: float
    m: int
    h: int
    shares: tuple[float, float, float] = (1 / 3, 1 / 3, 1 / 3)
    early_leaf_bonus: bool = False

    @property
    def sketch(self) -> float:
        return self.eps_tree * self.shares[0]

    @property
    def sketch_feature(self) -> float:
        return self.sketch / self.m

    def leaf(self, depth: int | None = None) -> float:
        """The leaves' eps; with the bonus, a leaf above the last level also gets what its levels did not spend."""
        unspent = self.level * (self.h - depth) if self.early_leaf_bonus and depth is not None else 0.0
        return self.eps_tree * self.shares[1] + unspent

    @property
    def level(self) -> float:
        return self.eps_tree * self.shares[2] / self.h

    def charges(self, tree: int) -> list[Charge]:
        """Everything the tree releases, summing to eps_tree on every path from the root to a leaf."""
        out = [Charge(tree, "sketch", -1, f"feature {k}", self.sketch_feature, composition="parallel over bins") for k in range(self.m)]
        out += [Charge(tree, "split", d, f"level {d}", self.level, composition="parallel over nodes") for d in range(self.h)]
        return [*out, Charge(tree, "leaf", self.h, "leaves", self.leaf(), composition="parallel over leaves")]


def plan_ensemble(eps_total: float, trees: int, gamma: float, m: int, h: int, shares=(1 / 3, 1 / 3, 1 / 3), tree_weights: Sequence[float] | None = None, early_leaf_bonus: bool = False) -> list[BudgetPlan]:
    """One plan per tree: the ensemble's eps is divided over the trees, each on a gamma sample of its own."""
    if not eps_total > 0 or trees < 1 or not 0 < gamma <= 1:
        raise ValueError("a positive eps, a tree at least and a fraction in (0, 1] are needed")
    weights = list(tree_weights or [1.0] * trees)
    if len(weights) != trees or min(weights) <= 0:
        raise ValueError("one positive weight per tree is needed")
    total = math.fsum(weights)
    return [BudgetPlan(before_sampling(eps_total * w / total, gamma), m, h, tuple(shares), early_leaf_bonus) for w in weights]


@dataclass
class Ledger:
    """Charges made so far, against a limit."""

    limit: float = math.inf
    gamma: float = 1.0
    charges: list[Charge] = field(default_factory=list)
    disjoint_trees: bool = False

    def tree_epsilon(self, tree: int) -> float:
        """Privacy of one tree after sampling: scopes in sequence, each the largest of its charges."""
        scopes: dict[tuple[str, str], list[float]] = {}
        for c in self.charges:
            if c.tree == tree:
                scopes.setdefault((c.mechanism, c.scope), []).append(c.epsilon)
        return amplified(sequential([parallel(v) for v in scopes.values()]), self.gamma)

    def total(self) -> float:
        each = [self.tree_epsilon(t) for t in sorted({c.tree for c in self.charges})]
        return parallel(each) if self.disjoint_trees else sequential(each)

    def total_by(self, accountant: Accountant) -> tuple[float, float]:
        """(epsilon, delta) of all trees under another accountant; trees on disjoint rows cost the largest."""
        each = [self.tree_epsilon(t) for t in sorted({c.tree for c in self.charges})]
        return (parallel(each), 0.0) if self.disjoint_trees else accountant.total(each)

    def charge(self, new: Sequence[Charge]) -> None:
        """Record charges, or refuse all of them."""
        after = replace(self, charges=[*self.charges, *new])
        if after.total() > self.limit * (1 + 1e-9):
            raise ValueError(f"the budget of {self.limit} does not allow a total of {after.total():.6f}")
        self.charges.extend(new)

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(c.tree, c.mechanism, c.level, c.scope, c.epsilon, c.delta, c.composition, c.note) for c in self.charges], SCHEMA)


class Accountant(Protocol):
    """What composes the charges of releases on the same rows to one (epsilon, delta)."""

    def total(self, epsilons: Sequence[float]) -> tuple[float, float]: ...


@dataclass(frozen=True)
class PureAccountant:
    """Charges add up; no delta. The ledger's own rule."""

    def total(self, epsilons: Sequence[float]) -> tuple[float, float]:
        return sequential(epsilons), 0.0


@dataclass(frozen=True)
class AdvancedAccountant:
    """Advanced composition of unequal charges, for a delta; never above the plain sum."""

    delta: float

    def total(self, epsilons: Sequence[float]) -> tuple[float, float]:
        drift = math.fsum(e * math.expm1(e) for e in epsilons)
        spread = math.sqrt(2 * math.log(1 / self.delta) * math.fsum(e * e for e in epsilons))
        plain = sequential(epsilons)
        return (plain, 0.0) if plain <= drift + spread else (drift + spread, self.delta)


@dataclass(frozen=True)
class ConcentratedAccountant:
    """Zero-concentrated privacy: a pure charge of e counts e**2 / 2, and sums are brought back for a delta."""

    delta: float

    def total(self, epsilons: Sequence[float]) -> tuple[float, float]:
        rho = math.fsum(e * e / 2 for e in epsilons)
        bound, plain = rho + 2 * math.sqrt(rho * math.log(1 / self.delta)), sequential(epsilons)
        return (plain, 0.0) if plain <= bound else (bound, self.delta)


def total_of(ledger: DataFrame, gamma: float = 1.0) -> DataFrame:
    """The ledger's total as a DataFrame: largest by scope, sum by tree, amplified, sum over trees."""
    scopes = ledger.groupBy("tree", "mechanism", "scope").agg(F.max("epsilon").alias("e"))
    trees = scopes.groupBy("tree").agg(F.sum("e").alias("e"))
    return trees.agg(F.round(F.sum(F.log1p(F.lit(gamma) * F.expm1("e"))), 6).alias("epsilon"), F.count(F.lit(1)).alias("trees"))
