"""Mergeable weighted quantile summary with rank bounds."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass
class Summary:
    """Sorted values, their own weight, and bounds of the weight before them (low) and up to them (high)."""

    value: np.ndarray
    low: np.ndarray
    high: np.ndarray
    weight: np.ndarray

    @property
    def total(self) -> float:
        return float(self.high[-1]) if len(self.high) else 0.0


def build(values: np.ndarray, weights: np.ndarray) -> Summary:
    """The exact summary of weighted points."""
    value, at = np.unique(values, return_inverse=True)
    weight = np.bincount(at, weights, len(value)) if len(value) else np.zeros(0)
    high = np.cumsum(weight)
    return Summary(value, high - weight, high, weight)


def bounds_at(s: Summary, values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(low, high, weight) that s gives for any values: its own entries, or what lies between neighbours."""
    if not len(s.value):
        zero = np.zeros(len(values))
        return zero, zero, zero
    at = np.searchsorted(s.value, values)
    inside = np.minimum(at, len(s.value) - 1)
    own = s.value[inside] == values
    before = np.maximum(at - 1, 0)
    low = np.where(own, s.low[inside], np.where(at > 0, s.low[before] + s.weight[before], 0.0))
    high = np.where(own, s.high[inside], np.where(at < len(s.value), s.high[inside] - s.weight[inside], s.total))
    return low, high, np.where(own, s.weight[inside], 0.0)


def merge(a: Summary, b: Summary) -> Summary:
    """The summary of both inputs; bounds add up."""
    value = np.union1d(a.value, b.value)
    (la, ha, wa), (lb, hb, wb) = bounds_at(a, value), bounds_at(b, value)
    return Summary(value, la + lb, ha + hb, wa + wb)


def prune(s: Summary, size: int) -> Summary:
    """At most about `size` entries: the ends and those nearest to even ranks; adds total / size of error at most."""
    if len(s.value) <= size:
        return s
    middle = (s.low + s.high) / 2
    at = np.searchsorted(middle, np.linspace(0, s.total, size))
    keep = np.unique(np.clip(np.concatenate(([0], at, [len(s.value) - 1])), 0, len(s.value) - 1))
    return Summary(s.value[keep], s.low[keep], s.high[keep], s.weight[keep])


def query(s: Summary, ranks: np.ndarray) -> np.ndarray:
    """The value whose rank bounds are nearest to each rank."""
    middle = (s.low + s.high) / 2
    return s.value[np.abs(middle[None, :] - np.asarray(ranks)[:, None]).argmin(axis=1)] if len(s.value) else np.zeros(0)


#: Levels of merging that the rank error is shared out over: 2**LEVELS parts, of batches and tasks together.
LEVELS = 32


def entries_for(sketch_eps: float) -> int:
    """Entries of a pruned summary, so that LEVELS prunings on the way up add sketch_eps of the total weight at most."""
    return int(np.ceil(LEVELS / sketch_eps)) + 2


class Stack:
    """Summaries by level, as digits of a binary counter: two of a level are merged and pruned to one of the next.

    A part of the input is pruned once a level on its way up, and the parts of a level add up to the input, so the error is
    the number of levels over `size`, however many parts there are. Points are gathered first, so the parts are large.
    """

    def __init__(self, size: int):
        self.size, self.levels, self.values, self.weights, self.held = size, [], [], [], 0

    def add(self, values: np.ndarray, weights: np.ndarray) -> None:
        self.values.append(values)
        self.weights.append(weights)
        self.held += len(values)
        if self.held >= 4 * self.size:
            self.flush()

    def flush(self) -> None:
        if self.held:
            self.push(build(np.concatenate(self.values), np.concatenate(self.weights)))
            self.values, self.weights, self.held = [], [], 0

    def push(self, s: Summary) -> None:
        s, k = prune(s, self.size), 0
        while k < len(self.levels) and self.levels[k] is not None:
            s, self.levels[k] = prune(merge(self.levels[k], s), self.size), None
            k += 1
        self.levels[k : k + 1] = [s]

    def whole(self) -> Summary:
        self.flush()
        total = build(np.zeros(0), np.zeros(0))
        for s in self.levels:
            total = merge(total, s) if s is not None else total
        return prune(total, self.size)


def summaries(rows: DataFrame, m: int, sketch_eps: float, tasks: int | None = None) -> DataFrame:
    """One summary per feature as rows (feature, value, low, high, weight), with rank bounds within sketch_eps of the total.

    Each task summarises its rows; summaries then meet in two steps, some thousand groups at first, so no task reads those
    of all others.
    """
    size = entries_for(sketch_eps)
    names = ["feature", "value", "low", "high", "weight"]

    def table(feature: int, s: Summary) -> pa.Table:
        return pa.table({"feature": np.full(len(s.value), feature, np.int32), "value": s.value, "low": s.low, "high": s.high, "weight": s.weight})

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [Stack(size) for _ in range(m)]
        for batch in batches:
            w = batch.column("w").to_numpy(zero_copy_only=False)
            for k in range(m):
                x = batch.column(f"x_{k}").to_numpy(zero_copy_only=False)
                ok = ~np.isnan(x)
                held[k].add(x[ok], w[ok])
        for k, s in enumerate(held):
            yield from table(k, s.whole()).to_batches()

    def merged(part: pa.Table) -> pa.Table:
        stack = Stack(size)
        tasks, columns = part["task"].to_numpy(), [part[c].to_numpy() for c in names[1:]]
        for t in np.unique(tasks):
            at = np.flatnonzero(tasks == t)
            at = at[np.argsort(columns[0][at], kind="stable")]
            stack.push(Summary(*[c[at] for c in columns]))
        out = table(part["feature"][0].as_py(), stack.whole())
        return out.append_column("task", pa.array(np.full(len(out), part["group"][0].as_py()), pa.int32()))

    kind = "feature int, value double, low double, high double, weight double"
    parts = rows.mapInArrow(partial, kind).withColumn("task", F.spark_partition_id())
    groups = max(1, int((tasks or rows.rdd.getNumPartitions()) ** 0.5))
    for ways in (groups, 1):
        parts = parts.withColumn("group", F.pmod("task", F.lit(ways))).groupBy("feature", "group").applyInArrow(merged, f"{kind}, task int")
    return parts.select(*names)


def propose(rows: DataFrame, m: int, max_cuts: int, weight_col: str | None = None, sketch_eps: float = 0.005) -> DataFrame:
    """CUTS (feature, slot, cut) at even shares of each feature's weight, ranks within sketch_eps of the total weight.

    Missing values have no part; a feature without values has no cut, an empty table no rows.
    """

    def chosen(key: tuple, table: pa.Table) -> pa.Table:
        order = np.argsort(table["value"].to_numpy(), kind="stable")
        total = Summary(*[table[c].to_numpy()[order] for c in ("value", "low", "high", "weight")])
        cuts = np.unique(query(total, total.total * np.arange(1, max_cuts + 1) / (max_cuts + 1)))
        return pa.table({"feature": np.full(len(cuts), key[0].as_py(), np.int32), "slot": np.arange(len(cuts), dtype=np.int32), "cut": cuts.astype(np.float64)})

    weight = F.col(weight_col).cast("double") if weight_col else F.lit(1.0)
    rows = rows.select(*[F.col(f"x_{k}").cast("double").alias(f"x_{k}") for k in range(m)], weight.alias("w"))
    return summaries(rows, m, sketch_eps).groupBy("feature").applyInArrow(chosen, "feature int, slot int, cut double")
