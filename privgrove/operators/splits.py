"""Gradient histograms of a level's nodes, split candidates, their gains, and the choice of one per node."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from privgrove.functions.noise import in_race, race_key, race_keys, uniform, uniforms_of
from privgrove.operators.gradient import UNIT


def gain(gl, nl, gr, nr, lam: float):
    """Children's squared gradient sums over their regularised sizes; columns or arrays."""
    return gl * gl / (nl + lam) + gr * gr / (nr + lam)


gain_h = gain  # the same with hessian sums in place of counts


def slot_of(b: Column, cut_bins: list[int]) -> Column:
    """Slot of a bin: cuts before it; -1 for missing. Bins and cuts are small, so a literal array serves."""
    bins = max([*cut_bins, 0]) + 2
    table = [sum(c < x for c in cut_bins) for x in range(bins)]
    found = F.element_at(F.array(*[F.lit(t) for t in table]), F.least(b.cast("int"), F.lit(bins - 1)) + 1)
    return F.when(b < 0, F.lit(-1)).otherwise(found)


def level_histogram(workset: DataFrame, cuts: dict[int, list[int]], node: str = "node") -> DataFrame:
    """LEVEL_HIST (node, feature, slot, sg, sh, n) by unpivot and one hash aggregate, all in generated code."""
    slots = [slot_of(F.col(f"b_{k}"), c).alias(f"s_{k}") for k, c in sorted(cuts.items())]
    wide = workset.select(F.col(node).alias("node"), "g", "h", *slots)
    pairs = ", ".join(f"{k}, s_{k}" for k in sorted(cuts))
    long = wide.select("node", "g", "h", F.expr(f"stack({len(cuts)}, {pairs}) AS (feature, slot)"))
    return long.groupBy("node", "feature", "slot").agg(F.sum("g").alias("sg"), F.sum("h").alias("sh"), F.count(F.lit(1)).alias("n"))


def level_histogram_sets(workset: DataFrame, cuts: dict[int, list[int]], node: str = "node") -> DataFrame:
    """The same by grouping sets, one set per feature."""
    ks = sorted(cuts)
    slots = [slot_of(F.col(f"b_{k}"), cuts[k]).alias(f"s_{k}") for k in ks]
    workset.select(F.col(node).alias("node"), "g", "h", *slots).createOrReplaceTempView("_grove_level")
    sets = ", ".join(f"(node, s_{k})" for k in ks)
    ids = {k: ((1 << len(ks)) - 1) ^ (1 << (len(ks) - 1 - i)) for i, k in enumerate(ks)}
    feature = "CASE " + " ".join(f"WHEN gid = {ids[k]} THEN {k}" for k in ks) + " END"
    slot = "CASE " + " ".join(f"WHEN gid = {ids[k]} THEN s_{k}" for k in ks) + " END"
    names = ", ".join(f"s_{k}" for k in ks)
    return workset.sparkSession.sql(
        f"SELECT node, {feature} AS feature, {slot} AS slot, sg, sh, n FROM (SELECT node, {names}, grouping_id() & {(1 << len(ks)) - 1} AS gid, "
        f"sum(g) AS sg, sum(h) AS sh, count(*) AS n FROM _grove_level GROUP BY GROUPING SETS ({sets}))"
    )


def level_histogram_arrow(workset: DataFrame, cuts: dict[int, list[int]], node: str = "node") -> DataFrame:
    """The same with numpy partials per task; preferred for many features."""
    ks = sorted(cuts)
    edges = {k: np.array(cuts[k]) for k in ks}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            nodes, place = np.unique(batch.column("node").to_numpy(), return_inverse=True)
            g, h = batch.column("g").to_numpy(), batch.column("h").to_numpy()
            for k in ks:
                b = batch.column(f"b_{k}").to_numpy().astype(np.int64)
                slot = np.where(b < 0, 0, np.searchsorted(edges[k], b, "left") + 1)
                width = len(edges[k]) + 2
                cell = place * width + slot
                n = np.bincount(cell, minlength=len(nodes) * width)
                sg = np.zeros(len(n), np.int64)
                np.add.at(sg, cell, g)
                sh = np.bincount(cell, h, len(n))
                at = np.flatnonzero(n)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(nodes[at // width].astype(np.int32)), pa.array(np.full(len(at), k, np.int32)), pa.array((at % width - 1).astype(np.int32)), pa.array(sg[at]), pa.array(sh[at]), pa.array(n[at])],
                    names=["node", "feature", "slot", "sg", "sh", "n"],
                )

    cols = [F.col(node).cast("int").alias("node"), F.col("g"), F.col("h").cast("double").alias("h"), *[F.col(f"b_{k}") for k in ks]]
    part = workset.select(*cols).mapInArrow(run, "node int, feature int, slot int, sg bigint, sh double, n bigint")
    return part.groupBy("node", "feature", "slot").agg(F.sum("sg").alias("sg"), F.sum("sh").alias("sh"), F.sum("n").alias("n"))


def subtract_sibling(parent: DataFrame, child: DataFrame, sibling_node: int) -> DataFrame:
    """The larger child's histogram: its parent's less the smaller child's."""
    minus = child.select("feature", "slot", F.col("sg").alias("_g"), F.col("sh").alias("_h"), F.col("n").alias("_n"))
    both = parent.join(minus, ["feature", "slot"], "left").na.fill(0, ["_g", "_h", "_n"])
    return both.select(F.lit(sibling_node).alias("node"), "feature", "slot", (F.col("sg") - F.col("_g")).alias("sg"), (F.col("sh") - F.col("_h")).alias("sh"), (F.col("n") - F.col("_n")).alias("n")).where("n > 0")


def complete_slots(hist: DataFrame, nodes: list[int], cuts: dict[int, list[int]]) -> DataFrame:
    """Zeros for every public (node, feature, slot): the candidate list must not show which cells hold rows."""
    grid = hist.sparkSession.createDataFrame([(v, k, s) for v in nodes for k, c in cuts.items() for s in range(-1, len(c) + 1)], "node int, feature int, slot int")
    return F.broadcast(grid).join(hist, ["node", "feature", "slot"], "left").na.fill(0, ["sg", "sh", "n"])


def candidates(level_hist: DataFrame, cuts: dict[int, list[int]], lam: float, direction: str = "both", strict: bool = False) -> DataFrame:
    """CANDIDATES: each (node, feature, cut) with missing values sent left and sent right, and the gain.

    Where a node has no missing value of a feature the two coincide; strict mode keeps both, else one stays.
    """
    upto = Window.partitionBy("node", "feature").orderBy("slot").rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy("node", "feature")
    miss = lambda c: F.sum(F.when(F.col("slot") == -1, F.col(c)).otherwise(0)).over(whole)
    c = level_hist.select("node", "feature", "slot", *[F.sum(F.when(F.col("slot") >= 0, F.col(x)).otherwise(0)).over(upto).alias(f"{x}_l") for x in ("sg", "n")], *[miss(x).alias(f"{x}_m") for x in ("sg", "n")], *[F.sum(x).over(whole).alias(f"{x}_t") for x in ("sg", "n")])
    last = F.coalesce(*[F.when(F.col("feature") == k, F.lit(len(v))) for k, v in cuts.items()])
    c = c.where((F.col("slot") >= 0) & (F.col("slot") < last))
    sides = [x for x in (True, False) if direction == "both" or (direction == "left") == x]
    c = c.withColumn("default_left", F.explode(F.array(*[F.lit(x) for x in sides])))
    if len(sides) == 2 and not strict:
        c = c.where((F.col("n_m") > 0) | F.col("default_left"))
    move = F.when(F.col("default_left"), 1).otherwise(0)
    gl, nl = F.col("sg_l") + F.col("sg_m") * move, F.col("n_l") + F.col("n_m") * move
    c = c.withColumns({"gl": gl, "nl": nl, "gr": F.col("sg_t") - gl, "nr": F.col("n_t") - nl})
    value = gain(F.col("gl") / UNIT, F.col("nl"), F.col("gr") / UNIT, F.col("nr"), lam)
    return c.select("node", "feature", "slot", "default_left", "gl", "nl", "gr", "nr", value.alias("gain"))


def admissible(cands: DataFrame, min_child: int, min_gain: float | None = None, lam: float = 0.1, strict: bool = False) -> DataFrame:
    """Candidates that the stop rules allow; strict mode allows all, as a gate on exact counts would tell of rows."""
    if strict:
        return cands
    out = cands.where((F.col("nl") >= min_child) & (F.col("nr") >= min_child))
    if min_gain is not None:
        g, n = (F.col("gl") + F.col("gr")) / UNIT, F.col("nl") + F.col("nr")
        out = out.where(F.col("gain") - g * g / (n + lam) > min_gain)
    return out


ORDER = ("feature", "slot", "default_left")


def choose_dp(cands: DataFrame, eps_level: float, g_star: float, key: str, tree: int = 0) -> DataFrame:
    """SPLITS: one candidate per node by the exponential mechanism on the gain, run as a race."""
    u = uniform(f"{key}|split|{tree}", "node", "feature", "slot", F.col("default_left").cast("int"))
    raced = cands.withColumn("race_key", race_key(F.col("gain") * (eps_level / (6 * g_star**2)), u))
    row = F.struct("feature", "slot", "default_left", "gain", "gl", "nl", "gr", "nr", "race_key")
    return raced.groupBy("node").agg(F.min_by(row, F.struct("race_key", *ORDER)).alias("r")).select("node", "r.*")


def choose_greedy(cands: DataFrame) -> DataFrame:
    """SPLITS: the candidate of the largest gain per node; ties go to the first feature, slot, direction."""
    row = F.struct("feature", "slot", "default_left", "gain", "gl", "nl", "gr", "nr")
    key = F.struct((-F.round("gain", 6)).alias("k"), "feature", "slot", (~F.col("default_left")).alias("right"))
    return cands.groupBy("node").agg(F.min_by(row, key).alias("r")).select("node", "r.*")


@dataclass(frozen=True)
class Split:
    """A chosen split; sums in units of the gradient."""

    feature: int
    cut_bin: int
    default_left: bool
    gain: float
    gl: float
    nl: int
    gr: float
    nr: int


def best_split(sg: np.ndarray, n: np.ndarray, cuts: list[np.ndarray], lam: float, min_child: int, min_gain: float | None, strict: bool, eps_level: float | None, g_star: float, ids: tuple, at: list[np.ndarray] | None = None) -> Split | None:
    """Choose one node's split from its (feature, 1 + bin) sums of fixed-point gradients and counts; column 0 is missing.

    The histogram of a node is bounded by features times bins, so this last step is the driver's. eps_level None is
    greedy. Gives None when no candidate is allowed. `at` has the places of the cuts among columns 1 on, where these are not
    all bins.
    """
    sizes = [len(edges) for edges in cuts]
    if not sum(sizes):
        return None
    feature, slot = np.repeat(np.arange(len(cuts)), sizes), np.concatenate([np.arange(x) for x in sizes])
    cut, upto = (np.concatenate(x).astype(np.intp) for x in (cuts, cuts if at is None else at))
    left_g, left_n = np.cumsum(sg[:, 1:], axis=1)[feature, upto], np.cumsum(n[:, 1:], axis=1)[feature, upto]
    left = np.ones(len(cut), bool)
    if strict or n[:, 0].any():  # by feature: missing values to the left, then to the right
        right = np.flatnonzero(strict | (n[feature, 0] > 0))
        left = np.concatenate((left, np.zeros(len(right), bool)))
        feature, slot, cut, left_g, left_n = (np.concatenate((x, x[right])) for x in (feature, slot, cut, left_g, left_n))
        order = np.lexsort((slot, ~left, feature))
        feature, slot, cut, left, left_g, left_n = (x[order] for x in (feature, slot, cut, left, left_g, left_n))
        left_g, left_n = left_g + np.where(left, sg[feature, 0], 0), left_n + np.where(left, n[feature, 0], 0)
    total_g, total_n = int(sg[0].sum()), int(n[0].sum())
    gl, nl = left_g.astype(np.float64) / UNIT, left_n
    gr, nr = total_g / UNIT - gl, total_n - nl
    value = gain(gl, nl, gr, nr, lam)
    ok = np.ones(len(cut), bool)
    if not strict:
        ok = (nl >= min_child) & (nr >= min_child)
        if min_gain is not None:
            ok &= value - (total_g / UNIT) ** 2 / (total_n + lam) > min_gain
    ok = np.flatnonzero(ok)
    if not len(ok):
        return None
    if eps_level is None or eps_level == float("inf"):
        best = ok[int(np.argmax(np.round(value[ok], 6)))]
    else:
        weight = value * eps_level / (6 * g_star**2)
        ok = ok[in_race(weight[ok])]
        u = uniforms_of(ids, [f"{f}|{s}|{d}" for f, s, d in zip(feature[ok].tolist(), slot[ok].tolist(), left[ok].astype(int).tolist())])
        best = ok[int(np.argmin(race_keys(weight[ok], u)))]
    return Split(int(feature[best]), int(cut[best]), bool(left[best]), float(value[best]), float(gl[best]), int(nl[best]), float(gr[best]), int(nr[best]))
