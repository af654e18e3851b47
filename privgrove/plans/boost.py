"""Training: private cuts, private splits, private leaves, tree after tree on fresh samples.

Any number of models, such as the trials and budgets of a study, are trained in step: a level of all of them is one job.
Only counts leave the tasks. Rows are written once, in blocks of packed bins with a bit for each sample, so a tree's sample
is read from them at a byte or two per feature and never stored. One job per level sums fixed-point gradients by (node, feature, bin) and decides on
the split of a node in the task where its sums meet. What reaches the driver is a row per node. Where a run's samples fit
a task, that task asks its own rows for the sums, and a job grows as many trees of all models as have few rows enough to
be dealt out at once; the trees are the same.
"""

from __future__ import annotations

import pickle
import time
from collections.abc import Callable, Iterator
from dataclasses import asdict, dataclass, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel, TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from privgrove.functions.closed import before_sampling, strict_average_charge
from privgrove.functions.noise import laplace_of, uniform_of, uniforms_of
from privgrove.operators import leaves, sampling
from privgrove.operators.gradient import UNIT
from privgrove.operators.proposals import cuts_of, joint_quantiles
from privgrove.operators.schema import DatasetSpec
from privgrove.operators.splits import Split, best_split
from privgrove.plans.ledger import BudgetPlan, Charge, Ledger, plan_ensemble, sequential
from privgrove.plans.tree import Codes, Router, Tree, TreeModel
from privgrove.sources.io import freed, stored


@dataclass(frozen=True)
class BoostParams:
    """Everything that training takes. noise_key is a secret of the caller, fresh for every fit; tests fix it."""

    epsilon_total: float = 1.0
    trees: int = 20
    max_depth: int = 6
    learning_rate: float = 0.3
    lam: float = 0.1
    g_star: float = 1.0
    min_child: int = 500
    min_hessian: float = 0.0  # of a child; each row's hessian is 1 under squared loss
    min_gain: float | None = None
    subsample: float = 0.1
    max_cuts: int = 50
    bins: int = 64
    private: bool = True
    proposal: str = "global"  # or local, joint
    proposal_noise: bool = True
    split_mode: str = "exponential"  # or greedy
    leaf_mode: str = "min_child"
    shares: tuple[float, float, float] = (1 / 3, 1 / 3, 1 / 3)
    tree_weights: tuple[float, ...] | None = None
    early_leaf_bonus: bool = False
    strict: bool = False
    disjoint: bool = False
    shared_draws: bool = False  # a hash of a row serves several trees; the samples are others, and as independent
    gradient_filter: bool = True
    noise_key: str = "k0"

    def open(self) -> BoostParams:
        """The same model without privacy: exact cuts, greedy splits, exact leaves, no filter."""
        return BoostParams(**(asdict(self) | {"private": False, "proposal_noise": False, "split_mode": "greedy", "leaf_mode": "exact", "gradient_filter": False}))


#: Rows that a chunk is filled up to, and cells of a task's sums up to which they are held whole.
CHUNK, DENSE = 1 << 15, 1 << 21
CHUNKS = "tree_id int, draw smallint, n int, bins binary, y binary"
CHUNK_KINDS, CHUNK_NAMES = [pa.int32(), pa.int16(), pa.int32(), pa.binary(), pa.binary()], ["tree_id", "draw", "n", "bins", "y"]
EMPTY_CHUNKS = pa.RecordBatch.from_arrays([pa.array([], t) for t in CHUNK_KINDS], names=CHUNK_NAMES)


def coarser(bins: np.ndarray, shift: int) -> np.ndarray:
    """1 + bin of rows, where 2**shift even bins are one; 0 stays."""
    return (bins + ((1 << shift) - 1)) >> shift if shift else bins


#: Gradient of a row that the filter leaves out.
LEFT_OUT = np.iinfo(np.int64).min


def matrix_of(bins: bytes, n: int, m: int, indices: bool = True) -> np.ndarray:
    """1 + bin by (feature, row), as indices or as it is stored."""
    width = len(bins) // max(1, n * m)
    stored = np.frombuffer(bins, {1: np.uint8, 2: np.uint16}.get(width, np.uint32)).reshape(m, n) if m else np.zeros((0, n), np.uint8)
    return stored.astype(np.intp) if indices else stored


def packed_targets(y: np.ndarray) -> bytes:
    """Targets as plain bytes: one each for classes, else eight."""
    return (y.astype(np.int8) if (np.abs(y) == 1).all() else y).tobytes()


def targets_of(y: bytes, n: int) -> np.ndarray:
    return np.frombuffer(y, np.int8).astype(np.float64) if len(y) == n else np.frombuffer(y)


def rows_of(chunks: list[pa.RecordBatch], m: int) -> tuple[np.ndarray, np.ndarray]:
    """(1 + bin by (feature, row), targets) of a tree's chunks, in as few bytes as they have there."""
    parts = [(matrix_of(b, n, m, False), targets_of(y, n)) for x in chunks for n, b, y in zip(*(x.column(c).to_pylist() for c in ("n", "bins", "y")))]
    if not parts:
        return np.zeros((m, 0), np.uint8), np.zeros(0)
    return np.concatenate([b for b, _ in parts], axis=1), np.concatenate([y for _, y in parts])


def kind_of(bins: int) -> type:
    """The integers that hold 1 + bin."""
    return np.uint8 if bins < 256 else np.uint16 if bins < 1 << 16 else np.uint32


def chunk(tree: int, draw: int, bins: np.ndarray, y: np.ndarray) -> tuple:
    return tree, draw, len(y), bins.tobytes(), packed_targets(y)


def chunked(drawn: DataFrame, features: list[int], target: str, bins: int) -> DataFrame:
    """CHUNKS of drawn rows (b_.., a target, tree_id, draw): what a tree and a draw have in a task, bins by feature and
    targets as plain bytes. None is large."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            key = batch.column("draw").to_numpy().astype(np.int64) << 32 | batch.column("tree_id").to_numpy()
            order = np.argsort(key, kind="stable")
            key, y = key[order], batch.column(target).to_numpy(zero_copy_only=False)[order]
            b = np.stack([(batch.column(f"b_{k}").to_numpy(zero_copy_only=False) + 1).astype(kind_of(bins))[order] for k in features] or [np.zeros((0, len(key)))])
            ends = np.flatnonzero(np.diff(key, append=-1)) + 1
            rows = [chunk(int(key[i] & 0xFFFFFFFF), int(key[i] >> 32), b[:, i:j], y[i:j]) for i, j in zip([0, *ends.tolist()], ends.tolist())]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), CHUNK_KINDS)], names=CHUNK_NAMES) if rows else EMPTY_CHUNKS

    return drawn.select(*[f"b_{k}" for k in features], F.col(target).cast("double").alias(target), "tree_id", "draw").mapInArrow(run, CHUNKS)


def rows_in(p: BoostParams, ids: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    """(place, tree) of what a draw's samples have of rows at hand."""
    if p.disjoint:
        return sampling.disjoint_rows(ids, parts_of(p), p.noise_key)
    return (sampling.shared_rows if p.shared_draws else sampling.own_rows)(ids, p.trees, p.subsample, p.noise_key)


@dataclass(frozen=True)
class Samples:
    """The samples of all trees and draws, of one target: which rows of stored blocks each has."""

    blocks: DataFrame  # n, bins by feature, y_.., has_.. and a tree's bits by (draw, row) as t_..
    place: int  # of the target
    features: list[int]  # of those that the blocks have
    width: int  # features of the blocks
    sizes: np.ndarray  # rows by (draw, tree)

    def chunks(self, trees: range, draws: list[int]) -> DataFrame:
        """CHUNKS of some trees and draws, read from the blocks where they lie."""
        features, width, place, every = self.features, self.width, self.place, len(self.sizes)
        whole = features == list(range(width))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                column = {c: batch.column(c).to_pylist() for c in batch.schema.names}
                for k, n in enumerate(column["n"]):
                    b, y, has = matrix_of(column["bins"][k], n, width, False), targets_of(column[f"y_{place}"][k], n), column[f"has_{place}"][k]
                    b, rows = b if whole else b[features], []
                    for t in trees:
                        bits = np.frombuffer(column[f"t_{t}"][k], np.uint8).reshape(every, -1)
                        bits = bits if has is None else bits & np.frombuffer(has, np.uint8)
                        for d in draws:
                            at = np.flatnonzero(np.unpackbits(bits[d], count=n))
                            if len(at):
                                rows.append(chunk(t, d, b.take(at, axis=1), y.take(at)))
                    if rows:
                        yield pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(zip(*rows), CHUNK_KINDS)], names=CHUNK_NAMES)

        return self.blocks.select("n", "bins", f"y_{place}", f"has_{place}", *[f"t_{t}" for t in trees]).mapInArrow(run, CHUNKS)


def sampled(rows: DataFrame, draws: list[BoostParams], parts: list[tuple[list[int], str]], bins: int) -> list[Samples]:
    """The samples of all draws, for each part: some of the features and a target, without whose value a row is in none of
    its. Rows are written once, in blocks, with a bit for each draw and tree."""
    used, ys, trees = sorted({k for features, _ in parts for k in features}), [y for _, y in parts], max((p.trees for p in draws), default=0)
    names = ["n", "bins", *[f"{x}_{i}" for x in ("y", "has") for i in range(len(ys))], "sizes", *[f"t_{t}" for t in range(trees)]]

    def block(found: list[tuple]) -> pa.RecordBatch:
        b, y, has, bits = (np.concatenate(x, axis=-1) for x in zip(*found))
        targets = [packed_targets(np.where(h, v, 1.0)) for v, h in zip(y, has)]
        present = [None if h.all() else np.packbits(h).tobytes() for h in has]
        sizes = np.stack([(bits if h.all() else bits & h).sum(axis=-1) for h in has]).astype(np.int64).tobytes()
        values = [b.shape[1], b.tobytes(), *targets, *present, sizes, *[np.packbits(bits[:, t], axis=-1).tobytes() for t in range(trees)]]
        return pa.RecordBatch.from_arrays([pa.array([v], pa.binary() if k else pa.int32()) for k, v in enumerate(values)], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in batches:
            ids = batch.column("row_key").cast(pa.binary()).to_pylist()
            bits = np.zeros((len(draws), trees, len(ids)), bool)
            for d, p in enumerate(draws):
                at, tree = rows_in(p, ids)
                bits[d, tree, at] = True
            b = np.empty((len(used), len(ids)), kind_of(bins))
            for i, k in enumerate(used):
                b[i] = batch.column(f"b_{k}").to_numpy(zero_copy_only=False) + 1
            y = np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in ys])
            held.append((b, y, np.stack([batch.column(c).is_valid().to_numpy(zero_copy_only=False) for c in ys]), bits))
            n += len(ids)
            if n >= CHUNK:
                yield block(held)
                held, n = [], 0
        if n:
            yield block(held)

    columns = [f"b_{k}" for k in used] + [F.col(y).cast("double").alias(y) for y in dict.fromkeys(ys)]
    made = rows.select(*columns, F.col("row_key").cast("string").alias("row_key")).mapInArrow(run, ", ".join(f"{c} {'binary' if k else 'int'}" for k, c in enumerate(names)))
    blocks, sizes = stored(made, "samples"), np.zeros((len(ys), len(draws), trees), np.int64)

    def added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(sizes.size, np.int64)
        for batch in batches:
            for x in batch.column(0):
                total += np.frombuffer(x.as_py(), np.int64)
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["sizes"])

    for r in blocks.select("sizes").mapInArrow(added, "sizes binary").collect():
        sizes += np.frombuffer(r["sizes"], np.int64).reshape(sizes.shape)
    return [Samples(blocks, i, [used.index(k) for k in features], len(used), sizes[i]) for i, (features, _) in enumerate(parts)]


WORKSET = "n int, draw smallint, bins binary, g binary"


def workset_of(m: int, released: Callable[[int], list[Router]], by_draw: dict[int, list[int]], params: list[BoostParams], shifts: dict[int, int]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A function of a tree's chunks to WORKSET: the fixed-point gradients of every run that uses a draw, at its margins over
    its released trees, filtered by gradient size."""
    bound = {r: params[r].g_star if params[r].gradient_filter else np.inf for rs in by_draw.values() for r in rs}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for d, n, packed, y in zip(*(batch.column(c).to_pylist() for c in ("draw", "n", "bins", "y"))):
                if d not in by_draw:
                    continue
                whole, y, out = matrix_of(packed, n, m), targets_of(y, n), np.empty((len(by_draw[d]), n), np.int64)
                by_shift = {x: coarser(whole, x) for x in {shifts[r] for r in by_draw[d]}}
                for k, r in enumerate(by_draw[d]):
                    g, bins = np.zeros(n), by_shift[shifts[r]]
                    for router in released(r):
                        g += router.values(bins)
                    g -= y
                    out[k] = np.where(np.abs(g) <= bound[r], np.trunc(g * UNIT).astype(np.int64), LEFT_OUT)
                yield pa.RecordBatch.from_arrays([pa.array([n], pa.int32()), pa.array([d], pa.int16()), pa.array([packed], pa.binary()), pa.array([out.tobytes()], pa.binary())], names=["n", "draw", "bins", "g"])

    return run


def cell_sums(cell: np.ndarray, g: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(sums, counts) by cell of integers; exact. One pass serves both where a float holds a count beside a sum."""
    most = int(np.abs(g).max(initial=0)) * len(g)
    shift = most.bit_length() + 1
    if shift + len(g).bit_length() <= 53:
        both = np.bincount(cell, g + float(1 << shift), size)
        n = np.rint(both * 2.0**-shift)
        return (both - n * (1 << shift)).astype(np.int64), n.astype(np.int64)
    # halves below 2**53 in float sums, so integers come out whole
    return (np.bincount(cell, g >> 16, size).astype(np.int64) << 16) + np.bincount(cell, g & 0xFFFF, size).astype(np.int64), np.bincount(cell, minlength=size)


def level_sums(asked: dict[int, tuple[Tree, list[int]]], by_draw: dict[int, list[int]], m: int, bins: dict[int, int], shifts: dict[int, int]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A function of workset batches to (run, node, cells): what they sum up to per run and open node of its tree, as bytes
    the cells (feature, 1 + bin) that have rows, their counts and gradient sums. It gives a row per open node, or where all
    cells of a level are too many to be held, per open node and chunk."""
    ways = {}
    for run, (tree, nodes) in asked.items():
        router = Router(tree, m, bins[run])
        slot = np.full(len(router.ids), len(nodes))
        slot[np.searchsorted(router.ids, nodes)] = np.arange(len(nodes))
        ways[run] = router, slot[router.order], nodes, bins[run] + 1, shifts[run]

    def sent(run: int, sums: np.ndarray, counts: np.ndarray, cells: np.ndarray | None = None) -> pa.RecordBatch:
        """Of sums by (node, cell), or of given cells, all nodes' in turn."""
        nodes, each = ways[run][2], m * ways[run][3]
        if cells is None:
            cells = np.flatnonzero(counts)
            sums, counts = sums[cells], counts[cells]
        ends = np.searchsorted(cells, np.arange(len(nodes) + 1) * each).tolist()
        blobs = [(cells[a:b] - k * each).astype(np.int32).tobytes() + counts[a:b].astype(np.int32).tobytes() + sums[a:b].tobytes() for k, (a, b) in enumerate(zip(ends, ends[1:]))]
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(nodes), run, np.int16)), pa.array(nodes, pa.int32()), pa.array(blobs, pa.binary())], names=["run", "node", "cells"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for batch in batches:
            for n, d, packed, gs in zip(*(batch.column(c).to_pylist() for c in ("n", "draw", "bins", "g"))):
                by_shift = {0: matrix_of(packed, n, m)}
                for run, g in zip(by_draw.get(d, ()), np.frombuffer(gs, np.int64).reshape(-1, n)):
                    if run not in ways:
                        continue
                    router, slot, nodes, width, shift = ways[run]
                    if shift not in by_shift:
                        by_shift[shift] = coarser(by_shift[0], shift)
                    b = by_shift[shift]
                    own, out = slot.take(router.place(b)), g == LEFT_OUT
                    if out.any():
                        own[out], g = len(nodes), np.where(out, 0, g)
                    if len(nodes) * m * width > DENSE:
                        keep = np.flatnonzero(own < len(nodes))
                        cell = ((own[keep] * m)[:, None] + np.arange(m)) * width + b[:, keep].T
                        cells, at = np.unique(cell, return_inverse=True)
                        yield sent(run, *cell_sums(at.ravel(), np.repeat(g[keep], m), len(cells)), cells)
                        continue
                    base, size = own * width, (len(nodes) + 1) * width
                    parts = [cell_sums(base + b[k], g, size) for k in range(m)]
                    both = tuple(np.stack([x[i].reshape(-1, width)[:-1] for x in parts], axis=1) for i in (0, 1))
                    held[run] = tuple(x + y for x, y in zip(held[run], both)) if run in held else both
        for run, (sums, counts) in held.items():
            yield sent(run, sums.ravel(), counts.ravel())

    return add


def cuts_for(counts: np.ndarray, plan: BudgetPlan | None, params: BoostParams, ids: tuple) -> list[np.ndarray]:
    """Cut bins of every feature from its bin counts: noised and clamped where the plan asks for it."""
    out = []
    for k in range(len(counts)):
        w = counts[k, 1:].astype(np.float64)
        noised = plan is not None and params.proposal_noise
        if noised and params.proposal == "joint":
            # the joint choice is the release itself; a count moves by 1 and the utility by 2
            out.append(np.array(joint_quantiles(w, min(params.max_cuts, len(w) - 1), plan.sketch_feature, "|".join(map(str, ids)), k)))
            continue
        if noised:
            scale = plan.m / plan.sketch / (1 if params.proposal == "global" else 1 / plan.h)
            w = np.maximum(0.0, w + [laplace_of(u, scale) for u in uniforms_of((*ids, k), list(map(str, range(len(w))))).tolist()])
        out.append(cuts_of(w, params.max_cuts))
    return out


def plans_of(spec: DatasetSpec, params: BoostParams) -> list[BudgetPlan] | None:
    if not params.private:
        return None
    if params.disjoint:  # trees on disjoint rows: each has the whole budget
        eps = before_sampling(params.epsilon_total, 1.0)
        return [BudgetPlan(eps, spec.m, params.max_depth, params.shares, params.early_leaf_bonus)] * params.trees
    return plan_ensemble(params.epsilon_total, params.trees, params.subsample, spec.m, params.max_depth, params.shares, params.tree_weights, params.early_leaf_bonus)


@dataclass(frozen=True)
class Grower:
    """What a run decides on for one of its trees, node by node."""

    params: BoostParams
    plan: BudgetPlan | None
    number: int
    cuts: tuple[np.ndarray, ...] | None = None  # of the whole tree, once chosen

    def choose(self, node: int, sums: np.ndarray, n: np.ndarray, bins: np.ndarray | None = None) -> tuple[Split | None, list[np.ndarray]]:
        """(split, cuts) of a node from its sums and counts by feature and 1 + bin; with `bins`, of the columns
        listed there by feature only, ascending: the others are empty, and a cut there parts the rows as one before it."""
        p, key = self.params, self.params.noise_key
        if self.cuts is not None:
            cuts = list(self.cuts)
        else:
            whole = n
            if bins is not None:
                whole = np.zeros((len(n), p.bins + 1), n.dtype)
                np.add.at(whole, (np.arange(len(n))[:, None], bins), n)
            cuts = cuts_for(whole, self.plan, p, (key, "sketch", self.number, node) if p.proposal == "local" else (f"{key}|sketch|{self.number}",))
        eps = self.plan.level if self.plan and p.split_mode == "exponential" else None
        at = bins if bins is None else [np.searchsorted(bins[k, 1:], c + 1, "right") - 1 for k, c in enumerate(cuts)]
        return best_split(sums, n, cuts, p.lam, max(p.min_child, p.min_hessian), p.min_gain, p.strict, eps, p.g_star, (f"{key}|split|{self.number}", node), at), cuts

    def released(self, tree: Tree) -> Tree:
        """The tree with its leaves' released values, from their exact sums."""
        p = self.params
        for leaf in tree.leaves():
            eps = self.plan.leaf(leaf.depth) if self.plan else float("inf")
            u = uniform_of(f"{p.noise_key}|leaf|{self.number}", leaf.node)
            value = leaves.leaf_value(p.leaf_mode, leaf.value, leaf.n, eps, p.g_star, p.lam, p.min_child, u, self.number, p.learning_rate, p.strict)
            leaf.value = value * p.learning_rate
        for x in tree.nodes.values():  # inner sums and exact counts are not released
            x.n = 0 if self.plan else x.n
            x.value = 0.0 if x.feature >= 0 else x.value
        return tree


DECIDED = "run smallint, node int, g double, n bigint, feature int, cut_bin int, default_left boolean, gl double, nl bigint, gr double, nr bigint, cuts binary"
EMPTY = b""


def node_sums(blobs: list[bytes], m: int, bins: int) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """(sums, counts, None) by feature and 1 + bin of a node from what tasks sent; or where that is too much to be held,
    (sums, counts, places) of the 1 + bin that have rows, with 0, 1 and the last."""
    size = [len(b) // 16 for b in blobs]
    cells, counts = (np.concatenate([np.frombuffer(b, np.int32, k, i * 4 * k) for b, k in zip(blobs, size)] or [np.zeros(0, np.int32)]).astype(np.int64) for i in (0, 1))
    sums = np.concatenate([np.frombuffer(b, np.int64, k, 8 * k) for b, k in zip(blobs, size)] or [np.zeros(0, np.int64)])
    if m * (bins + 1) <= DENSE // 32:
        out = np.zeros((2, m * (bins + 1)), np.int64)
        np.add.at(out[0], cells, sums)
        np.add.at(out[1], cells, counts)
        return *out.reshape(2, m, bins + 1), None
    kept, at = np.unique(cells, return_inverse=True)
    s, n = np.zeros((2, len(kept)), np.int64)
    np.add.at(s, at, sums)
    np.add.at(n, at, counts)
    each = [kept[np.searchsorted(kept, k * (bins + 1)) : np.searchsorted(kept, (k + 1) * (bins + 1))] - k * (bins + 1) for k in range(m)]
    places = [np.unique(np.concatenate((x, [0, 1, bins]))) for x in each]
    most = max(map(len, places))
    found, out, done = np.full((m, most), bins), np.zeros((2, m, most), np.int64), 0
    for k, (own, place) in enumerate(zip(each, places)):
        found[k, : len(place)] = place
        inside = np.searchsorted(place, own)
        out[0, k, inside], out[1, k, inside] = s[done : done + len(own)], n[done : done + len(own)]
        done += len(own)
    return *out, found


def decided(run: int, node: int, blobs: list[bytes], grower: Grower, m: int) -> tuple:
    """A DECIDED row from what tasks sent."""
    return decided_by(run, node, *node_sums(blobs, m, grower.params.bins), grower, m)


def decided_by(run: int, node: int, sums: np.ndarray, n: np.ndarray, bins: np.ndarray | None, grower: Grower, m: int) -> tuple:
    """A DECIDED row from a node's sums."""
    g, total = (float(sums[0].sum()) / UNIT, int(n[0].sum())) if m else (0.0, 0)
    if not grower.params.max_depth or not m:
        return run, node, g, total, -1, -1, True, 0.0, 0, 0.0, 0, EMPTY
    split, cuts = grower.choose(node, sums, n, bins)
    told = np.concatenate(([len(c) for c in cuts], *cuts)).astype(np.int32).tobytes() if node == 0 else EMPTY
    if not split:
        return run, node, g, total, -1, -1, True, 0.0, 0, 0.0, 0, told
    return run, node, g, total, split.feature, split.cut_bin, split.default_left, split.gl, split.nl, split.gr, split.nr, told


def merged(batches: Iterator[pa.RecordBatch], growers: dict[int, Grower], m: int) -> list[tuple]:
    """DECIDED rows of nodes from what was sent of their cells."""
    held: dict[tuple[int, int], list[bytes]] = {}
    for batch in batches:
        for run, node, cells in zip(*(batch.column(c).to_pylist() for c in ("run", "node", "cells"))):
            held.setdefault((run, node), []).append(cells)
    return [decided(run, node, blobs, growers[run], m) for (run, node), blobs in held.items()]


def grown(growers: dict[int, Grower], m: int, ask: Callable[[dict[int, tuple[Tree, list[int]]], dict[int, Grower]], list[tuple]]) -> dict[int, Tree]:
    """One tree of each run, level by level; `ask` gives the DECIDED rows of the runs' open nodes."""
    trees, asked, growers = {r: Tree() for r in growers}, {r: [0] for r in growers}, dict(growers)
    while asked:
        found = {x[:2]: x for x in ask({r: (trees[r], nodes) for r, nodes in asked.items()}, {r: growers[r] for r in asked})}
        following = {}
        for r, nodes in asked.items():
            tree, p = trees[r], growers[r].params
            for node in nodes:
                _, _, g, n, feature, cut_bin, default_left, gl, nl, gr, nr, told = found.get((r, node)) or decided(r, node, [], growers[r], m)
                if node == 0:
                    tree.nodes[0].n, tree.nodes[0].value = n, g  # until released
                    if told and p.proposal != "local":
                        told = np.frombuffer(told, np.int32)
                        growers[r] = replace(growers[r], cuts=tuple(np.split(told[m:].astype(np.int64), np.cumsum(told[: m - 1]))))
                if feature >= 0:
                    left, right = tree.split(node, feature, cut_bin, default_left)
                    left.value, left.n, right.value, right.n = gl, nl, gr, nr
                    if left.depth < p.max_depth:
                        following.setdefault(r, []).extend((left.node, right.node))
        asked = following
    return {r: growers[r].released(tree) for r, tree in trees.items()}


def grown_by_jobs(work: DataFrame, growers: dict[int, Grower], by_draw: dict[int, list[int]], m: int, bins: dict[int, int], shifts: dict[int, int]) -> dict[int, Tree]:
    """Trees over any number of rows. A level of all of them is one job: tasks sum up their rows, a node's sums meet in a
    task, which decides on its split, and the driver gets the splits."""
    ways = max(1, work.sparkSession.sparkContext.defaultParallelism)

    def ask(asked: dict[int, tuple[Tree, list[int]]], here: dict[int, Grower]) -> list[tuple]:
        def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            if rows := merged(batches, here, m):
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), KINDS)], names=NAMES)

        sums = work.mapInArrow(level_sums(asked, by_draw, m, bins, shifts), "run smallint, node int, cells binary")
        part = sums.repartition(ways, "run", "node").mapInArrow(decide, DECIDED).toArrow()
        return list(zip(*(part[c].to_pylist() for c in NAMES)))

    return grown(growers, m, ask)


#: Rows of a tree's sample up to which one task grows all trees of a run; it holds some 50 bytes and three bins per feature of each.
IN_A_TASK = 1 << 22
#: Rows of samples, with their copies, that a job deals out to tasks: on disk, some 10 to 20 bytes each until the next job.
DEALT = 1 << 24


def gradients_of(codes: Codes, y: np.ndarray, routers: list[Router], bound: float) -> np.ndarray:
    """The fixed-point gradients of a run's rows at its margins over its trees, as `workset_of` gives them."""
    g = codes.margins(routers, CHUNK)
    g -= y
    out = np.trunc(g * UNIT).astype(np.int64)
    out[np.abs(g) > bound] = LEFT_OUT
    return out


class HeldRows:
    """A tree's rows in one task, by the open node that each is in: a split parts its node's rows, the smaller part is
    summed up, and the sums of the larger are what is left of the node's."""

    def __init__(self, codes: Codes, g: np.ndarray):
        """Of rows and their fixed-point gradients."""
        self.codes, self.bins, self.g, self.width = codes, codes.bins, g, codes.width
        rows = np.flatnonzero(g != LEFT_OUT)
        self.most = int(np.abs(g[rows]).max(initial=0))
        self.open: dict[int, tuple[np.ndarray, tuple[np.ndarray, np.ndarray] | None]] = {0: (rows, None)}

    def sums(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(sums, counts) by feature and 1 + bin; exact."""
        g, out = self.g.take(rows), np.zeros((2, len(self.bins), self.width), np.int64)
        most = self.most * len(rows)
        shift = most.bit_length() + 1
        both, plain = shift + len(rows).bit_length() <= 53, most < 1 << 53
        weight = g + float(1 << shift) if both else g.astype(np.float64) if plain else None
        if plain and len(rows) > self.codes.cells:  # by groups of features, whose sums are then parted
            for k, (code, size) in enumerate(zip(self.codes.codes, self.codes.sizes)):
                cell = code.take(rows)
                g, n = np.bincount(cell, weight, size), None if both else np.bincount(cell, minlength=size)
                if both:
                    n = np.rint(g * 2.0**-shift)
                    g -= n * (1 << shift)
                self.codes.parted(k, g.astype(np.int64), out[0])
                self.codes.parted(k, n.astype(np.int64), out[1])
            return out[0], out[1]
        found = np.empty((len(self.bins), self.width))
        for k, own in enumerate(self.bins):
            cell = own.take(rows)
            if both:  # a float holds a count beside a sum
                found[k] = np.bincount(cell, weight, self.width)
            elif plain:
                out[0, k], out[1, k] = np.bincount(cell, weight, self.width), np.bincount(cell, minlength=self.width)
            else:
                out[0, k], out[1, k] = cell_sums(cell, g, self.width)
        if both:
            n = np.rint(found * 2.0**-shift)
            out[0], out[1] = found - n * (1 << shift), n
        return out[0], out[1]

    def level(self, tree: Tree, nodes: list[int]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(node, sums, counts) of the nodes of a level, whose parents were the level before."""
        kept = len(nodes) * len(self.bins) * self.width <= DENSE
        if nodes != [0]:
            before, self.open = self.open, {}
            for x in (tree.nodes[v] for v in sorted({(v - 1) // 2 for v in nodes})):
                rows, whole = before.pop(x.node)
                b = self.bins[x.feature].take(rows)
                left = b <= x.cut_bin + 1
                if not x.default_left:
                    left &= b > 0
                parts = [(x.left, rows.compress(left)), (x.right, rows.compress(~left))]
                (small, few), (large, many) = sorted(parts, key=lambda part: len(part[1]))
                found = self.sums(few) if kept and whole else None
                self.open[small] = few, found
                self.open[large] = many, found and (whole[0] - found[0], whole[1] - found[1])
        for v in nodes:
            rows, found = self.open[v]
            found = found or self.sums(rows)
            if kept:
                self.open[v] = rows, found
            yield v, *found


def windows(rows: list[int], most: int) -> Iterator[range]:
    """All trees in turn, as many at a time as have at most so many rows together; one that has more is alone."""
    first, total = 0, 0
    for t, n in enumerate(rows):
        if t > first and total + n > most:
            yield range(first, t)
            first, total = t, 0
        total += n
    yield range(first, len(rows))


def ways_to_part(draws: int, ways: int) -> int:
    """Into how many sets the runs of each draw go, each with a copy of its rows: the fewest that leave no core idle that
    more would not."""
    return min(range(1, max(1, 3 * ways // draws) + 1), key=lambda k: (-(-draws * k // ways) / k, k))


def whole_models(samples: Samples, growers: dict[int, list[Grower]], by_draw: dict[int, list[int]], m: int, bins: dict[int, int], shifts: dict[int, int]) -> dict[int, tuple[list[Tree], list[float]]]:
    """(trees, seconds of each) of runs whose samples fit a task: a task has some of a draw's runs and its chunks in order of
    their trees, and asks its own rows level by level, so as many trees of all the models are one job as DEALT lets be."""
    spark = samples.blocks.sparkSession
    parts = ways_to_part(len(by_draw), max(1, spark.sparkContext.defaultParallelism))  # each has a copy of its draw's chunks
    sets = [(d, rs[k::parts]) for d, rs in by_draw.items() for k in range(min(parts, len(rs)))]
    trees = max(map(len, growers.values()))
    rows, found, released = sum(samples.sizes[d, :trees] for d, _ in sets).tolist(), {r: ([], []) for r in growers}, []
    for window in windows(rows, DEALT):
        got = models_of(samples.chunks(window, list(by_draw)), window, released, {r: gs for r, gs in growers.items() if len(gs) > window.start}, sets, m, bins, shifts)
        for r, each in got.items():
            for all_, some in zip(found[r], each):
                all_.extend(some)
        if window.stop < trees:
            released.append(spark.sparkContext.broadcast({r: [Router(x, m, bins[r]) for x in new] for r, (new, _) in got.items()}))
            freed(spark)
    for routers in released:
        routers.destroy()
    return found


def models_of(chunks: DataFrame, window: range, released: list, growers: dict[int, list[Grower]], sets: list[tuple[int, list[int]]], m: int, bins: dict[int, int], shifts: dict[int, int]) -> dict[int, tuple[list[Tree], list[float]]]:
    """The same for some of the trees, in a job; the routers of those before are released."""
    params = {r: gs[0].params for r, gs in growers.items()}
    bound = {r: p.g_star if p.gradient_filter else np.inf for r, p in params.items()}

    def asks(r: int, codes: Codes, y: np.ndarray, routers: list[Router]) -> Callable[[dict[int, tuple[Tree, list[int]]], dict[int, Grower]], list[tuple]]:
        """What tells of a run's open nodes, from the rows of a tree's sample."""
        rows = HeldRows(codes, gradients_of(codes, y, routers, bound[r]))
        return lambda asked, growing: [decided_by(r, v, *sums, None, growing[r], m) for v, *sums in rows.level(*asked[r])]

    def asks_sparsely(r: int, held: list[pa.RecordBatch], draw: int, routers: list[Router]) -> Callable[[dict[int, tuple[Tree, list[int]]], dict[int, Grower]], list[tuple]]:
        """The same where the cells of a node are too many to be held."""
        work = list(workset_of(m, lambda _: routers, {draw: [r]}, params, shifts)(held))
        return lambda asked, growing: merged(level_sums(asked, {draw: [r]}, m, bins, shifts)(work), growing, m)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, models, took, at = None, {}, [], -1

        def grow(upto: int) -> None:
            """The trees before `upto`, each from the rows that are held for it."""
            nonlocal held, at
            for t in range(at, upto):
                began = time.time()
                whole = y = codes = None
                for r in sorted(sets[here][1], key=shifts.get):
                    if r in models and t < len(growers[r]):
                        routers, tree = models[r]
                        if m * (bins[r] + 1) > DENSE // 32:
                            ask = asks_sparsely(r, held, sets[here][0], routers)
                        else:
                            if whole is None:
                                whole, y = rows_of(held, m)
                            if codes is None or codes[0] != shifts[r]:
                                codes = shifts[r], Codes(coarser(whole, shifts[r]), bins[r] + 1)
                            ask = asks(r, codes[1], y, routers)
                        tree.append(grown({r: growers[r][t]}, m, ask)[r])
                        routers.append(Router(tree[-1], m, bins[r]))
                took.append((time.time() - began) / max(1, len(models)))
                held = []
            at = upto

        held: list[pa.RecordBatch] = []

        def ended() -> Iterator[pa.RecordBatch]:
            if here is not None:
                grow(min(window.stop, max((len(growers[r]) for r in models), default=0)))
                for r, (_, trees) in models.items():
                    yield pa.RecordBatch.from_arrays([pa.array([r], pa.int16()), pa.array([pickle.dumps((trees, took[: len(trees)]))], pa.binary())], names=["run", "model"])

        for batch in batches:
            for k in range(batch.num_rows):
                part, t = batch.column("part")[k].as_py(), batch.column("tree_id")[k].as_py()
                if part != here:
                    yield from ended()
                    here, took, at, held = part, [], window.start, []
                    models = {r: ([x for before in released for x in before.value.get(r, [])], []) for r in sets[part][1] if r in growers}
                if t > at:
                    grow(t)
                held.append(batch.slice(k, 1))
        yield from ended()

    draws = {d: F.array(*[F.lit(k) for k, (x, _) in enumerate(sets) if x == d]) for d, _ in sets}
    owner = F.coalesce(*[F.when(F.col("draw") == d, own) for d, own in draws.items()])
    dealt = chunks.withColumn("part", F.explode(owner)).repartitionById(len(sets), F.col("part")).sortWithinPartitions("part", "tree_id")
    found = {r["run"]: pickle.loads(r["model"]) for r in dealt.mapInArrow(run, "run smallint, model binary").collect()}
    for r in growers.keys() - found.keys():  # no row was drawn for it
        own = growers[r][window.start : window.stop]
        found[r] = [grown({r: g}, m, lambda asked, growing: [])[r] for g in own], [0.0] * len(own)
    return found


NAMES = [x.split()[0] for x in DECIDED.split(", ")]
KINDS = [{"smallint": pa.int16(), "int": pa.int32(), "bigint": pa.int64(), "double": pa.float64(), "boolean": pa.bool_(), "binary": pa.binary()}[x.split()[1]] for x in DECIDED.split(", ")]


def charges_of(params: BoostParams, plan: BudgetPlan, number: int) -> list[Charge]:
    """What a tree releases. In strict mode a noisy average also tells of an exact count; that charge is extra, and the
    whole tree is scaled by `strict_plan` so that both fit."""
    charges = plan.charges(number)
    if params.strict and params.leaf_mode == "noisy_average":
        more = strict_average_charge(plan.leaf(), params.min_child, params.lam) - plan.leaf()
        charges.append(Charge(number, "leaf count", params.max_depth, "leaf counts", more, note="exact count, floored"))
    return charges


def strict_plan(params: BoostParams, plan: BudgetPlan) -> BudgetPlan:
    """The largest plan whose charges, with those for exact counts, stay within the given plan's eps."""
    if not (params.strict and params.leaf_mode == "noisy_average"):
        return plan
    low, high = 0.0, plan.eps_tree
    for _ in range(100):
        middle = (low + high) / 2
        spent = sequential([c.epsilon for c in charges_of(params, replace(plan, eps_tree=middle), 0)])
        low, high = (middle, high) if spent <= plan.eps_tree else (low, middle)
    return replace(plan, eps_tree=low)


def parts_of(params: BoostParams) -> list[float]:
    """The shares of the trees' disjoint parts."""
    return [params.learning_rate * (1 - params.learning_rate) ** t for t in range(params.trees)]


def drawn_for(binned: DataFrame, draws: list[BoostParams], later: dict[int, BoostParams] | None = None) -> DataFrame:
    """The rows of all trees' samples of each draw, with tree_id and the draw's number; the samples by draws of one share
    are from one pass. Draws in `later` are left to `sampled`, which has all of them from one pass: its rows are without both."""
    found, shares = [], {}
    if later:
        found.append(binned.withColumns({"tree_id": F.lit(None).cast("int"), "draw": F.lit(None).cast("smallint")}))
    for d, p in enumerate(draws):
        if later and d in later:
            continue
        if p.disjoint:
            found.append(sampling.disjoint(binned, parts_of(p), p.noise_key).withColumn("draw", F.lit(d).cast("smallint")))
        else:
            shares.setdefault((p.subsample, p.shared_draws), []).append((d, p.trees, p.noise_key))
    return reduce(DataFrame.unionByName, [*found, *(sampling.with_draws(binned, each, gamma, shared=shared) for (gamma, shared), each in shares.items())])


@dataclass(frozen=True)
class Target:
    """What runs learn from rows (row_key, b_.., and targets): some of their features, in the spec's order, and a target."""

    spec: DatasetSpec
    runs: list[BoostParams]
    features: list[int]
    y: str = "y"


def fit_many(binned: DataFrame, spec: DatasetSpec, runs: list[BoostParams], materialized: bool = True, bins: int | None = None) -> list[tuple[TreeModel, Ledger, list[float]]]:
    """(model, ledger, seconds per tree) of every run, for BINNED rows (row_key, b_.., y) of one bin count.

    Runs that draw alike share their samples. A tree of all runs takes one job a level; its seconds are shared out evenly.
    Every run's result is what `fit` gives for it alone. With `bins`, the even bins of the rows, runs may have coarser ones:
    a half as many, a quarter and so on, which are the same as if the rows had them.
    """
    return fit_targets(binned, [Target(spec, runs, list(range(spec.m)))], materialized, bins)[0]


def fit_targets(binned: DataFrame, targets: list[Target], materialized: bool = True, bins: int | None = None) -> list[list[tuple[TreeModel, Ledger, list[float]]]]:
    """The same for several targets of the same rows, of each what `fit_many` gives for it alone: samples of all are drawn
    once. A row whose target is null is not one of that target."""
    every = [p for target in targets for p in target.runs]
    if bins is None and len({p.bins for p in every}) != 1:
        raise ValueError("runs need one bin count, that of the rows")
    bins = bins or every[0].bins
    if any(p.bins << ((bins // p.bins).bit_length() - 1) != bins for p in every):
        raise ValueError("a run's bin count must be that of the rows, or a half of it, a quarter and so on")
    drawing = [(p.noise_key, p.trees, p.disjoint, *((p.learning_rate, False) if p.disjoint else (p.subsample, p.shared_draws))) for p in every]
    draws = sorted(set(drawing))
    each = [every[drawing.index(d)] for d in draws]
    drawn = drawn_for(binned, each, dict(enumerate(each)) if materialized else None)
    if materialized:
        held = sampled(drawn, each, [(target.features, target.y) for target in targets], bins)
    out, done = [], 0
    for i, target in enumerate(targets):
        draw_of = [draws.index(d) for d in drawing[done : done + len(target.runs)]]
        done += len(target.runs)
        out.append(fit_drawn(held[i] if materialized else drawn.where(F.col(target.y).isNotNull()), target, draw_of, bins))
    return out


def fit_drawn(drawn: Samples | DataFrame, target: Target, draw_of: list[int], bins: int) -> list[tuple[TreeModel, Ledger, list[float]]]:
    """The models of a target from its samples, or from drawn rows, and the draw of each run."""
    materialized = isinstance(drawn, Samples)
    spark, spec, runs = (drawn.blocks if materialized else drawn).sparkSession, target.spec, target.runs
    width_of, shifts = {r: p.bins for r, p in enumerate(runs)}, {r: (bins // p.bins).bit_length() - 1 for r, p in enumerate(runs)}
    by_draw = {d: [r for r in range(len(runs)) if draw_of[r] == d] for d in sorted(set(draw_of))}
    plans = [x and [strict_plan(p, plan) for plan in x] for p, x in ((p, plans_of(spec, p)) for p in runs)]
    ledgers = [Ledger(p.epsilon_total if x else float("inf"), 1.0 if p.disjoint else p.subsample, disjoint_trees=p.disjoint) for p, x in zip(runs, plans)]
    models, seconds = [TreeModel(spec, p.bins, params=asdict(p) | {"noise_key": ""}) for p in runs], [[] for _ in runs]
    growers = {r: [Grower(p, plans[r][t] if plans[r] else None, t) for t in range(p.trees)] for r, p in enumerate(runs)}
    for r, p in enumerate(runs):
        for t in range(p.trees if plans[r] else 0):
            ledgers[r].charge(charges_of(p, plans[r][t], t))
    large = set(by_draw)
    if materialized:
        large = {d for d in by_draw if drawn.sizes[d].max(initial=0) > IN_A_TASK}
    if small := {d: rs for d, rs in by_draw.items() if d not in large}:
        for r, (trees, each) in whole_models(drawn, {r: growers[r] for rs in small.values() for r in rs}, small, spec.m, width_of, shifts).items():
            models[r].trees, seconds[r] = trees, each
    many = {d: by_draw[d] for d in large}
    released = []
    for t in range(max((runs[r].trees for rs in many.values() for r in rs), default=0)):
        began = time.time()
        active = {d: [r for r in rs if t < runs[r].trees] for d, rs in many.items()}
        own = [d for d, rs in active.items() if rs]
        of_tree = drawn.chunks(range(t, t + 1), own) if materialized else chunked(drawn.where((F.col("tree_id") == t) & F.col("draw").isin(own)), target.features, target.y, bins)
        work = of_tree.mapInArrow(workset_of(spec.m, lambda r, trees=tuple(released): [x.value[r] for x in trees], active, runs, shifts), WORKSET).persist(StorageLevel.MEMORY_AND_DISK)
        trees = grown_by_jobs(work, {r: growers[r][t] for rs in active.values() for r in rs}, active, spec.m, width_of, shifts)
        released.append(spark.sparkContext.broadcast({r: Router(tree, spec.m, runs[r].bins) for r, tree in trees.items()}))
        for r, tree in trees.items():
            models[r].trees.append(tree)
            seconds[r].append((time.time() - began) / len(trees))
        work.unpersist()
    for trees in released:
        trees.destroy()
    return list(zip(models, ledgers, seconds))


def fit(binned: DataFrame, spec: DatasetSpec, params: BoostParams, materialized: bool = True) -> tuple[TreeModel, Ledger, list[float]]:
    """(model, ledger, seconds per tree) for BINNED rows (row_key, b_.., y)."""
    return fit_many(binned, spec, [params], materialized)[0]
