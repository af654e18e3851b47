"""Trees and ensembles: node tables, scoring expressions, vectorised scoring."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from privgrove.operators.schema import DatasetSpec

NODES = "tree int, node int, depth int, feature int, cut_bin int, cut double, default_left boolean, left int, right int, value double, n bigint"


@dataclass
class Node:
    """A node; a leaf has feature -1. Children of node i of a full tree are 2i+1 and 2i+2."""

    node: int
    depth: int
    feature: int = -1
    cut_bin: int = -1
    default_left: bool = True
    left: int = -1
    right: int = -1
    value: float = 0.0
    n: int = 0


@dataclass
class Tree:
    nodes: dict[int, Node] = field(default_factory=lambda: {0: Node(0, 0)})

    def leaves(self) -> list[Node]:
        return [x for x in self.nodes.values() if x.feature < 0]

    def split(self, at: int, feature: int, cut_bin: int, default_left: bool) -> tuple[Node, Node]:
        x = self.nodes[at]
        x.feature, x.cut_bin, x.default_left, x.left, x.right = feature, cut_bin, default_left, 2 * at + 1, 2 * at + 2
        pair = Node(x.left, x.depth + 1), Node(x.right, x.depth + 1)
        self.nodes |= {c.node: c for c in pair}
        return pair

    def expression(self, leaf=lambda x: F.lit(x.value), at: int = 0) -> Column:
        """Nested CASE over bins: `leaf` of the node that a row reaches."""
        x = self.nodes[at]
        if x.feature < 0:
            return leaf(x)
        b = F.col(f"b_{x.feature}")
        goes_left = (b <= x.cut_bin) & (b >= 0) | (F.lit(x.default_left) & (b < 0))
        return F.when(goes_left, self.expression(leaf, x.left)).otherwise(self.expression(leaf, x.right))

    def arrays(self) -> tuple[np.ndarray, ...]:
        """(feature, cut_bin, default_left, left, right, value, id) by dense position; a leaf is its own child."""
        ids = sorted(self.nodes)
        place = {i: k for k, i in enumerate(ids)}
        xs = [self.nodes[i] for i in ids]
        child = lambda x, c: place[c] if x.feature >= 0 else place[x.node]
        return (
            np.array([max(x.feature, 0) for x in xs]),
            np.array([x.cut_bin for x in xs]),
            np.array([x.default_left for x in xs]),
            np.array([child(x, x.left) for x in xs]),
            np.array([child(x, x.right) for x in xs]),
            np.array([x.value for x in xs]),
            np.array(ids),
        )

    def depth(self) -> int:
        return max(x.depth for x in self.nodes.values())


def routed(arrays: tuple[np.ndarray, ...], bins: np.ndarray, depth: int) -> np.ndarray:
    """Dense position of the node that each row of bins (rows, features) reaches."""
    feature, cut, default_left, left, right = arrays[:5]
    at, rows = np.zeros(len(bins), np.int64), np.arange(len(bins))
    for _ in range(depth):
        b = bins[rows, feature[at]]
        at = np.where(np.where(b < 0, default_left[at], b <= cut[at]), left[at], right[at])
    return at


def bins_of(batch: pa.RecordBatch, m: int) -> np.ndarray:
    return np.stack([batch.column(f"b_{k}").to_numpy(zero_copy_only=False) for k in range(m)], axis=1) if m else np.zeros((batch.num_rows, 0), np.int16)


def places_of(batch: pa.RecordBatch, m: int) -> np.ndarray:
    """1 + bin by (feature, row), as indices; place 0 is missing."""
    out = np.empty((m, batch.num_rows), np.intp)
    for k in range(m):
        np.add(batch.column(f"b_{k}").to_numpy(zero_copy_only=False), 1, out=out[k], casting="unsafe")
    return out


def first_bit(left: np.ndarray) -> np.ndarray:
    """The place of the lowest bit of each; none is 0."""
    left &= np.negative(left.view(np.int64)).view(np.uint64)  # a power of two, exact as a float; its exponent is the place
    return (left.astype(np.float64).view(np.int64) >> 52) - 1023


class Router:
    """Finds the leaves of one tree for many rows.

    A feature's bin rules out leaves: a table has, by feature and 1 + bin, a bit for each leaf in order that stays, and the
    first bit that all features leave is the row's leaf. Trees of over 64 leaves or with very large tables are walked.
    """

    MOST = 1 << 14

    def __init__(self, tree: Tree, m: int, bins: int):
        self.arrays, self.depth, self.used, self.tables = tree.arrays(), tree.depth(), [], []
        feature, cut, default_left, left, right, self.value, self.ids = self.arrays
        self.order = np.arange(len(self.ids))
        if len(tree.leaves()) > 64 or m * (bins + 1) > self.MOST:
            return
        order, tables = [], {}

        def walk(at: int) -> int:
            """The bits of the leaves below a node."""
            if left[at] == at:
                order.append(at)
                return 1 << (len(order) - 1)
            low = walk(left[at])
            high = walk(right[at])
            t = tables.setdefault(int(feature[at]), np.full(bins + 1, (1 << 64) - 1, np.uint64))
            stays = np.uint64(((1 << 64) - 1) ^ low)
            t[cut[at] + 2 :] &= stays
            if not default_left[at]:
                t[0] &= stays
            return low | high

        walk(0)
        self.order, self.used = np.array(order), sorted(tables)
        self.tables, self.arrays = [tables[k] for k in self.used], None

    def place(self, bins: np.ndarray) -> np.ndarray:
        """Of 1 + bin by (feature, row): each row's place in `order`, the dense positions of nodes."""
        if self.arrays is not None:
            return routed(self.arrays, bins.T - 1, self.depth)
        if not self.used:
            return np.zeros(bins.shape[1], np.int64)
        left = self.tables[0].take(bins[self.used[0]])
        held = np.empty_like(left)
        for t, k in zip(self.tables[1:], self.used[1:]):
            left &= np.take(t, bins[k], out=held, mode="clip")
        return first_bit(left)

    def values(self, bins: np.ndarray) -> np.ndarray:
        return self.value[self.order].take(self.place(bins))

    def joint(self, groups: list[list[int]], present: list[np.ndarray]) -> list[tuple[int, np.ndarray]]:
        """(group, table by code) of the groups of features that the tree uses; see `Codes`."""
        out, tables = [], dict(zip(self.used, self.tables))
        for i, group in enumerate(groups):
            if any(k in tables for k in group):
                t = np.full(1, (1 << 64) - 1, np.uint64)
                for k in group:
                    own = tables[k][present[k]] if k in tables else np.full(len(present[k]), (1 << 64) - 1, np.uint64)
                    t = (t[:, None] & own).ravel()
                out.append((i, t))
        return out


class Codes:
    """Rows in groups of features whose present bins have few combinations: a code a group, so that trees over the same
    rows look up groups in place of features."""

    def __init__(self, bins: np.ndarray, width: int):
        """Of 1 + bin by (feature, row) below `width`."""
        self.bins, self.width, most = bins, width, min(Router.MOST, bins.shape[1] // 8)
        self.present = [np.flatnonzero(np.bincount(b, minlength=width)) for b in bins]
        self.groups, self.sizes = [], []
        for k in sorted(range(len(bins)), key=lambda k: -len(self.present[k])):
            at = next((i for i, x in enumerate(self.sizes) if x * len(self.present[k]) <= most), None)
            if at is None:
                self.groups.append([])
                self.sizes.append(1)
                at = -1
            self.groups[at].append(k)
            self.sizes[at] *= len(self.present[k])
        self.cells, self.codes = sum(self.sizes), []
        for group, size in zip(self.groups, self.sizes):
            kind, code = np.uint16 if size <= 1 << 16 else np.int64, 0
            for k in group:
                place = np.zeros(width, kind)
                place[self.present[k]] = np.arange(len(self.present[k]))
                code = code * kind(len(self.present[k])) + place.take(bins[k])
            self.codes.append(code)

    def parted(self, group: int, sums: np.ndarray, out: np.ndarray) -> None:
        """Put the sums of a group's codes into those by feature and 1 + bin."""
        of = self.groups[group]
        sums = sums.reshape([len(self.present[k]) for k in of])
        for i, k in enumerate(of):
            out[k, self.present[k]] = sums.sum(axis=tuple(x for x in range(len(of)) if x != i))

    def margins(self, routers: list[Router], block: int) -> np.ndarray:
        """The sum of the trees' values of each row, tree after tree."""
        n = self.bins.shape[1]
        out, ways = np.zeros(n), [r.joint(self.groups, self.present) if r.arrays is None else None for r in routers]
        values = [r.value[r.order] for r in routers]
        for a in range(0, n, block):
            codes, g = [c[a : a + block].astype(np.intp) for c in self.codes], out[a : a + block]
            for router, way, value in zip(routers, ways, values):
                if way:
                    left = np.take(way[0][1], codes[way[0][0]], mode="clip")
                    for i, t in way[1:]:
                        left &= np.take(t, codes[i], mode="clip")
                    g += value.take(first_bit(left))
                else:
                    g += router.values(self.bins[:, a : a + block].astype(np.intp))
        return out


@dataclass
class TreeModel:
    """A released ensemble; scoring it is post-processing and costs no privacy."""

    spec: DatasetSpec
    bins: int
    trees: list[Tree] = field(default_factory=list)
    params: dict = field(default_factory=dict)

    def margin(self) -> Column:
        """The sum of all trees as one expression: stays in generated code; for up to some ten trees."""
        return sum((t.expression() for t in self.trees), F.lit(0.0))

    def predict(self, rows: DataFrame, path: str = "auto") -> DataFrame:
        """Add `margin` to encoded rows (row_key, x_.., y)."""
        binned = self.spec.binned(rows, self.bins)
        return self.predict_binned(binned, path)

    def predict_binned(self, binned: DataFrame, path: str = "auto") -> DataFrame:
        if path == "expression" or path == "auto" and len(self.trees) <= 8:
            return binned.withColumn("margin", self.margin())
        m = self.spec.m
        routers = [Router(t, m, self.bins) for t in self.trees]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                bins = places_of(batch, m)
                total = sum((r.values(bins) for r in routers), np.zeros(batch.num_rows))
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(total)], names=[*batch.schema.names, "margin"])

        return binned.mapInArrow(run, binned.withColumn("margin", F.lit(0.0)).schema)

    def nodes(self, spark: SparkSession) -> DataFrame:
        rows = [
            (t, x.node, x.depth, x.feature, x.cut_bin, self.spec.edge(x.feature, x.cut_bin, self.bins) if x.feature >= 0 else None, x.default_left, x.left, x.right, x.value, x.n)
            for t, tree in enumerate(self.trees)
            for x in tree.nodes.values()
        ]
        return spark.createDataFrame(rows, NODES)

    def save(self, spark: SparkSession, path: str) -> None:
        """NODES as Parquet and a JSON header, through Spark's writers."""
        self.nodes(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/nodes")
        spark.createDataFrame([(json.dumps({"bins": self.bins, "params": self.params, "features": [asdict(f) for f in self.spec.features]}, default=str),)], "header string").coalesce(1).write.mode("overwrite").text(f"{path}/header")

    @classmethod
    def load(cls, spark: SparkSession, path: str, spec: DatasetSpec) -> TreeModel:
        header = json.loads(spark.read.text(f"{path}/header").first()[0])
        model = cls(spec, header["bins"], params=header["params"])
        for r in spark.read.parquet(f"{path}/nodes").orderBy("tree", "node").collect():
            while len(model.trees) <= r["tree"]:
                model.trees.append(Tree({}))
            model.trees[r["tree"]].nodes[r["node"]] = Node(r["node"], r["depth"], r["feature"], r["cut_bin"], r["default_left"], r["left"], r["right"], r["value"], r["n"])
        return model

    def explain(self, tree: int = 0) -> list[str]:
        """One readable line per node."""
        out = []
        for x in sorted(self.trees[tree].nodes.values(), key=lambda x: x.node):
            name = self.spec.features[x.feature].name if x.feature >= 0 else ""
            out.append(f"{'  ' * x.depth}{x.node}: " + (f"{name} <= {self.spec.edge(x.feature, x.cut_bin, self.bins):.6g} or missing={x.default_left}" if name else f"value {x.value:.6f}"))
        return out
