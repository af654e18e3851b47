"""Row samples by keyed hash: the same rows in any engine, at any partitioning, after any retry."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privgrove.functions.noise import below, digests_of, keyed_text, least_digits, numbers_of, uniform

TEST = 0.2

#: Leading hex digits of a tree's number that a hash for several trees gives, and how many trees share one.
LEAD, SHARED = 3, 21


def is_test(id_col: str = "row_key"):
    return below(TEST, "split", id_col)


def split(df: DataFrame, id_col: str = "row_key") -> tuple[DataFrame, DataFrame]:
    """(train, test): a fixed fifth is held out."""
    return df.where(~is_test(id_col)), df.where(is_test(id_col))


def in_sample(key: str, tree: int, gamma: float, id_col: str = "row_key"):
    return below(gamma, f"{key}|sample|{tree}", id_col)


def bernoulli(df: DataFrame, gamma: float, tree: int, key: str, id_col: str = "row_key") -> DataFrame:
    """Each row on its own with probability gamma; a narrow predicate."""
    return df.where(in_sample(key, tree, gamma, id_col)) if gamma < 1 else df


def exact_fraction(df: DataFrame, gamma: float, tree: int, key: str, id_col: str = "row_key") -> DataFrame:
    """Exactly floor(gamma * n) rows without replacement: those with the smallest draws."""
    n = int(df.count() * gamma)
    return df.orderBy(uniform(f"{key}|sample|{tree}", id_col), id_col).limit(n)


def disjoint(df: DataFrame, parts: list[float], key: str, id_col: str = "row_key") -> DataFrame:
    """Add tree_id: each row is in one part, with probabilities in proportion to `parts`."""
    u = uniform(f"{key}|part", id_col)
    part = sum(((u >= e).cast("int") for e in edges_of(parts)), F.lit(0))
    return df.withColumn("tree_id", part.cast("int"))


def edges_of(parts: list[float]) -> list[float]:
    """Where one part of the unit interval ends and the next begins."""
    total, at, edges = sum(parts), 0.0, []
    for p in parts[:-1]:
        at += p / total
        edges.append(at)
    return edges


def disjoint_rows(ids: list[bytes | None], parts: list[float], key: str) -> tuple[np.ndarray, np.ndarray]:
    """`disjoint` for rows at hand: (place, part) of each, by parts."""
    part = np.searchsorted(edges_of(parts), numbers_of(digests_of(f"{key}|part", ids)), "right")
    order = np.argsort(part, kind="stable")
    return order, part[order]


def in_shared(gamma: float, common: Column, at: Column, own: Column, id_col: str = "row_key") -> Column:
    """Whether a row is in a tree's sample, where a hash serves several trees: of the tree's number the leading digits are
    those of the common hash from `at` on, the rest is of a hash of its own, which only equal digits need."""
    least = least_digits(gamma)
    if least is None:
        return F.lit(True)
    lead = F.substring(F.sha2(keyed_text(common, id_col), 256), at, F.lit(LEAD))
    return (lead < least[:LEAD]) | ((lead == least[:LEAD]) & (F.sha2(keyed_text(own, id_col), 256) < least[LEAD:]))


def shared_rows(ids: list[bytes | None], trees: int, gamma: float, key: str) -> tuple[np.ndarray, np.ndarray]:
    """The same for rows at hand and all trees: (place, tree) of each that a sample has, by trees."""
    least, n, found = least_digits(gamma), len(ids), []
    if least is None:
        return np.tile(np.arange(n), trees), np.repeat(np.arange(trees), n)
    for first in range(0, trees, SHARED):
        byte = np.zeros((33, n), np.uint16)  # three bytes are the digits of two trees
        byte[:32] = digests_of(f"{key}|samples|{first // SHARED}", ids).T
        lead = np.stack((byte[::3] << 4 | byte[1::3] >> 4, (byte[1::3] & 15) << 8 | byte[2::3]), axis=1).reshape(-1, n)[: min(SHARED, trees - first)]
        inside = lead < int(least[:LEAD], 16)
        for t, k in zip(*(x.tolist() for x in np.nonzero(lead == int(least[:LEAD], 16)))):
            own = f"{key}|sample|{first + t}".encode() + (b"" if ids[k] is None else b"|" + ids[k])
            inside[t, k] = hashlib.sha256(own).hexdigest() < least[LEAD:]
        tree, place = np.nonzero(inside)
        found.append((place, tree + first))
    return tuple(np.concatenate(x) for x in zip(*found))


def own_rows(ids: list[bytes | None], trees: int, gamma: float, key: str) -> tuple[np.ndarray, np.ndarray]:
    """The same where each tree has a hash of its own, as in `with_trees`."""
    least, n = least_digits(gamma), len(ids)
    if least is None:
        return np.tile(np.arange(n), trees), np.repeat(np.arange(trees), n)
    inside = [np.flatnonzero(digests_of(f"{key}|sample|{t}", ids).view(">u8")[:, 0] >> 12 < int(least, 16)) for t in range(trees)]
    return np.concatenate(inside), np.repeat(np.arange(trees), [len(x) for x in inside])


def with_trees(df: DataFrame, trees: int, gamma: float, key: str, id_col: str = "row_key") -> DataFrame:
    """One row per (row, tree whose sample has it), with tree_id: all samples from one pass."""
    return with_draws(df, [(0, trees, key)], gamma, id_col).drop("draw")


def with_draws(df: DataFrame, draws: list[tuple[int, int, str]], gamma: float, id_col: str = "row_key", shared: bool = False) -> DataFrame:
    """The same for several draws (number, trees, key), with the draw's number as `draw`: all from one pass. With `shared`,
    trees share hashes as in `in_shared`."""
    # one condition in a loop over trees: a condition each makes a method that is too long for the JVM to compile
    common = lambda key, t: [F.lit(f"{key}|samples|{t // SHARED}").alias("common"), F.lit(1 + LEAD * (t % SHARED)).alias("at")] if shared else []
    each = F.array(*[F.struct(F.lit(d).cast("smallint").alias("draw"), F.lit(t).alias("tree"), F.lit(f"{key}|sample|{t}").alias("key"), *common(key, t)) for d, trees, key in draws for t in range(trees)])
    drawn = df.withColumn("_draw", F.explode(each))
    if shared:
        drawn = drawn.where(in_shared(gamma, F.col("_draw.common"), F.col("_draw.at"), F.col("_draw.key"), id_col))
    elif gamma < 1:
        drawn = drawn.where(below(gamma, F.col("_draw.key"), id_col))
    return drawn.withColumns({"tree_id": F.col("_draw.tree"), "draw": F.col("_draw.draw")}).drop("_draw")


def materialize(df: DataFrame, path: str, trees: int, gamma: float, key: str, id_col: str = "row_key") -> DataFrame:
    """Write every tree's sample once, partitioned by tree_id, and read it back: a tree then reads only its own files."""
    drawn = with_trees(df, trees, gamma, key, id_col)
    drawn.write.mode("overwrite").partitionBy("tree_id").parquet(path)
    return df.sparkSession.read.schema(drawn.schema).parquet(path)
