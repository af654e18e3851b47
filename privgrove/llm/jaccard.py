"""Exact Jaccard join on word n-grams and its components, by rare-first prefix filtering.

1. Index: each text's set of distinct n-grams, as 64-bit hashes, gives its size, a 128-bit digest and its shape, the
   n-gram counts of some hash classes. Texts with equal sets are one node from here on. The same pass counts n-grams
   over all documents in a sketch of fixed size.
2. Postings: a node's n-grams are ordered rare first (by the sketch, then by hash; any common total order is exact), and
   only its prefix is posted: two sets that link must share an n-gram of both prefixes.
3. Candidates: pairs of a short list pass a length and a positional filter, and then, once each, the suffix filter: class
   counts that differ by more than two linked sets could are proof that they don't link. Of a long list, which a group
   of near copies gives, the members meet in cells of bounded size with the same three filters, and a cell gives only
   the edges that join what it has not joined yet.
4. Blocks: components of the candidates. Two sets that link are in one block, so blocks are verified on their own: every
   set is built and sent once, and each pair whose ends are not yet connected is compared at most once.
5. A block too large for a task is dealt out at random, several times over, and the links found are joined. Lists that
   still hold several components of such a block then give the pairs between them, each verified once on the whole sets.
6. Links: those inside a component are then counted, each pair of different sets once and without a row for it. A large
   component is cut into parts, and each pair of parts is a task.

Steps 3 to 5 need no pair inside a component, so groups of copies are not expanded; no link between components is lost.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privgrove.llm.textio import free_names, ragged, shared_dir, slices, stored, summed, texts_of
from privgrove.llm.wordhash import STEP_BYTES, mixed, word_hashes

#: Cells of the rarity sketch. Any order is exact; a fixed size only tells rare n-grams apart less well on larger inputs.
CELLS = 1 << 18
#: Bits of the Bloom filter for each node in it, and at most: beyond that more sets are sent than needed, none lost.
BLOOM_EACH, BLOOM_MOST = 16, 1 << 28
#: Sketch count from which a posting list is not read by one task but linked to its least node by a join.
LIST_ROWS = 50_000
#: Nodes of a list up to which its pairs are listed; a longer one is cut into cells of so many rows on either side, and
#: one of more than so many parts is linked to its least node.
LIST_PAIRS, CELL_ROWS, LIST_PARTS = 64, 4096, 16
#: Sets and n-grams that one task verifies together, and how often a larger block is dealt out.
BLOCK_SETS, BLOCK_GRAMS, DEALS = 2048, 2_000_000, 3
#: Hash classes of the suffix filter: between a quarter and an eighth of the set's size.
LEAST_CLASSES, MOST_CLASSES = 16, 1024

PLACES = [np.uint64(int(x)) for x in mixed(np.arange(100, 164, dtype=np.uint64)) | np.uint64(1)]
NO_ID = -1 << 63


def gram_sets(texts: pa.Array, words: int) -> list[np.ndarray]:
    """Each text's distinct word n-grams as sorted hashes; a shorter text's words are one n-gram, no words are none."""
    hashes, at = word_hashes(texts)
    n = np.diff(at)
    grams = np.zeros(max(0, len(hashes) - words + 1), np.uint64)
    for k in range(words if len(grams) else 0):
        grams += hashes[k : k + len(grams)] * PLACES[k]
    grams = mixed(grams)
    out = []
    for a, size in zip(at[:-1].tolist(), n.tolist()):
        if size >= words:
            own = np.sort(grams[a : a + size - words + 1])
            out.append(own[np.concatenate(([True], own[1:] != own[:-1]))])
        elif size:
            out.append(mixed((hashes[a : a + size] * np.array(PLACES[words : words + size])).sum(keepdims=True, dtype=np.uint64) + np.uint64(size)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def digest(grams: np.ndarray) -> bytes:
    return hashlib.blake2b(grams.tobytes(), digest_size=16).digest()


def key_of(name: bytes) -> int:
    """A short form of a digest. Only candidates use it: where two nodes share one, their blocks become one."""
    return int.from_bytes(name[:8], "little", signed=True)


def shape(grams: np.ndarray) -> bytes:
    """How many n-grams fall in each hash class, a byte each, 255 at most; a power of two of classes."""
    bits = (min(MOST_CLASSES, max(LEAST_CLASSES, 1 << max(0, (len(grams) - 1).bit_length() - 3)))).bit_length() - 1
    return np.minimum(np.bincount((grams >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits), 255).astype(np.uint8).tobytes()


def folded(counts: np.ndarray, classes: int) -> np.ndarray:
    """Rows of class counts brought to fewer classes."""
    return counts if counts.shape[1] == classes else np.minimum(counts.reshape(len(counts), classes, -1).sum(axis=2), 255).astype(np.uint8)


def most_apart(na: np.ndarray, nb: np.ndarray, percent: int) -> np.ndarray:
    """How many n-grams two linked sets of these sizes may have that the other lacks, both sides together."""
    return na + nb - 2 * -(-percent * (na + nb) // (100 + percent))


def indexed(rows: DataFrame, words: int, cells: int) -> DataFrame:
    """Per document (doc_id, mark, node, key, n, shape), and per task one row whose `cells` are its n-gram counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(cells, np.int64)
        names = ["doc_id", "mark", "node", "key", "n", "shape", "cells", "sketch"]
        for batch in slices(batches, most=STEP_BYTES):
            sets = gram_sets(batch.column("text"), words)
            if any(map(len, sets)):
                counts += np.bincount((np.concatenate(sets) & np.uint64(cells - 1)).astype(np.int64), minlength=cells)
            nodes = [digest(s) if len(s) else None for s in sets]
            columns = [pa.array(nodes, pa.binary()), pa.array([x and key_of(x) for x in nodes], pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array([shape(s) if len(s) else None for s in sets], pa.binary())]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("mark"), *columns, pa.nulls(len(sets), pa.binary()), pa.array([False] * len(sets))], names=names)
        nothing = [pa.nulls(1, t) for t in (pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.binary())]
        yield pa.RecordBatch.from_arrays([*nothing, pa.array([counts.astype("<i8").tobytes()], pa.binary()), pa.array([True])], names=names)

    return rows.mapInArrow(run, "doc_id long, mark long, node binary, key long, n long, shape binary, cells binary, sketch boolean")


class Prefixes:
    """Turns sets into postings of their rarest n-grams."""

    def __init__(self, rows: DataFrame, sketch: np.ndarray, percent: int, list_rows: int):
        self.counts = rows.sparkSession.sparkContext.broadcast(np.minimum(sketch, (1 << 31) - 1).astype(np.int32))
        self.percent, self.list_rows = percent, list_rows

    def of(self, sets: list[tuple[int, np.ndarray]]) -> pa.RecordBatch:
        """Postings of (key, n-grams): gram, heavy, key, and spot, which is size * 2**32 + place in the order."""
        counts, kept = self.counts.value, []
        for key, grams in sets:
            common = counts[(grams & np.uint64(len(counts) - 1)).astype(np.int64)]
            rank = (np.minimum(common, (1 << 20) - 1).astype(np.uint64) << np.uint64(44)) | (grams >> np.uint64(20))
            order = np.lexsort((grams, rank))[: len(grams) - (self.percent * len(grams) + 99) // 100 + 1]
            kept.append((grams[order], common[order], np.full(len(order), key, np.int64), (len(grams) << 32) + np.arange(len(order))))
        grams, common, keys, spots = (np.concatenate(x) for x in zip(*kept))
        order = np.argsort(grams.view(np.int64), kind="stable")  # as the lists are: what a task reads is in sorted runs already
        return pa.RecordBatch.from_arrays([pa.array(grams.view(np.int64)[order]), pa.array(common[order] >= self.list_rows), pa.array(keys[order]), pa.array(spots[order])], names=["gram", "heavy", "key", "spot"])


POSTS = "gram long, heavy boolean, key long, spot long"


def posted(rows: DataFrame, words: int, prefixes: Prefixes) -> DataFrame:
    """The postings of every document's set; equal sets are posted once a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        for batch in slices(batches, most=STEP_BYTES):
            sets = []
            for grams in gram_sets(batch.column("text"), words):
                if len(grams) and (name := digest(grams)) not in seen:
                    if len(seen) < 200_000:  # beyond, a set may be posted again: lists drop repeated keys
                        seen.add(name)
                    sets.append((key_of(name), grams))
            if sets:
                yield prefixes.of(sets)

    return rows.select("text").mapInArrow(run, POSTS)


def posted_sets(sets: DataFrame, prefixes: Prefixes) -> DataFrame:
    """The same postings from sets (key, grams)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                yield prefixes.of([(k, g.values.to_numpy().view(np.uint64)) for k, g in zip(part.column("key").to_pylist(), part.column("grams"))])

    return sets.select("key", "grams").mapInArrow(run, POSTS)


def flagged(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.Table, bool]]:
    """Batches as tables, with whether each is the last one."""
    before = None
    for batch in batches:
        if batch.num_rows:
            if before is not None:
                yield before, False
            before = pa.Table.from_batches([batch])
    if before is not None:
        yield before, True


def once(table: pa.Table) -> pa.Table:
    """The first of each list's rows of one node: tasks post a node that they share once each, and rows are sorted."""
    gram, key = table["gram"].to_numpy(), table["key"].to_numpy()
    again = np.zeros(len(gram), bool)
    again[1:] = (gram[1:] == gram[:-1]) & (key[1:] == key[:-1])
    return table.filter(pa.array(~again)) if again.any() else table


def list_candidates(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """Of posting lists sorted by gram and key: of a short list the pairs (u, v) that pass the length and positional
    filter, with null grams; of a long one its own rows (gram, u, spot). A list that goes on in the next batch waits."""
    names, none = ["gram", "u", "v", "spot"], lambda n: pa.nulls(n, pa.int64())
    held, going = None, None  # a short list that may go on, and the gram of a long one
    for table, final in flagged(batches):
        table = once(pa.concat_tables([held, table]) if held is not None else table)
        gram, key, spot = (table[c].to_numpy() for c in ("gram", "key", "spot"))
        size, place, n = spot >> 32, spot & 0xFFFFFFFF, len(gram)
        new = np.concatenate(([True], gram[1:] != gram[:-1]))
        first, group = np.flatnonzero(new), np.cumsum(new) - 1
        sizes = np.diff(np.append(first, n))
        long = sizes > LIST_PAIRS
        long[0] |= going is not None and gram[0] == going
        open_ = n if final or long[-1] else int(first[-1])
        going = gram[-1] if long[-1] else None
        whole = np.flatnonzero(long[group])
        if len(whole):
            yield pa.RecordBatch.from_arrays([pa.array(gram[whole]), pa.array(key[whole]), none(len(whole)), pa.array(spot[whole])], names=names)
        short = ~long[group] & (np.arange(n) < open_)
        us, vs = [], []
        for gap in range(1, min(LIST_PAIRS, n)):
            a = np.flatnonzero(short[:-gap] & (group[:-gap] == group[gap:]))
            if not len(a):
                break
            b = a + gap
            ok = (100 * np.minimum(size[a], size[b]) >= percent * np.maximum(size[a], size[b])) & (2 * np.minimum(size[a] - place[a], size[b] - place[b]) >= size[a] + size[b] - most_apart(size[a], size[b], percent))
            us.append(key[a[ok]])
            vs.append(key[b[ok]])
        if us and sum(map(len, us)):
            pairs = np.unique(np.stack((np.concatenate(us), np.concatenate(vs)), axis=1), axis=0)  # keys rise in a list
            yield pa.RecordBatch.from_arrays([none(len(pairs)), pa.array(pairs[:, 0]), pa.array(pairs[:, 1]), none(len(pairs))], names=names)
        held = table.slice(open_) if open_ < n else None


def likely(pairs: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """The pairs (u, v) of keys that pass the suffix filter on their nodes' shapes."""
    for side in "uv":
        pairs = pairs.join(nodes.select(F.col("key").alias(side), F.col("n").alias(f"{side}_n"), F.col("shape").alias(f"{side}_shape")), side)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "u_shape"):
            a, b = ([np.frombuffer(x.as_buffer(), np.uint8) for x in batch.column(f"{s}_shape")] for s in "uv")
            wide = np.array([(len(x), len(y)) for x, y in zip(a, b)])
            apart = np.zeros(len(a), np.int64)
            for x, y in np.unique(wide, axis=0).tolist():
                at = np.flatnonzero((wide == (x, y)).all(axis=1))
                for some in np.array_split(at, len(at) * max(x, y) // 4_000_000 + 1):
                    left, right = (folded(np.stack([side[k] for k in some]), min(x, y)) for side in (a, b))
                    apart[some] = np.abs(left.astype(np.int16) - right).sum(axis=1, dtype=np.int64)
            keep = apart <= most_apart(*(batch.column(f"{s}_n").to_numpy() for s in "uv"), percent)
            yield batch.select(["u", "v"]).filter(pa.array(keep))

    return pairs.select("u", "v", "u_n", "v_n", "u_shape", "v_shape").mapInArrow(run, "u long, v long")


def cell_pairs(spot: np.ndarray, shapes: list[bytes], side: np.ndarray | None, group: np.ndarray, percent: int, spanning: bool) -> Iterator[tuple[int, np.ndarray]]:
    """(row, later rows) of one list that pass the three filters and are not in one group; with `side`, only pairs
    between its False and True rows. With spanning, rows that a pair has joined count as one group from then on."""
    size, place = spot >> 32, spot & 0xFFFFFFFF
    order = np.argsort(size, kind="stable")
    size, place, shapes, group = size[order], place[order], [shapes[k] for k in order], group[order].copy()
    side = side[order] if side is not None else None
    wide = np.array([len(s) for s in shapes])
    tables: dict[int, np.ndarray] = {}
    for classes in np.unique(wide).tolist():  # of all rows with at least so many classes, folded to these
        tables[classes] = np.concatenate([np.zeros((int((wide < classes).sum()), classes), np.uint8), *(folded(np.frombuffer(b"".join(s for s in shapes if len(s) == w), np.uint8).reshape(-1, w), classes) for w in np.unique(wide[wide >= classes]).tolist())])
    ends = np.searchsorted(size, 100 * size // percent, "right")
    for i in range(len(size)):
        later = np.arange(i + 1, ends[i])
        later = later[group[later] != group[i]]
        if side is not None:
            later = later[side[later] != side[i]]
        if not len(later):
            continue
        most = most_apart(size[i], size[later], percent)
        later, most = (x[2 * np.minimum(size[i] - place[i], size[later] - place[later]) >= size[i] + size[later] - most] for x in (later, most))
        table = tables[wide[i]]
        near = later[np.abs(table[later].astype(np.int16) - table[i]).sum(axis=1, dtype=np.int64) <= most]
        if not len(near):
            continue
        if spanning:
            joined, at = np.unique(group[near], return_index=True)
            near = near[at]
            group[np.isin(group, joined)] = group[i]
        yield int(order[i]), order[near]


def celled(posts: DataFrame, nodes: DataFrame, percent: int, list_parts: int | None, cell_rows: int, grouped: bool = False) -> DataFrame:
    """Candidate pairs (u, v) of keys from whole posting lists (gram, key, spot).

    Without `grouped`, a cell's candidates only span what they join, and a list of more than `list_parts` parts is linked
    to its least node. With it, nodes have a root, and all candidates between different roots are given.
    """
    size = posts.groupBy("gram").agg(F.ceil(F.count(F.lit(1)) / cell_rows).cast("int").alias("parts"))
    posts = posts.join(size, "gram")
    star = None
    if list_parts is not None:
        huge = posts.where(F.col("parts") > list_parts)
        star = huge.join(huge.groupBy("gram").agg(F.min("key").alias("v")), "gram").where("key <> v").select(F.col("key").alias("u"), "v")
        posts = posts.where(F.col("parts") <= list_parts)
    own = posts.join(nodes.select("key", "shape", *(["root"] if grouped else [])), "key")
    own = own.withColumn("part", F.pmod(F.xxhash64("key"), F.col("parts")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    own = own.select("gram", F.least("part", "other").alias("low"), F.greatest("part", "other").alias("high"), "part", "key", "spot", "shape", *(["root"] if grouped else []))

    def run(table: pa.Table) -> pa.Table:
        key, spot, part = (table[c].to_numpy() for c in ("key", "spot", "part"))
        keep = np.unique(key, return_index=True)[1]
        high = table["high"][0].as_py()
        side = None if table["low"][0].as_py() == high else part[keep] == high
        group = np.unique(table["root"].to_numpy(zero_copy_only=False), return_inverse=True)[1][keep] if grouped else np.arange(len(keep))
        found = list(cell_pairs(spot[keep], table["shape"].take(pa.array(keep)).to_pylist(), side, group, percent, not grouped))
        u, v = (key[keep[np.concatenate([np.zeros(0, np.int64), *x]).astype(np.int64)]] for x in ([np.repeat(i, len(b)) for i, b in found], [b for _, b in found]))
        return pa.table({"u": pa.array(np.minimum(u, v), pa.int64()), "v": pa.array(np.maximum(u, v), pa.int64())})

    pairs = own.groupBy("gram", "low", "high").applyInArrow(run, "u long, v long")
    return pairs if star is None else pairs.unionByName(star)


def bloom_positions(nodes: list[bytes], bits: int) -> np.ndarray:
    raw = np.frombuffer(b"".join(nodes), "<u4").reshape(-1, 4)
    return raw.astype(np.int64) & (bits - 1)


def bloom_holds(bloom: np.ndarray, nodes: list[bytes]) -> np.ndarray:
    where = bloom_positions(nodes, 8 * len(bloom))
    return ((bloom[where >> 3] >> (where & 7).astype(np.uint8)) & 1).all(axis=1)


def bloom_of(nodes: DataFrame) -> np.ndarray:
    """A Bloom filter over the column `node`, of a size that follows their number up to a limit; each task makes a part."""
    held = nodes.count()
    bits = min(BLOOM_MOST, max(1 << 13, 1 << (BLOOM_EACH * held).bit_length()))

    def parts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bloom = np.zeros(bits // 8, np.uint8)
        for batch in batches:
            if batch.num_rows:
                where = bloom_positions(batch.column(0).to_pylist(), bits).ravel()
                np.bitwise_or.at(bloom, where >> 3, (1 << (where & 7)).astype(np.uint8))
        yield pa.RecordBatch.from_arrays([pa.array([bloom.tobytes()], pa.binary())], names=["bloom"])

    return summed(nodes.select("node").mapInArrow(parts, "bloom binary"), "bloom", "u1", bits // 8, np.bitwise_or)


def named(node: bytes, number: int) -> bytes:
    """A digest of a node and the document that stands for it."""
    return hashlib.md5(node + str(number).encode()).digest()


def rebuilt_sets(rows: DataFrame, nodes: DataFrame, words: int) -> DataFrame:
    """(node, doc_id, grams) of documents that pass a Bloom filter of the (node, doc_id) given; join exactly after."""
    name = F.unhex(F.md5(F.concat("node", F.encode(F.col("doc_id").cast("string"), "UTF-8")))).alias("node")
    shared = rows.sparkSession.sparkContext.broadcast(bloom_of(nodes.select(name)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        have, seen = shared.value, set()
        for batch in slices(batches, most=STEP_BYTES):
            own = [(digest(s), i, s) for i, s in zip(batch.column("doc_id").fill_null(NO_ID).to_pylist(), gram_sets(batch.column("text"), words)) if len(s)]
            if not own:
                continue
            names, kept = [named(d, i) for d, i, _ in own], []
            for x, name, ok in zip(own, names, bloom_holds(have, names)):
                if ok and name not in seen:
                    if len(seen) < 200_000:  # rows that repeat id and set are dropped for good after
                        seen.add(name)
                    kept.append(x)
            if kept:
                offsets = np.concatenate(([0], np.cumsum([len(x[2]) for x in kept]))).astype(np.int32)
                grams = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate([x[2] for x in kept]).view(np.int64)))
                yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in kept], pa.binary()), pa.array([x[1] for x in kept], pa.int64()), grams], names=["node", "doc_id", "grams"])

    return rows.select("doc_id", "text").mapInArrow(run, "node binary, doc_id long, grams array<long>")


def block_links(sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Links between the sets, enough of them for all components, by search from set to set over an inverted index.

    The index holds sets that no component has taken yet and is rebuilt as they become few.
    """
    sizes = np.array([len(s) for s in sets])
    codes = np.unique(np.concatenate(sets), return_inverse=True)[1]
    starts = np.cumsum(sizes) - sizes
    owner = np.repeat(np.arange(len(sets)), sizes)
    free = np.ones(len(sets), bool)
    links: list[tuple[int, int]] = []

    def index() -> tuple[np.ndarray, np.ndarray, int]:
        keep = free[owner]
        order = np.argsort(codes[keep], kind="stable")
        return owner[keep][order], np.concatenate(([0], np.cumsum(np.bincount(codes[keep], minlength=codes.max() + 1)))), int(free.sum())

    posts, at, held = index()
    left = held
    for seed in range(len(sets)):
        if not free[seed]:
            continue
        free[seed] = False
        left -= 1
        queue = [seed]
        while queue and left:
            if left < held // 2:
                posts, at, held = index()
            i = queue.pop()
            own = codes[starts[i] : starts[i] + sizes[i]]
            both = np.bincount(posts[ragged(at[own], at[own + 1] - at[own])], minlength=len(sets))
            near = np.flatnonzero(free & (100 * both >= percent * (sizes[i] + sizes - both)) & (both > 0))
            free[near] = False
            left -= len(near)
            links += [(i, int(k)) for k in near]
            queue += near.tolist()
    return links


def verified_blocks(sets: DataFrame, percent: int) -> DataFrame:
    """Links (u, v) inside each group of (part, node, grams)."""

    def run(table: pa.Table) -> pa.Table:
        names, lists = table["node"].to_pylist(), table["grams"].combine_chunks()
        own = {name: k for k, name in enumerate(names)}
        order = list(own.values())
        grams = [lists[k].values.to_numpy() for k in order]
        links = block_links(grams, percent)
        keys = list(own)
        return pa.table({"u": pa.array([keys[a] for a, _ in links], pa.binary()), "v": pa.array([keys[b] for _, b in links], pa.binary())})

    return sets.groupBy("part").applyInArrow(run, "u binary, v binary")


def verified_pairs(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (u, v) whose whole sets are similar enough."""
    left = sets.select(F.col("node").alias("u"), F.col("grams").alias("u_grams"))
    right = sets.select(F.col("node").alias("v"), F.col("grams").alias("v_grams"))
    both = F.size(F.array_intersect("u_grams", "v_grams"))
    whole = F.size("u_grams") + F.size("v_grams") - both
    return pairs.join(left, "u").join(right, "v").where(100 * both >= percent * whole).select("u", "v")


def components(edges: DataFrame, at: str, tag: str) -> DataFrame:
    """(node, root) of every node in edges: the smallest node that edges reach.

    Alternates large-star and small-star steps until the edges no longer change; every step is a grouped minimum, which
    combines before its shuffle, and a join.
    """

    def canonical(df: DataFrame) -> DataFrame:
        return df.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()

    edges, before, step = stored(canonical(edges), f"{tag}_0", at), None, 0
    while True:
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before or not now[0]:
            break
        before, step = now, step + 1
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("low")).select("u", F.least("u", "low").alias("low"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("low").alias("v"))
        large = stored(canonical(large.unionByName(low.select("u", F.col("low").alias("v")))), f"{tag}_{step}l", at)
        low = large.groupBy("u").agg(F.min("v").alias("low"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("low").alias("v"))
        edges = stored(canonical(small.unionByName(low.select("u", F.col("low").alias("v")))), f"{tag}_{step}s", at)
    roots = edges.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
    return roots.unionByName(roots.select(F.col("root").alias("node")).distinct().withColumn("root", F.col("node")))


def first_nodes(index: DataFrame) -> DataFrame:
    """One row per node: node, key, n, shape, copies, its smallest id (least), and that id or NO_ID (doc_id)."""
    found = index.where("node IS NOT NULL").groupBy("node", "key", "n").agg(F.first("shape").alias("shape"), F.min("doc_id").alias("least"), F.min(F.coalesce("doc_id", F.lit(NO_ID))).alias("doc_id"), F.count(F.lit(1)).alias("copies"))
    return found


def candidates(posts: DataFrame, nodes: DataFrame, percent: int, at: str, cell_rows: int, list_parts: int, heavy_lists: bool) -> DataFrame:
    """Edges (u, v) of keys, enough of them for all components of the pairs that pass the filters."""
    lists = posts.where("NOT heavy").select("gram", "key", "spot") if heavy_lists else posts.select("gram", "key", "spot")
    lists = lists.repartition("gram").sortWithinPartitions("gram", "key")
    found = stored(lists.mapInArrow(lambda batches: list_candidates(batches, percent), "gram long, u long, v long, spot long"), "candidates", at)
    edges = likely(found.where("gram IS NULL").select("u", "v").distinct(), nodes, percent)
    long = found.where("gram IS NOT NULL").select("gram", F.col("u").alias("key"), "spot")
    edges = edges.unionByName(celled(long, nodes, percent, list_parts, cell_rows))
    if heavy_lists:
        heavy = posts.where("heavy").select("gram", F.col("key").alias("u")).distinct()
        edges = edges.unionByName(heavy.join(heavy.groupBy("gram").agg(F.min("u").alias("v")), "gram").where("u <> v").select("u", "v"))
    return stored(edges.distinct(), "edges", at)


def between_components(sets: DataFrame, nodes: DataFrame, prefixes: Prefixes, links: DataFrame, percent: int, cell_rows: int, at: str) -> DataFrame:
    """Links between the components that `links` make of the large blocks' sets (node, key, grams).

    Candidates between components are first verified one for each pair of components, then, where two are still apart,
    all of them.
    """
    roots = sets.select("node", "key").join(components(links, at, "partly"), "node", "left").withColumn("root", F.coalesce("root", "node"))
    roots = stored(roots, "partly", at)
    posts = posted_sets(sets, prefixes).drop("heavy").join(roots.select("key", "root"), "key")
    several = posts.groupBy("gram").agg(F.min("root").alias("a"), F.max("root").alias("b")).where("a <> b").select("gram")
    posts = stored(posts.drop("root").distinct().join(several, "gram", "left_semi"), "between", at)
    known = roots.join(nodes.select("node", "shape"), "node")
    pairs = celled(posts, known, percent, None, cell_rows, grouped=True).distinct()
    side = lambda s: roots.select(F.col("key").alias(s), F.col("node").alias(f"{s}_node"), F.col("root").alias(f"{s}_root"))
    pairs = pairs.join(side("u"), "u").join(side("v"), "v").where("u_root <> v_root")
    pairs = stored(pairs.select(F.col("u_node").alias("u"), F.col("v_node").alias("v"), F.least("u_root", "v_root").alias("a"), F.greatest("u_root", "v_root").alias("b")), "pairs", at)
    if pairs.isEmpty():
        return links
    first = pairs.groupBy("a", "b").agg(F.min(F.struct("u", "v")).alias("pair")).select("pair.u", "pair.v")
    found = stored(verified_pairs(first, sets, percent), "links_first", at)
    merged = components(links.unionByName(found), at, "first")
    apart = pairs.select("u", "v")
    for s in "uv":
        apart = apart.join(merged.select(F.col("node").alias(s), F.col("root").alias(f"{s}_root")), s, "left")
    apart = apart.where(F.coalesce("u_root", "u") != F.coalesce("v_root", "v")).select("u", "v").join(first, ["u", "v"], "left_anti")
    return links.unionByName(found).unionByName(stored(verified_pairs(apart, sets, percent), "links_rest", at))


def linked(rows: DataFrame, words: int, percent: int, cells: int, at: str, block_sets: int = BLOCK_SETS, block_grams: int = BLOCK_GRAMS, list_rows: int = LIST_ROWS, cell_rows: int = CELL_ROWS, list_parts: int = LIST_PARTS) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(index, nodes, sets, links): the index has every document; links are verified (u, v) between nodes, enough of them
    for all components; sets (node, key, grams) has each node that could have a link."""
    index = stored(indexed(rows, words, cells), "index", at)
    sketch = summed(index.where("sketch"), "cells", "<i8", cells)
    index = index.where("NOT sketch").drop("cells", "sketch")
    nodes = stored(first_nodes(index), "nodes", at)
    list_rows += 4 * int(np.median(sketch))  # a cell also counts n-grams that only share it
    prefixes = Prefixes(rows, sketch, percent, list_rows)
    edges = candidates(posted(rows, words, prefixes), nodes, percent, at, cell_rows, list_parts, bool(sketch.max() >= list_rows))
    blocks = components(edges, at, "blocks").withColumnRenamed("node", "key")
    blocks = stored(blocks.join(nodes.select("node", "key", "doc_id", "n"), "key"), "blocks", at)
    size = blocks.groupBy("root").agg(F.greatest(F.ceil(F.count(F.lit(1)) / block_sets), F.ceil(F.sum("n") / block_grams)).cast("int").alias("parts"))
    dealt = blocks.join(size, "root").select("node", "key", "doc_id", "root", "parts")
    sets = rebuilt_sets(rows, blocks, words).join(dealt, ["node", "doc_id"]).drop("doc_id")
    sets = stored(sets.dropDuplicates(["node"]) if has_repeats(index) else sets, "sets", at)

    def deal(which: DataFrame, number: int) -> DataFrame:
        part = F.xxhash64("root", F.pmod(F.xxhash64("node", F.lit(number)), F.col("parts")))
        return stored(verified_blocks(which.select(part.alias("part"), "node", "grams"), percent), f"links_{number}", at)

    links, large = deal(sets, 0), sets.where("parts > 1")
    if not large.isEmpty():
        for number in range(1, DEALS):
            links = links.unionByName(deal(large, number))
        links = between_components(large, nodes, prefixes, links, percent, cell_rows, at)
    return index, nodes, sets.select("node", "key", "grams"), links


def has_repeats(index: DataFrame) -> bool:
    """Whether several rows share an id and a set, so that one node could be built from each of them."""
    return not index.where("node IS NOT NULL").groupBy("doc_id", "node").count().where("count > 1").isEmpty()


def cell_links(sets: list[np.ndarray], side: np.ndarray | None, percent: int) -> Iterator[tuple[int, np.ndarray]]:
    """(set, linked sets) with each linked pair once: of all sets, or with `side` only between its False and True sets."""
    sizes = np.array([len(s) for s in sets])
    codes = np.unique(np.concatenate(sets), return_inverse=True)[1]
    starts, owner = np.cumsum(sizes) - sizes, np.repeat(np.arange(len(sets)), sizes)
    held = np.ones(len(codes), bool) if side is None else side[owner]
    posts = owner[held][np.argsort(codes[held], kind="stable")]
    at = np.concatenate(([0], np.cumsum(np.bincount(codes[held], minlength=codes.max() + 1))))
    for i in range(len(sets)) if side is None else np.flatnonzero(~side):
        own = codes[starts[i] : starts[i] + sizes[i]]
        both = np.bincount(posts[ragged(at[own], at[own + 1] - at[own])], minlength=len(sets))
        near = np.flatnonzero((both > 0) & (100 * both >= percent * (sizes[i] + sizes - both)))
        yield int(i), near[near > i] if side is None else near


def component_links(sets: DataFrame, members: DataFrame, percent: int, at: str, pairs: bool = False, block_sets: int = BLOCK_SETS, block_grams: int = BLOCK_GRAMS) -> DataFrame:
    """Of members (node, root, n, copies) with their sets: (node, linked), documents whose set is another one that links;
    rows of a node add up. With pairs, every linked pair of nodes (u, v)."""
    size = members.groupBy("root").agg(F.count(F.lit(1)).alias("held"), F.greatest(F.ceil(F.count(F.lit(1)) / block_sets), F.ceil(F.sum("n") / block_grams)).cast("int").alias("parts")).where("held > 1")
    dealt = members.join(size, "root").withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    cells = sets.select("node", "grams").join(dealt.select("node", "root", "part", "parts", "copies"), "node").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    cells = cells.select("root", F.least("part", "other").alias("low"), F.greatest("part", "other").alias("high"), "part", "node", "copies", "grams")

    def run(table: pa.Table) -> pa.Table:
        at = list({name: k for k, name in enumerate(table["node"].to_pylist())}.values())
        names, copies, lists = (table[c].take(pa.array(at)) for c in ("node", "copies", "grams"))
        names, copies, part = names.to_pylist(), copies.to_numpy(), table["part"].to_numpy()[at]
        high = table["high"][0].as_py()
        side = None if table["low"][0].as_py() == high else part == high
        if len(names) < 2 or side is not None and (side.all() or not side.any()):
            return pa.table({"u": pa.array([], pa.binary()), "v": pa.array([], pa.binary())}) if pairs else pa.table({"node": pa.array([], pa.binary()), "linked": pa.array([], pa.int64())})
        grams = [x.values.to_numpy() for x in lists]
        if pairs:
            found = [(names[i], names[k]) for i, near in cell_links(grams, side, percent) for k in near]
            return pa.table({"u": pa.array([min(f) for f in found], pa.binary()), "v": pa.array([max(f) for f in found], pa.binary())})
        linked = np.zeros(len(names), np.int64)
        for i, near in cell_links(grams, side, percent):
            linked[i] += copies[near].sum()
            linked[near] += copies[i]
        return pa.table({"node": pa.array(names, pa.binary()), "linked": pa.array(linked)})

    return stored(cells.groupBy("root", "low", "high").applyInArrow(run, "u binary, v binary" if pairs else "node binary, linked long"), "pairs_all" if pairs else "linked", at)


def marked(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc_id, text, mark); mark is a hash of the text, so that (doc_id, mark) names a row where ids repeat."""
    return texts_of(docs, id_col, text_col).withColumn("mark", F.xxhash64("text"))


def grouped(rows: DataFrame, words: int, percent: int, cells: int, at: str, **sizes: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(index, members, sets): of every document, and of every node its root, one document, its size and its copies."""
    index, nodes, sets, links = linked(rows, words, percent, cells, at, **sizes)
    roots = stored(components(links, at, "all"), "roots", at)
    return index, stored(nodes.drop("shape", "key").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node")), "members", at), sets


def block_sizes(sizes: dict[str, int]) -> dict[str, int]:
    return {k: v for k, v in sizes.items() if k.startswith("block")}


def set_links(docs: DataFrame, words: int = 5, percent: int = 80, cells: int = CELLS, id_col: str = "doc_id", text_col: str = "text", **sizes: int) -> tuple[DataFrame, DataFrame]:
    """(membership, links): node of every document (doc_id, node), and every linked pair (u, v) of different nodes once.

    Documents of one node link as well. Pairs grow with the square of a group; near_duplicates counts them without rows.
    """
    at = shared_dir(docs.sparkSession)
    index, members, sets = grouped(marked(docs, id_col, text_col), words, percent, cells, at, **sizes)
    return index.select("doc_id", "node"), component_links(sets, members, percent, at, True, **block_sizes(sizes))


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80, cells: int = CELLS, id_col: str = "doc_id", text_col: str = "text", count_links: bool = True, **sizes: int) -> DataFrame:
    """Per document: doc_id, n_shingles, component_id (the smallest doc_id that links reach, itself included), and with
    count_links n_links, the number of other documents that it links with, copies included.

    Two documents link when 100 * intersection >= percent * union of their word n-gram sets. Null or empty texts, and
    texts of white space, have an empty set and link with nothing. Rows with equal sets are linked, however many there
    are; a repeated id gives a row each. A null id is never a component id unless its component has no other. Extra
    columns are ignored; an empty table gives no rows.
    """
    at = shared_dir(docs.sparkSession)
    index, nodes, sets = grouped(marked(docs, id_col, text_col), words, percent, cells, at, **sizes)
    least = nodes.groupBy("root").agg(F.min("least").alias("component_id"))
    named = nodes.join(least, "root").select("node", "component_id", "copies")
    out = [F.col("doc_id"), F.col("n").alias("n_shingles"), F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id")]
    if count_links:
        sums = component_links(sets, nodes, percent, at, **block_sizes(sizes)).groupBy("node").agg(F.sum("linked").alias("linked"))
        named = named.join(sums, "node", "left")
        out.append((F.coalesce("linked", F.lit(0)) + F.coalesce(F.col("copies") - 1, F.lit(0))).alias("n_links"))
    return index.join(stored(named, "named", at), "node", "left").select(*out)


def row_key(id_col: str, text_col: str) -> Column:
    """What names a row of documents here: its id, null last, and the mark of its text."""
    key = F.col(id_col).cast("long")
    return F.struct(key.isNull().alias("without_id"), F.coalesce(key, F.lit(0)).alias("id"), F.xxhash64(F.coalesce(F.col(text_col).cast("string"), F.lit(""))).alias("mark"))


def first_of_each(docs: DataFrame, words: int = 5, percent: int = 80, cells: int = CELLS, id_col: str = "doc_id", text_col: str = "text", **sizes: int) -> DataFrame:
    """One row of every component stays, with all of its columns: that of the smallest id, or of a null one if no row of
    the component has an id.

    Rows are told apart by id and text, so repeated ids lose nothing: each row goes or stays with its own component. Of
    rows of one id in a component the one of the smallest text hash stays, of rows equal in id and text the one of the
    smallest hash over all columns. Texts without words link with nothing and all stay.
    """
    at = shared_dir(docs.sparkSession)
    index, nodes, _ = grouped(marked(docs, id_col, text_col), words, percent, cells, at, **sizes)
    key = F.struct(F.col("doc_id").isNull().alias("without_id"), F.coalesce("doc_id", F.lit(0)).alias("id"), "mark")
    found = index.where("node IS NOT NULL").select("node", key.alias("_key")).groupBy("node", "_key").agg(F.count(F.lit(1)).alias("held"))
    found = stored(found.join(nodes.select("node", "root"), "node"), "found", at)
    best = found.groupBy("root").agg(F.min("_key").alias("best"))
    decided = stored(found.join(best, "root").select(F.col("_key.without_id").alias("without_id"), F.col("_key.id").alias("id"), F.col("_key.mark").alias("mark"), (F.col("_key") == F.col("best")).alias("stays"), "held"), "decided", at)
    names = free_names(docs.columns, "without_id", "id_key", "mark")
    own = docs.select("*", *[row_key(id_col, text_col)[f].alias(n) for f, n in zip(("without_id", "id", "mark"), names)])
    match = lambda df: df.select(*[F.col(f).alias(n) for f, n in zip(("without_id", "id", "mark"), names)])
    repeated = decided.where("stays AND held > 1")
    several = not repeated.isEmpty()
    kept = own.join(match(decided.where("NOT stays OR held > 1" if several else "NOT stays")), names, "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])
    if not several:
        return kept
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    one = own.join(match(repeated), names, "left_semi").groupBy(*names).agg(F.min_by(whole, F.xxhash64(*[F.col(f"`{c}`") for c in docs.columns])).alias("_row"))
    return kept.unionByName(one.select("_row.*"))
