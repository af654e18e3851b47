"""Exact BM25 top-k search over a sharded inverted index, with block-max pruning.

Every task turns the texts it reads into shards: a sorted term list, postings of (document, frequency), and for every
term and aligned block of documents the largest impact. Shards are rows of a table in the shared folder. Statistics are
global: document count and mean length from the shards, and the document frequency of each query term summed over them.

A query's bound for a block is the sum of its terms' block maxima. The blocks with the highest bounds are scored first;
with the k-th best score so far as threshold, only blocks whose bound reaches it are scored at all. This is the pivot
test of block-max WAND, made for all blocks of a shard at once. Nothing that could enter the top k is skipped, ties
included: equal rounded scores are ranked by the smaller id. Documents lie in a shard by their commonest frequent terms
and length, so that a block holds like texts and its bounds are tight. Terms that are frequent in a shard are held as
rows of a matrix, so that bounds and scores of many queries are matrix products. A block of 32 documents holds about one
posting of any other term, which then is its own block maximum: those postings go into the bounds as they are, and no
cursor moves over them.

The square root of all shards is searched first, with each query's k-th best score there as the threshold for the rest:
what the rest returns is then a few rows a query, not k from every shard. Shards' results are merged by rank.

Queries go to the tasks in blocks of bounded size; each block is one pass over the index.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from privgrove.llm.textio import gathered, ragged, shared_dir, slices, stored, summed, texts_of
from privgrove.llm.wordhash import MARKS, STEP_BYTES, word_hashes

K1, B = 1.2, 0.75
SHARD_BYTES = 16 << 20
BLOCK = 32
QUERY_BYTES = 16 << 20
ROUND = 6


class Shard:
    """An inverted index of some documents, as arrays."""

    FIELDS = (("ids", "<i8"), ("sizes", "<i4"), ("terms", "<u8"), ("starts", "<i8"), ("docs", "<u2"), ("counts", "<u4"))

    def __init__(self, ids, sizes, terms, starts, docs, counts):
        self.ids, self.sizes, self.terms, self.starts, self.docs, self.counts = ids, sizes, terms, starts, docs, counts

    def to_bytes(self) -> bytes:
        parts = [np.ascontiguousarray(getattr(self, name), kind).tobytes() for name, kind in self.FIELDS]
        return b"".join([np.array([len(p) for p in parts], "<i8").tobytes(), *parts])

    @classmethod
    def from_bytes(cls, raw: bytes) -> Shard:
        sizes = np.frombuffer(raw, "<i8", len(cls.FIELDS))
        at, arrays = 8 * len(cls.FIELDS), []
        for size, (_, kind) in zip(sizes.tolist(), cls.FIELDS):
            arrays.append(np.frombuffer(raw, kind, size // np.dtype(kind).itemsize, at))
            at += size
        return cls(*arrays)


def term_counts(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(term, document, count, words of each document) of a batch's texts, sorted by term, then document."""
    hashes, owners, sizes, base = [], [], [], 0
    for part in slices(iter([batch]), most=STEP_BYTES):
        found, offsets = word_hashes(part.column("text"), MARKS)
        size = np.diff(offsets)
        hashes.append(found)
        owners.append(np.repeat(np.arange(base, base + len(size), dtype=np.int32), size))
        sizes.append(size)
        base += len(size)
    term, doc = np.concatenate(hashes), np.concatenate(owners)
    order = np.argsort(term, kind="stable")  # documents stay in order
    term, doc = term[order], doc[order]
    new = np.flatnonzero(np.concatenate(([True], (term[1:] != term[:-1]) | (doc[1:] != doc[:-1])))) if len(term) else np.zeros(0, np.int64)
    return term[new], doc[new], np.diff(np.append(new, len(term))), np.concatenate(sizes)


def build_shard(batch: pa.RecordBatch) -> Shard:
    """Index a batch of (doc_id, text); at most 65,536 documents."""
    term, doc, count, sizes = term_counts(batch)
    n = len(sizes)
    head = np.flatnonzero(np.concatenate(([True], term[1:] != term[:-1]))) if len(term) else np.zeros(0, np.int64)
    spread = np.diff(np.append(head, len(term)))
    # like texts together: by the frequent term that fills most of a document, then by length
    rank = np.repeat(np.argsort(np.argsort(-spread, kind="stable"), kind="stable"), spread)
    frequent = np.flatnonzero(rank < 64)
    load = np.zeros((n, 64), np.int32)
    load[doc[frequent], rank[frequent]] = count[frequent]
    place = np.empty(n, np.int64)
    place[np.lexsort((sizes, load.argmax(axis=1)))] = np.arange(n)
    moved = place[doc]
    order = np.argsort(np.repeat(np.arange(len(head)), spread) * n + moved, kind="stable")
    back = np.argsort(place)
    ids = batch.column("doc_id").fill_null(np.iinfo(np.int64).min).to_numpy()
    return Shard(ids[back], sizes[back], term[head], np.append(head, len(term)), moved[order], count[order])


def build_index(docs: DataFrame, at: str, id_col: str = "doc_id", text_col: str = "text", shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """Write the shards of all documents: (number, n, words, shard)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack, number = zstandard.ZstdCompressor(level=1), TaskContext.get().partitionId() << 32
        for batch in gathered(batches, most=shard_bytes):
            for begin in range(0, batch.num_rows, 65_536):
                shard = build_shard(batch.slice(begin, 65_536))
                number += 1
                yield pa.RecordBatch.from_arrays(
                    [pa.array([number], pa.int64()), pa.array([len(shard.ids)], pa.int64()), pa.array([int(shard.sizes.sum())], pa.int64()), pa.array([pack.compress(shard.to_bytes())], pa.binary())], names=["number", "n", "words", "shard"]
                )

    return stored(texts_of(docs, id_col, text_col).mapInArrow(run, "number long, n long, words long, shard binary"), "shards", at)


def opened(batches: Iterator[pa.RecordBatch]) -> Iterator[Shard]:
    for batch in batches:
        for raw in batch.column("shard"):
            yield Shard.from_bytes(zstandard.ZstdDecompressor().decompress(raw.as_py()))


def query_terms(queries: DataFrame) -> DataFrame:
    """(query_id, terms, counts) of each query with a word, as packed arrays."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, most=STEP_BYTES):
            found, offsets = word_hashes(batch.column("text"), MARKS)
            rows = [np.unique(found[a:b], return_counts=True) for a, b in zip(offsets[:-1], offsets[1:])]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array([t.astype("<u8").tobytes() for t, _ in rows], pa.binary()), pa.array([c.astype("<i4").tobytes() for _, c in rows], pa.binary())], names=["query_id", "terms", "counts"]
            )

    return queries.mapInArrow(run, "query_id long, terms binary, counts binary").where(F.octet_length("terms") > 0)


class QueryBlock:
    """Queries as (term number, weight) lists over the block's own sorted terms."""

    def __init__(self, rows: list):
        self.ids = np.array([r["query_id"] for r in rows], np.int64)
        lists = [np.frombuffer(r["terms"], "<u8") for r in rows]
        self.counts = np.concatenate([np.frombuffer(r["counts"], "<i4") for r in rows]).astype(np.float64)
        self.offsets = np.concatenate(([0], np.cumsum([len(x) for x in lists])))
        self.terms, self.numbers = np.unique(np.concatenate(lists), return_inverse=True)
        self.idf = np.zeros(len(self.terms))


def places(shard: Shard, terms: np.ndarray) -> np.ndarray:
    """Where each term is in the shard's list, or -1."""
    at = np.searchsorted(shard.terms, terms)
    at[at == len(shard.terms)] = 0
    return np.where(shard.terms[at] == terms, at, -1) if len(shard.terms) else np.full(len(terms), -1)


class Impacts:
    """A shard's impacts for a block's terms: frequent terms as a matrix per document block, with its maxima; postings of the
    rest."""

    def __init__(self, shard: Shard, block: QueryBlock, mean: float):
        self.at = places(shard, block.terms)
        used = np.unique(self.at[self.at >= 0])
        lengths = np.diff(shard.starts)[used]
        self.size, self.blocks = len(shard.ids), -(-len(shard.ids) // BLOCK)
        frequent = lengths >= max(8, self.size // 25)

        def impacts(terms: np.ndarray, spread: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            picked = ragged(shard.starts[terms], spread)
            docs, counts = shard.docs[picked].astype(np.int64), shard.counts[picked].astype(np.float64)
            return docs, counts * (K1 + 1) / (counts + K1 * (1 - B + B * shard.sizes[docs] / mean))

        docs, value = impacts(used[frequent], lengths[frequent])
        self.matrix = np.zeros((self.blocks, int(frequent.sum()), BLOCK))
        self.matrix[docs // BLOCK, np.repeat(np.arange(self.matrix.shape[1]), lengths[frequent]), docs % BLOCK] = value
        self.tops = self.matrix.max(axis=2).T
        self.docs, self.value = impacts(used[~frequent], lengths[~frequent])
        self.bounds = np.concatenate(([0], np.cumsum(lengths[~frequent])))
        self.row = np.full(len(shard.terms) + 1, -1)  # of frequent terms; -2 - k for the k-th other term
        self.row[used[frequent]] = np.arange(self.matrix.shape[1])
        self.row[used[~frequent]] = -2 - np.arange(int((~frequent).sum()))


def search_shard(shard: Shard, block: QueryBlock, mean: float, k: int, floor: np.ndarray, together: int = 128, tally: np.ndarray | None = None) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(query number, document ids, rounded scores) of each query's best k in the shard that reach its floor.

    `tally`, if given, is added to: (query, block) pairs with any shared term, and those scored.
    """
    if not len(shard.ids) or not len(shard.terms):
        return
    own, slack = Impacts(shard, block, mean), 10.0 ** (1 - ROUND)
    width, lead = own.blocks * BLOCK, max(1, -(-2 * k // BLOCK))
    for begin in range(0, len(block.ids), together):
        end = min(begin + together, len(block.ids))
        span = slice(block.offsets[begin], block.offsets[end])
        query = np.repeat(np.arange(end - begin), np.diff(block.offsets[begin : end + 1]))
        numbers = block.numbers[span]
        place = own.row[own.at[numbers]]  # a term that the shard lacks is at -1, the last entry
        weight = block.counts[span] * block.idf[numbers]
        matrix = np.zeros((end - begin, own.matrix.shape[1]))
        often = place >= 0
        matrix[query[often], place[often]] = weight[often]
        other = np.flatnonzero(place < -1)
        term = -2 - place[other]
        spread = own.bounds[term + 1] - own.bounds[term]
        posts = ragged(own.bounds[term], spread)
        rare = np.bincount(np.repeat(query[other], spread) * width + own.docs[posts], np.repeat(weight[other], spread) * own.value[posts], (end - begin) * width).reshape(-1, width)
        limit = matrix @ own.tops + rare.reshape(-1, own.blocks, BLOCK).max(axis=2)
        scores = np.zeros_like(rare)

        def score(wanted: np.ndarray) -> None:
            for b in np.flatnonzero(wanted.any(axis=0)):
                rows, cols = np.flatnonzero(wanted[:, b]), slice(b * BLOCK, (b + 1) * BLOCK)
                scores[rows, cols] = matrix[rows] @ own.matrix[b] + rare[rows, cols]

        first = np.zeros(limit.shape, bool)
        np.put_along_axis(first, np.argpartition(-limit, min(lead, own.blocks) - 1, axis=1)[:, :lead], True, axis=1)
        first &= limit >= np.maximum(floor[begin:end, None] - slack, 1e-12)
        score(first)
        least = np.partition(scores, -k, axis=1)[:, -k] if width >= k else np.zeros(end - begin)
        least = np.maximum(least, floor[begin:end])
        rest = ~first & (limit > 0) & (limit >= least[:, None] - slack)
        score(rest)
        if tally is not None:
            tally += ((limit > 0).sum(), first.sum() + rest.sum())
        for q in range(end - begin):
            hit = np.flatnonzero(scores[q] > max(0.0, least[q] - slack))
            value = np.round(scores[q, hit], ROUND)
            keep = value >= floor[begin + q]
            hit, value = hit[keep], value[keep]
            best = np.lexsort((shard.ids[hit], -value))[:k]
            if len(best):
                yield begin + q, shard.ids[hit][best], value[best]


def search_block(shards: DataFrame, rows: list, n: int, words: int, held: int, k: int, at: str) -> DataFrame:
    """(query_id, rank, doc_id, score) of a block of queries against all `held` shards."""
    context, block = shards.sparkSession.sparkContext, QueryBlock(rows)
    terms = context.broadcast(block.terms)

    def frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for shard in opened(batches):
            place = places(shard, terms.value)
            size = np.diff(shard.starts)
            found = np.where(place >= 0, size[np.maximum(place, 0)] if len(size) else 0, 0)
            yield pa.RecordBatch.from_arrays([pa.array([found.astype("<i8").tobytes()], pa.binary())], names=["df"])

    df = summed(shards.select("shard").mapInArrow(frequencies, "df binary"), "df", "<i8", len(block.terms))
    block.idf = np.log(1 + (n - df + 0.5) / (df + 0.5))
    shared, mean = context.broadcast(block), words / n

    def found(which: DataFrame, floors, name: str) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for shard in opened(batches):
                own = list(search_shard(shard, shared.value, mean, k, floors.value))
                if own:
                    number = np.repeat([q for q, *_ in own], [len(d) for _, d, _ in own]).astype(np.int32)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(number), pa.array(shared.value.ids[number]), pa.array(np.concatenate([d for _, d, _ in own])), pa.array(np.concatenate([s for *_, s in own]))], names=["query_no", "query_id", "doc_id", "score"]
                    )

        return stored(which.select("shard").mapInArrow(run, "query_no int, query_id long, doc_id long, score double"), name, at)

    order = Window.partitionBy("query_no").orderBy(F.desc("score"), "doc_id")
    top = lambda df: df.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    share = F.pmod(F.xxhash64("number"), F.lit(max(1, int(held**0.5)))) == 0
    early = found(shards.where(share), context.broadcast(np.zeros(len(block.ids))), "early")
    floor = np.zeros(len(block.ids))
    for r in top(early).where(F.col("rank") == k).select("query_no", "score").toLocalIterator():
        floor[r["query_no"]] = r["score"]
    late = found(shards.where(~share), context.broadcast(floor), "late")
    return stored(top(early.unionByName(late)).select("query_id", "rank", "doc_id", "score"), "best", at)


def search(docs: DataFrame, queries: DataFrame, k: int = 10, query_bytes: int = QUERY_BYTES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The k best documents of each query row by BM25: query_id, rank, doc_id, score (6 decimals).

    Words are runs of ASCII letters and digits and of all other characters beyond ASCII, with A-Z lowered. Only documents
    that share a word with the query are ranked; null or empty queries have none. Scores that round to the same value are
    ranked by the smaller id. A null document id reads as the smallest number; rows that repeat an id are documents of
    their own. Empty tables give no rows; extra columns are ignored.
    """
    spark, at = docs.sparkSession, shared_dir(docs.sparkSession)
    shards = build_index(docs, at, id_col, text_col)
    n, words, held = shards.agg(F.sum("n"), F.sum("words"), F.count(F.lit(1))).first()
    terms = stored(query_terms(texts_of(queries, id_col, text_col)), "queries", at)
    size = terms.agg(F.sum(F.octet_length("terms"))).first()[0] or 0
    out = spark.range(0).selectExpr("id AS query_id", "CAST(id AS INT) AS rank", "id AS doc_id", "CAST(id AS DOUBLE) AS score")
    if not n or not size:
        return out
    blocks = -(-2 * size // query_bytes)
    for number in range(blocks):
        rows = terms.where(F.pmod(F.xxhash64("query_id", "terms"), F.lit(blocks)) == number).orderBy("query_id").collect()
        if rows:
            out = out.unionByName(search_block(shards, rows, n, words or 1, held, k, f"{at}/{number}"))
    return out


def search_sql(table: str = "documents", k: int = 10, modulus: int = 100) -> str:
    """The search of every row whose id is a multiple of `modulus`, as DuckDB SQL."""
    words = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
    return f"""
    WITH w AS (SELECT doc_id, unnest(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{words}')) AS term FROM {table}),
    tf AS (SELECT doc_id, term, count(*) AS tf FROM w GROUP BY ALL),
    dl AS (SELECT doc_id, sum(tf) AS dl FROM tf GROUP BY doc_id),
    st AS (SELECT count(*) AS n, (SELECT sum(dl) FROM dl) / count(*) AS mean FROM {table}),
    df AS (SELECT term, count(*) AS df FROM tf GROUP BY term),
    scored AS (SELECT q.doc_id AS query_id, d.doc_id, round(sum(q.tf * ln(1 + (n - df + 0.5) / (df + 0.5)) * d.tf * {K1 + 1} / (d.tf + {K1} * ({1 - B} + {B} * dl / mean))), {ROUND}) AS score
      FROM tf q JOIN tf d ON q.term = d.term JOIN df ON df.term = q.term JOIN dl ON dl.doc_id = d.doc_id, st WHERE q.doc_id % {modulus} = 0 GROUP BY q.doc_id, d.doc_id),
    ranked AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id) AS INTEGER) AS rank, doc_id, score FROM scored)
    SELECT * FROM ranked WHERE rank <= {k}
    """
