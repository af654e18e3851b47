"""Token counts by rank-synchronous merging of ragged arrays.

Pre-tokens of many texts are held as one flat symbol array with sequence numbers. Each round finds every sequence's
lowest-rank pair of neighbours and merges it in all sequences at once; a sequence that has no pair left leaves the
arrays. What survives is counted. The merges are those of a BPE model with byte fallback whose pieces carry ranks.

A pair of characters that stands next to each other in no piece can never be merged across, so pre-tokens are cut there;
this is exact, and keeps sequences short. Several occurrences of the lowest-rank pair merge in one round, left to right,
unless a piece that begins or ends with the merged one has a lower rank; then only the leftmost does, as the model would.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from privgrove.llm.textio import Chunks, gathered, plain, segment_sums, texts_of

SPACE = "▁"
NONE = np.int64(1) << 60


class PairTable:
    """Open-addressing table from pairs of symbols to a merged symbol, with vectorised lookup."""

    def __init__(self, pairs: dict[tuple[int, int], int]):
        self.shift = 64 - max(4, (4 * len(pairs)).bit_length())
        slots = 1 << (64 - self.shift)
        self.keys, self.values = np.full(slots, -1, np.int64), np.full(slots, -1, np.int32)
        self.longest = 1
        for (a, b), merged in pairs.items():
            key = (a << 32) | b
            at = self.slot(np.array([key]))[0]
            probes = 1
            while self.keys[at] >= 0:
                at = (at + 1) % slots
                probes += 1
            self.keys[at], self.values[at] = key, merged
            self.longest = max(self.longest, probes)

    def slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(self.shift)).astype(np.int64)

    def find(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The merged symbol of each pair, or -1."""
        key = (a.astype(np.int64) << 32) | b
        at = self.slot(key)
        out = np.where(self.keys[at] == key, self.values[at], -1)
        open_ = np.flatnonzero((out < 0) & (self.keys[at] >= 0))
        for _ in range(self.longest - 1):
            if not len(open_):
                break
            at[open_] = (at[open_] + 1) % len(self.keys)
            seen = self.keys[at[open_]]
            hit = seen == key[open_]
            out[open_[hit]] = self.values[at[open_[hit]]]
            open_ = open_[~hit & (seen >= 0)]
        return out


class MergeModel:
    """The merges of a sentencepiece BPE model, as arrays."""

    def __init__(self, path: str):
        from sentencepiece import sentencepiece_model_pb2 as proto

        model = proto.ModelProto()
        with open(path, "rb") as file:
            model.ParseFromString(file.read())
        spec = model.normalizer_spec
        plain_text = spec.name == "identity" and not spec.precompiled_charsmap and not spec.remove_extra_whitespaces and spec.escape_whitespaces
        if model.trainer_spec.model_type != 2 or not plain_text or model.trainer_spec.treat_whitespace_as_suffix or not model.trainer_spec.byte_fallback:
            raise ValueError("this merge order is for BPE models with byte fallback and identity normalisation")
        self.prefix = SPACE if spec.add_dummy_prefix else ""
        normal = {p.piece: -p.score for p in model.pieces if p.type == 1}
        number = {piece: k for k, piece in enumerate(normal)}
        self.rank = np.array(list(normal.values()), np.float64)
        order = np.argsort(self.rank, kind="stable")
        self.rank_no = np.empty(len(order), np.int64)
        self.rank_no[order] = np.unique(self.rank[order], return_inverse=True)[1]
        self.char_id = np.full(0x110000, -1, np.int32)
        for piece, k in number.items():
            if len(piece) == 1:
                self.char_id[ord(piece)] = k
        pairs, lowest = {}, np.full(len(number), np.inf)
        joined: set[tuple[int, int]] = set()
        for piece, k in number.items():
            for cut in range(1, len(piece)):
                joined.add((ord(piece[cut - 1]), ord(piece[cut])))
                left, right = number.get(piece[:cut]), number.get(piece[cut:])
                for part in (left, right):
                    if part is not None:
                        lowest[part] = min(lowest[part], self.rank[k])
                if left is not None and right is not None:
                    pairs[left, right] = k
        self.together = lowest >= self.rank
        self.pairs = PairTable(pairs)
        single = {c: self.char_id[c] for c in range(0x110000) if self.char_id[c] >= 0}
        self.neighbours = PairTable({(int(single[a]), int(single[b])): 1 for a, b in joined if a in single and b in single})
        if any(SPACE in p.lstrip(SPACE) for p in number):
            raise ValueError("pieces that go over a space are not supported")

    def count(self, chunks: list[str]) -> np.ndarray:
        """Tokens of each chunk; a space is the model's space symbol already."""
        text = "".join(chunks)
        points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        sizes = np.fromiter(map(len, chunks), np.int64, len(chunks))
        owner = np.repeat(np.arange(len(chunks)), sizes)
        symbols = self.char_id[points]
        out = np.zeros(len(chunks), np.int64)
        unknown = symbols < 0
        bytes_of = 1 + (points > 0x7F).astype(np.int64) + (points > 0x7FF) + (points > 0xFFFF)
        out += np.bincount(owner[unknown], bytes_of[unknown], len(chunks)).astype(np.int64)
        known = np.flatnonzero(~unknown)
        if not len(known):
            return out
        symbols, owner = symbols[known].astype(np.int64), owner[known]
        touches = (np.diff(known) == 1) & (np.diff(owner) == 0)
        touches[touches] = self.neighbours.find(symbols[:-1][touches], symbols[1:][touches]) > 0
        sequence = np.concatenate(([0], np.cumsum(~touches)))
        self.merge(symbols, sequence, owner, out)
        return out

    def merge(self, symbols: np.ndarray, sequence: np.ndarray, owner: np.ndarray, out: np.ndarray) -> None:
        """Merge round by round; add the survivors of each finished sequence to out[owner]."""
        merged = np.full(len(symbols), -1, np.int64)  # what symbol i and the next one make
        merged[:-1] = np.where(sequence[:-1] == sequence[1:], self.pairs.find(symbols[:-1], symbols[1:]), -1)
        while True:
            heads = np.flatnonzero(np.concatenate(([True], sequence[1:] != sequence[:-1])))
            ranks = np.where(merged >= 0, self.rank_no[merged], NONE)
            best = np.minimum.reduceat(ranks, heads)
            sizes = np.diff(np.append(heads, len(symbols)))
            alive = best < NONE
            if not alive.all():
                done = np.flatnonzero(~alive)
                np.add.at(out, owner[heads[done]], sizes[done])
                if not alive.any():
                    return
                keep = np.repeat(alive, sizes)
                symbols, sequence, owner, merged, ranks = (x[keep] for x in (symbols, sequence, owner, merged, ranks))
                best, sizes = best[alive], sizes[alive]
                heads = np.cumsum(sizes) - sizes
            hit = np.flatnonzero(ranks == np.repeat(best, sizes))
            group = sequence[hit]
            first = np.concatenate(([True], group[1:] != group[:-1]))
            if not first.all():  # overlapping ones alternate from the left; unsafe ones wait
                run = np.concatenate(([True], (np.diff(hit) != 1) | first[1:]))
                place = np.arange(len(hit)) - np.maximum.accumulate(np.where(run, np.arange(len(hit)), 0))
                hit = hit[first | ((place % 2 == 0) & self.together[merged[hit]])]
            symbols[hit] = merged[hit]
            keep = np.ones(len(symbols), bool)
            keep[hit + 1] = False
            fresh = np.zeros(len(symbols), bool)
            fresh[hit] = True
            symbols, sequence, owner, merged, fresh = (x[keep] for x in (symbols, sequence, owner, merged, fresh))
            fresh[:-1] |= fresh[1:]
            at = np.flatnonzero(fresh)
            merged[at] = -1
            inner = at[: -1 if at[-1] == len(symbols) - 1 else None]
            inner = inner[sequence[inner] == sequence[inner + 1]]
            merged[inner] = self.pairs.find(symbols[inner], symbols[inner + 1])


@lru_cache(2)
def merge_model(path: str) -> MergeModel:
    """One model per Python worker."""
    return MergeModel(path)


def counts(texts: pa.Array, model: MergeModel) -> np.ndarray:
    """Tokens of each text. Chunks begin at runs of spaces, which no piece goes over."""
    texts = plain(texts, pa.string())
    full = pc.binary_join_element_wise(pa.scalar(model.prefix), pc.replace_substring(texts, " ", SPACE), "")
    full = pc.if_else(pc.equal(pc.binary_length(texts), 0), "", full)
    runs = pc.match_substring(full, SPACE + SPACE).to_numpy(zero_copy_only=False)
    easy = pc.replace_substring(pc.if_else(pa.array(runs), "", full), SPACE, " ")
    chunks = Chunks(easy)
    words = chunks.words.to_numpy(zero_copy_only=False)
    found = model.count([SPACE + w for w in words])
    codes = chunks.codes.astype(np.int64)
    out = segment_sums(found[codes], chunks.offsets)
    # the part before a text's first space symbol has none of its own
    first = codes[chunks.offsets[:-1]]
    starts = [words[c] for c in first.tolist()]
    bare: dict[str, int] = {}
    where = np.array([bare.setdefault(w, len(bare)) for w in starts], np.int64)
    found_bare = model.count(list(bare)) if bare else np.zeros(0, np.int64)
    if len(where):
        out += found_bare[where] - found[first]
    if runs.any():
        pick = np.flatnonzero(runs)
        out[pick] = model.count(full.take(pa.array(pick)).to_pylist())
    return out


def token_counts(docs: DataFrame, model_path: str, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: doc_id, n_bytes, n_tokens, over_limit.

    Null texts count as empty: no tokens. Rows are independent; repeated ids, ties and extra columns change nothing, and
    an empty table gives no rows.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = merge_model(model_path)
        for batch in gathered(batches):
            found = counts(batch.column("text"), model)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pc.binary_length(batch.column("text")).cast(pa.int64()), pa.array(found), pa.array(found > limit)],
                names=["doc_id", "n_bytes", "n_tokens", "over_limit"],
            )

    return texts_of(docs, id_col, text_col).mapInArrow(count, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
