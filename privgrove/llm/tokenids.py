"""Whole texts to token ids with the tokenizers library, one model call per distinct word.

A text is cut at single spaces; a cut never falls inside a pre-token, so the ids of the chunks, one after another,
are the ids of the text. Letters-only words (below U+0250, where normal forms and case are settled) go straight to the
library's BPE model; every other chunk, and every text with special strings or runs of spaces, to its full encoder.
"""

from __future__ import annotations

import os
from array import array
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from privgrove.llm.textio import Chunks, plain, ragged

#: Trailing characters that every pre-tokenizer here separates from a preceding letter.
TRAILING = ".,;:!?*#&$%|)"
#: Text that one step encodes: a worker's arrays stay within some tens of MB.
TEXT_BYTES = 4 << 20
#: Chunks that the full encoder takes at once; its results are large.
BATCH = 1000
#: Entries that a worker keeps from slice to slice; a full cache starts anew.
CACHE = 200_000


def byte_letters() -> dict[int, str]:
    """The printable character that byte-level BPE vocabularies write for each byte, keyed by the byte."""
    shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    rest = [b for b in range(256) if b not in set(shown)]
    return {b: chr(b) for b in shown} | {b: chr(256 + i) for i, b in enumerate(rest)}


class WordEncoder:
    """Token ids of texts; `spaced` says that a word's leading space is part of its first token."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # Spark runs a worker per core
        from tokenizers import Tokenizer

        self.full = Tokenizer.from_file(path)
        self.model = self.full.model
        self.spaced = self.model.end_of_word_suffix is None
        self.special = [t.content for t in self.full.get_added_tokens_decoder().values()]
        self.letters = byte_letters()
        self.cache: dict[str, bytes] = {}

    def whole(self, texts: list[str]) -> list[bytes]:
        """The full encoder's ids of each text, as 32-bit numbers."""
        out = []
        for at in range(0, len(texts), BATCH):
            out += [array("I", e.ids).tobytes() for e in self.full.encode_batch_fast(texts[at : at + BATCH], add_special_tokens=False)]
        return out

    def word(self, stem: str) -> bytes:
        """Ids of a letters-only word."""
        if not self.spaced:
            stem = stem.lower()
        if not stem.isascii():
            stem = stem.encode().decode("latin-1").translate(self.letters)
        return array("I", [t.id for t in self.model.tokenize(f"Ġ{stem}" if self.spaced else stem)]).tobytes()

    def distinct(self, words: pa.Array) -> list[bytes]:
        """Ids of each chunk, with its leading space where that counts."""
        stems = pc.utf8_rtrim(words, characters=TRAILING)
        cache, out, rest = self.cache, [], []
        if len(cache) > CACHE:
            cache.clear()
        for k, (word, stem) in enumerate(zip(words.to_numpy(zero_copy_only=False), stems.to_numpy(zero_copy_only=False))):
            if stem.isalpha() and (stem.isascii() or max(stem) < "ɐ" and "İ" not in stem):  # whose lower case has a mark
                ids = cache.get(stem)
                if ids is None:
                    ids = cache[stem] = self.word(stem)
                if len(word) > len(stem):
                    tail = word[len(stem) :]
                    more = cache.get(tail)
                    if more is None:
                        more = cache[tail] = self.whole([tail])[0]
                    ids = ids + more
                out.append(ids)
            else:
                rest.append((k, word))
                out.append(None)
        for (k, _), ids in zip(rest, self.whole([f" {w}" if self.spaced else w for _, w in rest])):
            out[k] = ids
        return out

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids, offsets): the ids of text i are ids[offsets[i]:offsets[i+1]]."""
        texts = plain(texts, pa.string())
        odd = np.zeros(len(texts), bool)
        for mark in [*self.special, *["  "] * self.spaced]:
            odd |= pc.match_substring(texts, mark).to_numpy(zero_copy_only=False)
        easy = pc.if_else(pa.array(odd), "", texts)
        chunks = Chunks(easy)
        lists = self.distinct(chunks.words)
        codes = chunks.codes.astype(np.int64)
        if self.spaced:  # a text's first chunk has no space before it
            first = chunks.offsets[:-1]
            bare = pc.take(chunks.words, pa.array(codes[first]))
            found: dict[str, int] = {}
            codes[first] = [len(lists) + found.setdefault(w, len(found)) for w in bare.to_numpy(zero_copy_only=False)]
            lists += self.whole(list(found))
        sizes = np.fromiter(map(len, lists), np.int64, len(lists)) // 4
        flat = np.frombuffer(b"".join(lists), np.uint32)
        starts = np.cumsum(sizes) - sizes
        ids = flat[ragged(starts[codes], sizes[codes])]
        ends = np.concatenate(([0], np.cumsum(sizes[codes])))
        offsets = ends[chunks.offsets]
        if odd.any():
            offsets, ids = self.with_odd(texts, odd, offsets, ids)
        return ids, offsets

    def with_odd(self, texts, odd, offsets, ids):
        """Put the ids of the texts that were encoded whole at their places."""
        own = dict(zip(np.flatnonzero(odd), self.whole(texts.filter(pa.array(odd)).to_pylist())))
        parts = [np.frombuffer(own[i], np.uint32) if i in own else ids[offsets[i] : offsets[i + 1]] for i in range(len(odd))]
        return np.concatenate(([0], np.cumsum([len(p) for p in parts]))).astype(np.int64), np.concatenate(parts)


@lru_cache(2)
def encoder(path: str) -> WordEncoder:
    """One encoder per Python worker and vocabulary."""
    return WordEncoder(path)


def with_end(ids: np.ndarray, offsets: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
    """Append the id `end` to each text's ids."""
    n = len(offsets) - 1
    out = np.empty(len(ids) + n, np.uint32)
    ends = offsets[1:] + np.arange(n)
    mask = np.ones(len(out), bool)
    mask[ends] = False
    out[mask] = ids
    out[ends] = end
    return out, offsets + np.arange(n + 1)
