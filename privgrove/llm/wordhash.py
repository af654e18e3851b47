"""64-bit hashes of all words of many texts at once, from running sums over their bytes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from privgrove.llm.textio import plain

#: Text bytes that one step hashes; its arrays take some 40 times as much.
STEP_BYTES = 1 << 20
BASE = 0x9E3779B97F4A7C15
INVERSE = pow(BASE, -1, 1 << 64)

LOWERED = np.arange(256, dtype=np.uint8)
LOWERED[65:91] += 32
#: Bytes that are no part of a word: ASCII white space, or every ASCII byte but letters and digits.
WHITE = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
MARKS = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


BYTE_VALUES = mixed(LOWERED.astype(np.uint64) + np.uint64(1))
_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base ** i modulo 2 ** 64 for i below n."""
    held = _powers.get(base)
    if held is None or len(held) < n:
        full = np.full(max(n, STEP_BYTES + 1), base, np.uint64)
        full[0] = 1
        held = np.cumprod(full)
        if n <= 4 * STEP_BYTES:
            _powers[base] = held
    return held[:n]


def word_hashes(texts: pa.Array, apart: np.ndarray = WHITE) -> tuple[np.ndarray, np.ndarray]:
    """(hash of each word, offsets of each text's words), with A-Z lowered; words end at the bytes in `apart`."""
    texts = plain(texts, pa.large_string())
    begin = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = texts.buffers()[2]
    raw = np.frombuffer(data, np.uint8)[begin[0] : begin[-1]] if data is not None else np.zeros(0, np.uint8)
    begin = begin - begin[0]
    if not len(raw):
        return np.zeros(0, np.uint64), np.zeros(len(texts) + 1, np.int64)
    solid = ~apart[raw]
    edge = np.zeros(len(raw) + 1, bool)
    edge[begin] = True
    starts = np.flatnonzero(solid & (edge[:-1] | np.concatenate(([True], ~solid[:-1]))))
    ends = np.flatnonzero(solid & (edge[1:] | np.concatenate((~solid[1:], [True])))) + 1
    sums = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum(BYTE_VALUES[raw] * powers(BASE, len(raw)), out=sums[1:])
    words = mixed((sums[ends] - sums[starts]) * powers(INVERSE, len(raw))[starts])
    return words, np.searchsorted(starts, begin)
