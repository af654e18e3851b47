"""Language identification by a linear-chain conditional random field over words.

Every word of a text has a label; neighbouring labels are joined by learned transition weights, so a text that switches
language is labelled piece by piece. A word's emission weights come from its affixes, its inner byte n-grams and a
lexicon entry of its own, all hashed into one weight table. Forward-backward runs over all texts of a slice at once, a
position at a time, both directions together. A text's language is the one with the most expected words.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from privgrove.llm.textio import Chunks, gathered, plain, ragged, segment_sums, texts_of

UNKNOWN = "und"
#: Stripped from both ends of a word.
EDGES = "".join(chr(c) for c in range(33, 127) if not chr(c).isalnum()) + "«»„“”‘’…–—¿¡"
BITS = 17
GRAMS, AFFIXES = (2, 3, 4), (1, 2, 3, 4)
TEXT_BYTES = 2 << 20


@dataclass
class LanguageModel:
    """Labels and weights: emission[feature, label], transition[from, to], first[label]."""

    labels: list[str]
    emission: np.ndarray
    transition: np.ndarray
    first: np.ndarray


def scrambled(x: np.ndarray) -> np.ndarray:
    x = x * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(29))


def word_features(words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(feature, offsets): the hashed features of lower-case word i are feature[offsets[i]:offsets[i+1]]."""
    words = plain(words, pa.binary())
    n = len(words)
    size = pc.binary_length(words).to_numpy(zero_copy_only=False).astype(np.int64)
    begin = np.frombuffer(words.buffers()[1], np.int32)[words.offset : words.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(words.buffers()[2] or b"", np.uint8)[begin[0] : begin[-1]]
    full = size + 2  # with a mark at each end
    start = np.cumsum(full) - full
    data = np.full(int(full.sum()), 1, np.uint64)
    data[ragged(start + 1, size)] = raw
    mask, parts, counts = np.uint64((1 << BITS) - 1), [], []

    def add(values: np.ndarray, owner_counts: np.ndarray, kind: int) -> None:
        parts.append(((scrambled(values * np.uint64(64) + np.uint64(kind)) >> np.uint64(20)) & mask).astype(np.int32))
        counts.append(owner_counts)

    longest = max((*GRAMS, *AFFIXES)) + 1
    windows, rolling = {}, np.zeros(len(data) + longest, np.uint64)
    padded = np.concatenate((data, np.zeros(longest, np.uint64)))
    for k in range(1, longest + 1):
        rolling[: len(data)] = rolling[: len(data)] * np.uint64(257) + padded[k - 1 : k - 1 + len(data)]
        windows[k] = rolling[: len(data)].copy()
    for k in GRAMS:
        each = np.maximum(full - k + 1, 0)
        add(windows[k][ragged(start, each)], each, k)
    for k in AFFIXES:
        has = (size >= k).astype(np.int64)
        at = np.flatnonzero(has)
        add(windows[k + 1][start[at]], has, 16 + k)
        add(windows[k + 1][start[at] + full[at] - k - 1], has, 32 + k)
    value = np.concatenate((np.zeros(1, np.uint64), np.cumsum(data * np.power(np.uint64(0x2545F4914F6CDD1D), (np.arange(len(data)) % 61).astype(np.uint64)))))
    whole = value[start + full] - value[start]
    first = start % 61  # undo the word's place among the words
    add(whole * INVERSES[first], np.ones(n, np.int64), 63)
    total = np.sum(counts, axis=0)
    offsets = np.concatenate(([0], np.cumsum(total)))
    out, base = np.empty(int(offsets[-1]), np.int32), offsets[:-1].copy()
    for part, each in zip(parts, counts):
        out[ragged(base, each)] = part
        base += each
    return out, offsets


INVERSES = np.array([pow(pow(0x2545F4914F6CDD1D, k, 1 << 64), -1, 1 << 64) for k in range(61)], np.uint64)


def word_scores(features: np.ndarray, offsets: np.ndarray, emission: np.ndarray) -> np.ndarray:
    """Emission weights of each word, scaled by the square root of its number of features."""
    size = np.maximum(np.diff(offsets), 1)
    return np.stack([segment_sums(emission[features, k].astype(np.float64), offsets) for k in range(emission.shape[1])], axis=1) / np.sqrt(size)[:, None]


def marginals(scores: np.ndarray, offsets: np.ndarray, model: LanguageModel) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(probabilities, forward, backward) of every word's labels; sequence i is offsets[i]:offsets[i+1]."""
    weight = np.exp(np.maximum(scores - scores.max(axis=1, keepdims=True), -30.0))
    lengths = np.diff(offsets)
    order = np.argsort(-lengths, kind="stable")
    lengths, start = lengths[order], offsets[:-1][order]
    n, labels = len(order), len(model.labels)
    step, back = np.exp(model.transition), np.exp(model.transition).T
    ahead, behind = np.empty_like(weight), np.empty_like(weight)
    active = np.searchsorted(-lengths, -np.arange(1, (lengths[0] if n else 0) + 1), "right")
    here = np.broadcast_to(np.exp(model.first), (n, labels))
    there = np.ones((n, labels))
    last = start + lengths - 1
    for t, k in enumerate(active.tolist()):
        at, to = start[:k] + t, last[:k] - t
        if t:
            here, there = here[:k] @ step, there[:k] @ back
        here, there = here[:k] * weight[at], there[:k] * weight[to]
        here = here / here.sum(axis=1, keepdims=True)
        there = there / there.sum(axis=1, keepdims=True)
        ahead[at], behind[to] = here, there
    out = ahead * behind / weight
    return out / np.maximum(out.sum(axis=1, keepdims=True), 1e-300), ahead, behind


class Words:
    """The words of texts that have a letter: codes into distinct lower-case words, with their features."""

    def __init__(self, texts: pa.Array):
        texts = plain(texts, pa.string())
        chunks = Chunks(pc.replace_substring_regex(texts, r"[\t\n\v\f\r]+", " "))
        bare = pc.utf8_lower(pc.utf8_trim(chunks.words, characters=EDGES)).dictionary_encode()
        lettered = pc.match_substring_regex(bare.dictionary, r"\p{L}").to_numpy(zero_copy_only=False)
        codes = bare.indices.to_numpy(zero_copy_only=False)[chunks.codes]
        kept = lettered[codes]
        self.offsets = np.concatenate(([0], np.cumsum(kept)))[chunks.offsets]
        self.codes = codes[kept]
        self.words = bare.dictionary
        self.features, self.feature_offsets = word_features(self.words)


def likeliest(texts: pa.Array, model: LanguageModel) -> tuple[list[str], np.ndarray]:
    """Each text's language and the share of its words expected to be in it; `und` and 0 without letters."""
    words = Words(texts)
    n = len(words.offsets) - 1
    if not model.labels or not len(words.codes):
        return [UNKNOWN] * n, np.zeros(n)
    scores = word_scores(words.features, words.feature_offsets, model.emission)[words.codes]
    shares = marginals(scores, words.offsets, model)[0]
    sums = np.stack([segment_sums(shares[:, k], words.offsets) for k in range(shares.shape[1])], axis=1)
    size = np.diff(words.offsets)
    best = sums.argmax(axis=1)
    score = np.clip(sums[np.arange(n), best] / np.maximum(size, 1), 0, 1)
    return [model.labels[b] if s else UNKNOWN for b, s in zip(best, size)], np.where(size > 0, score, 0.0)


def fit(texts: list[str], langs: list[str], rounds: int = 30, rate: float = 1.0, decay: float = 1e-4, run: int = 40, seed: int = 7) -> LanguageModel:
    """Train on whole labelled texts, by AdaGrad on the conditional likelihood.

    A text's words carry its label. Sequences are runs of words; every third joins runs of different texts, so that
    transitions between languages are seen as well.
    """
    labels = sorted(set(langs))
    zero = LanguageModel(labels, np.zeros((1 << BITS, len(labels)), np.float32), np.zeros((len(labels),) * 2), np.zeros(len(labels)))
    if not labels:
        return zero
    words, rng = Words(pa.array(texts, pa.string())), np.random.default_rng(seed)
    own = {x: k for k, x in enumerate(labels)}
    runs = [(a, min(a + run, b), own[langs[i]]) for i, (s, b) in enumerate(zip(words.offsets[:-1].tolist(), words.offsets[1:].tolist())) for a in range(s, b, run)]
    if not runs:
        return zero
    sequences: list[list[tuple[int, int, int]]] = []
    order = rng.permutation(len(runs))
    at = 0
    while at < len(order):
        many = 3 if len(sequences) % 3 == 2 else 1
        sequences.append([(a, b if many == 1 else min(b, a + int(rng.integers(3, run))), k) for a, b, k in (runs[i] for i in order[at : at + many])])
        at += many
    flat = [piece for s in sequences for piece in s]
    token = np.concatenate([np.arange(a, b) for a, b, _ in flat])
    truth = np.repeat([k for *_, k in flat], [b - a for a, b, _ in flat])
    offsets = np.concatenate(([0], np.cumsum([sum(b - a for a, b, _ in s) for s in sequences])))
    codes, (n, count) = words.codes[token], (len(token), len(labels))
    inner = np.ones(n, bool)
    inner[offsets[:-1]] = False
    inner = np.flatnonzero(inner)
    seen = np.zeros((n, count))
    seen[np.arange(n), truth] = 1
    pairs = np.zeros((count, count))
    np.add.at(pairs, (truth[inner - 1], truth[inner]), 1)
    scale = 1 / np.sqrt(np.maximum(np.diff(words.feature_offsets), 1))
    owner = np.repeat(np.arange(len(scale)), np.diff(words.feature_offsets))
    model = zero
    squares = [np.full(x.shape, 1e-8) for x in (model.emission, model.transition, model.first)]
    for _ in range(rounds):
        scores = word_scores(words.features, words.feature_offsets, model.emission)[codes]
        shares, ahead, behind = marginals(scores, offsets, model)
        slack = seen - shares
        by_word = np.stack([np.bincount(codes, slack[:, k], len(scale)) for k in range(count)], axis=1) * scale[:, None]
        emission = np.stack([np.bincount(words.features, by_word[owner, k], 1 << BITS) for k in range(count)], axis=1) / n
        joint = ahead[inner - 1][:, :, None] * np.exp(model.transition) * behind[inner][:, None, :]
        transition = (pairs - (joint / joint.sum(axis=(1, 2), keepdims=True)).sum(axis=0)) / n
        first = slack[offsets[:-1]].sum(axis=0) / n
        for value, gradient, square in zip((model.emission, model.transition, model.first), (emission, transition, first), squares):
            gradient = gradient - decay / n * value
            square += gradient**2
            value += rate * 0.3 * gradient / np.sqrt(square)
    return model


def trained(docs: DataFrame, per_language: int = 250, longest: int = 6000, languages: int = 64, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> LanguageModel:
    """Fit on a bounded sample: per_language texts of at most `longest` bytes, of the `languages` most frequent labels;
    a label beyond those, or with longer texts only, is not learned and so never predicted.

    Rows whose crc32 of the id modulo 3 is 1 are held out, and so are null ids, texts and languages. The sample has the
    rows with the smallest hashes, so it is the same however the table is cut.
    """
    fold = F.crc32(F.col(id_col).cast("string").cast("binary")) % 3
    rows = docs.where((fold != 1) & F.col(text_col).isNotNull() & F.col(lang_col).isNotNull() & (F.octet_length(text_col) <= longest))
    rows = rows.select(F.col(text_col).alias("text"), F.col(lang_col).alias("lang"), F.xxhash64(F.col(id_col), F.col(text_col)).alias("key"))
    counts = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(languages).collect()}
    if not counts:
        return fit([], [])
    span = {lang: int(min(1.0, 2.0 * per_language / c) * 2**64) for lang, c in counts.items()}
    below = F.coalesce(*[F.when((F.col("lang") == k) & (F.col("key") < F.lit(min(v - 2**63, 2**63 - 1))), F.lit(True)) for k, v in span.items()], F.lit(False))
    picked = rows.where(below).orderBy("key", "text").limit(4 * per_language * len(span)).collect()
    held = {lang: [r["text"] for r in picked if r["lang"] == lang][:per_language] for lang in sorted(counts)}
    return fit([t for x in held.values() for t in x], [k for k, x in held.items() for _ in x])


def predicted(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: doc_id, lang_pred, score. Null texts and texts without a letter are `und` with score 0.

    Only the text counts. Repeated rows and ids give a row each, an empty table none; extra columns are ignored.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in gathered(batches, most=TEXT_BYTES):
            langs, score = likeliest(batch.column("text"), shared.value)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(langs, pa.string()), pa.array(score)], names=["doc_id", "lang_pred", "score"])

    return texts_of(docs, id_col, text_col).mapInArrow(run, "doc_id long, lang_pred string, score double")


def kept(docs: DataFrame, model: LanguageModel, least: float, text_col: str = "text") -> DataFrame:
    """The rows whose text has a language with a score of `least` or more, with their own columns.

    Every row is decided by its own text, so null or repeated ids change nothing. Null texts and texts without a letter
    have no language and go; an empty table gives no rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in gathered(batches, text_col, TEXT_BYTES):
            langs, score = likeliest(batch.column(at).fill_null(""), shared.value)
            yield batch.filter(pa.array((score >= least) & (np.array(langs, object) != UNKNOWN)))

    return docs.mapInArrow(run, docs.schema)


def labelled_words(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: doc_id, words and their likeliest labels, for code-switched text."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = np.array([*shared.value.labels, UNKNOWN], object)
        for batch in gathered(batches, most=TEXT_BYTES):
            words = Words(batch.column("text"))
            best = np.full(len(words.codes), len(names) - 1)
            if len(words.codes) and len(names) > 1:
                best = marginals(word_scores(words.features, words.feature_offsets, shared.value.emission)[words.codes], words.offsets, shared.value)[0].argmax(axis=1)
            ends = pa.array(words.offsets.astype(np.int32))
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.ListArray.from_arrays(ends, words.words.take(pa.array(words.codes))), pa.ListArray.from_arrays(ends, pa.array(names[best], pa.string()))],
                names=["doc_id", "words", "labels"],
            )

    return texts_of(docs, id_col, text_col).mapInArrow(run, "doc_id long, words array<string>, labels array<string>")


def languages(docs: DataFrame, **options) -> DataFrame:
    """Train on the labelled rows and predict every row: doc_id, held_out, lang_pred, score."""
    model = trained(docs, **options)
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))
    return predicted(docs, model).select("doc_id", held.alias("held_out"), "lang_pred", "score")
