"""The whole corpus pipeline against brute force, stage by stage, on documents with awkward rows."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest

pytest.importorskip("public_tokenizers")
import public_tokenizers

corpus_pipeline = pytest.importorskip("corpus_pipeline")
from privgrove.llm import langid, mixing

ODD = [
    (1, "Repeated id with a text of its own, quite unlike the others in this table of documents", "en", "s9"), (1, "Repeated id with a text of its own, quite unlike the others in this table of documents", "en", "s9"),
    (2, "Zweite Zeile mit derselben Nummer und einem anderen Inhalt für diese kleine Sammlung von Texten", "de", None), (None, "A row without an id that says something nobody else says in these documents here", None, None),
    (None, "A row without an id that says something nobody else says in these documents here", None, None), (None, None, "en", "s1"), (9001, "", "en", "s1"), (9002, "12345 ... !!!", None, "s1"), (9003, "   ", "de", "s2"), (2, None, None, None),
]


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    """Every stage's rows, with what came in."""
    at = tmp_path_factory.mktemp("corpus")
    base = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    odd = spark.createDataFrame([(i, t, lang, source, len(t or "")) for i, t, lang, source in ODD], "doc_id long, text string, lang string, source string, n_chars long")
    base.unionByName(odd.select(*[odd[c].cast(base.schema[c].dataType).alias(c) for c in base.columns])).repartition(3).write.parquet(f"{at}/documents.parquet")
    docs, out = spark.read.parquet(f"{at}/documents.parquet"), {"input": None}
    out["input"] = docs.collect()
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, str(at)).write.parquet(f"{at}/{name}")
        docs = spark.read.parquet(f"{at}/{name}")
        out[name] = docs.collect()
    out["run"] = corpus_pipeline.run(spark, str(at)).collect()
    out["model"] = langid.trained(spark.read.parquet(f"{at}/documents.parquet"))
    return out


def counted(rows):
    return Counter(tuple(r) for r in rows)


def test_language_stage_decides_each_row_by_its_text(stages):
    want = []
    for r in stages["input"]:
        (lang,), (score,) = langid.likeliest(pa.array([r["text"] or ""]), stages["model"])
        if lang != langid.UNKNOWN and score >= corpus_pipeline.LEAST_SCORE:
            want.append(r)
    assert counted(stages["language_id"]) == counted(want) and 0 < len(want) < len(stages["input"])
    assert {r["doc_id"] for r in want} >= {1, 2, None}


def test_jaccard_stage_keeps_one_row_of_each_group(stages):
    rows, low = stages["language_id"], str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = []
    for r in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (r["text"] or "").translate(low))
        sets.append({tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    own = list(range(len(rows)))

    def root(x):
        while own[x] != x:
            x = own[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                own[root(a)] = root(b)
    groups = defaultdict(list)
    for k, r in enumerate(rows):
        groups[root(k) if sets[k] else (k,)].append(r)
    got = counted(stages["ngram_jaccard_join"])
    assert sum(got.values()) == len(groups) < len(rows)
    for group in groups.values():
        ids = [r["doc_id"] for r in group if r["doc_id"] is not None]
        kept = [r for r in {tuple(r): r for r in group}.values() if got[tuple(r)]]
        assert len(kept) == 1 and kept[0]["doc_id"] == min(ids, default=None)


def test_mixing_stage_draws_by_calibrated_probabilities(stages):
    rows = stages["ngram_jaccard_join"]

    def topic(t):
        low = t.lower()
        if "licen" in low or "rights reserved" in low:
            return "legal"
        if " | " in t or "@" in t:
            return "table" if " | " in t else "contact"
        counts = Counter((ord(x) - 97) % 8 for x in re.findall(r"([a-z])[a-z]{6,}", low))
        return f"words-{min(counts, key=lambda k: (-counts[k], k))}" if counts else "other"

    cell = [(r["source"] or "none", r["lang"] or "none", topic(r["text"] or "")) for r in rows]
    tokens = [len(re.findall(r"[^ \t\n\r]+", r["text"] or "")) for r in rows]
    sums = Counter()
    for c, n in zip(cell, tokens):
        sums[c] += n
    cells = [c for c in sums if sums[c]]
    total = sum(sums.values())
    weight, cap = (np.array([sums[c] / total for c in cells]) / x for x in (1, mixing.KEEP))
    sides = []
    for k, power in enumerate(mixing.SMOOTHING.values()):
        values = sorted({c[k] for c in cells})
        share = np.array([sum(sums[c] for c in cells if c[k] == v) / total for v in values]) ** power
        sides.append((np.array([values.index(c[k]) for c in cells]), share / share.sum()))
    for _ in range(mixing.ROUNDS):
        for at, target in sides:
            full = weight >= cap
            own, capped = np.bincount(at, weight, len(target)), np.bincount(at, np.where(full, weight, 0.0), len(target))
            with np.errstate(all="ignore"):
                more = np.minimum(cap, weight * ((target - capped) / (own - capped))[at])
            weight = np.where((own >= target)[at], weight * (target / own)[at], np.where(full, cap, more))
    chance = dict(zip(cells, np.round(np.minimum(1.0, weight / cap), 9)))
    draw = lambda i: (int(hashlib.sha256(f"mix|{'' if i is None else i}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52
    want = [r for r, c, n in zip(rows, cell, tokens) if draw(r["doc_id"]) < (chance[c] if n else 1.0)]
    assert counted(stages["mixing_to_target_weights"]) == counted(want) and 0.3 * len(rows) < len(want) < len(rows)


def test_packing_stage_places_every_token_once(stages):
    from tokenizers import Tokenizer

    library, want = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")), Counter()
    for r in stages["mixing_to_target_weights"]:
        ids = library.encode(r["text"] or "", add_special_tokens=False).ids + [0]
        want.update((r["doc_id"], k // 2048, k, len(ids[k : k + 2048]), zlib.crc32(np.array(ids[k : k + 2048], "<u4").tobytes())) for k in range(0, len(ids), 2048))
    bins = defaultdict(list)
    for r in stages["best_fit_packing"]:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    assert Counter(tuple(r)[:5] for r in stages["best_fit_packing"]) == want
    for held in bins.values():
        held.sort()
        assert [o for o, _ in held] == np.concatenate(([0], np.cumsum([n for _, n in held])[:-1])).tolist() and sum(n for _, n in held) <= 2048
    assert len(bins) <= 1.1 * sum(n for held in bins.values() for _, n in held) / 2048 + 1


def test_run_applies_the_stages_in_order(stages):
    assert counted(stages["run"]) == counted(stages["best_fit_packing"])
    assert [name for name, _ in corpus_pipeline.STAGES] == ["language_id", "ngram_jaccard_join", "mixing_to_target_weights", "best_fit_packing"]


def test_pipeline_of_no_rows(spark, tmp_path):
    spark.read.parquet("/root/testdata/sf0.001/documents.parquet").limit(0).write.parquet(f"{tmp_path}/documents.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
