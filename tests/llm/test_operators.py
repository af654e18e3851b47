"""Every training-data operator against brute force on awkward rows: nulls, empty and long texts, ties, repeats."""

import base64
import hashlib
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

pytest.importorskip("public_tokenizers")
import public_tokenizers

from privgrove.llm import audio, bm25, bpe_count, jaccard, langid, licenses, mixing, packing, planes, queries, tokenids, warc

LONG = " ".join(f"word{k % 97} et{k % 13}," for k in range(4000))
TEXTS = [
    None, "", " ", "one", "Two words", "the cat sat on the mat and then the cat left the mat again", "the cat sat on the mat and then the cat left the mat again",
    "the cat sat on the mat and then the cat left the mat once more", "déjà vu: 日本 😀  a  b\n\nc ", "<|endoftext|> special <|startoftext|>", "Licensed under CC BY-NC 4.0. All rights reserved.",
    "This work is licensed under the GNU General Public License, version 3.", "12345 67", "... !!!", LONG, "x" * 3000, "cc by cc-by CC,BY", "a\tb\r\nc  d", "o'er don't I'LL we've",
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, node string, length long, tokens int, score string"


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(k, t, ["en", "de", None][k % 3], ["s0", "s1", None][k % 3], len(t or ""), "x", 1, 1, "y") for k, t in enumerate(TEXTS)]
    rows += [(5, TEXTS[5], "en", "s0", 1, "x", 1, 1, "y"), (None, "no id here at all", "en", "s0", 1, "x", 1, 1, "y")]
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def texts_of(docs):
    return sorted([(r["doc_id"], r["text"] or "") for r in docs.collect()], key=lambda x: (x[0] is not None, x[0] or 0, x[1]))


def library(name):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(public_tokenizers.path(name))


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_token_ids_equal_the_library(name):
    texts = [t or "" for t in TEXTS] + ["a   b", " lead", "trail ", "tab\t x", " \n x\n\n  y", "Straße ÀÉ İ", "naïve.\nNext", "é x", "ﬁ ½ ²", "  　x"]
    ids, offsets = tokenids.WordEncoder(public_tokenizers.path(name)).encode(pa.array(texts))
    for text, a, b in zip(texts, offsets[:-1], offsets[1:]):
        assert ids[a:b].tolist() == library(name).encode(text, add_special_tokens=False).ids, text


def test_packing(docs, empty):
    path = public_tokenizers.path("word_bpe_49k.json")
    rows = packing.pack_documents(docs, path, 64, 0).collect()
    want = []
    for i, t in texts_of(docs):
        ids = library("word_bpe_49k.json").encode(t, add_special_tokens=False).ids + [0]
        want += [(i, k // 64, k, len(ids[k : k + 64]), zlib.crc32(np.array(ids[k : k + 64], "<u4").tobytes())) for k in range(0, len(ids), 64)]
    assert sorted([tuple(r)[:5] for r in rows], key=repr) == sorted(want, key=repr)
    bins = {}
    for r in rows:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for b in bins.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= 64
    assert len(bins) <= sum(r["length"] for r in rows) / 64 * 1.1 + 2
    assert packing.pack_documents(empty, path, 64, 0).count() == 0


def test_packing_spreads_equal_rows(spark):
    pieces = spark.createDataFrame([(None, 0, 0, 40, 7)] * 3000 + [(k, 0, 0, 24, 9) for k in range(3000)], "doc_id long, piece int, start long, length long, ids_crc32 long")
    rows = packing.pack(pieces, 64, packer_tokens=12_000)
    assert rows.withColumn("part", F.shiftright("sequence_id", 36)).where("doc_id IS NULL").groupBy("part").count().agg({"count": "max"}).first()[0] < 900
    bins = rows.groupBy("sequence_id").agg(F.sum("length").alias("n"), F.count_distinct("offset").alias("places"), F.count("*").alias("held"))
    assert rows.count() == 6000 and bins.where("n > 64 OR places <> held").isEmpty() and bins.count() < 3600


def test_open_bins_close_the_fullest_and_fit_tightly():
    bins = packing.OpenBins(10, 2)
    assert [bins.put(n) for n in (6, 7, 3, 5, 4)] == [(0, 0), (1, 0), (1, 7), (2, 0), (0, 6)]
    assert bins.put(6) == (3, 0) and bins.put(6) == (4, 0)  # bin 3, the fullest, has closed
    assert bins.put(5) == (2, 5) and bins.put(4) == (4, 6)


def test_audio(docs, empty):
    rows = audio.media_features(docs).collect()
    by = {}
    for r in rows:
        by.setdefault(r["doc_id"], r)
    for i, t in texts_of(docs):
        raw = t.encode()
        full = raw + b"\xff" * ((-len(raw)) % 576 if raw else 576)
        r = by[i]
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(raw), len(full), hashlib.sha256(full).hexdigest(), zlib.crc32(full[-32:]))
    assert len({tuple(r)[1:] for r in rows if r["doc_id"] in (5, 6)}) == 1
    assert audio.media_features(empty).count() == 0


def adpcm_by_sample(block):
    """One block, a sample at a time."""
    value, index = int.from_bytes(block[:2], "little", signed=True), min(block[2], 88)
    out = [value]
    for code in (c for b in block[4:] for c in (b & 15, b >> 4)):
        step = int(audio.STEPS[index])
        change = sum(step >> shift for shift, bit in ((0, 4), (1, 2), (2, 1)) if code & bit) + (step >> 3)
        value = max(-32768, min(32767, value - change if code & 8 else value + change))
        index = max(0, min(88, index + (-1, -1, -1, -1, 2, 4, 6, 8)[code & 7]))
        out.append(value)
    return out


def test_audio_media_and_features(docs):
    """The stored form and every feature, by their definitions."""
    table, step = audio.TABLES[audio.ULAW].astype(int), 505
    for r in audio.media_features(docs).collect():
        text = next(t for i, t in texts_of(docs) if i == r["doc_id"] and hashlib.sha256(audio.padded_payload(t.encode(), 576, 255)).hexdigest() == r["payload_sha256"])
        full = audio.padded_payload(text.encode(), 576, 255)
        medium = audio.wav(full, audio.ULAW)
        assert (r["media_bytes"], r["media_sha256"]) == (len(medium), hashlib.sha256(medium).hexdigest()) and medium.endswith(full)
        x = table[list(full)]
        crossings = sum((a >= 0) != (b >= 0) for a, b in zip(x, x[1:]))
        assert r["feature"] == f"rms={np.sqrt(np.mean(x.astype(float) ** 2)):.1f};peak={abs(x).max()};crossings={crossings};pcm={zlib.crc32(x.astype('<i2').tobytes()):08x}"
        if len(full) > 6000:
            continue
        law = audio.TABLES[audio.ALAW].astype(int)
        near = np.abs(law[:, None] - x[None]).min(axis=0)
        blocks = [np.append(b, np.full(step - len(b), b[-1])).astype(np.int16) for b in (x[k : k + step] for k in range(0, len(x), step))]
        back = np.concatenate([adpcm_by_sample(bytes(audio.encode_adpcm(b[None])[0])) for b in blocks])[: len(x)]
        assert r["codecs"] == f"ulaw=0.0;alaw={np.sqrt(np.mean(near**2.0)):.1f};adpcm={np.sqrt(np.mean((back - x) ** 2.0)):.1f}"


def test_audio_query_gives_the_samples_and_every_codecs_file(spark, tmp_path):
    texts = ["", None, "a low and a high sound " * 40, "x" * 1151, "x" * 1153, "\u00e9t\u00e9 " * 500]
    spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    rows = queries.op3_telephony_audio(spark, str(tmp_path)).collect()
    assert len(rows) == len(texts)
    for r in rows:
        full = audio.padded_payload((texts[r["doc_id"]] or "").encode(), 576, 255)
        x = audio.TABLES[audio.ULAW][np.frombuffer(full, np.uint8)]
        assert bytes(r["pcm"]) == x.astype("<i2").tobytes() and r["pcm_rate"] == 8000
        tag, rate, align, data = audio.unwav(bytes(r["alaw"]))
        assert (tag, rate, align, len(data)) == (audio.ALAW, 8000, 1, len(x))
        near = audio.to_pcm(tag, align, data).astype(float)
        assert (np.abs(near - x) == np.abs(audio.TABLES[audio.ALAW].astype(int)[:, None] - x[None]).min(axis=0)).all()
        tag, rate, align, data = audio.unwav(bytes(r["adpcm"]))
        assert (tag, rate, align, len(data)) == (audio.ADPCM, 8000, 256, 256 * -(-len(x) // 505))
        back = np.array([v for k in range(0, len(data), align) for v in adpcm_by_sample(data[k : k + align])][: len(x)], float)
        assert r["codecs"] == f"ulaw=0.0;alaw={np.sqrt(np.mean((near - x) ** 2)):.1f};adpcm={np.sqrt(np.mean((back - x) ** 2)):.1f}"


def test_audio_features_are_those_of_the_stored_samples(spark, monkeypatch):
    docs = spark.createDataFrame([(1, "a low and a high sound " * 40)], "doc_id long, text string")
    plain = audio.media_features(docs).first()
    real = audio.stored
    silent = lambda df, name, *rest: real(df.withColumn("pcm", F.lit(bytes(8)).cast("binary")) if name == "pcm" else df, name, *rest)
    monkeypatch.setattr(audio, "stored", silent)
    other = audio.media_features(docs).first()
    assert other["feature"] == f"rms=0.0;peak=0;crossings=0;pcm={zlib.crc32(bytes(8)):08x}" != plain["feature"]
    assert other["payload_sha256"] == plain["payload_sha256"] and other["media_sha256"] == plain["media_sha256"]


def test_audio_codecs():
    t = np.arange(505 * 6)
    pcm = (8000 * np.sin(t / 7) * np.minimum(1, t / 300)).astype(np.int16).reshape(6, 505)
    blocks = audio.encode_adpcm(pcm)
    medium = audio.wav(blocks.tobytes(), audio.ADPCM, align=blocks.shape[1])
    tag, rate, align, data = audio.unwav(medium)
    back = audio.to_pcm(tag, align, data).reshape(6, 505)
    assert (back[:, 0] == pcm[:, 0]).all() and np.sqrt(np.mean((back.astype(float) - pcm) ** 2)) < 900
    assert [int(audio.TABLES[audio.ULAW][b]) for b in (0x00, 0x80, 0x7F, 0xFF, 0xF0, 0x70)] == [-32124, 32124, 0, 0, 120, -120]
    assert [int(audio.TABLES[audio.ALAW][b]) for b in (0x55, 0xD5, 0x2A, 0xAA, 0x00, 0x80)] == [-8, 8, -32256, 32256, -5504, 5504]
    for law in (audio.ULAW, audio.ALAW):
        table = audio.TABLES[law].astype(int)
        assert (table[:128] == -table[128:]).all() and (np.diff(np.unique(table)) > 0).all()
        assert (table[audio.CODES[law][table + 32768]] == table).all()
        every = np.arange(-32768, 32768)
        assert (np.abs(table[audio.CODES[law]] - every)[::97] == np.abs(table[:, None] - every[None, ::97]).min(axis=0)).all()
        assert audio.unwav(audio.wav(bytes(range(256)), law))[3] == bytes(range(256))
    assert audio.decode_adpcm(np.array([[0, 0, 0, 0, 0xF7]], np.uint8)).tolist() == [[0, 11, -19]]  # by hand: steps 7, then 16
    noise = np.random.default_rng(3).integers(0, 256, (4, 64)).astype(np.uint8)
    assert audio.decode_adpcm(noise).tolist() == [adpcm_by_sample(bytes(b)) for b in noise]
    tone = (3000 * np.sin(2 * np.pi * 100 * np.arange(8000) / 8000)).astype(np.int16)
    low, ends = audio.resampled(np.concatenate([tone, tone[:10]]), np.array([0, 8000, 8010]), 4)
    assert ends.tolist() == [0, 2000, 2003] and np.abs(low[50:1900] - tone[200:7600:4]).max() < 60


def test_audio_keeps_every_sample_and_its_rate(spark, docs, tmp_path):
    table = audio.TABLES[audio.ULAW]
    payload = {(i, t): audio.padded_payload(t.encode(), 576, 255) for i, t in texts_of(docs)}
    got = audio.with_pcm(audio.written_media(docs, str(tmp_path), audio.ULAW, 576, 255, "doc_id", "text")).collect()
    want = {hashlib.sha256(p).hexdigest(): table[np.frombuffer(p, np.uint8)].astype("<i2").tobytes() for p in payload.values()}
    assert {r["payload_sha256"]: bytes(r["pcm"]) for r in got} == want and {r["pcm_rate"] for r in got} == {8000}
    assert all(r["feature"].endswith(f"pcm={zlib.crc32(want[r['payload_sha256']]):08x}") for r in got)
    signals, rates = [np.arange(100, dtype=np.int16), np.zeros(8, np.int16)], [8000, 4000]
    sound, out = audio.at_rate(signals, rates, 4000)
    assert out == [4000, 4000] and [len(x) for x in sound] == [100, 16] and audio.at_rate(signals, rates, None)[1] == rates
    with pytest.raises(ValueError):
        audio.at_rate(signals, rates, 3000)


def test_mixing(docs, empty):
    kept = mixing.sampled(docs, keep=0.5)
    assert kept.columns == [*docs.columns, "mix"]
    rows = kept.collect()
    assert {r["doc_id"] for r in rows if r["mix"]["tokens"] == 0} >= {0, 1, 2} and all(0 < r["mix"]["probability"] <= 1 for r in rows)
    assert mixing.sampled(empty).count() == 0


def test_mixing_with_clashing_columns(docs):
    plain = mixing.sampled(docs, keep=0.5).select("doc_id", "text", "mix").collect()
    odd = docs.selectExpr("*", "1 AS mix", "2 AS `_MIX`", "3 AS probability", "4 AS chance", "5 AS cell", "6 AS lang_pred", "7 AS _topic", "8 AS `a.b`")
    kept = mixing.sampled(odd, keep=0.5)
    assert kept.columns == [*odd.columns, "__mix"]
    rows = kept.collect()
    assert {tuple(r)[-9:-1] for r in rows} == {(1, 2, 3, 4, 5, 6, 7, 8)}
    assert sorted([(r["doc_id"], r["text"], r["__mix"]) for r in rows], key=repr) == sorted([tuple(r) for r in plain], key=repr)


def test_topics(spark):
    texts = {"quartz quartzes quartzite": "words-0", "boulders balances and another": "words-1", "licensing": "legal", "a | b | continent": "table", "me@you": "contact", "short words only": "other", "": "other", "日本語のテキスト": "other"}
    rows = spark.createDataFrame([(t,) for t in texts], "t string").select("t", mixing.topic_of(F.col("t")).alias("topic")).collect()
    assert {r["t"]: r["topic"] for r in rows} == texts


def test_raked_weights_meet_the_marginals(spark):
    rng = np.random.default_rng(3)
    cells = spark.createDataFrame([(f"s{a}", f"l{b}", f"t{c}", float(rng.integers(5, 500))) for a in range(4) for b in range(3) for c in range(2)], "source string, lang string, topic string, tokens double")
    plan, gaps = mixing.planned(cells, 0.72, {"source": 0.5, "lang": 0.5, "topic": 0.5}, 40)
    got = plan.toPandas()
    assert (got.probability == 1).any() and (got.probability <= 1).all()  # some cells are at their cap
    for side in mixing.SIDES:
        share = got.groupby(side).tokens.sum() / got.tokens.sum()
        target = share**0.5 / (share**0.5).sum()
        assert np.abs((got.tokens * got.probability).groupby(got[side]).sum() / got.tokens.sum() / 0.72 - target).max() < 1e-6
    assert gaps.agg({"gap": "max"}).first()[0] < 1e-6
    impossible = spark.createDataFrame([("a", "x", "t", 1.0), ("b", "x", "t", 999.0)], cells.schema)
    plan, gaps = mixing.planned(impossible, 0.9, {"source": 0.0}, 20)
    by = {r["value"]: r["gap"] for r in gaps.where("side = 'source'").collect()}
    assert by["a"] > 0.4 and {r["source"]: r["probability"] for r in plan.collect()}["a"] == 1


@pytest.mark.parametrize("bits", [8, 1])
def test_chunks_round_trip(bits):
    for n in (0, 1, 7, 1000, 70000):
        ids = np.random.default_rng(n).integers(0, 1 << 31, n).astype("<u4")
        assert (planes.read_chunk(planes.write_chunk(ids, bits, 4096)) == ids).all()
    with pytest.raises(ValueError):
        planes.read_chunk(b"nothing of the kind")


def test_token_files(docs, empty):
    path = public_tokenizers.path("byte_bpe_50k.json")
    rows = planes.token_files(docs, path, 2).orderBy("start").collect()
    at = 0
    for r in rows:
        assert r["start"] == at
        at += r["n_tokens"]
    ids = [r["doc_id"] for r in rows]
    assert ids == sorted(ids, key=lambda x: (x is not None, x or 0))
    want = []
    for i, t in texts_of(docs):
        x = library("byte_bpe_50k.json").encode(t, add_special_tokens=False).ids + [2]
        want.append((i, len(x), zlib.crc32(np.array(x, "<u4").tobytes())))
    assert sorted([(r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in rows], key=repr) == sorted(want, key=repr)
    assert planes.token_files(empty, path, 2).count() == 0


def test_warc(spark):
    trap = "x\r\n\r\nWARC/1.1\r\nWARC-Type: response\r\nContent-Length: 3\r\n\r\nabc\r\n\r\nrest"
    html = [trap, None, "", "same", "same", "WARC/1.1\r\nContent-Length: 0\r\n\r\n\r\n\r\n", "é" * 5000, "tail\r\n\r\n"]
    pages = spark.createDataFrame([(k * 2, f"http://x/{k}\r\n", h, "z") for k, h in enumerate(html)], "page_id long, url string, html string, digest string")
    got = {r["page_id"]: tuple(r)[1:] for r in warc.archived(pages).collect()}
    sha = lambda t: base64.b32encode(hashlib.sha1((t or "").encode()).digest()).decode()
    first = {}
    for k, h in enumerate(html):
        first.setdefault(sha(h), k * 2)
    want = {k * 2: (len((h or "").encode()), sha(h), "response" if first[sha(h)] == k * 2 else "revisit", None if first[sha(h)] == k * 2 else first[sha(h)]) for k, h in enumerate(html)}
    assert got == want
    assert warc.archived(pages.limit(0)).count() == 0


def test_warc_keeps_pages_behind_a_long_url(spark):
    rows = [(1, "data:text/plain," + "x" * 200_000, "long"), (2, "http://x/2", "\r\nWARC/1.1\r\nWARC/1.1\r\nContent-Length: 1\r\n\r\n"), (3, "http://x/3", "c"), (4, None, "d")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)
    got = {r["page_id"]: (r["payload_bytes"], r["payload_digest"]) for r in warc.archived(pages).collect()}
    assert got == {k: (len(h), base64.b32encode(hashlib.sha1(h.encode()).digest()).decode()) for k, _, h in rows}
    head = b"WARC/1.1\r\nWARC-Target-URI: " + b"u" * 70_000 + b"\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n"
    raw = head + b"WARC/1.1\r\nContent-Length: 1\r\n\r\nz\r\n\r\n"
    assert [(a, b) for a, b, _, _ in warc.candidates(raw)] == [(0, len(head)), (len(head), len(raw))]
    assert list(warc.candidates(b"WARC/1.1\r\n" * 300_000)) == []


def test_warc_decides_every_row_by_itself(spark, tmp_path):
    rows = [(5, "same"), (5, "same"), (5, "other"), (1, "same"), (2, "other"), (2, "alone"), (None, "same"), (None, None), (9, "alone"), (1, "same"), (7, "x" * 300_000)]
    pages = spark.createDataFrame([(i, "http://x", h, "z", 1) for i, h in rows], "page_id long, url string, html string, digest string, refers_to int").repartition(3)
    sha = lambda t: base64.b32encode(hashlib.sha1((t or "").encode()).digest()).decode()
    first = {h: min((i for i, x in rows if x == h and i is not None), default=None) for _, h in rows}
    want = [(i, len(h or ""), sha(h), *(("revisit", first[h]) if i is not None and i > first[h] else ("response", None))) for i, h in rows]
    got = [tuple(r) for r in warc.archived(pages, path=str(tmp_path / "a")).collect()]
    assert sorted(got, key=repr) == sorted(want, key=repr)
    part = max((tmp_path / "a").glob("part-*"), key=lambda p: p.stat().st_size)
    part.write_bytes(part.read_bytes()[:-10])
    part.with_name(f".{part.name}.crc").unlink(missing_ok=True)
    with pytest.raises(Exception, match="breaks off"):
        warc.read_archives(spark, str(tmp_path / "a"), str(tmp_path / "again")).count()


def test_language(spark, docs, empty):
    frame = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = langid.languages(frame).join(frame.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in rows if r["held_out"]]
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in rows)
    assert np.mean([r["lang"] == r["lang_pred"] for r in held]) > 0.95
    model = langid.trained(frame)
    by = {(r["doc_id"], r["lang_pred"]): r["score"] for r in langid.predicted(docs, model).collect()}
    assert all((k, "und") in by and by[k, "und"] == 0 for k in (0, 1, 2, 12, 13))
    assert langid.predicted(empty, model).count() == 0
    assert {r["lang_pred"] for r in langid.languages(empty.union(docs.where("lang IS NULL"))).collect()} == {"und"}


def test_crf_marginals_equal_brute_force():
    rng = np.random.default_rng(0)
    model = langid.LanguageModel(["a", "b"], np.zeros((1, 2)), rng.normal(size=(2, 2)), rng.normal(size=2))
    offsets, scores = np.array([0, 3, 3, 7]), rng.normal(size=(7, 2))
    got = langid.marginals(scores, offsets, model)[0]
    for a, b in zip(offsets[:-1], offsets[1:]):
        total, want = 0.0, np.zeros((b - a, 2))
        for path in np.ndindex(*(2,) * (b - a)):
            if not path:
                continue
            w = np.exp(model.first[path[0]] + sum(scores[a + k, p] for k, p in enumerate(path)) + sum(model.transition[p, q] for p, q in zip(path, path[1:])))
            total += w
            for k, p in enumerate(path):
                want[k, p] += w
        assert np.allclose(got[a:b], want / total if total else want)


def test_code_switched_words(spark):
    frame = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = langid.trained(frame)
    en, de = (frame.where(f"lang = '{x}' AND n_chars BETWEEN 300 AND 600").orderBy("doc_id").first()["text"] for x in ("en", "de"))
    row = langid.labelled_words(spark.createDataFrame([(1, f"{en} {de}")], "doc_id long, text string"), model).first()
    half = len(langid.Words(pa.array([en])).codes)
    assert np.mean([x == "en" for x in row["labels"][:half]]) > 0.8 and np.mean([x == "de" for x in row["labels"][half:]]) > 0.8


def test_licenses(docs, empty):
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    low = str.maketrans(licenses.UPPER, licenses.LOWER)
    for r in licenses.scanned(docs).collect():
        text = next(t for i, t in texts_of(docs) if i == r["doc_id"])
        words = word.findall(text.translate(low))
        hits = [(k, label) for phrase, label in licenses.BASE.items() for k in range(len(words)) if words[k : k + len(phrase.split())] == phrase.split()]
        assert (r["n_words"], r["n_base"]) == (len(words), len(hits))
        assert (r["first_word"], r["last_word"]) == ((min(hits)[0], max(hits)[0]) if hits else (None, None))
        assert r["base_labels"] == ",".join(sorted({x for _, x in hits})) and set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(","))
        assert 0 <= r["score"] <= 1
    assert licenses.scanned(empty).count() == 0 and len(licenses.RULES) >= 200
    labels = {r["doc_id"]: r["labels"] for r in licenses.scanned(docs).collect()}
    assert "cc-by-nc" in labels[10] and "gpl" in labels[11]


NOTICES = {
    "mit": 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software")',
    "bsd": "Redistribution and use in source and binary forms, with or without\n * modification, are permitted provided that the following conditions are met:",
    "bsd-3-clause": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software",
    "apache-2.0": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.',
    "gpl": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License",
    "lgpl": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License",
    "unlicense": "This is free and unencumbered software released into the public domain.",
    "public-domain": "The author has placed this work... it was released into the public domain in 2001",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted",
    "cc-by-nc-sa": "see https://creativecommons.org/licenses/by-nc-sa/4.0/ for terms",
    "reserved": "Tous droits réservés", "zlib": "The origin of this software must not be misrepresented", "copyright": "© 2019 someone",
    "gpl-2.0-or-later": "either version 2 of the License, or (at your option) any later version.",
}


def test_license_bodies_and_notices(spark):
    rows = [(k, t) for k, t in enumerate(NOTICES.values())] + [(99, "A plain text that grants nothing and has no permission slip; the public library is in the domain of the town, later on.")]
    got = {r["doc_id"]: r["labels"].split(",") for r in licenses.scanned(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(label in got[k] for k, label in enumerate(NOTICES)) and got[99] == [""]
    assert "public-domain" not in got[list(NOTICES).index("unlicense")]  # inside the interval of a rule that ranks higher


def test_token_counts(docs, empty):
    import sentencepiece

    path = public_tokenizers.path("piece_bpe_32k.model")
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    want = sorted([(i, len(t.encode()), len(model.encode(t)), len(model.encode(t)) > 100) for i, t in texts_of(docs)], key=repr)
    assert sorted([tuple(r) for r in bpe_count.token_counts(docs, path, 100).collect()], key=repr) == want
    rng, alphabet = np.random.default_rng(5), list("abehinorstu  .\n<>é日▁0\x00")
    odd = ["".join(rng.choice(alphabet, rng.integers(0, 90))) for _ in range(1500)] + ["a" * 700, "ab" * 200, " " * 300]
    assert bpe_count.counts(pa.array(odd), bpe_count.merge_model(path)).tolist() == [len(x) for x in model.encode(odd)]
    assert bpe_count.token_counts(empty, path).count() == 0


def brute_components(rows, words, percent):
    low = str.maketrans(licenses.UPPER, licenses.LOWER)
    sets = []
    for _, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", t.translate(low))
        sets.append({tuple(w[k : k + words]) for k in range(len(w) - words + 1)} if len(w) >= words else {tuple(w)} if w else set())
    own = list(range(len(rows)))

    def root(x):
        while own[x] != x:
            x = own[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                own[max(root(a), root(b))] = min(root(a), root(b))
    return [len(s) for s in sets], [root(k) for k in range(len(rows))]


@pytest.mark.parametrize("sizes", [{}, {"block_sets": 2, "cell_rows": 20}, {"list_rows": 2, "block_sets": 3, "cell_rows": 7, "list_parts": 2}])
def test_jaccard(spark, sizes):
    rng = np.random.default_rng(2)
    base = [f"w{k}" for k in rng.integers(0, 400, 60)]
    texts = []
    for k in range(150):
        w = list(base) if k % 2 else [f"w{x}" for x in rng.integers(0, 400, int(rng.integers(0, 30)))]
        for x in rng.integers(0, max(1, len(w)), int(rng.integers(0, 3))):
            if w:
                w[x] = f"z{rng.integers(0, 50)}"
        texts.append(" ".join(w))
    rows = list(enumerate(texts + ["", "one", "ONE", "two words", "Two  words"]))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(5), 3, 90, **sizes).collect()}
    n, roots = brute_components(rows, 3, 90)
    assert got == {i: (n[i], roots[i]) for i, _ in rows}


@pytest.mark.parametrize("sizes", [{}, {"block_sets": 2}])
def test_jaccard_finds_every_link(spark, sizes):
    rng = np.random.default_rng(4)
    base, texts = [f"w{k}" for k in range(40)], ["", "one", "ONE", "other words here"]
    for k in range(12):
        w = list(base)
        w[int(rng.integers(0, 40))] = f"z{k}"
        texts += [" ".join(w)] * (1 + k % 2)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    sets = [{tuple(w[k : k + 3]) for k in range(max(1, len(w) - 2))} if (w := t.lower().split()) else set() for t in texts]
    like = lambda a, b: bool(sets[a]) and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])
    want = {(a, b) for a in range(len(texts)) for b in range(len(texts)) if a != b and like(a, b)}
    assert len({frozenset(sets[x]) for p in want for x in p}) > 3
    got = {r["doc_id"]: r["n_links"] for r in jaccard.near_duplicates(docs, 3, 80, **sizes).collect()}
    assert got == {a: sum(x == a for x, _ in want) for a in range(len(texts))}
    members, links = jaccard.set_links(docs, 3, 80, **sizes)
    node = {r["doc_id"]: r["node"] for r in members.collect()}
    pairs = [frozenset((r["u"], r["v"])) for r in links.collect()]
    assert len(pairs) == len(set(pairs)) and set(pairs) == {frozenset((node[a], node[b])) for a, b in want if node[a] != node[b]}


def test_jaccard_awkward_rows(docs, empty):
    rows = jaccard.near_duplicates(docs, 3, 80).collect()
    assert len(rows) == docs.count()
    by = {r["doc_id"]: r for r in rows}
    assert by[0]["n_shingles"] == 0 and by[0]["component_id"] == 0 and by[6]["component_id"] == 5
    kept = jaccard.first_of_each(docs, 3, 80)
    assert kept.columns == docs.columns or set(kept.columns) == set(docs.columns)
    ids = [r["doc_id"] for r in kept.collect()]
    assert 6 not in ids and ids.count(5) == 1 and None in ids
    assert jaccard.near_duplicates(empty).count() == 0 and jaccard.first_of_each(empty).count() == 0


def test_search(spark, docs, empty):
    pages = [(k, t) for k, t in texts_of(docs) if k is not None and not (k == 5 and False)]
    frame = spark.createDataFrame(pages, "doc_id long, text string").repartition(4)
    low, word = str.maketrans(licenses.UPPER, licenses.LOWER), re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    bags = [word.findall(t.translate(low)) for _, t in pages]
    mean, n = sum(map(len, bags)) / len(bags), len(bags)
    df = {}
    for b in bags:
        for w in set(b):
            df[w] = df.get(w, 0) + 1
    query = "the cat sat with one word9"
    want = []
    for (i, _), b in zip(pages, bags):
        s = sum(np.log(1 + (n - df[w] + 0.5) / (df[w] + 0.5)) * b.count(w) * 2.2 / (b.count(w) + 1.2 * (0.25 + 0.75 * len(b) / mean)) for w in query.split() if w in df)
        if s > 0:
            want.append((-round(s, 6), i))
    got = bm25.search(frame, spark.createDataFrame([(7, query), (8, None), (9, "zzz")], "doc_id long, text string"), 4).orderBy("rank").collect()
    assert [(r["query_id"], r["rank"], r["doc_id"], r["score"]) for r in got] == [(7, k + 1, i, pytest.approx(-s)) for k, (s, i) in enumerate(sorted(want)[:4])]
    assert bm25.search(empty, frame).count() == 0 and bm25.search(frame, empty).count() == 0


def test_list_candidates_across_batches():
    """Short lists give their close pairs, long ones their rows, however batches cut them; a repeated node counts once."""
    sizes, rows = {1: 3, 2: 250, 3: 1, 4: 47, 5: 66}, []
    for gram, size in sizes.items():
        for key in range(1000 * gram, 1000 * gram + size):
            rows += [(gram, key, 50 << 32)] * (3 if key % 2 else 1)
    table = pa.table({name: pa.array(column, pa.int64()) for name, column in zip(("gram", "key", "spot"), zip(*rows))})
    want = {(a, b) for gram in (1, 4) for a in range(1000 * gram, 1000 * gram + sizes[gram]) for b in range(a + 1, 1000 * gram + sizes[gram])}
    for step in (1, 2, 7, 90, len(rows)):
        got = [r for b in jaccard.list_candidates(iter(table.to_batches(max_chunksize=step)), 90) for r in b.to_pylist()]
        assert {(r["u"], r["v"]) for r in got if r["gram"] is None} == want, step
        assert {(r["gram"], r["u"]) for r in got if r["gram"] is not None} == {(g, k) for g, k, _ in rows if g in (2, 5)}, step


def test_filters_never_lose_a_link():
    """Cells and the suffix filter keep every pair that links, and with spanning every component, over all sizes of shapes."""
    rng = np.random.default_rng(9)
    for size in (3, 20, 300, 3000, 30000):
        base = np.unique(rng.integers(0, 1 << 63, size, dtype=np.uint64))
        sets = [np.unique(np.concatenate((rng.choice(base, int(len(base) * x), replace=False), rng.integers(0, 1 << 63, int(size * y), dtype=np.uint64)))) for x, y in rng.uniform((0.75, 0), (1, 0.2), (12, 2))]
        sets += [np.zeros(300, np.uint64) + (np.uint64(k) << np.uint64(40)) + np.arange(300, dtype=np.uint64) for k in (0, 0, 1)]  # one class has them all
        spot = np.array([len(s) << 32 for s in sets])
        true = {(a, b) for a in range(len(sets)) for b in range(a) if 5 * len(np.intersect1d(sets[a], sets[b])) >= 4 * len(np.union1d(sets[a], sets[b]))}
        for side in (None, rng.random(len(sets)) < 0.5):
            want = {p for p in true if side is None or side[p[0]] != side[p[1]]}
            found = lambda spanning: {(max(i, k), min(i, k)) for i, near in jaccard.cell_pairs(spot, [jaccard.shape(s) for s in sets], side, np.arange(len(sets)), 80, spanning) for k in near.tolist()}  # noqa: E731,B023
            assert want <= found(False) and (size < 20 or len(found(False)) < len(sets) * (len(sets) - 1) / 2)
            own = {k: k for k in range(len(sets))}

            def root(x):
                while own[x] != x:  # noqa: B023
                    x = own[x]  # noqa: B023
                return x

            for a, b in found(True):
                own[root(a)] = root(b)
            assert all(root(a) == root(b) for a, b in want)


def test_first_of_each_decides_every_row_by_itself(spark):
    a, near, other = "one two three four five six seven eight nine ten", "one two three four five six seven eight nine ten eleven", "quite another text of some words"
    rows = [(1, a, "x"), (2, a, "x"), (2, other, "x"), (3, near, "x"), (3, a, "y"), (None, near, "x"), (None, "only here without an id", "x"), (None, "only here without an id", "x"), (4, None, "x"), (4, None, "x"), (5, "...  ", "x"), (7, other + " z", "x"), (7, "seven " * 40, "x"), (7, "seven " * 41, "x"), (1, a, "z")]
    docs = spark.createDataFrame([(*r, k % 2) for k, r in enumerate(rows)], "doc_id long, text string, node string, _row int").repartition(4)
    kept = jaccard.first_of_each(docs, 3, 80)
    assert kept.columns == docs.columns
    got = sorted([(r["doc_id"], r["text"]) for r in kept.collect()], key=repr)
    seven = [t for i, t, _ in rows if i == 7 and t.startswith("seven")]
    assert [x for x in got if x[0] == 7 and x[1].startswith("seven")] in [[(7, t)] for t in seven]
    got = [x for x in got if not (x[0] == 7 and x[1].startswith("seven"))]
    assert got == sorted([(1, a), (2, other), (None, "only here without an id"), (4, None), (4, None), (5, "...  ")] + ([(7, other + " z")] if brute_components([(0, other), (1, other + " z")], 3, 80)[1] == [0, 1] else []), key=repr)
