"""The ten operators against brute force, exact round trips, or planted rows, with odd inputs."""

from __future__ import annotations

import hashlib
import itertools
import random
import re
import struct
import time
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from eventpulse.llm import bpe, embed_dedup, media, minhash, mixing, pii, quality, token_counts, toxicity, url_filters
from eventpulse.llm.words import shingle_sets
from tests.oracle import connect, rows

BYTE, WORD = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double, component_id long, kept boolean, taken long, size long"
LONG = "".join(f"w{i % 977} " for i in range(30_000))
TEXTS = [None, "", " \n\t", "one", "one two three four", "one two three four five", "ONE two three four FIVE", "one two three four five", LONG, LONG + "tail", "é" * 70, "a<|endoftext|>b", "x" * 40_000, "mail me: jo.doe@mail.example.com or 10.0.0.1"]


def odd_docs(spark):
    """Odd texts, with repeated rows, null ids and columns named as results are."""
    data = [(i, t, "en", None if i % 4 == 0 else f"s{i % 3}", 0, 0.5, -1, False, -1, -1) for i, t in enumerate(TEXTS)]
    data += [data[5], data[5], (None, "one two three four five", "en", "s1", 0, 0.5, -1, False, -1, -1)]
    return spark.createDataFrame(data, DOCS)


def nothing(spark):
    return spark.createDataFrame([], DOCS)


def labels(spark, docs):
    return spark.createDataFrame([(i, i % 2, i % 2) for i in range(5)] + [(None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")


# --- 1 PII -------------------------------------------------------------------------------------


def pii_brute(t):
    out = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) <= 255 for p in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        n = re.sub("[^0-9]", "", m.group())
        total = sum(int(c) if i % 2 == 0 else sum(map(int, str(2 * int(c)))) for i, c in enumerate(n[::-1]))
        out += [("card", *m.span())] if 14 <= len(n) <= 19 and total % 10 == 0 else []
    out += [("phone", *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 10 <= len(re.sub("[^0-9]", "", m.group())) <= 15]
    return sorted(out)


def test_pii_base_equals_plain_patterns():
    rnd = random.Random(4)
    texts = ["".join(rnd.choice("aB1230459..@@--+ ()%_ é\n") for _ in range(rnd.randint(0, 70))) for _ in range(8000)]
    texts += ["".join(rnd.choice("0123456789012345 -") for _ in range(30)) for _ in range(2000)] + ["4111 1111-1111 1111", "a@b.c@d.e", "a@b@c.d", "1.2.3.4.5.6.7.8", "999.1.1.1 1.1.1.1"]
    for t in texts:
        assert sorted(x[:3] for x in pii.base_matches(t) if x[3]) == pii_brute(t), t


def test_pii_query_rows(spark):
    df = odd_docs(spark)
    got = {r["doc_id"]: r for r in pii.detect(df).collect()}
    assert pii.detect(df).count() == df.count() and pii.detect(nothing(spark)).count() == 0
    assert got[13]["spans"] == "email:9:32,ip:36:44" and got[13]["n_email"] == 1
    assert got[0]["base_sha256"] == hashlib.sha256(b"").hexdigest() == got[1]["base_sha256"]


def test_pii_model_adds_and_masks():
    seen = [((1, 0, 0, 1, 0, 1), pii.features('x token = "a1b2c3d4e5f6a7b8"', "secret", 11, 27, True), 50), ((-1, -1, 0, 0, 0, 0), pii.features("see 12345678901234", "card", 4, 18, False), 80)]
    model = pii.train(seen)
    text = 'x token = "a1b2c3d4e5f6a7b8" and 12345678901234'
    base, every = pii.find(text, model)
    assert base == [] and every == [("secret", 11, 27)]
    assert pii.masked(text, every) == 'x token = "[SECRET]" and 12345678901234'
    assert model["reliability"]["checksum"] > 0.5


def test_pii_linear_on_long_runs():
    model = pii.train([])
    for t in ("1" * 300_000, "1." * 100_000, "a@" * 100_000, "+1" + " " * 200_000):
        pii.find(t, model)


def test_pii_sweep_over_many_spans_is_linear():
    text = "a@b.cd 999.1.1.1 " * 240_000  # 4 MB: every second span is taken, the others fail
    began = time.perf_counter()
    base, free = pii.candidates(text)
    assert time.perf_counter() - began < 10 and len(base) == len(free) == 240_000


def test_pii_candidates_are_apart():
    rnd = random.Random(12)
    parts = ["a@b.cd", "999.1.1.1", "10.1.2.3", "+1 (555) 010-9999", "555-010-9999", "078-05-1120", "token=", "abcdef123456", "Mr. ", "Anna ", "Smith", " ", "GB29 NWBK 6016 1331 9268 19", "jo (at) x (dot) org", "4111 1111 1111 1111"]
    for _ in range(3000):
        t = "".join(rnd.choice(parts) for _ in range(rnd.randint(1, 14)))
        base, free = pii.candidates(t)
        kept = []
        for kind, a, z, _ in free:
            assert not any(a < y and x < z for _, x, y in [*base, *kept])
            kept.append((kind, a, z))


def test_pii_redaction_keeps_columns(spark):
    df = odd_docs(spark)
    out = pii.redact(df)
    assert out.schema == df.schema and out.count() == df.count()
    assert out.where("doc_id = 13").first()["text"] == "mail me: [EMAIL] or [IP]"
    assert out.where("doc_id = 0").first()["text"] is None


# --- 2 BPE, 5 token counts ---------------------------------------------------------------------

ALPHABET = "abcdefghi    \n\t\r\x0b\x1c\x85\xa0 'sStTllvereéΣ日本語العربيةдав½²٣<|endoftext|>🙂==--..!!0123456789\u200d\u0301"


@pytest.fixture(scope="module")
def noise():
    rnd = random.Random(8)
    return ["".join(rnd.choice(ALPHABET) for _ in range(rnd.randint(0, 80))) for _ in range(1500)] + [t or "" for t in TEXTS] + ["a<|endoftext|> <|endoftext|>b", "=" * 500, "aaaa" * 300, "\n\n \n x"]


def test_bpe_equals_library(noise):
    own, lib = bpe.ByteBpe(BYTE), Tokenizer.from_file(BYTE)
    packed = own.encode_batch(noise)
    for t, ids, e in zip(noise, packed, lib.encode_batch(noise, add_special_tokens=False), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == e.ids, t
        assert own.decode(ids) == lib.decode(e.ids, skip_special_tokens=False)


def test_bpe_shares_prefixes():
    own = bpe.ByteBpe(BYTE)
    words = [b"stream", b"streams", b"streaming", b"street", b"a"]
    assert [w for w, _ in own.encode_words(words)] == sorted(words)


def test_bpe_rows(spark):
    df = odd_docs(spark)
    got = {r["doc_id"]: r for r in bpe.digests(df, BYTE).collect()}
    assert got[0]["n_tokens"] == got[1]["n_tokens"] == 0 and bpe.digests(df, BYTE).count() == df.count()
    assert got[8]["decoded_sha256"] == hashlib.sha256(LONG.encode()).hexdigest()
    back = bpe.decode(bpe.encode(df, BYTE), BYTE)
    assert {r["doc_id"]: r["text"] for r in back.collect()} == {r["doc_id"]: r["text"] or "" for r in df.collect()}
    assert bpe.digests(nothing(spark), BYTE).count() == 0


PIECE = public_tokenizers.path("piece_bpe_32k.model")


def library_counts(path, texts):
    if path == PIECE:
        import sentencepiece

        return [len(ids) for ids in sentencepiece.SentencePieceProcessor(model_file=path).encode(texts)]
    return [len(e) for e in Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)]


@pytest.mark.parametrize("path", [WORD, BYTE, PIECE])
def test_token_counts_equal_library(noise, path):
    enc = token_counts.encoder(path)
    assert enc.proven and isinstance(enc, token_counts.WordEncoder) == (path == WORD)
    rnd = random.Random(6)
    texts = [t for t in noise if len(t) < 50_000] + [" ".join("".join(rnd.choice("abeé日x.1Σ'") for _ in range(rnd.randint(1, 9))) for _ in range(400)) for _ in range(20)]
    want = library_counts(path, texts)
    assert [c.n for c in token_counts.count_texts(enc, texts)] == want
    for chunk, overlap, agree in ((7, 3, 1), (40, 10, 2), (200, 30, 4)):
        found = [token_counts.count_long(enc, t, chunk, overlap, agree) for t in texts]
        assert [c.n for c in found] == want
        assert sum(c.widened for c in found) > 0 and sum(c.splices for c in found) > 0


@pytest.mark.parametrize("path", [WORD, BYTE, PIECE])
def test_token_counts_widen_where_the_first_overlap_fails(path):
    enc = token_counts.encoder(path)
    text = "plain words, and a run: " * 200 + "ab1" * 1500 + " then words again;  two blanks" * 300
    got = token_counts.count_long(enc, text, 2000, 64)
    assert [got.n] == library_counts(path, [text]) and got.widened > 0 and got.splices > 0


def test_token_offsets_equal_library(noise):
    enc, lib = token_counts.encoder(WORD), Tokenizer.from_file(WORD)
    for t, e in zip(noise, enc.encode(noise), strict=True):
        want = lib.encode(t, add_special_tokens=False)
        assert e.ids.tolist() == want.ids
        if t.isascii():
            assert e.starts.tolist() == [a for a, _ in want.offsets]


def test_unproven_tokenizers_are_never_spliced():
    import json

    with open(WORD, encoding="utf-8") as f:
        spec = json.load(f)
    assert token_counts.blank_rule(spec) == "dropped"
    assert token_counts.blank_rule(spec | {"pre_tokenizer": {"type": "Whitespace"}}) is None
    assert token_counts.blank_rule(spec | {"added_tokens": [spec["added_tokens"][0] | {"content": "a b"}]}) is None
    enc = token_counts.LibraryEncoder(Tokenizer.from_file(BYTE), False)
    assert token_counts.count_long(enc, LONG[:20_000], 2000, 64) == (*library_counts(BYTE, [LONG[:20_000]]), 0, 4)


def test_token_count_rows(spark):
    df = odd_docs(spark)
    got = {r["doc_id"]: r for r in token_counts.counts(df, WORD).collect()}
    assert got[8]["over_limit"] and not got[3]["over_limit"] and got[10]["n_bytes"] == 140
    assert token_counts.counts(df, WORD).count() == df.count() and token_counts.counts(nothing(spark), WORD).count() == 0


# --- 3 media -----------------------------------------------------------------------------------


def test_media_round_trip(spark):
    rng = np.random.default_rng(3)
    for n in (64, 128, 4096, 4160, 64 * 200):
        payload = rng.integers(0, 256, n, dtype=np.uint8).tobytes()
        frames, back, fps = media.read_avi(media.write_avi(payload))
        assert back == payload and fps == media.FPS and len(frames) == -(-n // (64 * min(n // 64, 64)))
    df = odd_docs(spark)
    got = {r["doc_id"]: r for r in media.digests(df).collect()}
    raw = LONG.encode() + b"\0" * (-len(LONG.encode()) % 64)
    assert (got[8]["payload_sha256"], got[8]["tail_crc32"]) == (hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-64:]))
    assert got[0]["payload_bytes"] == 64 and got[0]["media_sha256"] == got[1]["media_sha256"]
    assert media.clips(media.store(df)).where("doc_id = 8").count() >= 1 and media.digests(nothing(spark)).count() == 0


def packed(codes):
    """(length, code) pairs as an entropy-coded segment."""
    bits = "".join(f"{c:0{n}b}" for n, c in codes if n)
    bits += "1" * (-len(bits) % 8)
    return int(bits, 2).to_bytes(len(bits) // 8, "big").replace(b"\xff", b"\xff\x00")


def category(d):
    s = abs(d).bit_length()
    return s, (s, d if d >= 0 else d + (1 << s) - 1)


def foreign_lossless(x, predictor, restart_rows=0):
    """A lossless frame whose table has five-bit codes, for any predictor."""
    rows, cols = x.shape
    x = x.astype(int)
    segments, codes = [], []
    top = 0
    for r in range(rows):
        if restart_rows and r and r % restart_rows == 0:
            segments.append(packed(codes))
            codes, top = [], r
        for c in range(cols):
            if r == top:
                p = x[r, c - 1] if c else 128
            elif not c:
                p = x[r - 1, 0]
            else:
                a, b, k = x[r, c - 1], x[r - 1, c], x[r - 1, c - 1]
                p = {1: a, 2: b, 3: k, 4: a + b - k, 5: a + ((b - k) >> 1), 6: b + ((a - k) >> 1), 7: (a + b) >> 1}[predictor]
            s, extra = category(int(x[r, c] - p))
            codes += [(5, s), extra]
    segments.append(packed(codes))
    table = bytes([0, 0, 0, 0, 0, 17, *[0] * 11, *range(17)])
    out = media.SOI + media._segment(0xC3, struct.pack(">BHHB", 8, rows, cols, 1) + b"\x01\x11\x00") + media._segment(0xC4, table)
    out += media._segment(0xDD, struct.pack(">H", restart_rows * cols)) if restart_rows else b""
    scan = segments[0] + b"".join(b"\xff" + bytes([0xD0 + i % 8]) + s for i, s in enumerate(segments[1:]))
    return out + media._segment(0xDA, bytes([1, 1, 0, predictor, 0, 0])) + scan + media.EOI


@pytest.mark.parametrize("predictor", range(1, 8))
def test_media_reads_other_lossless_frames(predictor):
    x = np.random.default_rng(predictor).integers(0, 256, (9, 13)).astype(np.uint8)
    assert (media.decode_jpeg(foreign_lossless(x, predictor)) == x).all()
    assert (media.decode_jpeg(foreign_lossless(x, predictor, 3)) == x).all()


def test_media_reads_baseline_frames():
    rows, cols = 20, 27
    y, x = np.mgrid[:rows, :cols]
    picture = np.clip(128 + 60 * np.sin(x / 5) + 50 * np.cos(y / 4), 0, 255).round()
    full = np.pad(picture, ((0, -rows % 8), (0, -cols % 8)), mode="edge") - 128
    c = np.array([[np.cos((2 * a + 1) * u * np.pi / 16) * (np.sqrt(1 / 8) if u == 0 else 0.5) for u in range(8)] for a in range(8)])
    zigzag = [0, 1, 8, 16, 9, 2, 3, 10, 17, 24, 32, 25, 18, 11, 4, 5, 12, 19, 26, 33, 40, 48, 41, 34, 27, 20, 13, 6, 7, 14, 21, 28, 35, 42, 49, 56, 57, 50, 43, 36, 29, 22, 15, 23, 30, 37, 44, 51, 58, 59, 52, 45, 38, 31, 39, 46, 53, 60, 61, 54, 47, 55, 62, 63]
    codes, last = [], 0
    symbols = [16 * run + size for run in range(16) for size in range(11) if size or run in (0, 15)]
    for top in range(0, full.shape[0], 8):
        for left in range(0, full.shape[1], 8):
            z = np.rint((c.T @ full[top : top + 8, left : left + 8] @ c).ravel()[zigzag]).astype(int)
            s, extra = category(int(z[0]) - last)
            codes += [(4, s), extra]
            last, run = int(z[0]), 0
            for v in z[1:].tolist():
                if not v:
                    run += 1
                    continue
                while run > 15:
                    codes.append((8, symbols.index(0xF0)))
                    run -= 16
                s, extra = category(v)
                codes += [(8, symbols.index(16 * run + s)), extra]
                run = 0
            codes += [(8, 0)] if run else []
    dht = bytes([0, 0, 0, 0, 12, *[0] * 12, *range(12)]) + bytes([16, *[0] * 7, len(symbols), *[0] * 8, *symbols])
    data = media.SOI + media._segment(0xDB, bytes([0, *[1] * 64])) + media._segment(0xC0, struct.pack(">BHHB", 8, rows, cols, 1) + b"\x01\x11\x00")
    data += media._segment(0xC4, dht) + media._segment(0xDA, bytes([1, 1, 0, 0, 63, 0])) + packed(codes) + media.EOI
    assert np.abs(media.decode_jpeg(data).astype(int) - picture).max() <= 1


def test_shots_are_cut_where_the_picture_changes():
    dark, light = np.full((6, 64, 64), 20, np.uint8), np.full((5, 64, 64), 220, np.uint8)
    assert media.shots(np.concatenate([dark, light])) == [(0, 6), (6, 11)]
    assert media.shots(dark) == [(0, 6)]


# --- 4 embeddings ------------------------------------------------------------------------------


def test_embeddings_against_brute_force(spark):
    rng = np.random.default_rng(1)
    base = rng.standard_normal((300, 16))
    near = base[:60] + 0.1 * rng.standard_normal((60, 16))
    star = base[7] + 0.05 * rng.standard_normal((80, 16))
    x = np.concatenate([base, near, star, base[:5], 3 * base[:2]])
    data = [(i, v.tolist(), 0) for i, v in enumerate(x)]
    data += [(1000, None, 0), (1001, [0.0] * 16, 0), (1002, [float("nan")] + [1.0] * 15, 0), (1003, [None] + [1.0] * 15, 0), (1004, [1.0] * 3, 0), (1005, [float("inf")] + [1.0] * 15, 0), (None, [1.0] * 16, 0)]
    df = spark.createDataFrame(data, "vec_id long, embedding array<double>, n_links int")
    got = {r["vec_id"]: r for r in embed_dedup.near_duplicates(df).collect()}
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    hit = u @ u.T >= 0.9
    n = hit.sum(axis=1) - 1
    assert sum(got[i]["n_links"] for i in range(len(x))) >= 0.97 * n.sum()
    assert all(got[i]["n_links"] <= n[i] for i in range(len(x)))
    assert all(got[i]["component_id"] == 7 for i in range(360, 440))
    assert all(got[k]["n_links"] == 0 and got[k]["kept"] for k in (1000, 1001, 1002, 1003, 1004, 1005, None))
    assert embed_dedup.near_duplicates(df.limit(0)).count() == 0


def brute_links(x):
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    return (u @ u.T >= 0.9).sum(axis=1) - 1


def test_embeddings_of_several_lengths(spark):
    rng = np.random.default_rng(3)
    rows = [(0, [2.0]), (1, [3.0]), (2, [-1.0]), (3, [1.0, 2.0, 3.0]), (4, [1.0, 2.0, 3.0]), (5, [2.0, 4.0, 6.1]), (6, []), (7, [0.0]), (8, [1.0, 0.0])]
    parts, at = [rows], 100
    for d in (8, 24):  # longer than one block: codebooks of their own
        base = rng.standard_normal((1400, d))
        x = np.concatenate([base, base[:200] + 0.05 * rng.standard_normal((200, d))])
        parts.append([(at + i, v.tolist()) for i, v in enumerate(x)])
        at += len(x)
    df = spark.createDataFrame([r for p in parts for r in p], "vec_id long, embedding array<double>")
    got = {r["vec_id"]: r for r in embed_dedup.near_duplicates(df).collect()}
    assert [got[i]["n_links"] for i in range(9)] == [1, 1, 0, 2, 2, 2, 0, 0, 0]
    assert [got[i]["component_id"] for i in range(9)] == [0, 0, 2, 3, 3, 3, 6, 7, 8]
    for p in parts[1:]:
        want, own = brute_links(np.array([v for _, v in p])), np.array([got[i]["n_links"] for i, _ in p])
        assert (own <= want).all() and own.sum() >= 0.97 * want.sum() > 0


def test_embeddings_recall_on_a_table_and_at_the_threshold(spark):
    df = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    rows = df.select("vec_id", "embedding").toPandas()
    x = np.array(rows["embedding"].tolist(), dtype=np.float64)
    got = dict(embed_dedup.near_duplicates(df).select("vec_id", "n_links").toPandas().to_numpy().tolist())
    assert sum(got.values()) >= 0.98 * brute_links(x).sum()
    u = embed_dedup.unit(x)[:1500]
    away = np.random.default_rng(4).standard_normal(u.shape)
    away -= (away * u).sum(axis=1, keepdims=True) * u
    edge = 0.9001 * u + np.sqrt(1 - 0.9001**2) * away / np.linalg.norm(away, axis=1, keepdims=True)
    pairs = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(np.concatenate([u, edge]))], "vec_id long, embedding array<double>")
    found = embed_dedup.near_duplicates(pairs).toPandas()
    want = brute_links(np.concatenate([u, edge]))
    assert found["n_links"].sum() >= 0.95 * want.sum()


def test_a_vec_id_with_two_vectors_is_one_node(spark):
    rows = [(1, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [1.0, 0.1]), (3, [0.1, 1.0]), (4, [-1.0, -1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = sorted(map(tuple, embed_dedup.near_duplicates(df).select("vec_id", "component_id").collect()))
    assert got == [(1, 1), (1, 1), (2, 1), (3, 1), (4, 4)]


def test_grid_order_is_by_distance():
    rng = np.random.default_rng(2)
    x = embed_dedup.unit(rng.standard_normal((500, 8)))
    g = embed_dedup.Grid(x, 40_000)
    a, b = embed_dedup._distances(x[:, :4], g.first), embed_dedup._distances(x[:, 4:], g.second)
    full = (a[:, :, None] + b[:, None, :]).reshape(len(x), -1)
    for v in (1, 3, g.cells):
        assert np.allclose(np.take_along_axis(full, g.ordered(x, v)[0], 1), np.sort(full, axis=1)[:, :v])


def test_cells_are_left_out_only_if_they_hold_no_link():
    rng = np.random.default_rng(5)
    x = embed_dedup.unit(np.concatenate([c + 0.2 * rng.standard_normal((60, 8)) for c in 2 * rng.standard_normal((40, 8))]))
    g = embed_dedup.Grid(x, 100_000)
    cells, near = g.ordered(x, g.cells)
    kept = [set(c[n].tolist()) for c, n in zip(cells, near, strict=True)]
    for i, j in zip(*np.nonzero(x @ x.T >= 0.9), strict=True):
        assert cells[j, 0] in kept[i]
    assert sum(map(len, kept)) < 0.5 * near.size


def test_calibration_ranks_as_the_order_does():
    rng = np.random.default_rng(6)
    x, y = (embed_dedup.unit(rng.standard_normal((200, 8))) for _ in range(2))
    g = embed_dedup.Grid(x, 40_000)
    order, own = g.ordered(x, g.cells)[0], g.ordered(y, 1)[0]
    assert (g._rank(x, y) == (order == own).argmax(axis=1)).all()


# --- 6 toxicity, 9 quality ---------------------------------------------------------------------


def brute_marginals(unary, trans):
    n = len(unary)
    total, on = 0.0, np.zeros(n)
    for states in itertools.product((0, 1), repeat=n):
        s = sum(u for u, z in zip(unary, states, strict=True) if z) + sum(trans[a, b] for a, b in itertools.pairwise(states))
        total += np.exp(s)
        on += np.exp(s) * np.array(states)
    return on / total, np.log(total)


def test_marginals_equal_enumeration_across_rows():
    rng = np.random.default_rng(0)
    trans = 2 * rng.standard_normal((2, 2))
    weights = 2 * rng.standard_normal(5)
    docs = [rng.integers(0, 5, n) for n in (1, 0, 9, 2, 12, 3, 4, 0)]
    ids, first = np.concatenate(docs), np.concatenate([[0], np.cumsum([len(d) for d in docs])])
    for window in (2, 3, 4, 64):  # rows of a text pass their messages on
        m, pairs = toxicity.Chains(ids, first, window).marginals(weights, trans)
        want = [brute_marginals(weights[d], trans)[0] for d in docs if len(d)]
        assert np.allclose(m, np.concatenate(want))
        assert np.isclose(pairs.sum(), sum(len(d) - 1 for d in docs if len(d)))
        assert np.isclose(pairs[:, 1].sum(), sum(w[1:].sum() for w in want))


def test_long_chain_has_no_cuts():
    rng = np.random.default_rng(1)
    ids = rng.integers(0, 40, 100_000)
    weights, trans = 3 * rng.standard_normal(40), np.array([[2.0, -2.0], [-2.0, 2.0]])
    first = np.array([0, len(ids)])
    assert np.allclose(toxicity.marginals(ids, first, weights, trans, 64), toxicity.marginals(ids, first, weights, trans, len(ids)), atol=1e-9)


LABELLED = "/root/testdata/sf0.01"


def held_out_share(op, target, spark, sf):
    """Share of right predictions and rows, over the labelled rows that no fitting reads."""
    docs, lab = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    got = op(docs, lab).join(lab, "doc_id").toPandas()
    assert all(bool(h) == (zlib.crc32(str(i).encode()) % 5 == 0) for i, h in zip(got["doc_id"], got["held_out"], strict=True))
    fold = got[got["held_out"]]
    return (fold["predicted"] == fold[target]).mean(), len(fold)


def test_toxicity_held_out(spark):
    share, n = held_out_share(toxicity.classify, "toxic", spark, LABELLED)
    assert share > 0.95 and n > 50


def test_toxic_spans():
    rnd = random.Random(0)
    plain = [" ".join("".join(rnd.choice("bdfgklmaeiou") for _ in range(9)) for _ in range(30)) for _ in range(60)]
    bad = [p.replace(" ", " idiot ", 1) for p in plain[:30]]
    t = toxicity.Tagger(plain + bad, [0] * 60 + [1] * 30)
    assert t.score(["you Idiot! yes"])[0] > 0.5 > t.score(["a fine river"])[0]
    rare = toxicity.Tagger(plain * 8 + bad, [0] * 480 + [1] * 30)
    assert "idiot" in rare.lexicon
    assert [("you IDIOT! İ idiot")[a:z] for a, z in t.spans("you IDIOT! İ idiot")] == ["IDIOT", "idiot"]


@pytest.mark.parametrize("op", [toxicity.classify, quality.classify])
def test_classifiers_on_odd_rows(spark, op):
    df = odd_docs(spark)
    out = op(df, labels(spark, df)).toPandas()
    assert len(out) == df.count() and out["score"].between(0, 1).all()
    assert op(nothing(spark), labels(spark, df)).count() == 0
    assert op(df, labels(spark, df).limit(0)).count() == df.count()


def test_toxic_rows_go_and_others_stay(spark):
    docs, lab = spark.read.parquet(f"{LABELLED}/documents.parquet"), spark.read.parquet(f"{LABELLED}/labels.parquet")
    kept = toxicity.keep_clean(docs, lab)
    bad = {r["doc_id"] for r in toxicity.classify(docs, lab).where("predicted = 1").collect()}
    assert kept.schema == docs.schema and {r["doc_id"] for r in kept.collect()} == {r["doc_id"] for r in docs.collect()} - bad


def test_quality_held_out_and_compiled_rules(spark, small):
    docs, lab = spark.read.parquet(f"{small}/documents.parquet"), spark.read.parquet(f"{small}/labels.parquet")
    model = quality.fit(docs, lab)
    got = quality.classify(docs, lab, model=model).join(lab, "doc_id").toPandas()
    assert (got["predicted"] == got["quality"]).mean() > 0.9  # a whole table, for the columns; the held-out fold is below
    df, names = quality.statistics(docs)
    table = df.select("doc_id", *names, model.column().alias("s")).toPandas()
    want = 1 / (1 + np.exp(-(quality.holds(model.rules, table[names].to_numpy()) @ model.weights + model.intercept)))
    assert np.allclose(table["s"], want, atol=1e-6)


def test_quality_held_out(spark):
    share, n = held_out_share(quality.classify, "quality", spark, LABELLED)
    assert share > 0.95 and n > 50


def test_lasso_meets_its_optimality_conditions():
    rng = np.random.default_rng(2)
    z = rng.integers(0, 2, (400, 30)).astype(float)
    y = (rng.random(400) < 1 / (1 + np.exp(-(2 * z[:, 0] - 3 * z[:, 1] + 0.5)))).astype(float)
    for penalty in (0.02, 0.003):
        b, w = quality.lasso(z, y, penalty, 20_000)
        r = 1 / (1 + np.exp(-(z @ w + b))) - y
        slope = z.T @ r / len(y)
        on = w != 0
        assert abs(r.mean()) < 1e-5 and 0 < on.sum() < 30
        assert np.allclose(slope[on], -penalty * np.sign(w[on]), atol=1e-5) and (np.abs(slope[~on]) <= penalty + 1e-5).all()


def test_a_tree_takes_the_best_cut():
    rng = np.random.default_rng(3)
    x = rng.random((300, 3))
    y = ((x[:, 1] > 0.6) ^ (rng.random(300) < 0.1)).astype(float)
    g, h = y - 0.5, np.full(300, 0.25)
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, 34)[1:-1])) for f in range(3)]
    rules, out = set(), np.zeros(300)
    quality._tree(x, g, h, cuts, 1, np.arange(300), (), rules, out)

    def gain(f, cut):
        up = x[:, f] > cut
        if min(up.sum(), (~up).sum()) < quality.LEAF:
            return -1
        return sum(g[s].sum() ** 2 / (h[s].sum() + 1) for s in (up, ~up))

    best = max(((gain(f, c), f, c) for f in range(3) for c in cuts[f]))
    assert rules == {((best[1], False, best[2]),), ((best[1], True, best[2]),)}
    for up in (False, True):
        side = (x[:, best[1]] > best[2]) == up
        assert np.allclose(out[side], g[side].sum() / (h[side].sum() + 1))


# --- 7 URLs ------------------------------------------------------------------------------------

RULES = [("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"), ("allow", "a.b.example.org/es/x")]
URLS = [None, "", "no scheme", "http://ORG/", "http://org", "https://example.org/es/", "https://www.Example.org/en/12?q", "https://notexample.org/es/", "ftp://x.com/fr/#a", "http://com/de/x", "http://a.b.example.org/es/xy", "http://example.org./es/", "http://.org/", "x://y://z.org/", "http://org:80/", "http://a.com/de", "http://org?/x", "http://\nx.org/y"]


def url_brute(url):
    host = path = ""
    if url and "://" in url:
        rest = url.split("://", 1)[1]
        host = re.match(r"[^/?#]*", rest).group()
        path = re.match(r"[^?#]*", rest[len(host) :]).group()
        host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
    fit = [(r, v) for v, r in RULES if (host == r.split("/")[0] or host.endswith("." + r.split("/")[0])) and path.startswith("/" + r.split("/", 1)[1])]
    r, v = min(fit, key=lambda x: (-len(x[0]), x[0])) if fit else (None, "allow")
    return host, path, r, v


def test_urls_against_brute_force(spark):
    data = [(i, u, "old") for i, u in enumerate(URLS)] + [(3, URLS[3], "old")]
    df = spark.createDataFrame(data, "page_id long, url string, verdict string")
    for sweeps in (1, 5):
        got = url_filters.filter_urls(df, RULES, sweeps=sweeps).collect()
        assert len(got) == len(data)
        for r in got:
            assert (r["host"], r["path"], r["rule"], r["verdict"]) == url_brute(r["url"]), r["url"]
    assert url_filters.filter_urls(df.limit(0), RULES).count() == 0 and url_filters.filter_urls(df, []).where("rule is null").count() == len(data)


def test_url_query_equals_sql(spark, small):
    from eventpulse.llm import queries

    want = connect(small).sql(queries.ORACLES["op7_url_filter"]).df()
    assert rows(queries.QUERIES["op7_url_filter"](spark, small).toPandas()) == rows(want)


# --- 8 mixing ----------------------------------------------------------------------------------


def shares(sizes, weights=(1, 2, 3)):
    """Targets by sharing the excess until none is above."""
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % 3] for i, s in enumerate(names)}
    total, fixed = sum(sizes.values()), {}
    while True:
        left = total - sum(fixed.values())
        rest = [s for s in names if s not in fixed]
        part = {s: left * w[s] / sum(w[x] for x in rest) for s in rest}
        over = {s: 3.0 * sizes[s] for s in rest if part[s] > 3 * sizes[s]}
        if not over:
            return fixed | part
        fixed |= over


def test_mixing_targets_and_copies(spark, monkeypatch):
    monkeypatch.setattr(mixing, "LEAF", 16)
    rnd = random.Random(6)
    data = [(i, " ".join(["w"] * rnd.choice([0, 1, 5, 40, 300])), rnd.choice(["a"] * 20 + ["b", "c", "d", None])) for i in range(900)]
    df = spark.createDataFrame(data, "doc_id long, text string, source string")
    got = mixing.mix(df).toPandas()
    sizes = {s: sum(len((t or "").split()) for _, t, x in data if x == s) for s in {x for *_, x in data}}
    goal = shares(sizes)
    for s, part in got.groupby("source", dropna=False):
        s = None if s != s else s
        assert part["target"].iloc[0] == pytest.approx(goal[s])
        assert abs(part["taken"].sum() - goal[s]) <= 301
    assert (got["taken"] <= 3 * got["size"]).all() and len(got) == len(data)
    again = mixing.mix(df.repartition(7)).toPandas()
    key = ["doc_id", "taken"]
    assert sorted(map(tuple, got[key].to_numpy().tolist())) == sorted(map(tuple, again[key].to_numpy().tolist()))


def test_rounding_keeps_the_sum_and_the_expectation():
    size = np.array([50, 30, 30, 20, 10, 5, 5, 1.0])
    p = np.full(8, 0.3)
    out = np.array([mixing.round_block(size, p, np.random.default_rng(s)) for s in range(3000)])
    assert np.allclose(out @ size, p @ size) and ((out > 0) & (out < 1)).sum(axis=1).max() <= 1
    assert np.allclose(out.mean(axis=0), p, atol=0.05)


def test_mixing_odd_rows(spark):
    df = odd_docs(spark)
    got = mixing.mix(df).collect()
    assert len(got) == df.count() and mixing.mix(nothing(spark)).count() == 0
    out = mixing.mixed(df)
    assert out.columns == df.columns and out.count() == sum(r["copies"] for r in got)
    assert mixing.mix(df.where("doc_id < 3")).agg(F.sum("taken")).first()[0] == 0


def test_targets_of_many_sources(spark):
    rnd = random.Random(9)
    sizes = {f"host{i:04d}": rnd.choice([0, 1, 7, 40, 900]) for i in range(700)} | {None: 33}
    got = mixing.targets(spark.createDataFrame(list(sizes.items()), "source string, size long"))
    want = shares(sizes)
    assert {r["source"]: r["target"] for r in got.collect()} == pytest.approx(want)


def test_mix_of_rows_without_keys(spark):
    data = [(None, f"some words {i % 40}", "a" if i % 3 else "b") for i in range(300)]
    df = spark.createDataFrame(data, "doc_id long, text string, source string")
    want: dict = {}
    for r in mixing.mix(df).collect():
        want[r["source"]] = want.get(r["source"], 0) + r["copies"]
    got = {r["source"]: r["count"] for r in mixing.mixed(df).groupBy("source").count().collect()}
    assert sum(got.values()) == sum(want.values()) > 0


# --- 10 MinHash --------------------------------------------------------------------------------


def near_brute(docs, words=5, percent=85):
    sets = {}
    for i, t in docs:
        w = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        sets[i] = {tuple(w[k : k + words]) for k in range(len(w) - words + 1)} if len(w) >= words else ({tuple(w)} if w else set())
    part = {i: i for i in sets}

    def root(i):
        while part[i] != i:
            i = part[i]
        return i

    for a, b in itertools.combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if sets[a] and sets[b] and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
            x, y = sorted((root(a), root(b)))
            part[y] = x
    return {i: (len(sets[i]), root(i)) for i in sets}


def test_near_duplicates_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(minhash, "BLOCK", 16)
    monkeypatch.setattr(minhash, "BLOCK_CONFIRMED", 8)
    rnd = random.Random(3)
    prose = lambda n: [f"{rnd.choice('abcdefghij')}{rnd.randint(0, 60)}" for _ in range(n)]
    docs, k = [], 0
    for size in (60, 200, 900):
        for _ in range(6):
            base = prose(size)
            for edits in (0, 0, 1, 2, 3, 5, 8):
                own = list(base)
                for _ in range(edits * size // 200 + (edits > 0)):
                    own[rnd.randrange(size)] = "edit" + str(rnd.randint(0, 9999))
                docs.append((k, " ".join(own)))
                k += 1
    hot = prose(150)
    for _ in range(60):  # a group whose members are near the threshold of each other
        own = list(hot)
        for _ in range(3):
            own[rnd.randrange(150)] = "z" + str(rnd.randint(0, 9999))
        docs.append((k, " ".join(own)))
        k += 1
    docs += [(k + 1, None), (k + 2, ""), (k + 3, " \n"), (k + 4, "just four words here"), (k + 5, "JUST four words here")]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in minhash.near_duplicates(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == near_brute(docs)


def test_near_duplicates_odd_rows(spark):
    df = odd_docs(spark)
    got = minhash.near_duplicates(df).collect()
    assert len(got) == df.count() and minhash.near_duplicates(nothing(spark)).count() == 0
    by = {r["doc_id"]: r for r in got}
    assert by[6]["component_id"] == by[7]["component_id"] == 5 and by[9]["component_id"] == 8 and by[None]["component_id"] is None
    assert by[0]["kept"] and by[0]["n_shingles"] == 0
    out = minhash.deduplicate(df)
    assert out.columns == df.columns and sorted(str(r["doc_id"]) for r in out.collect()) == sorted(str(i) for i in [*range(6), 8, 10, 11, 12, 13, None])


def test_near_duplicates_of_one_id_with_two_texts(spark):
    one, other = "a b c d e f g h i j k l", "n o p q r s t u v w x y"
    df = spark.createDataFrame([(1, one), (1, other), (2, one), (3, other + " z"), (4, "q")], "doc_id long, text string")
    got = sorted((r["doc_id"], r["component_id"]) for r in minhash.near_duplicates(df).collect())
    assert got == [(1, 1), (1, 1), (2, 1), (3, 1), (4, 4)]
    kept = [minhash.deduplicate(df.repartition(n)).orderBy("doc_id").collect() for n in (1, 3)]
    assert kept[0] == kept[1] and [r["doc_id"] for r in kept[0]] == [1, 4]


def test_shingles_are_exact():
    texts = ["a a a a a a a b b b", "of of to to of of to to of", "x", "", "a b c d e f g"]
    want = [len({tuple(w[k : k + 5]) for k in range(len(w) - 4)}) if len(w := t.split()) >= 5 else int(bool(w)) for t in texts]
    assert [len(s) for s in shingle_sets([t.encode() for t in texts])] == want
