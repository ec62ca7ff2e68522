"""Operators and stages do their whole job."""

from __future__ import annotations

import time

import corpus_pipeline
import numpy as np
from eventpulse.llm import minhash, pii
from eventpulse.llm.words import shingle_sets


def test_stage_drops_near_copies_between_80_and_85_percent(spark, small):
    words = [f"w{i}" for i in range(204)]
    near, far = list(words), list(words)
    for i in (40, 80, 120, 160):
        near[i] = f"x{i}"
    for i in (30, 60, 90, 120, 150):
        far[i] = f"y{i}"
    texts = [" ".join(w) for w in (words, near, far)]
    a, b, c = (set(s.tolist()) for s in shingle_sets([t.encode() for t in texts], 5))
    assert 0.8 <= len(a & b) / len(a | b) < 0.85 and len(a & c) / len(a | c) < 0.8
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {r["doc_id"] for r in corpus_pipeline.drop_near_duplicates(spark, docs, small).collect()} == {0, 2}
    assert minhash.PERCENT == 85 and minhash.deduplicate(docs).count() == 3


def everything() -> dict:
    """A model that takes each candidate."""
    w = np.zeros(sum(pii._WIDTHS) + 1)
    w[-1] = 30
    return {"weights": w}


def test_redaction_masks_long_secrets_names_and_addresses_whole(spark):
    secret = "".join("aB3_x9Kz"[i % 8] for i in range(1000))
    local, host = "q" * 100, ".".join("h" * 80 for _ in range(7))
    texts = [f"token={secret} end", f"Dr. {'N' + 'n' * 60} {'M' + 'm' * 60} end", f"to {local} (at) {host} end"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = [r["text"] for r in pii.redact(df, everything()).orderBy("doc_id").collect()]
    assert got == ["token=[SECRET] end", "[NAME] end", "to [EMAIL_SPELT] end"]


def test_wide_patterns_are_linear():
    began = time.perf_counter()
    for t in ("token=" + "a.-" * 200_000, "token" * 100_000, "token=aaaa " * 50_000, "Mr A" + "a" * 500_000, "a." * 200_000 + " (at) b", "a(at)" * 100_000, "a (at) b.c" * 50_000, "(at)" + "b" * 400_000):
        list(pii._wider(t))
    assert time.perf_counter() - began < 15
