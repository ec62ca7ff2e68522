"""The corpus pipeline: every stage's decisions on planted documents."""

from __future__ import annotations

import corpus_pipeline
import pytest


@pytest.fixture(scope="module")
def sf() -> str:
    return "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = [docs.toPandas()]
    df = docs
    for _, stage in corpus_pipeline.STAGES:
        df = stage(spark, df, sf)
        out.append(df.toPandas())
    return out


def test_columns_and_order(stages):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "pii", "mixing", "bpe"]
    for df in stages[:-1]:
        assert list(df.columns) == list(stages[0].columns)
    assert list(stages[-1].columns) == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]


def test_each_stage_takes_effect(stages):
    raw, clean, single, masked, mixed, encoded = stages
    assert set(clean["doc_id"]) < set(raw["doc_id"])
    assert set(single["doc_id"]) <= set(clean["doc_id"]) and single["doc_id"].is_unique
    assert set(masked["doc_id"]) == set(single["doc_id"]) and not masked["text"].str.contains(r"@mail[0-9]").any()
    assert set(mixed["doc_id"]) <= set(masked["doc_id"]) and mixed["doc_id"].value_counts().max() <= 3
    assert sorted(encoded["doc_id"]) == sorted(mixed["doc_id"]) and (encoded["n_tokens"] > 0).any()


def test_run(spark, sf, stages):
    got = corpus_pipeline.run(spark, sf).toPandas()
    assert sorted(map(tuple, got.to_numpy().tolist())) == sorted(map(tuple, stages[-1].to_numpy().tolist()))
