"""The clustering jobs, batch and stream, against a plain reference, on posts whose order matters."""

from __future__ import annotations

import json
from dataclasses import replace

import pytest

from eventpulse.config import ClusterConfig
from eventpulse.functions import vectors
from eventpulse.operators import bursts, clusters, measures
from eventpulse.plans.burst_queries import W1, doc_tokens
from eventpulse.plans.cluster_queries import DOC_CFG, chain_tokens
from eventpulse.plans.scratch import materialize, new_dir
from eventpulse.sources import posts as P
from eventpulse.streaming import replay
from eventpulse.streaming.clusters import cluster_stream
from tests import reference_clusters as ref

CHAIN_CFG = ClusterConfig(min_cluster_posts=5)
VARIANTS = {
    "plain": {}, "one": {"shards": 1}, "two": {"shards": 2}, "three": {"shards": 3}, "eight": {"shards": 8}, "best": {"match": "best"},
    "fixpoint": {"passes": "fixpoint"}, "stale": {"stale_after": 1}, "sized": {"posts_per_shard": 90}, "new": {"new_is_event": True},
}


@pytest.fixture(scope="module")
def streams(spark, small):
    return {"chain": (materialize(chain_tokens(spark, small), "t-chain"), CHAIN_CFG), "documents": (materialize(doc_tokens(spark, small), "t-docs"), DOC_CFG)}


def posts_of(tokens, cfg):
    dealt = clusters.deal(tokens.where("size(tokens) > 0"), cfg).select("block_no", "ts", "post_id", "shard", "tokens")
    return [tuple(r) for r in dealt.collect()]


def vec(v):
    return tuple(sorted((w, round(x, 7)) for w, x in v.items()))


def fold_rows(fold):
    rows = fold.where("kind = 'cluster'").collect()
    return sorted((r["block_no"], r["cluster_id"], r["n_added"], r["n_posts"], round(r["growth"], 9), r["is_event"], vec(r["vec"] if isinstance(r["vec"], dict) else json.loads(r["vec"]))) for r in rows)


@pytest.mark.parametrize("name", VARIANTS)
@pytest.mark.parametrize("stream", ["chain", "documents"])
def test_two_stage_equals_reference(streams, stream, name):
    tokens, cfg = streams[stream]
    cfg = replace(cfg, **VARIANTS[name])
    local_rows, merged_rows, rows = ref.two_stage(posts_of(tokens, cfg), cfg)
    local = materialize(clusters.cluster_local(vectors.vectorize(tokens), cfg), "t-local")
    assert sorted((r["block_no"], r["shard"], r["n_posts"], r["min_post"], vec(r["vec"])) for r in local.collect()) == sorted(local_rows)
    merged = clusters.merge_local(local, cfg)
    assert sorted((r["block_no"], r["n_posts"], r["min_post"]) for r in merged.collect()) == sorted(merged_rows)
    fold = clusters.fold_blocks(clusters.drop_small(clusters.prune_local(merged, cfg), cfg.min_cluster_posts), cfg)
    assert fold_rows(fold) == sorted(rows) and rows


def test_variants_differ_on_the_chain(streams):
    tokens, cfg = streams["chain"]
    rows = {}
    for name, change in VARIANTS.items():
        own = replace(cfg, **change)
        rows[name] = ref.two_stage(posts_of(tokens, own), own)
    assert len({str(r[2]) for k, r in rows.items() if k in ("plain", "one", "two", "three", "eight")}) == 5
    for name in ("best", "fixpoint", "new"):
        assert rows[name] != rows["plain"], name


@pytest.mark.parametrize("stream", ["chain", "documents"])
def test_single_stage_equals_reference(streams, stream):
    tokens, cfg = streams[stream]
    cfg = replace(cfg, stale_after=2)
    if stream == "documents":
        tokens = tokens.where("block_no <= 4")
    want = ref.single_stage(posts_of(tokens, cfg), cfg)
    assert fold_rows(clusters.cluster_single_stage(tokens, cfg)) == sorted(want) and want


@pytest.mark.parametrize("stream", ["chain", "documents"])
def test_stream_equals_reference(spark, streams, stream):
    tokens, cfg = streams[stream]
    path = new_dir(spark, "t-stream")
    t = tokens.select("post_id", "ts", "region", "tokens")
    replay.write_replay(t, path, 5)
    fold = replay.to_table(cluster_stream(replay.read_replay(spark, path, t.schema), "6 minutes", P.START_US, cfg), "t-clusters")
    assert fold_rows(fold) == sorted(ref.two_stage(posts_of(tokens, cfg), cfg)[2])


@pytest.mark.parametrize(("stale", "ids"), [(1, ["1-0", "3-100", "7-200"]), (2, ["1-0", "1-0", "7-200"]), (4, ["1-0", "1-0", "1-0"])])
def test_stale_clusters_take_no_posts(spark, stale, ids):
    """Five equal posts in blocks 1, 3 and 7, with other posts in block 5 that leave no cluster."""
    rows = [(100 * k + i, b, ["storm", "coast"]) for k, b in enumerate((1, 3, 7)) for i in range(5)] + [(900, 5, ["other", "words"])]
    tokens = spark.createDataFrame(rows, "post_id long, block_no long, tokens array<string>").selectExpr("post_id", "block_no", "tokens", "'r' as region", "timestamp_seconds(block_no * 360 + post_id % 100) as ts")
    cfg = ClusterConfig(min_cluster_posts=5, stale_after=stale)
    got = fold_rows(clusters.cluster_two_stage(tokens, cfg))
    assert [r[1] for r in got] == ids and got == sorted(ref.two_stage(posts_of(tokens, cfg), cfg)[2])


def test_epochs_cut_where_all_are_stale(spark):
    rows = [("r", b) for b in (1, 2, 5, 6, 10, 11, 15)] + [("s", 3)]
    got = clusters.epochs(spark.createDataFrame(rows, "region string, block_no long"), 3).collect()
    assert {(r["region"], r["block_no"]): r["epoch"] for r in got} == {("r", 1): 0, ("r", 2): 0, ("r", 5): 0, ("r", 6): 0, ("r", 10): 1, ("r", 11): 1, ("r", 15): 2, ("s", 3): 0}


def test_overlap_on_documents_equals_reference(spark, small):
    """The comparison of both detectors, by region: clusters that hold a burst word, and burst words that a cluster holds."""
    cfg, burst = replace(DOC_CFG, new_is_event=True), replace(W1, min_count=5)
    tokens = materialize(doc_tokens(spark, small, region="lang"), "t-lang")
    words = bursts.detect_bursts(tokens, burst)
    got = {r["region"]: r for r in measures.overlap(clusters.cluster_words(clusters.cluster_two_stage(tokens, cfg)), words).collect()}
    burst_words: dict = {}
    for r in words.collect():
        burst_words.setdefault(r["region"], set()).add(r["word"])
    for lang in {r["region"] for r in tokens.select("region").distinct().collect()}:
        events = [r for r in ref.two_stage(posts_of(tokens.where(tokens["region"] == lang), cfg), cfg)[2] if r[5]]
        held = {r[1]: set() for r in events if r[6]}
        for r in events:
            for w, _ in r[6]:
                held[r[1]].add(w)
        own = burst_words.get(lang, set())
        hit = [c for c, ws in held.items() if ws & own]
        g = got[lang]
        assert (g["clusters"], g["clusters_hit"], g["words"], g["words_hit"]) == (len(held), len(hit), len(own), len(own & set().union(*held.values())))
    assert sum(r["clusters_hit"] for r in got.values()) > 0


def test_jobs_hold_no_group_of_posts(spark, small):
    """Clustering streams over sorted rows, and no window holds a block."""
    plan = clusters.cluster_two_stage(chain_tokens(spark, small), CHAIN_CFG)._jdf.queryExecution().executedPlan().toString()
    local = clusters.cluster_local(vectors.vectorize(doc_tokens(spark, small)), DOC_CFG)._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapGroupsInPandas" not in plan + local and "Window" not in local and local.count("Exchange") == 1
