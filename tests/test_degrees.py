"""Clusters under several numbers of shards in one pass, against the method run for each number by itself."""

from __future__ import annotations

import random
from collections import Counter
from dataclasses import replace

import numpy as np
import pyarrow as pa
import pytest

from eventpulse.config import ClusterConfig
from eventpulse.functions import vectors
from eventpulse.operators import clusters, degrees
from eventpulse.plans import comparison_queries
from eventpulse.plans.burst_queries import doc_tokens
from eventpulse.plans.cluster_queries import DOC_CFG, chain_tokens

DEGREES = [1, 3, 8]


def vec(v):
    return tuple(sorted((w, round(x, 7)) for w, x in v.items()))


def stretch(seed, digest):
    """Posts of three blocks over few words, so that all kinds of clusters form."""
    rnd, held = random.Random(seed), []
    for block in (1, 2, 5):
        texts = [[rnd.choice("abcdefghijklmnopqrstuvwxyz"[: rnd.choice((6, 26))]) for _ in range(rnd.randint(1, 6))] for _ in range(rnd.randint(1, 40))]
        texts += rnd.choices(texts, k=15)
        cols = [list(range(100 * block, 100 * block + len(texts))), [rnd.getrandbits(63) - 2**62 for _ in texts], [digest(t) for t in texts], texts]
        types = {"post_id": pa.int64(), "number": pa.int64(), "digest": pa.int64(), "tokens": pa.list_(pa.string())}
        part = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types.values(), strict=True)], list(types))
        held += [(("ALL", block), part.slice(0, 7)), (("ALL", block), part.slice(7))] if len(texts) > 7 else [(("ALL", block), part)]
    return held


def one_by_one(held, cfg):
    for key in dict.fromkeys(k for k, _ in held):
        rows = [r for k, part in held if k == key for r in part.to_pylist()]
        posts = [(r["post_id"], r["number"], {w: n / len(r["tokens"]) for w, n in Counter(r["tokens"]).items()}) for r in rows]
        yield from ((s, *key, c.n, c.first, vec(c.vec)) for s in DEGREES for c in degrees.grown(posts, s, cfg) if c.n >= cfg.min_cluster_posts)


@pytest.mark.parametrize("variant", [{}, {"match": "best"}, {"passes": "fixpoint"}, {"theta": 0.8}, {"merge_theta": 0.9}, {"theta": 1.0}, {"min_cluster_posts": 1}], ids=str)
@pytest.mark.parametrize("digest", [lambda t: hash(tuple(t)), lambda t: len(t)], ids=["digest", "colliding"])
def test_blocks_equal_the_method_on_all_posts(monkeypatch, variant, digest):
    cfg = replace(ClusterConfig(min_cluster_posts=2), **variant)
    for seed in range(30):
        monkeypatch.setattr(degrees, "CELLS", (50, 2_000_000)[seed % 2])
        held = stretch(seed, digest)
        got = sorted((*r[:-1], vec(r[-1])) for r in degrees.clusters_of_blocks(held, DEGREES, cfg))
        assert got == sorted(one_by_one(held, cfg)) and got


def test_what_meets_nothing_is_left_out():
    """Two close posts, one that only both of them together reach, one that none reaches."""
    words = [{0: 1, 1: 1}, {0: 1, 1: 1, 2: 1}, {0: 2, 3: 3, 4: 3}, {0: 1, 5: 5}]
    row, word, weight = (np.array(x) for x in zip(*[(i, w, float(n)) for i, v in enumerate(words) for w, n in v.items()], strict=True))
    meets = degrees.meeting(np.zeros(4, dtype=int), row, word, weight, np.ones(4, dtype=int), 0.35)
    assert meets.tolist() == [True, True, True, False]
    assert degrees.meeting(np.arange(4), row, word, weight, np.ones(4, dtype=int), 0.35).tolist() == [False] * 4


@pytest.mark.parametrize("stream", ["chain", "documents"])
def test_degrees_equal_runs_of_their_own(spark, small, stream):
    tokens, cfg = (chain_tokens(spark, small), ClusterConfig(min_cluster_posts=5)) if stream == "chain" else (doc_tokens(spark, small), DOC_CFG)
    rows = degrees.merged_by_degree(tokens, DEGREES, cfg).collect()
    for s in DEGREES:
        own = replace(cfg, shards=s)
        want = clusters.drop_small(clusters.merge_local(clusters.cluster_local(vectors.vectorize(tokens), own), own), cfg.min_cluster_posts)
        got = sorted((r["region"], r["block_no"], r["n_posts"], r["min_post"], vec(r["vec"])) for r in rows if r["shards"] == s)
        assert got == sorted((r["region"], r["block_no"], r["n_posts"], r["min_post"], vec(r["vec"])) for r in want.collect()) and got
    found = {r["shards"]: (r["events"], r["clusters"]) for r in degrees.shard_sensitivity(tokens, DEGREES, cfg).collect()}
    for s in DEGREES:
        fold = clusters.cluster_two_stage(tokens, replace(cfg, shards=s)).where("kind = 'cluster'")
        assert found[s] == (fold.where("is_event").count(), fold.count())


def test_no_clusters_is_zero_for_each_degree(spark, small):
    got = degrees.shard_sensitivity(doc_tokens(spark, small), [1, 2], replace(DOC_CFG, min_cluster_posts=10**6)).collect()
    assert [tuple(r) for r in got] == [(1, 0, 0), (2, 0, 0)]


def test_posts_are_clustered_once_for_all_degrees(spark, small, monkeypatch):
    """One stored table, that of the merged clusters, whatever the number of degrees."""
    stored, store = [], clusters.materialize
    monkeypatch.setattr(clusters, "materialize", lambda df, tag: (stored.append(tag), store(df, tag))[1])
    assert comparison_queries.QUERIES["W_6_clusters_by_parallelism"](spark, small).count() == 4
    assert stored == ["clusters-merged"]
