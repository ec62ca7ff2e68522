"""Bursts of posts whose words are one text, against those of their tokens."""

from __future__ import annotations

import random
from collections import Counter
from dataclasses import replace

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from eventpulse.operators import bursts, measures, packed, routing
from eventpulse.plans import burst_queries, comparison_queries
from eventpulse.plans.burst_queries import W1, W10, conv_tokens, doc_tokens
from tests.oracle import rows


@pytest.mark.parametrize("together", [1, 7, 100, 10**6])
def test_counts_of_blocks_equal_a_plain_count(together):
    rnd, want, parts = random.Random(together), Counter(), []
    for _ in range(30):
        posts = [(rnd.choice("ab"), rnd.choice((1, 2, 2, 2, 9)), [rnd.choice(("x", "y", "zé", "w")) for _ in range(rnd.randint(1, 6))]) for _ in range(rnd.randint(1, 9))]
        want.update((r, b, w) for r, b, words in posts for w in words)
        batch = pa.RecordBatch.from_pylist([{"region": r, "block_no": b, "words": " ".join(words)} for r, b, words in posts])
        parts += packed.partial(batch).to_pylist()
    parts.sort(key=lambda r: (r["region"], r["block_no"]))
    batches = [pa.RecordBatch.from_pylist(parts[i : i + 5], schema=packed.PARTIAL) for i in range(0, len(parts), 5)]
    for least in (1, 20):
        got = [r for b in packed.whole_blocks(batches, least, together) for r in b.to_pylist()]
        assert sorted(((r["region"], r["block_no"], r["word"]), r["cnt"]) for r in got) == sorted((k, n) for k, n in want.items() if n >= least)
        for r in got:
            own = [n for k, n in want.items() if k[:2] == (r["region"], r["block_no"])]
            assert (r["block_terms"], r["block_distinct"]) == (sum(own), len(own))


VARIANTS = [{}, {"denominator": "distinct"}, {"corpus": "full"}, {"blocks": "nonempty"}, {"scope": "common", "previous": "common"}, {"scope": "common"}, {"prev_zero": "floor", "floor": 0.001}, {"quiet_window": 3}, {"min_count": 1}]


@pytest.mark.parametrize("variant", VARIANTS, ids=str)
def test_packed_posts_make_the_same_events(spark, small, variant):
    cfg = replace(W1, **({"min_count": 4} | variant))
    tokens = doc_tokens(spark, small, region="lang").where("pmod(post_id, 3) = 0 or block_no % 5 > 0")
    odd = tokens.limit(1)
    for extra in (F.array().cast("array<string>"), F.array(F.lit("x"), F.lit(None))):
        tokens = tokens.unionByName(odd.withColumn("tokens", extra))
    tokens = tokens.unionByName(odd.withColumn("region", F.lit(None).cast("string")))
    got = bursts.detect_bursts(routing.route_direct(packed.pack(tokens), 3, "post_id"), cfg).toPandas()
    assert rows(got) == rows(bursts.detect_bursts(tokens, cfg).toPandas()) and len(got)


def test_nothing_to_count(spark, small):
    assert bursts.detect_bursts(packed.pack(doc_tokens(spark, small).limit(0)), W1).count() == 0


def test_words_cross_only_if_they_are_common_somewhere(spark, small, monkeypatch):
    """Each degree deals the posts to its tasks; a word that is common in no block costs no row of an exchange."""
    given, detect = [], bursts.detect_bursts
    monkeypatch.setattr(bursts, "detect_bursts", lambda t, cfg: given.append((t, cfg)) or detect(t, cfg))
    assert {r["shards"] for r in burst_queries.QUERIES["W_6_bursts_by_parallelism"](spark, small).collect()} == {1, 2, 4, 8}
    tokens = doc_tokens(spark, small)
    counts, posts = bursts.count_words(tokens).count(), tokens.count()
    assert [t.select(F.spark_partition_id()).distinct().count() for t, _ in given] == [1, 2, 4, 8]
    for t, cfg in given:
        assert t.count() == posts
        assert max(n for n, _ in measures.shuffled(detect(t, cfg))) < counts / 2


def test_timed_runs_count_where_posts_are_dealt_to(spark, small, monkeypatch):
    """C_1_execution_time: no barrier run lets a row for each word of a block cross, and the events are those of the tokens."""
    given, detect = [], bursts.detect_bursts
    monkeypatch.setattr(bursts, "detect_bursts", lambda t, cfg: given.append((t, cfg)) or detect(t, cfg))
    found = [r for r in comparison_queries.QUERIES["C_1_execution_time"](spark, small).collect() if r["method"] == "barrier"]
    assert [r["parallelism"] for r in found] == [2, 4, 8] * 2 and all(packed.is_packed(t) for t, _ in given)
    want = {"documents": detect(doc_tokens(spark, small), W1).count(), "conversations": detect(conv_tokens(spark, small), W10).count()}
    assert all(r["events"] == want[r["stream"]] for r in found)
