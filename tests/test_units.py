"""Inline fixtures: cleaning, vectors, scores, growth, pruning, overlaps."""

from __future__ import annotations

import math
import re

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from eventpulse.config import BurstConfig, ClusterConfig
from eventpulse.functions import clean, stem, vectors
from eventpulse.operators import blocks, bursts, clusters, measures, pairs
from eventpulse.operators.components import connected_components
from eventpulse.sources import posts as P


def one(spark, value, expr):
    return spark.createDataFrame([(value,)], "t string").select(expr(F.col("t"))).first()[0]


@pytest.mark.parametrize(("word", "want"), [("looong", "long"), ("cool", "cool"), ("hmmmm", "hm"), ("ééé", "é"), ("111", "111")])
def test_squeeze(spark, word, want):
    assert one(spark, word, clean.squeeze_runs) == want


def test_urls_and_checkins(spark):
    assert one(spark, "see https://a.example/x now", clean.strip_urls) == "see  now"
    assert one(spark, "I am at the pier. It rains.", clean.drop_checkins).strip() == "It rains."
    assert one(spark, None, clean.clean_tokens) == []
    assert one(spark, "the of and", clean.clean_tokens) == []


def test_spellings_meet_on_one_stem():
    assert stem.porter("firing") == stem.porter("fire") == "fire"
    assert [stem.porter(w) for w in ("caresses", "ponies", "cats", "agreed", "plastered", "hopping", "relational", "adjustment", "probate", "controll")] == ["caress", "poni", "cat", "agre", "plaster", "hop", "relat", "adjust", "probat", "control"]


def tokens(spark, rows):
    return spark.createDataFrame(rows, "region string, block_no long, post_id long, seq long, tokens array<string>")


def test_vector_of_a_post(spark):
    v = vectors.vectorize(tokens(spark, [("A", 1, 1, 0, ["river", "coast", "river", "north"]), ("A", 1, 2, 1, [])])).collect()
    assert [r["vec"] for r in v] == [{"coast": 0.25, "north": 0.25, "river": 0.5}]


def test_cosine_on_the_threshold(spark):
    a, b = {"a": 0.5, "b": 0.5}, {"a": 0.5, "c": 0.5}
    assert clusters.cosine(a, b) == pytest.approx(0.5)
    row = spark.createDataFrame([(a, b, {}, None)], "a map<string,double>, b map<string,double>, e map<string,double>, n map<string,double>")
    got = row.select(vectors.cosine_map(F.col("a"), F.col("b")), vectors.cosine_map(F.col("a"), F.col("e")), vectors.cosine_map(F.col("n"), F.col("a"))).first()
    assert tuple(got) == pytest.approx((0.5, 0.0, 0.0))
    book = clusters.Book()
    assert len(clusters.assign_posts([(1, a), (2, b)], 0.5, "first", book)) == 2  # above only
    two = [clusters.Cluster(a, 1, 1), clusters.Cluster(b, 1, 2)]
    assert len(clusters.merge_similar(two, 0.5, "single", book)) == 1  # or equal


def test_scores_of_a_new_word(spark):
    filler = lambda b, k: [f"w{b}_{i}" for i in range(k)]
    rows = [("A", b, b, 0, filler(b, 10)) for b in (1, 2)] + [("A", 3, 3, 0, ["x", *filler(3, 9)]), ("A", 4, 4, 0, ["x"] * 4 + filler(4, 6))]
    ws = bursts.score(tokens(spark, rows), BurstConfig(min_count=1, rate=2.0)).where("word = 'x'").orderBy("block_no").collect()
    assert [r["tfidf"] for r in ws] == pytest.approx([0.1 * math.log(3 / 2), 0.4 * math.log(4 / 3)])
    assert ws[1]["tfidf"] / ws[1]["prev_tfidf"] == pytest.approx(2.838, abs=1e-3)


def test_a_word_in_every_block_is_no_event(spark):
    rows = [("A", b, b, 0, ["x"] * b + ["y"]) for b in range(1, 9)]
    assert bursts.detect_bursts(tokens(spark, rows), BurstConfig(min_count=1, rate=1.0)).where("word in ('x', 'y')").count() == 0


def test_growth_is_strict():
    cfg = ClusterConfig()
    grown = lambda n, add: clusters.fold_block([clusters.Cluster({"a": 1.0}, n, 1, "c", 1, 1)], [clusters.Cluster({"a": 1.0}, add, 2)], 2, cfg, clusters.Book())[0][1]
    assert grown(30, 40) and not grown(30, 30)


def test_emptied_and_stale_clusters():
    cfg, book, live = ClusterConfig(), clusters.Book(), []
    clusters.fold_block(live, [clusters.Cluster({f"w{i}": 0.04 for i in range(25)}, 30, 1)], 1, cfg, book)
    assert live[0].vec == {} and book.counts["emptied_clusters"] == 1
    clusters.fold_block(live, [], 3, cfg, clusters.Book())
    assert len(live) == 1
    clusters.fold_block(live, [], 4, cfg, clusters.Book())
    assert live == []


def test_pruning_needs_more_than_fifty_posts(spark):
    df = spark.createDataFrame([({"a": 0.009, "b": 0.02}, 60), ({"a": 0.009, "b": 0.02}, 40)], "vec map<string,double>, n_posts long")
    assert [len(r["vec"]) for r in clusters.prune_local(df).collect()] == [1, 2]


def test_overlap_arithmetic(spark):
    c = [("C", 1, f"c{i}", f"x{i}" if i < 2 else f"c{i}") for i in range(7)]
    c += [("C", 1, "c0", f"x{i}") for i in range(2, 6)]
    b = [("C", 1, f"x{i}") for i in range(17)]
    row = measures.overlap(spark.createDataFrame(c, "region string, block_no long, cluster_id string, word string"), spark.createDataFrame(b, "region string, block_no long, word string")).first()
    assert (row["clusters_hit"], row["clusters"], row["words_hit"], row["words"]) == (2, 7, 6, 17)
    assert (round(row["cluster_rate"], 3), round(row["word_rate"], 3)) == (0.286, 0.353)
    assert (round(24 / 290, 3), round(68 / 220, 3)) == (0.083, 0.309)


def test_bounding_boxes(spark):
    df = spark.createDataFrame([(0.0, 0.0), (10.0, 50.0), (-100.0, 40.0), (100.0, 10.0)], "lon double, lat double")
    assert P.bbox_filter(df, [(-130, 20, -60, 70), (5, 40, 20, 60)]).count() == 2


def test_components_of_a_chain_a_star_and_rubbish(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 30)] + [(7, 7), (3, 2), (None, 5)]
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(edges, "src long, dst long")).collect()}
    assert got == {i: 0 for i in range(41)} | {100 + i: 100 for i in range(30)}
    assert connected_components(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_pruned_pairs_equal_all_pairs(spark, small):
    from eventpulse.plans.burst_queries import doc_tokens

    t = doc_tokens(spark, small)
    words = t.select("region", "block_no", "post_id", F.size("tokens").alias("n"), F.explode("tokens").alias("word"))
    v = words.groupBy("region", "block_no", "post_id", "word").agg((F.count("*") / F.first("n").cast("double")).alias("weight"))
    keys = lambda df: {(r["a"], r["b"]) for r in df.collect()}
    assert keys(pairs.similar_pairs(v, 0.6, True)) == keys(pairs.similar_pairs(v, 0.6, False))


def test_bursts_do_not_depend_on_partitions(spark, small):
    from eventpulse.plans.burst_queries import W1, doc_tokens

    t = doc_tokens(spark, small)
    runs = [sorted(map(tuple, bursts.detect_bursts(t.repartition(n), W1).select("word", "block_no", F.round("tfidf", 9)).collect())) for n in (1, 3, 8)]
    assert runs[0] == runs[1] == runs[2]


def test_two_wide_exchanges_for_the_burst_method(spark, small):
    """Words are shuffled once to be counted (counts and totals read that exchange, which the plan names for each) and once to bring
    a word's blocks together; the rest goes by block."""
    from eventpulse.plans.burst_queries import W1, doc_tokens

    plan = bursts.detect_bursts(doc_tokens(spark, small, region="lang"), W1)._jdf.queryExecution().executedPlan().toString()
    keys = [re.findall(r"([a-z_]+)#", e) for e in re.findall(r"Exchange hashpartitioning\(([^)]*)\)", plan)]
    keys = [["region" if c == "lang" else c for c in k] for k in keys]
    assert keys.count(["region", "block_no", "word"]) == 2 and keys.count(["region", "word"]) == 1
    assert all(k == ["region", "block_no"] for k in keys if "word" not in k)
    assert "CartesianProduct" not in plan and "Python" not in plan


def test_arrival_order_over_slices_equals_a_block_window(spark, small):
    from pyspark.sql.window import Window

    from eventpulse.plans.burst_queries import doc_tokens

    t = doc_tokens(spark, small)
    w = Window.partitionBy("region", "block_no").orderBy("ts", "post_id")
    want = t.select("post_id", (F.row_number().over(w) - 1).alias("seq"), F.coalesce(F.sum(F.size("tokens")).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("terms_before"), F.count("*").over(Window.partitionBy("region", "block_no")).alias("block_posts"))
    got = blocks.ordered(t, "tokens", 60_000_000).select("post_id", "seq", "terms_before", "block_posts")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_made_streams_need_no_job_for_their_first_time(spark, small):
    from eventpulse.plans import burst_queries as B

    tracker = spark.sparkContext.statusTracker()
    spark.sparkContext.setJobGroup("building", "")
    for make in (B.doc_tokens, B.conv_tokens, B.plant_tokens):
        make(spark, small)
    jobs = tracker.getJobIdsForGroup("building")
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(jobs) <= 3  # at most the read of a file's footer each


def test_ids_that_have_no_room_fail(spark):
    df = spark.createDataFrame([(1, 999), (1, 1000)], "a long, b long")
    assert df.where("b < 1000").select(P.two_part_id(F.col("a"), F.col("b"), 1000)).first()[0] == 1999
    with pytest.raises(Exception, match="no room"):
        df.select(P.two_part_id(F.col("a"), F.col("b"), 1000)).collect()


def test_long_lists_of_a_word_are_dealt_over_blocks(spark, monkeypatch):
    from eventpulse.operators import pairs as own

    rows = [("r", 1, i, w, 0.5) for i in range(60) for w in (("hot", f"w{i % 7}") if i % 2 else ("hot", "cold"))]
    v = spark.createDataFrame(rows, "region string, block_no long, post_id long, word string, weight double")
    keys = lambda df: sorted((r["a"], r["b"], round(r["cosine"], 9)) for r in df.collect())
    want = keys(own.similar_pairs(v, 0.5))
    assert len(want) == 60 * 59 // 2
    monkeypatch.setattr(own, "BLOCK", 7)
    assert keys(own.similar_pairs(v, 0.5)) == want == keys(own.similar_pairs(v, 0.5, False))


def test_word_state_compacts_and_forgets(spark):
    from eventpulse.plans.scratch import hadoop_path, new_dir
    from eventpulse.streaming.bursts import STATE, WordState

    state = WordState(spark, new_dir(spark, "t-state"), every=3)
    for k in range(10):
        assert state.before(k).count() == min(k, 4)
        state.after(k, spark.createDataFrame([("r", f"w{k % 4}", k, k, float(k))], STATE))
    assert {r["word"]: r["last_block"] for r in state.before(10).collect()} == {"w0": 8, "w1": 9, "w2": 6, "w3": 7}
    p, fs = hadoop_path(spark, state.path)
    assert {f.getPath().getName() for f in fs.listStatus(p)} == {"base=6", "base=9", *[f"change={k}" for k in range(6, 10)]}


def test_cluster_without_shared_folder_is_refused():
    from types import SimpleNamespace

    from eventpulse.plans.scratch import shared_dir

    fake = SimpleNamespace(conf=SimpleNamespace(get=lambda *_: None), sparkContext=SimpleNamespace(getCheckpointDir=lambda: None, master="yarn"))
    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        shared_dir(fake)


words = st.dictionaries(st.sampled_from("abcdef"), st.floats(0.01, 1), max_size=5)


@settings(max_examples=80, deadline=None)
@given(words, words, st.integers(1, 50), st.integers(1, 50))
def test_vector_laws(a, b, na, nb):
    c = clusters.cosine(a, b)
    assert -1e-12 <= c <= 1 + 1e-9 and c == pytest.approx(clusters.cosine(b, a))
    assert clusters.cosine({k: 7 * v for k, v in a.items()}, b) == pytest.approx(c)
    m = clusters.weighted_mean(a, na, b, nb)
    assert sum(m.values()) == pytest.approx((sum(a.values()) * na + sum(b.values()) * nb) / (na + nb))


def test_trend_chart():
    assert "polyline" in bursts.render_trend([(1, 0.0), (2, 0.5)]) and bursts.render_trend([]).endswith("/>")
