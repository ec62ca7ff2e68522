"""Queries over whole tables, against brute force."""

from __future__ import annotations

from collections import Counter

import pandas as pd

from eventpulse.operators import bursts
from eventpulse.plans import relational
from eventpulse.plans.burst_queries import W4, event_tokens


def test_range_join_takes_every_order_and_line_item(spark, small):
    got = {r["o_orderkey"]: r["n"] for r in relational.QUERIES["J_11_range_join"](spark, small).collect()}
    o, l = pd.read_parquet(f"{small}/orders.parquet"), pd.read_parquet(f"{small}/lineitem.parquet")
    days = lambda x: (pd.to_datetime(x) - pd.Timestamp(0)).dt.days.tolist()
    shipped = Counter(days(l["l_shipdate"]))
    want = {k: sum(shipped[t + i] for i in range(11)) for k, t in zip(o["o_orderkey"].tolist(), days(o["o_orderdate"]), strict=True)}
    assert got == {k: n for k, n in want.items() if n}
    assert any(k % 50 for k in got)


def test_as_of_returns_every_score_row(spark, small):
    got = {(r["word"], r["block_no"]): r["earlier"] for r in relational.QUERIES["J_12_as_of"](spark, small).collect()}
    want, last = {}, {}
    for r in bursts.score(event_tokens(spark, small), W4).orderBy("block_no").collect():
        want[r["word"], r["block_no"]] = last.get(r["word"])
        last[r["word"]] = r["tfidf"]
    assert set(got) == set(want) and any(b % 7 for _, b in got)
    assert all((got[k] is None) == (v is None) and (v is None or abs(got[k] - v) < 1e-8) for k, v in want.items())


def test_null_order_places_every_row(spark, small):
    got = sorted(relational.QUERIES["T_5_null_order"](spark, small).collect(), key=lambda r: r["place"])
    t = pd.read_parquet(f"{small}/documents.parquet")[["doc_id"]].merge(pd.read_parquet(f"{small}/labels.parquet"), on="doc_id", how="left")
    want = [(k, None if q != q else int(q)) for k, q in zip(t["doc_id"].tolist(), t["quality"].tolist(), strict=True)]
    want.sort(key=lambda x: (x[1] is None, x[1] or 0, x[0]))
    assert [(r["doc_id"], r["quality"]) for r in got] == want and want[-1][1] is None
    assert [r["place"] for r in got] == list(range(1, len(want) + 1))


def test_similar_posts_are_told_by_their_classes(spark, monkeypatch):
    """Copies cost a row each and no pairs among themselves; parts of a block lose no link."""
    from eventpulse.operators import pairs

    texts = [["hot", f"w{i % 7}"] if i % 2 else ["cold", "hot"] for i in range(400)] + [["far"]]
    t = spark.createDataFrame([("r", 1, i, w) for i, w in enumerate(texts)], "region string, block_no long, post_id long, tokens array<string>")
    first = sorted({texts.index(w) for w in texts[:400]})
    links = {(a, b) for a in first for b in first if a < b}
    for block in (8192, 50):
        monkeypatch.setattr(pairs, "BLOCK", block)
        for prune in (True, False):
            got = pairs.class_pairs(pairs.bags(t), 0.5, prune).collect()
            assert {(r["a"], r["b"]) for r in got if not r["copy"]} == links
            assert {r["b"]: r["a"] for r in got if r["copy"]} == {i: texts.index(w) for i, w in enumerate(texts[:400]) if texts.index(w) != i}
            assert len(got) == len(links) + 400 - len(first)
        assert {r["component"] for r in pairs.cluster_components(pairs.bags(t), 0.5).collect()} == {0}
        n = pairs.class_pairs_recall(pairs.bags(t), 0.5).toPandas().sum(numeric_only=True)
        assert n["exact"] == len(links) and n["wrong"] == 0


def test_dense_classes_and_searches_equal_brute_force(spark, monkeypatch):
    """Equal vectors cost a row each; odd ones link with nothing; a bucket may be dealt over parts."""
    import numpy as np
    from pyspark.sql import functions as F

    from eventpulse.operators import pairs

    x = np.random.default_rng(1).standard_normal((300, 8)).round(3)
    x[100:200] = x[7]
    rows = [(i, v) for i, v in enumerate(x.tolist())] + [(300, None), (301, [0.0] * 8), (302, [float("nan")] + [1.0] * 7), (303, [None] + [1.0] * 7)]
    e = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    c, first = u @ u.T, [i for i in range(300) if not 100 <= i < 200]
    want = {(a, b) for a in first for b in first if a < b and c[a, b] >= 0.7}
    for block in (8192, 3):
        monkeypatch.setattr(pairs, "BLOCK", block)
        got = pairs.dense_class_pairs(e, 0.7).collect()
        found = [(r["a"], r["b"]) for r in got if not r["copy"]]
        assert len(found) == len(set(found)) and set(found) <= want and len(found) >= 0.9 * len(want)
        assert {(r["a"], r["b"]) for r in got if r["copy"]} == {(7, i) for i in range(100, 200)}
    monkeypatch.setattr(pairs, "BLOCK", 200)
    exact = {(r["a"], r["b"]) for r in pairs.dense_brute(e, 0.7, F.col("class_id") % 20 == 0).collect()}
    assert exact == {(a, b) for a in range(300) for b in range(a + 1, 300) if c[a, b] >= 0.7 and (a % 20 == 0 or b % 20 == 0)}


def test_a_pause_for_every_block_in_few_triggers(spark):
    """Many block files take few triggers, and still a pause each; results do not depend on the files of a trigger."""
    from eventpulse.operators.bursts import detect_bursts_eager
    from eventpulse.plans import stream_queries as G
    from eventpulse.config import BurstConfig
    from eventpulse.sources import posts as P
    from eventpulse.streaming import replay
    from eventpulse.streaming.bursts import eager_stream
    from pyspark.sql import functions as F

    us = [P.START_US + b * 1_800_000_000 + k * 1_000_000 for b in range(30) for k in range(3)]
    t = spark.createDataFrame([(i, "r", ["a", f"w{i % 5}"] * (1 + i % 2)) for i in range(90)], "post_id long, region string, tokens array<string>")
    t = t.withColumn("ts", F.timestamp_micros(F.element_at(F.lit(us), (F.col("post_id") + 1).cast("int")))).withColumn("block_no", F.floor(F.col("post_id") / 3) + 1)
    cfg = BurstConfig(rate=1.1, min_count=2)
    plain = lambda df: sorted((r["block_no"], r["word"], round(r["tfidf"], 9)) for r in df.collect())
    want = plain(detect_bursts_eager(t, cfg))
    assert want
    for blocks in (7, 256):
        pace, seen = replay.Pause(0.02, blocks), []
        stream, files = G.blockwise_stream(spark, t, pace)
        found, seconds = eager_stream(spark, stream, "30 minutes", P.START_US, cfg, pace, files)
        assert files == 31 and seconds >= 0.02 * files and plain(found) == want
        replay.paced(G.blockwise_stream(spark, t, pace)[0], lambda b, k: seen.append(k), pace, "t-paced", files)
        assert len(seen) <= -(-(files + 1) // blocks)


def test_cleaning_undoes_what_was_added_where_pages_are_missing(spark):
    from eventpulse.functions import clean
    from eventpulse.sources import posts as P
    from pyspark.sql import functions as F

    docs = spark.createDataFrame([(1, "One text."), (2, "Aab baAb bab."), (12, "cab fog"), (11, "Two."), (21, None)], "doc_id long, text string")
    for rows in ([(7, "https://a.example/x"), (1, "https://b.example"), (1, "http://c.example")], [(99, "https://a.example")]):
        aug = P.augmented_texts(docs, spark.createDataFrame(rows, "page_id long, url string"), True).collect()
        assert len(aug) == 5
        again = spark.createDataFrame(aug, "doc_id long, original string, text string")
        assert again.where(clean.clean_tokens(F.col("text")) != clean.clean_tokens(F.col("original"))).count() == 0
    assert {r["doc_id"]: r["text"] for r in aug}[12] == "caaaaab fog"


def test_sources_deliver_a_given_table(spark, small):
    """The block source in both forms, the rate source, inline rows and the deployment take all events."""
    from eventpulse.plans import comparison_queries, stream_queries

    e = pd.read_parquet(f"{small}/events.parquet")
    want = (e["event_id"].min(), e["event_id"].max(), len(e))
    for name in ("S_5_block_source", "S_5_block_source_stream"):
        assert tuple(stream_queries.QUERIES[name](spark, small).first()) == want
    assert tuple(stream_queries.QUERIES["S_4_rate_source"](spark, small).first()) == (len(e), want[0], 50)
    assert comparison_queries.QUERIES["M_R8_deployment"](spark, small).first()["events"] == len(e)
    users = e.groupby("user_id").size()
    got = {r["min_count"]: r["users"] for r in relational.QUERIES["S_6_inline_rows"](spark, small).collect()}
    assert got == {k: int((users >= k).sum()) for k in (2, 3)}


def test_stored_tables_leave_no_shuffle_files(spark):
    """The degrees of parallelism run one after the other: what the write of a table has shuffled goes when it ends."""
    import time

    from pyspark.sql import functions as F

    from eventpulse.plans.scratch import CLEANUP, materialize

    files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    names = lambda: {f for f in files.getAllFiles().mkString("\n").split("\n") if "/shuffle_" in f}
    before = names()
    out = materialize(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count(), "t-clean")
    for _ in range(50):
        if not names() - before:
            break
        time.sleep(0.1)
    assert not names() - before and out.count() == 7 and spark.conf.get(CLEANUP, "false") != "true"
