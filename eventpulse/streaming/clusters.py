"""Two-stage clustering on a stream: two stateful steps, one after the other.

Stage one is keyed by region and shard. A post is clustered when it comes; what is kept of an open block are the shard's clusters, no
posts. An event-time timer at the end of a block sends them on. Stage two is keyed by region: it merges the
shards' clusters of a closed block, which all arrive in one batch, as their timers go by one watermark, and folds them into the live ones, which
are kept one by one, so that a block writes only what it has touched.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from eventpulse.config import ClusterConfig
from eventpulse.functions.vectors import vectorize
from eventpulse.operators.blocks import block_of, micros
from eventpulse.operators.clusters import Assigner, Book, Cluster, deal, fold_block, fold_rows, merge_similar
from eventpulse.plans.scratch import ship
from eventpulse.schemas import FOLD
from eventpulse.streaming.replay import SENTINEL

ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
LOCAL = "closed timestamp, region string, block_no long, shard int, nth long, n_posts long, min_post long, vec string, cosines long"
STREAM_FOLD = FOLD.replace("vec map<string,double>", "vec string")


def _columns(schema: str) -> list[str]:
    return [f.split()[0] for f in schema.split(", ")]


class ShardProcessor(StatefulProcessor):
    """State of a shard: the clusters of each open block. Posts of a batch are taken in order of time and id."""

    def __init__(self, cfg: ClusterConfig, length: int, origin: int):
        self.cfg, self.length, self.origin = cfg, length, origin

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.open = handle.getMapState("open", "block_no long", "grown string")

    def _load(self, block: int) -> Assigner:
        found = Assigner(self.cfg.theta, self.cfg.match, Book())
        if self.open.containsKey((block,)):
            held = json.loads(self.open.getValue((block,))[0])
            found.squares, found.n, found.first, found.book.cosines = held["squares"], held["n"], held["first"], held["cosines"]
            found.index = {w: {int(i): x for i, x in own.items()} for w, own in held["index"].items()}
        return found

    def _store(self, block: int, a: Assigner) -> None:
        self.open.updateValue((block,), (json.dumps({"squares": a.squares, "n": a.n, "first": a.first, "cosines": a.book.cosines, "index": a.index}),))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        new = pd.concat(list(rows))
        new = new[new["region"] != SENTINEL].sort_values(["block_no", "t", "post_id"])
        for block, part in new.groupby("block_no"):
            block = int(block)
            found = self._load(block)
            for pid, vec in zip(part["post_id"], part["vec"], strict=True):
                found.add(int(pid), json.loads(vec))
            self._store(block, found)
            self.handle.registerTimer((self.origin + block * self.length) // 1000)
        yield from ()

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        block = (expiredTimerInfo.getExpiryTimeInMs() * 1000 - self.origin) // self.length
        if self.open.containsKey((block,)):
            found = self._load(block)
            self.open.removeKey((block,))
            closed = pd.Timestamp(self.origin + block * self.length, unit="us")
            rows = [(closed, key[0], block, int(key[1]), i, c.n, c.first, json.dumps(c.vec), found.book.cosines if i == 0 else 0) for i, c in enumerate(found.clusters())]
            yield pd.DataFrame(rows, columns=_columns(LOCAL))

    def close(self) -> None:
        pass


class RegionProcessor(StatefulProcessor):
    """State of a region: its live clusters by id."""

    def __init__(self, cfg: ClusterConfig):
        self.cfg = cfg

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.live = handle.getMapState("live", "cid string", "cluster string")

    def _fold(self, region: str, block: int, part: pd.DataFrame) -> list[tuple]:
        book, cfg = Book(cosines=int(part["cosines"].sum())), self.cfg
        part = part.sort_values(["shard", "nth"])
        local = [Cluster(json.loads(v), int(n), int(f)) for v, n, f in zip(part["vec"], part["n_posts"], part["min_post"], strict=True)]
        merged = merge_similar(local, cfg.merge_theta, cfg.passes, book)
        for c in merged:
            if c.n > cfg.prune_posts:
                c.vec = {w: x for w, x in c.vec.items() if x >= cfg.prune_weight}
        kept = [c for c in merged if c.n >= cfg.min_cluster_posts]
        if not kept:
            return []
        before = {c.cid: c for c in (Cluster(**json.loads(v[0])) for v in self.live.values())}
        live = list(before.values())
        touched = fold_block(live, kept, block, cfg, book)
        for gone in before.keys() - {c.cid for c in live}:
            self.live.removeKey((gone,))
        for c, _ in touched:
            self.live.updateValue((c.cid,), (json.dumps(vars(c)),))
        return fold_rows(region, block, touched, book)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        out = [r for block, part in pd.concat(list(rows)).groupby("block_no") for r in self._fold(key[0], int(block), part)]
        yield pd.DataFrame(out, columns=_columns(STREAM_FOLD)).assign(vec=lambda f: f["vec"].map(lambda v: json.dumps(v) if isinstance(v, dict) else None))

    def close(self) -> None:
        pass


def cluster_stream(tokens: DataFrame, length: str, origin: int, cfg: ClusterConfig, delay: str = "0 seconds") -> DataFrame:
    """FOLD rows (vectors as JSON) of a stream of (ts, region, post_id, tokens), whose rows come in order of time."""
    spark = tokens.sparkSession
    ship(spark)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", ROCKSDB)
    n = micros(length)
    filled = tokens.withColumn("tokens", F.when(F.col("region") == SENTINEL, F.array(F.lit("end"))).otherwise(F.col("tokens")))
    posts = vectorize(filled).withColumn("block_no", block_of(F.col("ts"), n, origin)).withColumn("post_id", F.coalesce("post_id", F.lit(-1)))
    rows = deal(posts, cfg).withWatermark("ts", delay).select("ts", "region", "shard", "block_no", F.unix_micros("ts").alias("t"), "post_id", F.to_json("vec").alias("vec"))
    local = rows.groupBy("region", "shard").transformWithStateInPandas(ShardProcessor(cfg, n, origin), LOCAL, "append", "eventtime", eventTimeColumnName="closed")
    return local.groupBy("region").transformWithStateInPandas(RegionProcessor(cfg), STREAM_FOLD, "append", "none")
