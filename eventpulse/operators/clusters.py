"""Post clustering: local clusters by shard, merged by block, folded into live clusters by region.

What is order-dependent (first match wins, vectors change as they grow) runs in plain Python over rows that arrive
sorted, batch by batch: posts are never held, only the clusters of a shard, of a block, or the live ones of a region. The order is
canonical (time, then id), so that only how posts are dealt to shards can change a result.
"""

from __future__ import annotations

import math
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from eventpulse.config import EPS, ClusterConfig
from eventpulse.functions.vectors import prune_words, vectorize
from eventpulse.plans.scratch import materialize, ship
from eventpulse.schemas import CLUSTER, FOLD, arrow_rows

Vec = dict[str, float]


def cosine(a: Vec, b: Vec) -> float:
    """Cosine of two sparse vectors; 0 if one is empty or zero."""
    if len(b) < len(a):
        a, b = b, a
    dot = sum(w * b.get(k, 0.0) for k, w in a.items())
    if not dot:
        return 0.0
    return dot / math.sqrt(sum(w * w for w in a.values()) * sum(w * w for w in b.values()))


def weighted_mean(a: Vec, na: int, b: Vec, nb: int) -> Vec:
    """Mean of two vectors, weighted by the posts behind them."""
    out = {k: w * na / (na + nb) for k, w in a.items()}
    for k, w in b.items():
        out[k] = out.get(k, 0.0) + w * nb / (na + nb)
    return out


@dataclass
class Cluster:
    """A growing cluster: mean vector, posts, and its smallest post for a canonical order."""

    vec: Vec
    n: int
    first: int
    cid: str = ""
    born: int = 0
    last: int = 0
    added: int = 0


@dataclass
class Book:
    """Counts of what a run has done."""

    cosines: int = 0
    reads: int = 0
    writes: int = 0
    counts: dict[str, int] = field(default_factory=dict)

    def add(self, name: str, n: int = 1) -> None:
        self.counts[name] = self.counts.get(name, 0) + n


class Assigner:
    """Clusters of a shard, grown post by post from none: the first cluster above theta takes a post, or the best.

    A cluster is kept as the sum of its posts' vectors, whose cosines are those of the mean. An index from words to
    clusters gives the products with all clusters that share a word; others have a cosine of 0.
    """

    def __init__(self, theta: float, match: str, book: Book):
        self.theta, self.match, self.book = theta, match, book
        self.index: dict[str, dict[int, float]] = {}
        self.squares: list[float] = []
        self.n: list[int] = []
        self.first: list[int] = []

    def add(self, pid: int, vec: Vec) -> int:
        """The cluster that takes the post."""
        dots: dict[int, float] = {}
        for w, x in vec.items():
            for i, y in self.index.get(w, {}).items():
                dots[i] = dots.get(i, 0.0) + x * y
        square = sum(x * x for x in vec.values())
        chosen, best = None, self.theta + EPS
        for i in sorted(dots):
            self.book.cosines += 1
            c = dots[i] / math.sqrt(square * self.squares[i]) if dots[i] else 0.0
            if c > best:
                chosen, best = i, c
                if self.match == "first":
                    break
        if chosen is None:
            chosen = len(self.n)
            self.squares.append(square)
            self.n.append(1)
            self.first.append(pid)
        else:
            self.squares[chosen] += 2 * dots[chosen] + square
            self.n[chosen] += 1
            self.first[chosen] = min(self.first[chosen], pid)
        for w, x in vec.items():
            own = self.index.setdefault(w, {})
            own[chosen] = own.get(chosen, 0.0) + x
        return chosen

    def clusters(self) -> list[Cluster]:
        """The clusters so far, with mean vectors, in the order of their birth."""
        out = [Cluster({}, n, first) for n, first in zip(self.n, self.first, strict=True)]
        for w, own in self.index.items():
            for i, x in own.items():
                out[i].vec[w] = x / out[i].n
        return out


def assign_posts(posts: Iterable[tuple[int, Vec]], theta: float, match: str, book: Book) -> list[Cluster]:
    """Cluster (id, vector) posts in their order from nothing."""
    found = Assigner(theta, match, book)
    for pid, vec in posts:
        found.add(pid, vec)
    return found.clusters()


def merge_similar(clusters: list[Cluster], theta: float, passes: str, book: Book) -> list[Cluster]:
    """Merge clusters with a cosine of theta or more, the larger ones first; once, or until nothing merges."""
    while True:
        kept: list[Cluster] = []
        index: dict[str, dict[int, float]] = {}
        squares: list[float] = []
        for c in sorted(clusters, key=lambda c: (-c.n, c.first)):
            dots: dict[int, float] = {}
            for w, x in c.vec.items():
                for i, y in index.get(w, {}).items():
                    dots[i] = dots.get(i, 0.0) + x * y
            square = sum([x * x for x in c.vec.values()])
            target = None
            for i in sorted(dots):
                book.cosines += 1
                if (dots[i] / math.sqrt(square * squares[i]) if dots[i] else 0.0) >= theta - EPS:
                    target = i
                    break
            if target is None:
                target = len(kept)
                k = Cluster(dict(c.vec), c.n, c.first, c.cid, c.born, c.last, c.added)
                kept.append(k)
                squares.append(square)
            else:
                k = kept[target]
                k.vec, k.n, k.first, k.added = weighted_mean(k.vec, k.n, c.vec, c.n), k.n + c.n, min(k.first, c.first), k.added + c.added
                squares[target] = sum([x * x for x in k.vec.values()])
                book.add("merged")
            for w, x in k.vec.items():
                index.setdefault(w, {})[target] = x
        if passes == "single" or len(kept) == len(clusters):
            return kept
        clusters = kept


def runs(batches: Iterable[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[tuple, pa.RecordBatch]]:
    """(key, rows) of consecutive rows with one key; a key whose rows go on in the next batch comes again."""
    for b in batches:
        if not b.num_rows:
            continue
        cols = [b.column(k).to_numpy(zero_copy_only=False) for k in keys]
        new = np.zeros(b.num_rows, dtype=bool)
        new[0] = True
        for c in cols:
            new[1:] |= c[1:] != c[:-1]
        first = np.flatnonzero(new).tolist()
        for a, z in zip(first, [*first[1:], b.num_rows], strict=True):
            yield tuple(c[a].item() if isinstance(c[a], np.generic) else c[a] for c in cols), b.slice(a, z - a)


def _vectors(part: pa.RecordBatch) -> list[Vec]:
    return [dict(v) for v in part.column("vec").to_pylist()]


def _stored(part: pa.RecordBatch) -> list[Cluster]:
    return [Cluster(v, n, f) for v, n, f in zip(_vectors(part), part.column("n_posts").to_pylist(), part.column("min_post").to_pylist(), strict=True)]


def deal(posts: DataFrame, cfg: ClusterConfig) -> DataFrame:
    """``posts`` with shard, by a hash of the post's id: ``cfg.shards`` for every block, or as many as leave about
    ``cfg.posts_per_shard`` posts in each. No window: a block's posts never meet in one task."""
    number = F.xxhash64("post_id")
    if cfg.posts_per_shard is None:
        return posts.withColumn("shard", F.pmod(number, F.lit(cfg.shards)).cast("int"))
    held = posts.groupBy("region", "block_no").agg(F.ceil(F.count("*") / cfg.posts_per_shard).alias("_shards"))
    return posts.join(held, ["region", "block_no"]).withColumn("shard", F.pmod(number, F.col("_shards")).cast("int")).drop("_shards")


def cluster_local(vectors: DataFrame, cfg: ClusterConfig = ClusterConfig()) -> DataFrame:
    """Local clusters of each (region, block, shard), every shard beginning with none.

    ``vectors``: region, block_no, ts, post_id, vec. Posts are dealt to shards (:func:`deal`) and sorted; a task
    holds the clusters of one shard at a time, whatever the number of posts.
    """
    ship(vectors.sparkSession)
    theta, match = cfg.theta, cfg.match
    keys = ["region", "block_no", "shard"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def closed() -> pa.RecordBatch:
            region, block, shard = key
            return arrow_rows([(region, block, shard, f"{block}-{shard}-{i}", c.n, c.first, c.vec, found.book.cosines if i == 0 else 0) for i, c in enumerate(found.clusters())], CLUSTER)

        key, found = None, None
        for k, part in runs(batches, keys):
            if k != key:
                if key is not None:
                    yield closed()
                key, found = k, Assigner(theta, match, Book())
            for pid, vec in zip(part.column("post_id").to_pylist(), _vectors(part), strict=True):
                found.add(pid, vec)
        if key is not None:
            yield closed()

    dealt = deal(vectors, cfg).select(*keys, "ts", "post_id", "vec").repartition(*keys)
    return dealt.sortWithinPartitions(*keys, "ts", "post_id").drop("ts").mapInArrow(run, CLUSTER)


def merge_local(local: DataFrame, cfg: ClusterConfig = ClusterConfig()) -> DataFrame:
    """The block's local clusters merged among themselves; only clusters are shuffled, no posts."""
    ship(local.sparkSession)
    theta, passes = cfg.merge_theta, cfg.passes
    keys = ["region", "block_no"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def closed() -> pa.RecordBatch:
            region, block = key
            book = Book()
            kept = merge_similar(own, theta, passes, book)
            rows = [(region, block, 0, f"{block}-{c.first}", c.n, c.first, c.vec, spent + book.cosines if i == 0 else 0, book.counts.get("merged", 0) if i == 0 else 0) for i, c in enumerate(kept)]
            return arrow_rows(rows, MERGED)

        key, own, spent = None, [], 0
        for k, part in runs(batches, keys):
            if k != key:
                if key is not None:
                    yield closed()
                key, own, spent = k, [], 0
            own += _stored(part)
            spent += sum(part.column("cosines").to_pylist())
        if key is not None:
            yield closed()

    sorted_ = local.repartition(*keys).sortWithinPartitions(*keys, "shard", "cluster_id")
    return sorted_.mapInArrow(run, MERGED)


def prune_local(merged: DataFrame, cfg: ClusterConfig = ClusterConfig()) -> DataFrame:
    """Without the light words of clusters with many posts."""
    return merged.withColumn("vec", prune_words(F.col("vec"), F.col("n_posts"), cfg.prune_weight, cfg.prune_posts))


def drop_small(clusters: DataFrame, least: int) -> DataFrame:
    """Clusters with at least ``least`` posts."""
    return clusters.where(F.col("n_posts") >= least)


def admit_new(clusters: DataFrame, min_weight: float = 0.05) -> DataFrame:
    """Clusters as they enter the live set: without words under ``min_weight``."""
    return clusters.withColumn("vec", F.map_filter("vec", lambda _, w: w >= min_weight))


def growth_rate(df: DataFrame) -> DataFrame:
    """``df`` with growth: posts added in the block over all posts of the cluster."""
    return df.withColumn("growth", F.try_divide(F.col("n_added").cast("double"), F.col("n_posts").cast("double")))


def expire(df: DataFrame, block_no: int, stale_after: int) -> DataFrame:
    """Clusters that were updated within the last ``stale_after`` blocks."""
    return df.where(F.lit(block_no) - F.col("last_block") < stale_after)


def settle(live: list[Cluster], block: int, cfg: ClusterConfig, book: Book) -> None:
    """Delete the live clusters that are stale at the end of a block, in place."""
    stale = sum(block - g.last >= cfg.stale_after for g in live)
    if stale:
        book.add("deleted", stale)
        live[:] = [g for g in live if block - g.last < cfg.stale_after]


def fold_block(live: list[Cluster], local: list[Cluster], block: int, cfg: ClusterConfig, book: Book) -> list[tuple[Cluster, bool]]:
    """Merge a block's clusters into the live set, in place; the clusters touched and whether each is an event.

    Every live cluster in turn absorbs all similar local ones, its vector updated as it goes; what is left
    becomes new live clusters; stale ones go. Blocks without clusters may be skipped: what was stale before this block
    goes first. Cosines of vectors without a common word are counted, and not computed.
    """
    book.reads += 1
    book.writes += 1
    settle(live, block - 1, cfg, book)
    touched: list[tuple[Cluster, bool]] = []
    left = dict(enumerate(sorted(local, key=lambda c: (-c.n, c.first))))
    by_word: dict[str, set[int]] = {}
    for i, c in left.items():
        for w in c.vec:
            by_word.setdefault(w, set()).add(i)
    for g in sorted(live, key=lambda c: (c.born, c.cid)):
        g.added = 0
        book.cosines += len(left)
        near = set().union(*[by_word.get(w, ()) for w in g.vec])
        for i in sorted(near & left.keys()):
            c = left[i]
            if cosine(g.vec, c.vec) >= cfg.merge_theta - EPS:
                g.vec, g.n, g.added = weighted_mean(g.vec, g.n, c.vec, c.n), g.n + c.n, g.added + c.n
                book.add("absorbed")
                del left[i]
        if g.added:
            g.vec = {w: x for w, x in g.vec.items() if x >= cfg.prune_weight}
            g.last = block
            book.add("updated")
            touched.append((g, g.added / g.n > cfg.growth + EPS))
    for c in left.values():
        new = Cluster({w: x for w, x in c.vec.items() if x >= cfg.new_prune_weight}, c.n, c.first, f"{block}-{c.first}", block, block, c.n)
        book.add("created")
        if not new.vec:
            book.add("emptied_clusters")
        live.append(new)
        touched.append((new, cfg.new_is_event))
    settle(live, block, cfg, book)
    book.counts["live"] = len(live)
    return touched


#: Clusters of a block, with how many merges made them.
MERGED = CLUSTER + ", merged long"


def fold_rows(region: str, block: int, touched: list[tuple[Cluster, bool]], book: Book) -> list[tuple]:
    """FOLD rows of a block: the clusters it touched, and its costs."""
    rows = [("cluster", region, block, c.cid, c.added, c.n, c.added / c.n, c.born, c.last, event, c.vec, None, None) for c, event in touched]
    costs = {"cosines": book.cosines, "state_reads": book.reads, "state_writes": book.writes, **book.counts}
    return rows + [("cost", region, block, None, None, None, None, None, None, None, None, k, float(v)) for k, v in sorted(costs.items())]


def epochs(merged: DataFrame, stale_after: int) -> DataFrame:
    """``merged`` with epoch: blocks of a region between which every live cluster has become stale are in different
    epochs, which share nothing. The window is over one row for each block."""
    order = Window.partitionBy("region").orderBy("block_no")
    held = merged.select("region", "block_no").distinct()
    cut = F.coalesce(F.col("block_no") - F.lag("block_no").over(order) > stale_after, F.lit(False)).cast("int")
    return merged.join(held.withColumn("_cut", cut).withColumn("epoch", F.sum("_cut").over(order)).drop("_cut"), ["region", "block_no"])


def fold_blocks(merged: DataFrame, cfg: ClusterConfig = ClusterConfig()) -> DataFrame:
    """The live clusters of each region carried through its blocks: rows of kind cluster (each cluster a
    block has touched) and cost. Regions, and epochs of a region, run in parallel; inside an epoch blocks are taken in order,
    which is the method's nature, and a task holds the live clusters and those of one block."""
    ship(merged.sparkSession)
    if "merged" not in merged.columns:
        merged = merged.withColumn("merged", F.lit(0).cast("long"))
    keys = ["region", "epoch", "block_no"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def closed() -> pa.RecordBatch:
            book = Book(cosines=spent, counts={"merged": merges} if merges else {})
            return arrow_rows(fold_rows(key[0], key[2], fold_block(live, own, key[2], cfg, book), book), FOLD)

        key, live, own, spent, merges = None, [], [], 0, 0
        for k, part in runs(batches, keys):
            if k != key:
                if key is not None:
                    yield closed()
                    if k[:2] != key[:2]:
                        live = []
                key, own, spent, merges = k, [], 0, 0
            own += _stored(part)
            spent += sum(part.column("cosines").to_pylist())
            merges += sum(part.column("merged").to_pylist())
        if key is not None:
            yield closed()

    rows = epochs(materialize(merged, "clusters-merged"), cfg.stale_after)
    rows = rows.select(*keys, "n_posts", "min_post", "vec", "cosines", "merged").repartition("region", "epoch")
    return rows.sortWithinPartitions(*keys, "min_post").mapInArrow(run, FOLD)


def cluster_two_stage(tokens: DataFrame, cfg: ClusterConfig = ClusterConfig()) -> DataFrame:
    """The two-stage method end to end, from tokened posts to FOLD rows."""
    local = cluster_local(vectorize(tokens), cfg)
    return fold_blocks(drop_small(prune_local(merge_local(local, cfg), cfg), cfg.min_cluster_posts), cfg)


def cluster_single_stage(tokens: DataFrame, cfg: ClusterConfig = ClusterConfig(stale_after=2)) -> DataFrame:
    """The rejected design: every post against every live cluster, one after the other, with clusters merged
    at block ends. A region's posts stream through one task, which holds its live clusters."""
    ship(tokens.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def closed() -> pa.RecordBatch:
            nonlocal live
            region, block = key
            live = merge_similar(live, cfg.merge_theta, "single", book)
            for g in live:
                g.last = block if g.added else g.last
            touched = [(g, g.n >= cfg.min_cluster_posts and g.born < block and g.added / g.n > cfg.growth + EPS) for g in live if g.added]
            settle(live, block, cfg, book)
            book.counts["live"] = len(live)
            return arrow_rows(fold_rows(region, block, [t for t in touched if t[0].n >= cfg.min_cluster_posts], book), FOLD)

        key, live, book = None, [], Book()
        for k, part in runs(batches, ["region", "block_no"]):
            if k != key:
                if key is not None:
                    yield closed()
                    if k[0] != key[0]:
                        live = []
                key, book = k, Book()
                settle(live, k[1] - 1, cfg, book)
                for g in live:
                    g.added = 0
            for pid, vec in zip(part.column("post_id").to_pylist(), _vectors(part), strict=True):
                home = None
                book.reads += 1
                book.writes += 1
                for g in live:
                    book.cosines += 1
                    if cosine(vec, g.vec) > cfg.theta + EPS:
                        home = g
                        break
                if home is None:
                    live.append(Cluster(vec, 1, pid, f"{k[1]}-{pid}", k[1], k[1], 1))
                    book.add("created")
                else:
                    home.vec, home.n, home.added, home.last = weighted_mean(home.vec, home.n, vec, 1), home.n + 1, home.added + 1, k[1]
                    book.add("updated")
        if key is not None:
            yield closed()

    posts = vectorize(tokens).select("region", "block_no", "ts", "post_id", "vec").repartition("region")
    return posts.sortWithinPartitions("region", "block_no", "ts", "post_id").drop("ts").mapInArrow(run, FOLD)


def cluster_events(fold: DataFrame) -> DataFrame:
    """CLUSTER_EVENT rows of a fold."""
    e = fold.where((F.col("kind") == "cluster") & F.col("is_event"))
    return e.select("region", "block_no", "cluster_id", "n_added", "n_posts", "growth", top_words().alias("top_words"))


def top_words(k: int = 5):
    """The k heaviest words of a cluster, joined; equal weights by word."""
    ranked = F.array_sort(F.transform(F.map_entries("vec"), lambda e: F.struct((-F.round(e["value"], 9)).alias("w"), e["key"].alias("k"))))
    return F.array_join(F.transform(F.slice(ranked, 1, k), lambda e: e["k"]), " ")


def cluster_words(fold: DataFrame) -> DataFrame:
    """(region, block_no, cluster_id, word, weight) of the clusters that are events."""
    e = fold.where((F.col("kind") == "cluster") & F.col("is_event"))
    return e.select("region", "block_no", "cluster_id", F.explode("vec").alias("word", "weight"))


def describe_clusters(fold: DataFrame, k: int = 10) -> DataFrame:
    """Each live cluster's last state: posts, span of blocks, and its k heaviest words."""
    rows = fold.where("kind = 'cluster'").groupBy("region", "cluster_id").agg(F.max_by(F.struct("n_posts", "born_block", "last_block", "vec"), "block_no").alias("s"))
    return rows.select("region", "cluster_id", "s.*").select("region", "cluster_id", "n_posts", "born_block", "last_block", top_words(k).alias("top_words"))


def kmeans_blocks(tokens: DataFrame, k: int, features: int = 1 << 12, seed: int = 3) -> DataFrame:
    """The contrast that must know its number of clusters: k-means over hashed word counts.

    (region, block_no, prediction, n_posts): cluster sizes by block; a model over all blocks."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import HashingTF, Normalizer

    tf = HashingTF(inputCol="tokens", outputCol="tf", numFeatures=features).transform(tokens.where(F.size("tokens") > 0))
    x = Normalizer(inputCol="tf", outputCol="x").transform(tf)
    model = KMeans(k=k, seed=seed, featuresCol="x", maxIter=10).fit(x)
    return model.transform(x).groupBy("region", "block_no", F.col("prediction").cast("long").alias("prediction")).agg(F.count("*").alias("n_posts"))
