"""Local clusters under several numbers of shards at once: posts cross once, and what a block's posts have in common is found once.

Most posts of a block are like no other. A cluster of different posts begins with two whose cosine reaches a threshold, and the cosine
of a post with any sum of others is at most the root of the sum of its squared cosines with them (Cauchy and Schwarz; weights are not
negative). So who may be in such a cluster, however posts are dealt, follows from the pairs: those with a close one, then again and
again those for which that bound over the ones found so far reaches a threshold. They go through the method post by post;
the rest have only their copies with them.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eventpulse.config import ClusterConfig
from eventpulse.operators.clusters import Assigner, Book, Cluster, fold_blocks, merge_similar, prune_local, runs
from eventpulse.plans.scratch import ship
from eventpulse.schemas import arrow_rows

#: Merged clusters of a block under a number of shards.
BY_DEGREE = "shards long, region string, block_no long, n_posts long, min_post long, vec map<string,double>"
#: Posts whose blocks are looked at together; cells of a table of products, and products added up in it, at a time.
POSTS_TOGETHER, CELLS = 20_000, 2_000_000
#: How far under a threshold a bound must be.
MARGIN = 1e-6


def spread(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """``first``, ``first`` + 1, ... of each element, ``n`` of them."""
    return np.repeat(first - np.cumsum(n) + n, n) + np.arange(n.sum())


def copies(block: np.ndarray, digest: np.ndarray, codes: np.ndarray, first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The first post of its block with the same words, for each post. Digests propose, words decide: posts of which one
    has only the digest of its first are left as they are."""
    order = np.lexsort((digest, block))
    new = np.ones(len(order), dtype=bool)
    new[1:] = (block[order][1:] != block[order][:-1]) | (digest[order][1:] != digest[order][:-1])
    of = np.empty_like(order)
    of[order] = order[new][np.cumsum(new) - 1]
    if (n != n[of]).any() or (codes[spread(first, n)] != codes[spread(first[of], n)]).any():
        return np.arange(len(of))
    return of


def meeting(block: np.ndarray, row: np.ndarray, word: np.ndarray, weight: np.ndarray, times: np.ndarray, least: float) -> np.ndarray:
    """Whether each row may come to be in a cluster with rows of other words: its cosine with one of them is ``least``, or its
    squared cosines with the rows of its block that may, each as often as it occurs, sum to ``least`` squared.

    Rows are in the order of their blocks; (row, word, weight) are their words, once each, by row.
    """
    if least <= 0 or not len(block):
        return np.ones(len(block), dtype=bool)
    weight = weight / np.sqrt(np.bincount(row, weight * weight, len(block)))[row]
    _, start, held = np.unique(block, return_index=True, return_counts=True)
    start, held = np.repeat(start, held), np.repeat(held, held)  # of each row's block
    key = block[row] * (int(word.max()) + 1) + word
    order = np.argsort(key, kind="stable")
    key, row, weight = key[order], row[order], weight[order]
    ends = np.append(np.flatnonzero(key[1:] != key[:-1]) + 1, len(key))
    later = np.repeat(ends, np.diff(ends, prepend=0)) - np.arange(len(key)) - 1  # rows after this one with the word
    shared = np.flatnonzero(later)
    cost = held + np.bincount(row[shared], later[shared], len(block)).astype(np.int64)
    part = np.cumsum(cost) // CELLS
    at = np.cumsum(held) - held
    pairs = []
    for p in np.unique(part):
        lo, hi = np.searchsorted(part, [p, p + 1])
        own = shared[part[row[shared]] == p]
        a = np.repeat(own, later[own])
        b = spread(own + 1, later[own])
        i, j = row[a], row[b]
        dots = np.bincount(at[i] - at[lo] + j - start[i], weight[a] * weight[b], at[hi - 1] + held[hi - 1] - at[lo])
        cell = np.flatnonzero(dots)
        i = np.searchsorted(at[lo:hi], cell + at[lo], "right") - 1 + lo
        pairs.append((i, cell + at[lo] - at[i] + start[i], dots[cell] ** 2))
    i, j, square = (np.concatenate(x) for x in zip(*pairs, strict=True))
    joined = np.zeros(len(block), dtype=bool)
    near = square >= least * least
    new = np.zeros(len(block), dtype=bool)
    new[i[near]] = new[j[near]] = True
    total = np.zeros(len(block))
    while new.any():
        joined |= new
        a, b = new[i], new[j]
        total += np.bincount(j[a], (square * times[i])[a], len(block)) + np.bincount(i[b], (square * times[j])[b], len(block))
        new = (total >= least * least) & ~joined
    return joined


def grown(posts: list[tuple[int, int, dict]], shards: int, cfg: ClusterConfig) -> list[Cluster]:
    """The method on (id, number, vector) posts of a block, in order: clusters of each shard, merged."""
    found: dict[int, Assigner] = {}
    for pid, number, vec in posts:
        shard = number % shards
        if shard not in found:
            found[shard] = Assigner(cfg.theta, cfg.match, Book())
        found[shard].add(pid, vec)
    return merge_similar([c for _, a in sorted(found.items()) for c in a.clusters()], cfg.merge_theta, cfg.passes, Book())


def clusters_of_blocks(held: list[tuple[tuple, pa.RecordBatch]], degrees: list[int], cfg: ClusterConfig) -> Iterable[tuple]:
    """BY_DEGREE rows of whole blocks, given as (key, posts) stretches; clusters under ``cfg.min_cluster_posts`` posts are left out."""
    names: list[tuple] = []
    for k, _ in held:
        if not names or k != names[-1]:
            names.append(k)
    number_of = {k: i for i, k in enumerate(names)}
    posts = pa.Table.from_batches([part for _, part in held])
    block = np.repeat([number_of[k] for k, _ in held], [part.num_rows for _, part in held])
    pid, number, digest = (posts.column(c).to_numpy() for c in ("post_id", "number", "digest"))
    tokens = posts.column("tokens").combine_chunks()
    n = pc.list_value_length(tokens).to_numpy().astype(np.int64)
    encoded = tokens.flatten().dictionary_encode()
    codes, words = encoded.indices.to_numpy().astype(np.int64), encoded.dictionary
    first = np.cumsum(n) - n
    of = copies(block, digest, codes, first, n)

    kept, row_of, times = np.unique(of, return_inverse=True, return_counts=True)  # rows: posts with different words
    least_post = np.full(len(kept), np.iinfo(np.int64).max)
    np.minimum.at(least_post, row_of, pid)
    entry, count = np.unique(np.repeat(np.arange(len(kept)), n[kept]) * len(words) + codes[spread(first[kept], n[kept])], return_counts=True)
    row, word = entry // len(words), entry % len(words)
    weight = count / n[kept][row]
    ends = np.searchsorted(row, np.arange(len(kept) + 1))
    vector = lambda r: dict(zip(word[ends[r] : ends[r + 1]].tolist(), weight[ends[r] : ends[r + 1]].tolist(), strict=True))
    named = lambda vec: dict(zip(words.take(pa.array(list(vec), pa.int64())).to_pylist(), vec.values(), strict=True))

    least = min(cfg.theta, cfg.merge_theta) - MARGIN if max(cfg.theta, cfg.merge_theta) < 1 - MARGIN else 0.0  # else copies may not meet either
    meets = meeting(block[kept], row, word, weight, times, least)
    for r in np.flatnonzero(~meets & (times >= cfg.min_cluster_posts)):
        region, block_no = names[block[kept[r]]]
        vec = named(vector(r))
        for s in degrees:
            yield s, region, block_no, int(times[r]), int(least_post[r]), vec
    vectors = {r: vector(r) for r in np.flatnonzero(meets).tolist()}
    among = np.flatnonzero(meets[row_of])
    cuts = np.flatnonzero(np.diff(block[among], prepend=-1, append=-1)).tolist() if len(among) else []
    for a, z in zip(cuts, cuts[1:], strict=False):
        own = among[a:z]
        if len(own) < cfg.min_cluster_posts:
            continue
        region, block_no = names[block[own[0]]]
        here = list(zip(pid[own].tolist(), number[own].tolist(), [vectors[r] for r in row_of[own].tolist()], strict=True))
        for s in degrees:
            for c in grown(here, s, cfg):
                if c.n >= cfg.min_cluster_posts:
                    yield s, region, block_no, c.n, c.first, named(c.vec)


def merged_by_degree(tokens: DataFrame, degrees: list[int], cfg: ClusterConfig = ClusterConfig()) -> DataFrame:
    """BY_DEGREE rows: the block's clusters as :func:`clusters.cluster_local` and :func:`clusters.merge_local` make them under each number
    of shards, with ``cfg.min_cluster_posts`` posts at least. Cosines are not counted. A task holds the posts of some small
    blocks, or of one."""
    ship(tokens.sparkSession)
    keys = ["region", "block_no"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for k, part in runs(batches, keys):
            if n >= POSTS_TOGETHER and k != held[-1][0]:
                yield arrow_rows(list(clusters_of_blocks(held, degrees, cfg)), BY_DEGREE)
                held, n = [], 0
            held.append((k, part))
            n += part.num_rows
        if held:
            yield arrow_rows(list(clusters_of_blocks(held, degrees, cfg)), BY_DEGREE)

    posts = tokens.where(F.size("tokens") > 0).select(*keys, "ts", "post_id", "tokens").repartition(*keys)
    dealt = posts.sortWithinPartitions(*keys, "ts", "post_id").select(*keys, "post_id", F.xxhash64("post_id").alias("number"), F.xxhash64("tokens").alias("digest"), "tokens")
    return dealt.mapInArrow(run, BY_DEGREE)


def shard_sensitivity(tokens: DataFrame, shards: list[int], cfg: ClusterConfig = ClusterConfig()) -> DataFrame:
    """(shards, events, clusters) of the two-stage method under different numbers of shards (``cfg.posts_per_shard`` does not
    count). Posts are cleaned, dealt and compared once; the folds run side by side, as those of regions do."""
    merged = prune_local(merged_by_degree(tokens, shards, cfg), cfg)
    apart = merged.select(F.concat(F.col("shards").cast("string"), F.lit(" "), F.col("region")).alias("region"), "block_no", "n_posts", "min_post", "vec", F.lit(0).cast("long").alias("cosines"))
    fold = fold_blocks(apart, cfg).where("kind = 'cluster'").select(F.substring_index("region", " ", 1).cast("long").alias("_shards"), "is_event")
    counts = [F.struct(F.lit(s).cast("long").alias("shards"), F.count_if((F.col("_shards") == s) & F.col("is_event")).alias("events"), F.count_if(F.col("_shards") == s).alias("clusters")) for s in shards]
    return fold.agg(F.array(*counts).alias("_counts")).select(F.inline("_counts"))
