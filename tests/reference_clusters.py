"""The clustering method in plain dictionaries and lists, written apart from the engine, to check it against.

Posts are (block, time, id, shard, words) tuples; results are rows with rounded numbers.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from math import sqrt

SLACK = 1e-9


def as_vector(words):
    return {w: k / len(words) for w, k in Counter(words).items()}


def cos(a, b):
    up = sum(a[w] * b[w] for w in a.keys() & b.keys())
    return up / sqrt(sum(x * x for x in a.values())) / sqrt(sum(x * x for x in b.values())) if up else 0.0


def blend(a, m, b, n):
    return {w: (a.get(w, 0.0) * m + b.get(w, 0.0) * n) / (m + n) for w in a.keys() | b.keys()}


def local_clusters(posts, theta, match):
    """[vector, size, smallest id] of each cluster of a shard's posts, which come in order."""
    found = []
    for pid, vec in posts:
        close = [(cos(vec, c[0]), k) for k, c in enumerate(found)]
        close = [(s, k) for s, k in close if s > theta + SLACK]
        if not close:
            found.append([vec, 1, pid])
            continue
        k = close[0][1] if match == "first" else max(close, key=lambda x: (round(x[0], 12), -x[1]))[1]
        v, n, first = found[k]
        found[k] = [blend(v, n, vec, 1), n + 1, min(first, pid)]
    return found


def merged(found, theta, passes):
    """Larger clusters take smaller ones; once, or until none is taken."""
    while True:
        kept = []
        for vec, n, first in sorted(found, key=lambda c: (-c[1], c[2])):
            home = next((c for c in kept if cos(vec, c[0]) >= theta - SLACK), None)
            if home is None:
                kept.append([vec, n, first])
            else:
                home[:] = [blend(home[0], home[1], vec, n), home[1] + n, min(home[2], first)]
        if passes == "single" or len(kept) == len(found):
            return kept
        found = kept


def light_words_gone(vec, least):
    return {w: x for w, x in vec.items() if x >= least}


def row(block, c, event):
    return block, c["id"], c["added"], c["n"], round(c["added"] / c["n"], 9), event, tuple(sorted((w, round(x, 7)) for w, x in c["vec"].items()))


def by_shard(posts):
    out = defaultdict(lambda: defaultdict(list))
    for block, ts, pid, shard, words in sorted(posts, key=lambda p: (p[0], p[1], p[2])):
        if words:
            out[block][shard].append((pid, as_vector(words)))
    return out


def two_stage(posts, cfg):
    """(rows of local clusters, of merged clusters, of clusters touched by a block) of a region's posts."""
    local_rows, merged_rows, rows, live = [], [], [], []
    blocks = by_shard(posts)
    for block in range(1, max(blocks, default=0) + 1):
        here = []
        for shard in sorted(blocks.get(block, {})):
            found = local_clusters(blocks[block][shard], cfg.theta, cfg.match)
            local_rows += [(block, shard, n, first, tuple(sorted((w, round(x, 7)) for w, x in v.items()))) for v, n, first in found]
            here += found
        here = merged(here, cfg.merge_theta, cfg.passes)
        merged_rows += [(block, n, first) for _, n, first in here]
        here = [(light_words_gone(v, cfg.prune_weight) if n > cfg.prune_posts else v, n, first) for v, n, first in here if n >= cfg.min_cluster_posts]
        here.sort(key=lambda c: (-c[1], c[2]))
        for old in sorted(live, key=lambda c: (c["born"], c["id"])):
            old["added"], rest = 0, []
            for v, n, first in here:
                if cos(old["vec"], v) >= cfg.merge_theta - SLACK:
                    old["vec"] = blend(old["vec"], old["n"], v, n)
                    old["n"] += n
                    old["added"] += n
                else:
                    rest.append((v, n, first))
            here = rest
            if old["added"]:
                old["vec"], old["last"] = light_words_gone(old["vec"], cfg.prune_weight), block
                rows.append(row(block, old, old["added"] / old["n"] > cfg.growth + SLACK))
        for v, n, first in here:
            live.append({"id": f"{block}-{first}", "vec": light_words_gone(v, cfg.new_prune_weight), "n": n, "added": n, "born": block, "last": block})
            rows.append(row(block, live[-1], cfg.new_is_event))
        live = [c for c in live if block - c["last"] < cfg.stale_after]
    return local_rows, merged_rows, rows


def single_stage(posts, cfg):
    """Rows of the clusters that a block has touched, each post compared with all live clusters."""
    rows, live = [], []
    blocks = defaultdict(list)
    for block, ts, pid, _, words in sorted(posts, key=lambda p: (p[0], p[1], p[2])):
        if words:
            blocks[block].append((pid, as_vector(words)))
    for block in range(1, max(blocks, default=0) + 1):
        for c in live:
            c["added"] = 0
        for pid, vec in blocks.get(block, []):
            home = next((c for c in live if cos(vec, c["vec"]) > cfg.theta + SLACK), None)
            if home is None:
                live.append({"id": f"{block}-{pid}", "vec": vec, "n": 1, "added": 1, "first": pid, "born": block, "last": block})
            else:
                home["vec"] = blend(home["vec"], home["n"], vec, 1)
                home["n"], home["added"], home["last"] = home["n"] + 1, home["added"] + 1, block
        if blocks.get(block):
            kept = []
            for c in sorted(live, key=lambda c: (-c["n"], c["first"])):
                home = next((k for k in kept if cos(c["vec"], k["vec"]) >= cfg.merge_theta - SLACK), None)
                if home is None:
                    kept.append(c)
                else:
                    home["vec"] = blend(home["vec"], home["n"], c["vec"], c["n"])
                    home["n"], home["added"], home["first"] = home["n"] + c["n"], home["added"] + c["added"], min(home["first"], c["first"])
            live = kept
        for c in live:
            if c["added"]:
                c["last"] = block
                if c["n"] >= cfg.min_cluster_posts:
                    rows.append(row(block, c, c["born"] < block and c["added"] / c["n"] > cfg.growth + SLACK))
        live = [c for c in live if block - c["last"] < cfg.stale_after]
    return rows
