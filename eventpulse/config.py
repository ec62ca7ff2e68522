"""Parameters of the two detectors, with the decisions taken where the method leaves a choice."""

from __future__ import annotations

from dataclasses import dataclass, field

#: Slack at thresholds, shared by all comparisons of derived doubles.
EPS = 1e-9


@dataclass(frozen=True)
class PrepConfig:
    """Cleaning rules; each can be switched off."""

    urls: bool = True
    checkins: bool = True
    squeeze: bool = True
    stopwords: bool = True
    stem: str = "none"  # none, light or porter
    langs: tuple[str, ...] = ("en", "fr", "de", "es")


@dataclass(frozen=True)
class BurstConfig:
    """Word-burst detector.

    rate: growth of tf-idf over the previous block that makes an event (strictly above).
    min_count: occurrences in the block that make a word common.
    """

    rate: float = 2.0
    min_count: int = 10
    denominator: str = "total"  # or distinct: terms of a block counted once each
    corpus: str = "prefix"  # or full: which blocks document frequency and N look at
    scope: str = "all"  # or common: document frequency counts only blocks where the word was common
    blocks: str = "elapsed"  # or nonempty: whether empty blocks count in N
    previous: str = "raw"  # or common: whether a rare word's previous score counts
    prev_zero: str = "event"  # or skip, floor: a previous score that is absent or not positive
    floor: float = 1e-6
    quiet_window: int | None = None  # blocks over whose largest score the rate must also hold


@dataclass(frozen=True)
class ClusterConfig:
    """Two-stage post clustering."""

    theta: float = 0.5
    merge_theta: float = 0.5
    match: str = "first"  # or best
    shards: int = 4
    posts_per_shard: int | None = None  # if given, each block has as many shards as leave about so many posts in one
    passes: str = "single"  # or fixpoint
    min_cluster_posts: int = 30
    prune_weight: float = 0.01
    prune_posts: int = 50
    new_prune_weight: float = 0.05
    growth: float = 0.5
    stale_after: int = 3
    new_is_event: bool = False


@dataclass(frozen=True)
class Parallelism:
    """Degree of parallelism of the local and of the merging step."""

    local: int = 4
    merge: int = 4
    extra: dict[str, str] = field(default_factory=dict)
