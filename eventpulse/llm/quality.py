"""Quality of texts by a sparse ensemble of rules over text statistics.

Statistics of each text are Spark columns. On a bounded sample of labelled rows, small
boosted trees are grown over them; every path from a root to a node is a rule, a conjunction of
comparisons. A logistic model with a lasso penalty weights the rules, most of which get zero.
What is left is compiled into one column expression, so that scoring is a projection inside the scan's
stage, without Python.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eventpulse.llm.arrow import text_of
from eventpulse.llm.crc import held_out, labelled_evenly

#: Labelled rows that are learnt from, whatever the input.
MOST_ROWS = 20_000
TREES, DEPTH, CUTS, RATE, LEAF = 24, 3, 24, 0.4, 8

Rule = tuple[tuple[int, bool, float], ...]  # (statistic, above, cut) of each comparison


def statistics(df: DataFrame, text: str = "text") -> tuple[DataFrame, list[str]]:
    """``df`` with a double column for each statistic of the text, and their names; ratios to nothing are 0."""
    t = F.coalesce(F.col(text), F.lit(""))
    df = df.withColumn("_w", F.filter(F.split(t, r"[\x20\x09-\x0D]+"), lambda x: x != "")).withColumn("_l", F.filter(F.split(t, r"\n"), lambda x: x != ""))
    df = df.withColumn("_rest", F.regexp_replace(t, r"[a-zß-öø-ÿ\s]+", ""))  # what the character classes below count in: short
    chars, words, lines = F.length(t), F.size("_w"), F.size("_l")
    share = lambda a, b: F.coalesce(F.try_divide(a.cast("double"), b.cast("double")), F.lit(0.0))
    without = lambda which: F.length("_rest") - F.length(F.translate("_rest", which, ""))
    before, after = F.slice("_w", 1, F.greatest(words - 1, F.lit(0))), F.slice("_w", 2, F.greatest(words - 1, F.lit(0)))
    found = {
        "log_words": F.log1p(words.cast("double")),
        "chars_per_word": share(chars, words),
        "words_per_line": share(words, lines),
        "distinct_words": share(F.size(F.array_distinct("_w")), words),
        "distinct_lines": share(F.size(F.array_distinct("_l")), lines),
        "repeats": share(F.size(F.filter(F.zip_with(before, after, lambda a, b: a == b), lambda x: x)), words),
        "short_words": share(F.size(F.filter("_w", lambda x: F.length(x) <= 3)), words),
        "long_words": share(F.size(F.filter("_w", lambda x: F.length(x) >= 12)), words),
        "upper": share(without("ABCDEFGHIJKLMNOPQRSTUVWXYZÀÁÈÉÊÍÑÓÖÜÄÇ"), chars),
        "digits": share(without("0123456789"), chars),
        "stops": share(without(".,;:?"), chars),
        "shouts": share(without("!"), chars),
        "bars": share(without("|/\\_=<>{}[]~"), chars),
        "symbols": share(without("#$%&*@+^"), chars),
    }
    return df.withColumns(found).drop("_w", "_l", "_rest"), list(found)


def _tree(x: np.ndarray, g: np.ndarray, h: np.ndarray, cuts: list[np.ndarray], depth: int, rows: np.ndarray, path: Rule, rules: set, out: np.ndarray) -> None:
    """Grow a regression tree on gradients; its paths go to ``rules`` and its leaf values to ``out``."""
    if path:
        rules.add(path)
    best = None
    if depth and len(rows) >= 2 * LEAF:
        total_g, total_h = g[rows].sum(), h[rows].sum()
        for f, at in enumerate(cuts):
            if not len(at):
                continue
            bucket = np.searchsorted(at, x[rows, f], side="left")  # x <= at[k]: bucket <= k
            n = np.cumsum(np.bincount(bucket, minlength=len(at) + 1))[:-1]
            gs = np.cumsum(np.bincount(bucket, g[rows], len(at) + 1))[:-1]
            hs = np.cumsum(np.bincount(bucket, h[rows], len(at) + 1))[:-1]
            gain = gs**2 / (hs + 1) + (total_g - gs) ** 2 / (total_h - hs + 1) - total_g**2 / (total_h + 1)
            gain[(n < LEAF) | (n > len(rows) - LEAF)] = -1
            k = int(gain.argmax())
            if gain[k] > 1e-6 and (best is None or gain[k] > best[0]):
                best = gain[k], f, float(at[k])
    if best is None:
        out[rows] = g[rows].sum() / (h[rows].sum() + 1)
        return
    _, f, cut = best
    above = x[rows, f] > cut
    for side in (False, True):
        _tree(x, g, h, cuts, depth - 1, rows[above == side], (*path, (f, side, cut)), rules, out)


def grow_rules(x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH) -> list[Rule]:
    """Paths of boosted trees for a logistic loss, without repeated ones, in a fixed order."""
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, CUTS + 2)[1:-1])) for f in range(x.shape[1])]
    score, rules = np.zeros(len(y)), set()
    for _ in range(trees):
        p = 1 / (1 + np.exp(-score))
        step = np.zeros(len(y))
        _tree(x, y - p, p * (1 - p), cuts, depth, np.arange(len(y)), (), rules, step)
        score += RATE * np.clip(step, -4, 4)
    simple = {tuple(sorted(r)) for r in rules}
    return sorted(simple, key=lambda r: (len(r), r))


def holds(rules: list[Rule], x: np.ndarray) -> np.ndarray:
    """(rows, rules): 1 where a rule holds."""
    out = np.ones((len(x), len(rules)), dtype=np.float32)
    for k, rule in enumerate(rules):
        for f, above, cut in rule:
            out[:, k] *= (x[:, f] > cut) == above
    return out


def lasso(z: np.ndarray, y: np.ndarray, penalty: float, steps: int = 400) -> tuple[float, np.ndarray]:
    """Intercept and weights of a logistic model with an L1 penalty, by accelerated proximal gradient."""
    n, m = z.shape
    size = 4.0 / (np.linalg.norm(z, 2) ** 2 / n + 1.0)
    b = float(np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3)))
    w, v, vb, t = np.zeros(m), np.zeros(m), b, 1.0
    for _ in range(steps):
        r = 1 / (1 + np.exp(-np.clip(z @ v + vb, -30, 30))) - y
        new = v - size * (z.T @ r) / n
        new = np.sign(new) * np.maximum(np.abs(new) - size * penalty, 0)
        nb = vb - size * r.mean()
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, vb = new + (t - 1) / t2 * (new - w), nb + (t - 1) / t2 * (nb - b)
        if np.abs(new - w).max(initial=0) < 1e-7:
            w, b = new, nb
            break
        w, b, t = new, nb, t2
    return b, w


class RuleEnsemble:
    """Rules with their weights; ``names`` are the statistics they compare."""

    def __init__(self, names: list[str], x: np.ndarray, y: np.ndarray):
        self.names, self.rules, self.weights = names, [], np.zeros(0)
        self.intercept = float(np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3))) if len(y) else 0.0
        if len(y) < 4 * LEAF or y.min() == y.max():
            return
        rules = grow_rules(x, y)
        z = holds(rules, x).astype(np.float64)
        inner = np.arange(len(y)) % 4 == 0  # rows are in an order by hash
        loss = {}
        for penalty in (0.02, 0.008, 0.003, 0.001):
            b, w = lasso(z[~inner], y[~inner], penalty, 200)
            p = np.clip(1 / (1 + np.exp(-(z[inner] @ w + b))), 1e-6, 1 - 1e-6)
            loss[penalty] = -(y[inner] * np.log(p) + (1 - y[inner]) * np.log(1 - p)).mean()
        b, w = lasso(z, y, min(loss, key=lambda k: (loss[k], -k)))
        kept = np.flatnonzero(np.abs(w) > 1e-3)
        self.intercept, self.rules, self.weights = b, [rules[k] for k in kept], w[kept]

    def column(self) -> Column:
        """The score as an expression of the statistics."""
        total: Column = F.lit(float(self.intercept))
        for rule, w in zip(self.rules, self.weights.tolist(), strict=True):
            tests = [F.col(self.names[f]) > cut if above else F.col(self.names[f]) <= cut for f, above, cut in rule]
            total = total + F.when(reduce(Column.__and__, tests), F.lit(w)).otherwise(F.lit(0.0))
        return 1 / (1 + F.exp(-total))

    def describe(self) -> list[str]:
        """The rules as text, heaviest first."""
        order = np.argsort(-np.abs(self.weights), kind="stable")
        return [f"{self.weights[k]:+.3f} if " + " and ".join(f"{self.names[f]} {'>' if up else '<='} {cut:.4g}" for f, up, cut in self.rules[k]) for k in order]


def fit(docs: DataFrame, labels: DataFrame, text: str = "text", target: str = "quality", most: int = MOST_ROWS) -> RuleEnsemble:
    """Fit on at most ``most`` labelled documents outside the held-out fold; only their statistics
    reach the driver."""
    picked = labelled_evenly(labels, target, most)
    df, names = statistics(text_of(docs, "doc_id", text=text).join(F.broadcast(picked), "doc_id"))
    rows = df.select(F.xxhash64("doc_id").alias("_h"), "doc_id", "y", *names).toPandas().sort_values(["_h", "doc_id"])
    return RuleEnsemble(names, rows[names].to_numpy(dtype=float), rows["y"].to_numpy(dtype=float))


def classify(docs: DataFrame, labels: DataFrame, text: str = "text", target: str = "quality", cut: float = 0.3, model: RuleEnsemble | None = None) -> DataFrame:
    """(doc_id, held_out, score, predicted) of each row of ``docs``.

    Null texts count as empty, and an empty text is scored by its statistics, which are all 0. A null doc_id
    is not held out. With too few labels, or of one class, the score is the share of label 1. Repeated rows
    give repeated results; an empty table gives an empty table.
    """
    model = model or fit(docs, labels, text, target)
    df, _ = statistics(text_of(docs, "doc_id", text=text))
    out = df.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), model.column().alias("score"))
    return out.withColumn("predicted", (F.col("score") >= cut).cast("int"))
