"""Toxic spans by a linear-chain conditional random field.

Documents are labelled, tokens are not: a token of a toxic document is labelled toxic if
its word, or how the word begins, is significantly more frequent among toxic documents than among others. A chain of
two states over the tokens is fitted to these labels (weights of words and of beginnings
of words, a weight for unknown words, transitions) by gradient ascent on the likelihood. Forward-backward marginals give each
token a probability; a logistic model of their largest value, their sum and their density
gives the document's score, and runs of likely tokens give the offending offsets.

A chain is a whole text. For speed the tokens of a batch of texts lie in rows of ``WINDOW``, and what a row passes on to
its neighbours of the same text comes from the products of the rows' transfer matrices, so that the
marginals are those of the uncut chain.
"""

from __future__ import annotations

import math
import re
import sys
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from eventpulse.llm.arrow import map_batches, slices, text_of
from eventpulse.llm.crc import held_out, sample

WINDOW = 64
#: Labelled documents of each class that are learnt from, and their characters.
MOST_DOCS, MOST_CHARS = 2000, 16_000_000
#: Distinct witnesses of a toxic word.
WITNESSES = 5
_WORD = re.compile(r"[^\W\d_]+")
PAD = -1


def lowered(text: str) -> str:
    """The text in lower case, character by character, so that offsets stay."""
    low = text.lower()
    return low if len(low) == len(text) else "".join(c.lower() if len(c.lower()) == 1 else c for c in text)


def tokens(text: str) -> list[str]:
    """Lower-cased runs of letters."""
    return _WORD.findall(lowered(text))


#: Lengths of the word beginnings that are features beside whole words.
STEMS = range(3, 8)


def stems(word: str) -> list[str]:
    """The word's beginnings, marked as such, from the shortest."""
    return [word[:k] + "*" for k in STEMS if k < len(word)]


def toxic_words(docs: list[list[str]], y: np.ndarray, least: float = 20.0, witnesses: int = WITNESSES) -> dict[str, float]:
    """Words and beginnings of words that toxic documents have significantly more often than others, with
    their log-likelihood ratios.

    A document is a witness under the smallest hash of its long words (or the hash of all); near copies mostly share it
    and count once. Needed are ``witnesses`` of them, whatever the number of toxic documents, a ratio over
    e squared and a log-likelihood ratio over ``least``.
    """
    n1 = int(y.sum())
    features = lambda words: words.union(*map(stems, words))
    slot = lambda f: zlib.crc32(f.encode()) & 0x3FFFFF
    table = np.zeros(1 << 22, dtype=np.int32)  # toxic documents by a feature's slot: rules out those too rare to have their witnesses
    for words, label in zip(docs, y, strict=True):
        if label:
            table[np.unique(np.fromiter(map(slot, features(set(words))), dtype=np.int64))] += 1
    place: dict[str, int] = {}
    known: dict[int, int] = {}
    met: tuple[list, list] = ([], [])  # by label: feature and witness, as one number
    for doc, label in sorted(zip(docs, y, strict=True), key=lambda d: -d[1]):  # toxic ones name the features
        words = set(doc)
        long = [zlib.crc32(w.encode()) for w in words if len(w) >= 8]
        witness = min(long) if long else zlib.crc32(" ".join(sorted(words)).encode())
        nth = known.setdefault(witness, len(known))
        if label:
            own = [place.setdefault(f, len(place)) for f in features(words) if table[slot(f)] >= witnesses]
        else:
            own = [place[f] for f in features(words) if f in place]
        met[int(label)].append(np.array(own, dtype=np.int64) * len(y) + nth)
    del table
    seen = []
    for m in met:
        pairs = np.sort(np.concatenate([np.zeros(0, np.int64), *m]))
        m.clear()
        new = np.concatenate([[True], pairs[1:] != pairs[:-1]])[: len(pairs)]
        seen.append(np.bincount(pairs[new] // max(len(y), 1), minlength=len(place)))
    n0 = int(len(y) - n1)
    out = {}
    part = lambda k, n, share: k * math.log(k / n / share) if k else 0.0
    for f, b, a in zip(place, *(s.tolist() for s in seen), strict=True):
        a, b = min(a, n1), min(b, n0)
        if a >= witnesses and math.log((a + 0.5) / (n1 + 1)) - math.log((b + 0.5) / (n0 + 1)) > 2:
            share = (a + b) / (n1 + n0)
            ratio = 2 * (part(a, n1, share) + part(b, n0, share) + part(n1 - a, n1, 1 - share) + part(n0 - b, n0, 1 - share))
            if ratio > least:
                out[f] = ratio
    return out


class Features(dict):
    """Feature of each word: its best toxic word or beginning, else the word if known, else 0. Remembers
    what it has looked up, up to a bound."""

    def __init__(self, lexicon: dict[str, float], words: list[str]):
        best = sorted(lexicon)
        self.lexicon = lexicon
        self.place = {f: i + 1 for i, f in enumerate([*best, *words])}

    def __missing__(self, word: str) -> int:
        toxic = max((f for f in (word, *stems(word)) if f in self.lexicon), key=lambda f: (self.lexicon[f], len(f)), default=word)
        if len(self) > 200_000:
            self.clear()
        self[word] = i = self.place.get(toxic, 0)
        return i

    def __reduce__(self):
        return _features, (self.lexicon, self.place)


def _features(lexicon: dict[str, float], place: dict[str, int]) -> Features:
    out = Features(lexicon, [])
    out.place = place
    return out


class Chains:
    """The tokens of texts, a chain for each text, laid out in rows of ``window`` places.

    Ratios stand for the two-state messages: r = forward(1) / forward(0), s = backward(1) / backward(0).
    """

    def __init__(self, ids: np.ndarray, first: np.ndarray, window: int = WINDOW):
        n = np.diff(first)
        self.rows = -(-n // window)
        self.row0 = np.cumsum(self.rows) - self.rows
        self.place = np.arange(len(ids)) - np.repeat(first[:-1], n) + np.repeat(self.row0, n) * window
        flat = np.full(int(self.rows.sum()) * window, PAD, dtype=np.int32)
        flat[self.place] = ids
        self.words = flat.reshape(-1, window)
        self.opens = np.zeros(len(self.words), dtype=bool)
        self.opens[self.row0[self.rows > 0]] = True
        self.parts = [slice(lo, lo + 4096) for lo in range(0, len(self.words), 4096)]

    def _inputs(self, part: slice, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(exp of the unary scores, whether a place holds a token), by place and row."""
        w = np.ascontiguousarray(self.words[part].T)
        real = w != PAD
        return np.where(real, np.exp(np.clip(weights, -30, 30))[w], 1.0), real

    def _products(self, part: slice, weights: np.ndarray, g: np.ndarray) -> np.ndarray:
        """(4, rows) products of a row's transfer matrices up to a factor: from the state before it to its last state."""
        e, real = self._inputs(part, weights)
        opens = self.opens[part]
        p00, p01 = np.where(opens, 1.0, g[0, 0]), np.where(opens, 1.0, g[0, 1]) * e[0]
        p10, p11 = np.where(opens, 1.0, g[1, 0]), np.where(opens, 1.0, g[1, 1]) * e[0]
        for t in range(1, len(e)):
            q00, q01 = p00 * g[0, 0] + p01 * g[1, 0], (p00 * g[0, 1] + p01 * g[1, 1]) * e[t]
            q10, q11 = p10 * g[0, 0] + p11 * g[1, 0], (p10 * g[0, 1] + p11 * g[1, 1]) * e[t]
            scale = real[t] / (q00 + q01 + q10 + q11)
            for p, q in ((p00, q00), (p01, q01), (p10, q10), (p11, q11)):
                np.multiply(q, scale, out=p, where=real[t])
        return np.stack([p00, p01, p10, p11])

    def _carried(self, weights: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each row: r of the token before it, and s of its last token."""
        r, s = np.ones(len(self.words)), np.ones(len(self.words))
        order = np.argsort(-self.rows, kind="stable")
        rows, row0 = self.rows[order], self.row0[order]
        if not len(rows) or rows[0] < 2:
            return r, s
        m = np.concatenate([self._products(p, weights, g) for p in self.parts], axis=1)
        active = np.searchsorted(-rows, -np.arange(int(rows[0]) + 1), side="left")  # texts with more than k rows
        for k in range(1, int(rows[0])):
            at = row0[: active[k]] + k
            m00, m01, m10, m11 = m[:, at - 1]
            r[at] = (m01 + m11 * r[at - 1]) / (m00 + m10 * r[at - 1])
        for k in range(int(rows[0]) - 1, 0, -1):
            at = row0[: active[k]] + k
            m00, m01, m10, m11 = m[:, at]
            s[at - 1] = (m10 + m11 * s[at]) / (m00 + m01 * s[at])
        return r, s

    def marginals(self, weights: np.ndarray, trans: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(probability of state 1 of each token, pair marginals summed by (state, next))."""
        g = np.exp(trans)
        before, after = self._carried(weights, g)
        out, pairs = np.zeros(self.words.shape), np.zeros((2, 2))
        for part in self.parts:
            e, real = self._inputs(part, weights)
            opens, r = self.opens[part], np.empty((len(e) + 1, e.shape[1]))
            r[0] = before[part]
            for t in range(len(e)):
                r[t + 1] = e[t] * (g[0, 1] + g[1, 1] * r[t]) / (g[0, 0] + g[1, 0] * r[t])
                if t == 0:
                    np.copyto(r[1], e[0], where=opens)
            s, at_s = after[part].copy(), np.empty(e.shape)
            for t in range(len(e) - 1, -1, -1):
                at_s[t] = s
                x = e[t] * s
                np.copyto(s, (g[1, 0] + g[1, 1] * x) / (g[0, 0] + g[0, 1] * x), where=real[t])
            joint = r[1:] * at_s
            out[part] = (joint / (1 + joint)).T
            linked = real.copy()
            linked[0] &= ~opens
            x, y = (e * at_s)[linked], r[:-1][linked]
            j01, j10, j11 = g[0, 1] * x, g[1, 0] * y, g[1, 1] * x * y
            total = g[0, 0] + j01 + j10 + j11
            pairs += [[(g[0, 0] / total).sum(), (j01 / total).sum()], [(j10 / total).sum(), (j11 / total).sum()]]
        return out.reshape(-1)[self.place], pairs


def marginals(ids: np.ndarray, first: np.ndarray, weights: np.ndarray, trans: np.ndarray, window: int = WINDOW) -> np.ndarray:
    """Probability that each token is toxic, in the chain of its whole text."""
    return Chains(ids, first, window).marginals(weights, trans)[0] if len(ids) else np.zeros(0)


def fit_chain(ids: np.ndarray, first: np.ndarray, y: np.ndarray, words: int, steps: int = 40, ridge: float = 1e-4) -> tuple[np.ndarray, np.ndarray]:
    """Word weights and transitions that make the token labels likely (all chains in each step, adaptive steps)."""
    chains, yy = Chains(ids, first), (y > 0).astype(np.int8)
    inside = np.ones(len(ids), dtype=bool)
    inside[first[:-1][np.diff(first) > 0]] = False
    both = (2 * yy[:-1] + yy[1:])[inside[1:]]
    seen = np.array([[np.count_nonzero(both == 2 * then + now) for now in (0, 1)] for then in (0, 1)])
    del both, yy, inside
    n = np.maximum(np.bincount(ids, minlength=words), 1).astype(float)
    hits = np.bincount(ids, weights=y, minlength=words)
    weights = np.log((hits + 0.01) / (n - hits + 1.0))
    trans = np.zeros((2, 2))
    gw, gt = np.zeros(words), np.zeros((2, 2))
    for _ in range(steps):
        m, pairs = chains.marginals(weights, trans)
        dw = (hits - np.bincount(ids, weights=m, minlength=words)) / n - ridge * weights
        dt = (seen - pairs) / max(seen.sum(), 1) - ridge * trans
        gw, gt = 0.9 * gw + 0.1 * dw * dw, 0.9 * gt + 0.1 * dt * dt
        weights = weights + 0.1 * dw / (np.sqrt(gw) + 1e-6)
        trans = trans + 0.1 * dt / (np.sqrt(gt) + 1e-6)
    return weights, trans


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, steps: int = 60) -> np.ndarray:
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p))[:, None]) + ridge * np.eye(len(w)), x.T @ (p - y) + ridge * w)
        w -= step
        if np.abs(step).max() < 1e-9:
            break
    return w


def _summaries(prob: np.ndarray, first: np.ndarray) -> np.ndarray:
    """By document: 1, largest marginal, log of 1 + their sum, their share of the tokens."""
    n = np.diff(first)
    full = np.flatnonzero(n)
    top, total = np.zeros(len(n)), np.zeros(len(n))
    if len(full):
        top[full], total[full] = np.maximum.reduceat(prob, first[full]), np.add.reduceat(prob, first[full])
    return np.stack([np.ones(len(n)), top, np.log1p(total), total / np.maximum(n, 1)], axis=1)


class Tagger:
    """A fitted chain and document model. A word that two documents of the sample hold has a weight of its own; all others
    share one."""

    def __init__(self, texts: Iterable[str], y: list[int]):
        docs = [list(map(sys.intern, tokens(t))) for t in texts]
        label = np.array(y, dtype=int)
        lexicon = toxic_words(docs, label) if 0 < label.sum() < len(label) else {}
        once: set[str] = set()
        often: set[str] = set()
        for words in docs:
            new = set(words) - often
            often |= new & once
            once ^= new  # in for the first document, out for the second
        self.known = Features(lexicon, sorted(w for w in often if w not in lexicon))
        del once, often
        ids, first = self.ids(docs)
        del docs
        toxic = np.zeros(len(self.known.place) + 1)
        toxic[[self.known.place[f] for f in lexicon]] = 1
        token_y = toxic[ids].astype(np.int8) * np.repeat(label.astype(np.int8), np.diff(first)) if len(ids) else np.zeros(0)
        if len(ids):
            self.weights, self.trans = fit_chain(ids, first, token_y, len(toxic))
        else:
            self.weights, self.trans = np.zeros(len(toxic)), np.zeros((2, 2))
        x = _summaries(marginals(ids, first, self.weights, self.trans), first)
        self.document = _logistic(x, label) if len(label) else np.zeros(4)
        self.lexicon = sorted(lexicon)

    def ids(self, docs: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
        """Word ids of all tokens, and where each document's begin."""
        first = np.concatenate([[0], np.cumsum([len(d) for d in docs], dtype=np.int64)]).astype(np.int64)
        flat = np.fromiter((i for d in docs for i in map(self.known.__getitem__, d)), dtype=np.int64, count=int(first[-1]))
        return flat, first

    def judge(self, texts: list[str], least: float = 0.5) -> tuple[np.ndarray, list[list[tuple[int, int]]]]:
        """The probability that each text is toxic, and its runs of tokens whose marginal reaches ``least``, as offsets."""
        ids, first = self.ids([tokens(t) for t in texts])
        prob = marginals(ids, first, self.weights, self.trans)
        x = _summaries(prob, first)
        score = 1 / (1 + np.exp(-np.clip(x @ self.document, -30, 30)))
        return score, [_runs(t, prob[a:z], least) if top >= least else [] for t, a, z, top in zip(texts, first[:-1], first[1:], x[:, 1], strict=True)]

    def score(self, texts: list[str]) -> np.ndarray:
        """The probability that each text is toxic."""
        return self.judge(texts)[0]

    def spans(self, text: str, least: float = 0.5) -> list[tuple[int, int]]:
        """Offsets of runs of tokens whose marginal reaches ``least`` (code points, end exclusive)."""
        return self.judge([text], least)[1][0]


def _runs(text: str, prob: np.ndarray, least: float) -> list[tuple[int, int]]:
    """(first, last) offsets of runs of tokens that are ``least`` likely."""
    out: list[tuple[int, int]] = []
    before = False
    for m, p in zip(_WORD.finditer(lowered(text)), prob.tolist(), strict=True):
        if p >= least:
            out[len(out) - before :] = [(out[-1][0], m.end())] if before else [m.span()]
        before = p >= least
    return out


def fit(docs: DataFrame, labels: DataFrame, text: str = "text", target: str = "toxic", most: int = MOST_DOCS, chars: int = MOST_CHARS) -> Tagger:
    """Fit on at most ``most`` labelled documents of each class outside the held-out fold, in an order by hash, of which
    whole texts are taken as long as a class holds at most ``chars`` characters, or its first text."""
    found = sample(text_of(docs, "doc_id", text=text), labels, target, most).select("doc_id", "text", "y")
    order = Window.partitionBy("y").orderBy(F.xxhash64("doc_id"), "doc_id").rowsBetween(Window.unboundedPreceding, 0)
    found = found.withColumn("_sum", F.sum(F.length("text")).over(order)).where((F.col("_sum") <= chars) | (F.col("_sum") == F.length("text"))).drop("_sum")
    rows = found.toArrow()
    rows = rows.take(np.argsort(rows.column("doc_id").to_numpy(), kind="stable"))
    return Tagger((t.as_py() for t in rows.column("text")), rows.column("y").to_pylist())


#: Characters of text whose chains are in memory at once.
AT_ONCE = 2_000_000


def score(docs: DataFrame, tagger: Tagger, text: str = "text", least: float = 0.5) -> DataFrame:
    """(doc_id, score, spans) of each row; spans are ``first:last`` offsets of toxic runs of tokens, comma-joined. Null texts
    count as empty, whose score is the model's for no token; repeated rows give repeated results, an empty table an empty one."""
    shared = docs.sparkSession.sparkContext.broadcast(tagger)  # weights of the words of MOST_CHARS characters at most

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text", AT_ONCE):
                found, runs = shared.value.judge(b.column("text").to_pylist(), least)
                joined = [",".join(f"{a}:{z}" for a, z in r) for r in runs]
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(found, pa.float64()), pa.array(joined, pa.string())], ["doc_id", "score", "spans"])

    return map_batches(text_of(docs, "doc_id", text=text), run, "doc_id long, score double, spans string")


def spans(docs: DataFrame, tagger: Tagger, text: str = "text", least: float = 0.5) -> DataFrame:
    """(doc_id, first, last, span) of each toxic run of tokens: no row for null, empty and clean texts or an empty table."""
    shared = docs.sparkSession.sparkContext.broadcast(tagger)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text", AT_ONCE):
                texts = b.column("text").to_pylist()
                rows = [(k, a, z, t[a:z]) for k, t, r in zip(b.column("doc_id").to_pylist(), texts, shared.value.judge(texts, least)[1], strict=True) for a, z in r]
                cols = list(zip(*rows, strict=True)) or [[]] * 4
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, [pa.int64(), pa.int64(), pa.int64(), pa.string()], strict=True)], ["doc_id", "first", "last", "span"])

    return map_batches(text_of(docs, "doc_id", text=text), run, "doc_id long, first long, last long, span string")


def classify(docs: DataFrame, labels: DataFrame, text: str = "text", target: str = "toxic", cut: float = 0.5) -> DataFrame:
    """(doc_id, held_out, score, predicted, spans) of each row of ``docs``; spans are the offending offsets. A null doc_id
    is not held out.

    Without labels of both classes the score is that of an unfitted model. An empty table gives an
    empty table; repeated rows give repeated results.
    """
    out = score(docs, fit(docs, labels, text, target), text)
    return out.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= cut).cast("int").alias("predicted"), "spans")


def keep_clean(docs: DataFrame, labels: DataFrame, text: str = "text", key: str = "doc_id", cut: float = 0.5) -> DataFrame:
    """The rows of ``docs`` whose text the model does not call toxic, scored in place: no join, no shuffle. Null texts are
    judged as empty ones; repeated rows stay or go together; an empty table stays empty."""
    shared = docs.sparkSession.sparkContext.broadcast(fit(docs.withColumnRenamed(key, "doc_id"), labels, text))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, text, AT_ONCE):
                yield b.filter(pa.array(shared.value.score([t or "" for t in b.column(text).to_pylist()]) < cut))

    return map_batches(docs, run, docs.schema)
