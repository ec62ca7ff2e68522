"""Personal data by weak supervision.

Fixed patterns give the base spans of four kinds. Wider patterns propose further candidates
(secrets after a telling word, national numbers, account numbers, spelt-out addresses,
local phone numbers, names). On every candidate labelers vote: its shape, a checksum, gazetteers
and the words around it, each for, against or not at all. Expectation-maximisation over the counts
of vote patterns estimates how reliable each labeler is; its posteriors train a
logistic classifier on features of the span, which decides what is added to the base spans.

Votes and features have few values, so all that leaves the executors for fitting is a
table of patterns and counts, whose size the design bounds.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eventpulse.llm.arrow import map_batches, slices, text_of

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "secret", "national_id", "iban", "email_spelt", "phone_local", "name")

_LOCAL = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-"
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+").finditer
_DOTTED = re.compile(r"[0-9]++(?:\.[0-9]++)*+").finditer
_SPACED = re.compile(r"[0-9]++(?:[ -][0-9]++)*+").finditer
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]").finditer
_DIGIT = re.compile("[0-9]").search
_NO_DIGIT = re.compile(r"[^0-9]+")


def luhn(digits: str) -> bool:
    """Whether a string of digits passes the checksum of card numbers."""
    odd = sum(map(int, digits[-1::-2]))
    even = sum(sum(divmod(2 * int(d), 10)) for d in digits[-2::-2])
    return (odd + even) % 10 == 0


def _emails(text: str) -> Iterator[tuple[int, int]]:
    done = 0
    for m in _DOMAIN(text):
        at = m.start()
        lo = max(done, text.rfind("@", done, at) + 1)
        run = text[lo:at]
        size = len(run) - len(run.rstrip(_LOCAL))
        if size:
            done = m.end()
            yield at - size, done


def _numbers(text: str) -> Iterator[tuple[str, int, int, bool]]:
    """(kind, start, end, passed) of dotted quads and of spaced digit groups."""
    for m in _DOTTED(text):
        parts = m.group().split(".")
        at = m.start()
        for k in range(0, len(parts) - 3, 4):
            four = parts[k : k + 4]
            end = at + sum(map(len, four)) + 3
            yield "ip", at, end, all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in four)
            at = end + 1
    for m in _SPACED(text):
        if m.end() - m.start() >= 14:
            digits = _NO_DIGIT.sub("", m.group())
            if 14 <= len(digits) <= 19:
                yield "card", m.start(), m.end(), luhn(digits)


def base_matches(text: str) -> list[tuple[str, int, int, bool]]:
    """(kind, start, end, passed): the leftmost matches of each kind that do not overlap,
    with the failing ones marked. Runs in time linear in the text."""
    out = [("email", a, z, True) for a, z in _emails(text)] if "@" in text else []
    if not _DIGIT(text):
        return out
    out += _numbers(text)
    if "+" in text:
        out += [("phone", m.start(), m.end(), 10 <= len(_NO_DIGIT.sub("", m.group())) <= 15) for m in _PHONE(text)]
    return out


#: Words of the labelers and patterns.
SECRET_WORDS = ("token", "secret", "password", "passwd", "pwd", "api_key", "apikey", "api-key", "access_key", "private_key")
HONORIFICS = ("Mr", "Mrs", "Ms", "Dr", "Prof", "Herr", "Frau", "Monsieur", "Madame", "Señor", "Señora")
NAME_LEADS = ("name is", "name:", "my name", "called", "contact", "signed", "regards,", "sincerely,")
GIVEN_NAMES = ("James", "Mary", "John", "Patricia", "Robert", "Jennifer", "Michael", "Linda", "David", "Elizabeth", "William", "Barbara", "Richard", "Susan", "Joseph", "Jessica", "Thomas", "Sarah", "Anna", "Maria", "Peter", "Paul", "Hans", "Klaus", "Ursula", "Jean", "Marie", "Pierre", "Jacques", "Claire", "José", "Carmen", "Juan", "Luis", "Ana", "Elena", "Emma", "Olivia", "Noah", "Liam")
TOP_DOMAINS = ("com", "org", "net", "edu", "gov", "io", "de", "fr", "es", "uk", "ca", "us", "info", "eu")
CONTEXT = {
    "email": ("mail", "contact", "write", "reach"), "ip": ("ip", "host", "server", "login", "address"),
    "card": ("card", "visa", "mastercard", "amex", "credit", "payment"), "phone": ("phone", "call", "tel", "mobile", "fax", "whatsapp"),
    "secret": SECRET_WORDS, "national_id": ("ssn", "social", "security", "national", "id", "passport"), "iban": ("iban", "account", "bank", "transfer"),
    "email_spelt": ("mail", "contact", "write", "reach"), "phone_local": ("phone", "call", "tel", "mobile", "fax"), "name": NAME_LEADS,
}
AGAINST = ("version", "isbn", "order", "page", "section", "price", "total", "figure", "chapter", "build", "serial")

_WIDE = re.compile(
    r"(?P<secret>(?i:" + "|".join(map(re.escape, SECRET_WORDS)) + r")[\"']?[ \t]{0,3}[=:][ \t]{0,3}[\"']?(?P<value>[A-Za-z0-9_\-./+]{8,}+))"
    r"|(?P<name>\b(?:" + "|".join(HONORIFICS) + r")\.? [A-Z][\w'-]++(?: [A-Z][\w'-]++)?"
    r"|\b(?i:my name is|name:) [A-Z][\w'-]++(?: [A-Z][\w'-]++)?"
    r"|\b(?:" + "|".join(GIVEN_NAMES) + r") [A-Z][\w'-]++)"
).search
_SPELT_AT = re.compile(r" ?(?:\(at\)|\[at\]) ?[A-Za-z0-9-]++(?: ?(?:\(dot\)|\[dot\]|\.) ?[A-Za-z0-9-]++)++").finditer
_SPELT_FROM = re.compile(r"\b[A-Za-z0-9._%+-]").search
_CAPITAL = re.compile(r"\b[A-Z]\w+").findall
_NAMES = frozenset([*HONORIFICS, *GIVEN_NAMES])
_SIGNS = (*SECRET_WORDS, "name", "(at)", "[at]")


def _spelt(text: str, done: int) -> tuple[int, int] | None:
    """The first address with a spelt-out sign from ``done``. What precedes the sign is read backwards from it."""
    for m in _SPELT_AT(text, done):
        at = lo = m.start()
        while lo > done and text[lo - 1] in _LOCAL:
            lo -= 1
        first = _SPELT_FROM(text, lo, at)
        if first:
            return first.start(), m.end()
    return None


def _wider(text: str) -> Iterator[tuple[str, int, int]]:
    """(kind, start, end): the leftmost secrets, names and spelt-out addresses that do not overlap."""
    wide, spelt = _WIDE(text), _spelt(text, 0) if "(at)" in text or "[at]" in text else None
    while wide or spelt:
        if wide and not (spelt and spelt[0] < wide.start()):
            done = wide.end()
            yield ("secret", *wide.span("value")) if wide["secret"] else ("name", *wide.span())
        else:
            done = spelt[1]
            yield "email_spelt", *spelt
        wide = _WIDE(text, done) if wide and wide.start() < done else wide
        spelt = _spelt(text, done) if spelt and spelt[0] < done else spelt


def _wide_possible(text: str) -> bool:
    """Whether the text holds a word that every match of the wide patterns contains."""
    low = text.lower()
    return any(s in low for s in _SIGNS) or not _NAMES.isdisjoint(_CAPITAL(text))


_NATIONAL = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])").finditer
_LOCAL_PHONE = re.compile(r"(?<![0-9+(.-])\(?[0-9]{3}\)?[ .-][0-9]{3}[.-][0-9]{4}(?![0-9-])").finditer
_IBAN = re.compile(r"\b[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b").finditer


def candidates(text: str) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int, bool]]]:
    """The base spans, and further candidates (kind, start, end, shape holds) outside them and each other, leftmost
    first. One sweep over both, sorted by start."""
    matches = base_matches(text)
    base = [(k, a, z) for k, a, z, ok in matches if ok]
    more = [m for m in matches if not m[3]]
    if _DIGIT(text):
        more += [("national_id", m.start(), m.end(), True) for m in _NATIONAL(text)] if "-" in text else []
        more += [("phone_local", m.start(), m.end(), True) for m in _LOCAL_PHONE(text)] if "-" in text or "." in text else []
        more += [("iban", m.start(), m.end(), True) for m in _IBAN(text)]
    if _wide_possible(text):
        more += [(*m, True) for m in _wider(text)]
    taken: list[list[int]] = []  # the base spans' union, as spans that do not touch
    for _, x, y in sorted(base, key=lambda m: m[1]):
        if taken and x < taken[-1][1]:
            taken[-1][1] = max(taken[-1][1], y)
        else:
            taken.append([x, y])
    free, done, i = [], 0, 0
    for kind, x, y, ok in sorted(more, key=lambda m: (m[1], KINDS.index(m[0]))):
        while i < len(taken) and taken[i][1] <= x:
            i += 1
        if x >= done and not (i < len(taken) and taken[i][0] < y):
            free.append((kind, x, y, ok))
            done = y
    return base, free


def _iban_ok(s: str) -> bool:
    s = s.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


#: Labelers, in the order of the votes.
LABELERS = ("shape", "checksum", "gazetteer", "context", "counter_context", "randomness")


def votes(text: str, kind: str, a: int, z: int, passed: bool) -> tuple[int, ...]:
    """For (1), against (-1) or no vote (0), by labeler."""
    span, before, after = text[a:z], text[max(0, a - 40) : a].lower(), text[z : z + 12]
    shape = 1 if passed else -1
    checksum = gazetteer = randomness = 0
    if kind == "card":
        checksum = 1 if passed else -1
    elif kind == "iban":
        checksum = 1 if _iban_ok(span) else -1
    if kind == "email":
        gazetteer = 1 if span.rsplit(".", 1)[-1].lower() in TOP_DOMAINS else 0
    elif kind == "name":
        gazetteer = 1 if any(w in GIVEN_NAMES for w in re.split(r"\W+", span)) else 0
    elif kind == "national_id":
        gazetteer = -1 if span[:3] in ("000", "666") or span[0] == "9" else 1
    if kind == "secret":
        digits = sum(c.isdigit() for c in span)
        randomness = 1 if len(set(span)) >= 8 and (digits >= 3 or len(span) >= 20) else -1
    context = 1 if any(w in before for w in CONTEXT[kind]) else 0
    counter = -1 if any(w in before for w in AGAINST) or after[:1] in "%€$£" and after[:1] else 0
    return shape, checksum, gazetteer, context, counter, randomness


def features(text: str, kind: str, a: int, z: int, passed: bool) -> tuple[int, ...]:
    """A few small integers that describe a span: kind, length, digits, cases, neighbours."""
    span = text[a:z]
    n = z - a
    digits, upper = sum(c.isdigit() for c in span), sum(c.isupper() for c in span)
    left, right = text[a - 1 : a], text[z : z + 1]
    near = text[max(0, a - 40) : a].lower()
    return (KINDS.index(kind), min(n.bit_length(), 7), 4 * digits // max(n, 1), 4 * upper // max(n, 1), int(bool(left) and left.isalnum()), int(bool(right) and right.isalnum()), int(any(w in near for w in CONTEXT[kind])), int(passed))


_WIDTHS = (len(KINDS), 8, 5, 5, 2, 2, 2, 2)


def _row(f: tuple[int, ...]) -> np.ndarray:
    x = np.zeros(sum(_WIDTHS) + 1)
    x[-1] = 1
    for at, v in zip(np.cumsum([0, *_WIDTHS[:-1]]), f, strict=True):
        x[at + v] = 1
    return x


def estimate(table: list[tuple[tuple[int, ...], int]], rounds: int = 60) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(posterior of each vote pattern, reliability and coverage of each labeler) by expectation-maximisation.

    A labeler that votes is right with its reliability, whichever the truth. Reliabilities
    start at 0.8 and are held by a prior worth 20 votes, so that the classes keep their meaning.
    """
    v = np.array([p for p, _ in table], dtype=float).reshape(len(table), len(LABELERS))
    n = np.array([c for _, c in table], dtype=float)
    right, share = np.full(v.shape[1], 0.8), 0.5
    post = np.full(len(table), 0.5)
    for _ in range(rounds):
        odds = math.log(share / (1 - share)) + v @ np.log(right / (1 - right))
        post = 1 / (1 + np.exp(-np.clip(odds, -30, 30)))
        hit = (n[:, None] * np.where(v > 0, post[:, None], np.where(v < 0, 1 - post[:, None], 0))).sum(0)
        cast = (n[:, None] * (v != 0)).sum(0)
        right = np.clip((hit + 16) / (cast + 20), 0.5, 0.99)
        share = float(np.clip((post @ n + 2) / (n.sum() + 4), 0.02, 0.98))
    return post, right, (n[:, None] * (v != 0)).sum(0) / max(n.sum(), 1)


def train(rows: list[tuple[tuple[int, ...], tuple[int, ...], int]], steps: int = 300) -> dict:
    """The span classifier from (votes, features, count) patterns: labeler reliabilities and weights."""
    pattern: Counter = Counter()
    for vote, _, c in rows:
        pattern[vote] += c
    table = sorted(pattern.items())
    post, right, cover = estimate(table)
    soft = {p: q for (p, _), q in zip(table, post, strict=True)}
    w = np.zeros(sum(_WIDTHS) + 1)
    if rows:
        x = np.array([_row(f) for _, f, _ in rows])
        y, n = np.array([soft[v] for v, _, _ in rows]), np.array([c for *_, c in rows], dtype=float)
        n = np.minimum(n, n.sum() / 20 + 1)  # a very frequent pattern does not silence the others
        n /= n.sum()
        for _ in range(steps):
            p = 1 / (1 + np.exp(-x @ w))
            h = x.T @ (x * (n * p * (1 - p))[:, None]) + 1e-3 * np.eye(len(w))
            step = np.linalg.solve(h, x.T @ (n * (p - y)) + 1e-3 * w)
            w -= step
            if np.abs(step).max() < 1e-8:
                break
    return {"weights": w, "reliability": dict(zip(LABELERS, right.tolist(), strict=True)), "coverage": dict(zip(LABELERS, cover.tolist(), strict=True))}


def fit(df: DataFrame, text: str = "text") -> dict:
    """Fit labelers and classifier on all texts of ``df``. What reaches the driver is a row for each
    distinct pattern of votes and features: a few thousand at most, whatever the input."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()
        for b in batches:
            for t in b.column("text"):
                s = t.as_py()
                base, free = candidates(s)
                for k, a, z, ok in [*[(*x, True) for x in base], *free]:
                    seen[votes(s, k, a, z, ok), features(s, k, a, z, ok)] += 1
        keys = list(seen)
        ints = pa.list_(pa.int32())
        yield pa.RecordBatch.from_arrays([pa.array([list(k[0]) for k in keys], ints), pa.array([list(k[1]) for k in keys], ints), pa.array([seen[k] for k in keys], pa.int64())], ["votes", "features", "n"])

    counted = map_batches(text_of(df, text=text), run, "votes array<int>, features array<int>, n long")
    rows = counted.groupBy("votes", "features").agg(F.sum("n").alias("n")).collect()
    return train(sorted((tuple(r["votes"]), tuple(r["features"]), r["n"]) for r in rows))


def find(text: str, model: dict, least: float = 0.5) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
    """(base spans, all spans) of a text, each sorted by start, then kind."""
    base, free = candidates(text)
    w = model["weights"]
    more = [(k, a, z) for k, a, z, ok in free if 1 / (1 + math.exp(-max(-30.0, min(30.0, float(_row(features(text, k, a, z, ok)) @ w))))) >= least]
    order = lambda s: (s[1], KINDS.index(s[0]))
    return sorted(base, key=order), sorted([*base, *more], key=order)


def _joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{z}" for k, a, z in spans)


SPANS = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"


def detect(df: DataFrame, model: dict | None = None, text: str = "text") -> DataFrame:
    """The spans of each text of ``df``, by a model that is fitted on ``df`` if none is given.

    Offsets are code points, ends exclusive. Null texts count as empty and hold no span; repeated
    rows give repeated results; an empty table gives an empty table (and a model without candidates).
    """
    model = model or fit(df, text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [f.split()[0] for f in SPANS.split(", ")]
        types = [*[pa.int64()] * 4, pa.string(), pa.string()]
        for whole in batches:
            for b in slices(whole, "text"):
                rows = []
                for t in b.column("text"):
                    base, every = find(t.as_py(), model)
                    n = Counter(k for k, _, _ in base)
                    rows.append((*[n[k] for k in BASE], hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(every)))
                cols = list(zip(*rows, strict=True)) or [[] for _ in types]
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), *[pa.array(c, t) for c, t in zip(cols, types, strict=True)]], names)

    return map_batches(text_of(df, "doc_id", text=text), run, SPANS)


def masked(text: str, spans: list[tuple[str, int, int]]) -> str:
    """The text with each span replaced by its kind in brackets; overlapping spans are replaced as one."""
    out, at = [], 0
    for kind, a, z in spans:
        if a >= at:
            out += [text[at:a], f"[{kind.upper()}]"]
        at = max(at, z)
    return "".join([*out, text[at:]])


def redact(df: DataFrame, model: dict | None = None, text: str = "text", length: str = "n_chars") -> DataFrame:
    """``df`` with all spans masked. Null texts stay null; ``length``, if a column, follows the text. Repeated rows
    give repeated results, an empty table an empty one."""
    model = model or fit(df, text)
    names = df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, text):
                new = [None if t is None else masked(t, find(t, model)[1]) for t in b.column(text).to_pylist()]
                yield pa.RecordBatch.from_arrays([pa.array(new, pa.string()) if n == text else b.column(i) for i, n in enumerate(names)], names)

    out = map_batches(df, run, df.schema)
    return out.withColumn(length, F.length(text).cast(df.schema[length].dataType)) if length in names else out
