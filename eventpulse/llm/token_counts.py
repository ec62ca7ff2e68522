"""Token counts of huge texts by overlap resynchronisation.

A text is encoded as chunks, each beginning inside the one before, and every chunk gives
tokens with offsets. Two neighbouring encodings are spliced in their overlap at a boundary p that

* the tokenizer cannot reach across: a printed character ends before p and white space begins at p. This is
  proven from the tokenizer's own file (:func:`blank_rule`), not assumed;
* both encodings resynchronise at: from p to the last such boundary before the left chunk's
  end, both have the same tokens at the same offsets, ``AGREE`` of them at least.

Left of p the left encoding counts, from p on the right one. Where no boundary does, the overlap is
doubled, up to one chunk made of both. A file for which nothing can be proven has no such boundary, so
its texts grow into one chunk: slower, and right.

The chunk encoder of files that drop white space remembers the encodings (ids and
offsets) of a bounded number of words, as the library's model does behind its far dearer pre-tokenizer;
words it has not met are encoded by the library, with offsets. Other files are encoded by their library,
chunk by chunk.
"""

from __future__ import annotations

import json
import os
import re
from collections.abc import Iterator
from functools import lru_cache
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from eventpulse.llm.arrow import map_batches, slices, text_of

CHUNK, OVERLAP, AGREE, LIMIT = 16_384, 256, 4, 2048
#: Distinct words a worker remembers before it starts anew, and how many new ones are encoded as one text.
REMEMBERED, TOGETHER = 500_000, 200
#: The ASCII white space.
BLANKS = " \t\n\r\x0b\x0c"
_BLANK = str.maketrans(dict.fromkeys(BLANKS, " "))
_OTHER = re.compile(r"[\t-\r]").search
#: Where white space begins behind a character that no tokenizer's table takes for white space.
_EDGE = re.compile(r"(?<=[!-~\w])(?=[ \t-\r])").finditer
#: Alternatives of a split pattern that match no white space.
_SOLID = {r"[\p{L}]+", r"[\p{N}]", r"[^\s\p{L}\p{N}]+"}


class Encoding(NamedTuple):
    """Token ids of a piece of text and where in the piece each token begins."""

    ids: np.ndarray
    starts: np.ndarray


def _parts(spec: dict | None, inner: str) -> list[dict]:
    return [] if spec is None else [p for s in spec[inner] for p in _parts(s, inner)] if spec["type"] == "Sequence" else [spec]


def blank_rule(spec: dict) -> str | None:
    """What a tokenizers file does where white space follows a printed character: ``dropped`` (white space is no part of
    any token), ``leads`` (it begins the next token) or None if that cannot be proven."""
    for t in spec.get("added_tokens") or []:
        if t["lstrip"] or t["rstrip"] or t["single_word"] or any(c.isspace() for c in t["content"]):
            return None
    for n in _parts(spec.get("normalizer"), "normalizers"):
        if n["type"] not in ("NFC", "Lowercase") and (n["type"], n.get("pattern"), n.get("content")) != ("Replace", {"Regex": "\\s+"}, " "):
            return None
    model, pre = spec["model"], _parts(spec.get("pre_tokenizer"), "pretokenizers")
    if model["type"] != "BPE" or model.get("dropout") or any(p.get("add_prefix_space") for p in pre):
        return None
    if [(p["type"], p.get("use_regex")) for p in pre] == [("ByteLevel", True)]:
        return "leads"  # the published pattern: no alternative goes on from a printed character to a white one
    if [(p["type"], p.get("use_regex")) for p in pre] == [("Split", None), ("ByteLevel", False)]:
        split = pre[0]
        solid = all(a in _SOLID or re.fullmatch("'?[a-z]+", a) for a in split["pattern"].get("Regex", " ").split("|"))
        return "dropped" if solid and split["invert"] and split["behavior"] == "Removed" else None
    return None


class LibraryEncoder:
    """Chunks encoded by the tokenizers library."""

    def __init__(self, tok, proven: bool):
        self.tok, self.proven = tok, proven

    def encode(self, pieces: list[str]) -> list[Encoding]:
        found = self.tok.encode_batch(pieces, add_special_tokens=False)
        return [Encoding(np.array(e.ids, dtype=np.int64), np.array([a for a, _ in e.offsets], dtype=np.int64)) for e in found]


class PieceEncoder:
    """Chunks encoded by sentencepiece. White space is proven to begin tokens if no piece holds it behind another character."""

    def __init__(self, path: str):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces = map(self.model.id_to_piece, range(self.model.get_piece_size()))
        self.proven = not any(re.search("[^▁]▁", p) for p in pieces)

    def encode(self, pieces: list[str]) -> list[Encoding]:
        found = [self.model.encode(p, return_type="offset_mapping") for p in pieces]
        return [Encoding(np.array(e["ids"], dtype=np.int64), np.array([a for a, _ in e["offsets"]], dtype=np.int64)) for e in found]


class Growing:
    """Integers that are appended to, in a buffer that doubles."""

    def __init__(self):
        self.buffer, self.size = np.zeros(1024, dtype=np.int64), 0

    def extend(self, more: np.ndarray) -> None:
        end = self.size + len(more)
        if end > len(self.buffer):
            self.buffer = np.concatenate([self.buffer[: self.size], np.zeros(max(end, 2 * self.size) - self.size, dtype=np.int64)])
        self.buffer[self.size : end] = more
        self.size = end


class WordEncoder:
    """Chunks of a tokenizer that drops white space: encodings of words, remembered with their offsets."""

    def __init__(self, tok, remembered: int = REMEMBERED):
        self.library, self.remembered, self.proven = LibraryEncoder(tok, True), remembered, True
        self._forget()

    def _forget(self) -> None:
        """Word 0 is the empty one between two blanks."""
        self.place = {"": 0}
        self.n, self.first, self.ids, self.starts = (Growing() for _ in range(4))
        self.n.extend(np.zeros(1))
        self.first.extend(np.zeros(1))

    def _learn(self, words: list[str]) -> None:
        if len(self.place) > self.remembered:
            self._forget()
        new = list(set(words).difference(self.place))
        if not new:
            return
        self.place.update(zip(new, range(self.n.size, self.n.size + len(new)), strict=True))
        texts = [new[i : i + TOGETHER] for i in range(0, len(new), TOGETHER)]
        for own, e in zip(texts, self.library.encode([" ".join(t) for t in texts]), strict=True):
            size = np.fromiter(map(len, own), dtype=np.int64, count=len(own)) + 1
            at = np.cumsum(size) - size
            word = np.searchsorted(at, e.starts, side="right") - 1
            n = np.bincount(word, minlength=len(own))
            self.n.extend(n)
            self.first.extend(self.ids.size + np.cumsum(n) - n)
            self.ids.extend(e.ids)
            self.starts.extend(e.starts - at[word])

    def encode(self, pieces: list[str]) -> list[Encoding]:
        text = " ".join(pieces)
        words = (text.translate(_BLANK) if _OTHER(text) else text).split(" ")
        self._learn(words)
        which = np.fromiter(map(self.place.__getitem__, words), dtype=np.int64, count=len(words))
        at = np.cumsum([0, *map(len, words)])[:-1] + np.arange(len(words))
        n = self.n.buffer[which]
        own = np.arange(int(n.sum())) + np.repeat(self.first.buffer[which] - (np.cumsum(n) - n), n)
        ids, starts = self.ids.buffer[own], self.starts.buffer[own] + np.repeat(at, n)
        ends = np.cumsum([len(p) + 1 for p in pieces])
        cut = np.concatenate([[0], np.searchsorted(starts, ends)])
        return [Encoding(ids[a:z], starts[a:z] - (end - len(p) - 1)) for p, a, z, end in zip(pieces, cut[:-1].tolist(), cut[1:].tolist(), ends.tolist(), strict=True)]


@lru_cache(maxsize=4)
def encoder(path: str) -> LibraryEncoder | PieceEncoder | WordEncoder:
    """The chunk encoder of a tokenizer file (``.json`` or ``.model``), read once by each worker."""
    if path.endswith(".model"):
        return PieceEncoder(path)
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(path)
    tok.no_truncation()
    tok.no_padding()
    with open(path, encoding="utf-8") as f:
        rule = blank_rule(json.load(f))
    return WordEncoder(tok) if rule == "dropped" else LibraryEncoder(tok, rule is not None)


class Counted(NamedTuple):
    """Tokens of a text, the splices that joined its chunks, and how often an overlap was widened."""

    n: int
    splices: int = 0
    widened: int = 0


def _resynchronised(text: str, lo: int, hi: int, left: Encoding, right: Encoding, agree: int) -> int | None:
    """A proven boundary in (lo, hi) from which both encodings have the same tokens up to the last one in it.
    Starts are offsets in ``text``; the right piece begins at lo, the left one ends at hi."""
    edges = [m.start() + lo for m in _EDGE(text[lo:hi]) if m.start()]
    if len(edges) < 2:
        return None
    a, b = ((e.ids[(e.starts >= edges[0]) & (e.starts < edges[-1])], e.starts[(e.starts >= edges[0]) & (e.starts < edges[-1])]) for e in (left, right))
    for p in edges[:-1]:
        x, y = a[1] >= p, b[1] >= p
        if x.sum() < agree:
            return None
        if np.array_equal(a[0][x], b[0][y]) and np.array_equal(a[1][x], b[1][y]):
            return p
    return None


def count_long(enc, text: str, chunk: int = CHUNK, overlap: int = OVERLAP, agree: int = AGREE) -> Counted:
    """Tokens of ``text``, of which a chunk is encoded at once. Without a place to splice at, a chunk doubles."""
    begin, end, counted_from = 0, min(len(text), chunk), 0
    total = splices = widened = 0
    at = lambda lo, hi: Encoding((e := enc.encode([text[lo:hi]])[0]).ids, e.starts + lo)
    left = at(begin, end)
    while end < len(text):
        width, p = overlap, None
        while enc.proven and end - width > begin:
            lo, hi = end - width, min(len(text), end - width + max(chunk, 2 * width))
            right = at(lo, hi)
            p = _resynchronised(text, lo, end, left, right, agree)
            if p is not None:
                break
            width, widened = 2 * width, widened + 1
        if p is None:  # one chunk made of both, twice as long
            lo, hi, p = begin, min(len(text), end + max(chunk, end - begin)), counted_from
            right, widened = at(lo, hi), widened + 1
        else:
            total += int(((left.starts >= counted_from) & (left.starts < p)).sum())
            splices += 1
        left, begin, end, counted_from = right, lo, hi, p
    return Counted(total + int((left.starts >= counted_from).sum()), splices, widened)


def count_texts(enc, texts: list[str], chunk: int = CHUNK, overlap: int = OVERLAP, agree: int = AGREE) -> list[Counted]:
    """The tokens of each text. A text within a chunk is one chunk; such texts are encoded together."""
    short = iter(enc.encode([t for t in texts if len(t) <= chunk]))
    return [Counted(len(next(short).ids)) if len(t) <= chunk else count_long(enc, t, chunk, overlap, agree) for t in texts]


COUNTS = "doc_id long, n_bytes long, n_tokens long, over_limit boolean, splices long, widened long"


def counts(df: DataFrame, path: str, text: str = "text", chunk: int = CHUNK, overlap: int = OVERLAP, limit: int = LIMIT) -> DataFrame:
    """UTF-8 length and token count of each text, whether it exceeds ``limit`` tokens, and how its chunks were joined.

    Null texts count as empty; empty ones have no token; repeated rows give repeated results, an
    empty table gives an empty table, other columns of ``df`` play no part. ``path`` names the tokenizer file on every executor.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, names = encoder(path), [f.split()[0] for f in COUNTS.split(", ")]
        for whole in batches:
            for b in slices(whole, "text"):
                texts = b.column("text").to_pylist()
                found = count_texts(enc, texts, chunk, overlap)
                yield pa.RecordBatch.from_arrays([
                    b.column("doc_id"), pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array([c.n for c in found], pa.int64()),
                    pa.array([c.n > limit for c in found], pa.bool_()), pa.array([c.splices for c in found], pa.int64()), pa.array([c.widened for c in found], pa.int64()),
                ], names)

    return map_batches(text_of(df, "doc_id", text=text), run, COUNTS)
