"""Byte-level BPE encoding and decoding by a prefix-sharing walk over distinct words.

The encoding of a word's prefix ends in exactly one token t such that t "stays apart"
from the last token of what precedes it; so a word's encoding follows from the last tokens of
its prefixes. Distinct words are sorted, which is a depth-first walk of their trie: a
stack holds, for each byte of the current path, the last token of that prefix, and words
that share a prefix share its part of the stack. Each trie node is thus computed once.

Two tokens stay apart if no merge crosses their boundary while they are built: the right
edge of the first and the left edge of the second grow by merges of known ranks, and a pair
of neighbours that exist together merges if its rank comes before what would grow either.
"""

from __future__ import annotations

import hashlib
import json
from array import array
from collections.abc import Iterable, Iterator
from functools import lru_cache
from os.path import commonprefix

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from eventpulse.llm.arrow import map_batches, slices, text_of

#: Fixed value: the published split pattern of this kind of tokenizer, white space spelt out.
SPLIT = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
#: Texts with other characters are split by the library, whose Unicode tables may be of another age.
PLAIN = r"[^\x00-ɏΑ-Ρα-ωА-я -⁣₠-₿]"
#: Distinct words in each of the two generations that a worker remembers.
REMEMBERED = 150_000
#: Pairs of tokens whose verdict a worker remembers.
PAIRS = 400_000


def _byte_alphabet() -> dict[str, int]:
    """The printable stand-in of each byte in this kind of vocabulary file, by rule."""
    shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    hidden = [b for b in range(256) if b not in shown]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


class ByteBpe:
    """A byte-level BPE vocabulary read from a tokenizers file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        back = _byte_alphabet()
        as_bytes = lambda s: bytes(back[c] for c in s)
        model = spec["model"]
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        vocab = {s: i for s, i in model["vocab"].items() if s not in self.special}
        self.ids = {as_bytes(s): i for s, i in vocab.items()}
        self.longest = max(map(len, self.ids))
        self.bytes = [b""] * (max([*self.ids.values(), *self.special.values()]) + 1)
        for b, i in self.ids.items():
            self.bytes[i] = b
        for s, i in self.special.items():
            self.bytes[i] = s.encode()
        self.rank: dict[tuple[int, int], int] = {}
        parts: dict[int, tuple[int, int, int]] = {}
        for r, m in enumerate(model["merges"]):
            a, b = m.split(" ") if isinstance(m, str) else m
            pair = vocab[a], vocab[b]
            self.rank[pair] = r
            parts.setdefault(vocab[a + b], (*pair, r))
        never = len(self.rank) + 1
        # edges: from the outermost byte to the whole token, each with the rank at which it is absorbed
        self.left: list[list[tuple[int, int]]] = [[] for _ in self.bytes]
        self.right: list[list[tuple[int, int]]] = [[] for _ in self.bytes]
        for t in vocab.values():
            for side, edges in ((0, self.left), (1, self.right)):
                x, found = t, [(t, never)]
                while x in parts:
                    found.append((parts[x][side], parts[x][2]))
                    x = parts[x][side]
                edges[t] = found[::-1]
        self.apart: dict[int, bool] = {}
        self.packed = [i.to_bytes(4, "little") for i in range(len(self.bytes))]
        self.words: dict[str, bytes] = {}
        self.former: dict[str, bytes] = {}
        self.split = regex.compile(SPLIT).findall
        self.unusual = regex.compile(PLAIN).search
        self.at_special = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")").split if self.special else None
        self.path, self._library = path, None

    def _stay_apart(self, a: int, b: int) -> bool:
        right, left, rank = self.right[a], self.left[b], self.rank
        i = j = 0
        while True:
            (x, x_end), (y, y_end) = right[i], left[j]
            r = rank.get((x, y))
            if r is not None and r < x_end and r <= y_end:
                return False
            if i + 1 == len(right) and j + 1 == len(left):
                return True
            if x_end <= y_end:
                i += 1
            else:
                j += 1

    def encode_words(self, words: Iterable[bytes]) -> Iterator[tuple[bytes, list[int]]]:
        """(word, ids) of distinct words, in sorted order; nodes of their trie are computed once."""
        ids, apart, longest = self.ids, self.apart, self.longest
        last, starts, before = [-1], [0], b""  # by depth: last token of that prefix and where it begins
        for w in sorted(words):
            shared = len(commonprefix((before, w)))
            del last[shared + 1 :], starts[shared + 1 :]
            for end in range(shared + 1, len(w) + 1):
                for start in range(end - 1, max(0, end - longest) - 1, -1):  # the shortest is most often right
                    t = ids.get(w[start:end])
                    if t is None:
                        continue
                    p = last[start]
                    if p < 0:
                        break
                    ok = apart.get(p << 20 | t)
                    if ok is None:
                        if len(apart) > PAIRS:
                            apart.clear()
                        ok = apart[p << 20 | t] = self._stay_apart(p, t)
                    if ok:
                        break
                else:
                    raise ValueError(f"no token ends the prefix {w[:end]!r}")
                last.append(t)
                starts.append(start)
            out, at = [], len(w)
            while at:
                out.append(last[at])
                at = starts[at]
            yield w, out[::-1]
            before = w

    def _pieces(self, text: str) -> list[str]:
        if not self.unusual(text):
            return self.split(text)
        if self._library is None:
            from tokenizers import Tokenizer

            self._library = Tokenizer.from_file(self.path).pre_tokenizer
        return [text[a:z] for _, (a, z) in self._library.pre_tokenize_str(text)]

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit integers."""
        split: list[list[str]] = []
        for text in texts:
            if self.at_special and any(s in text for s in self.special):
                parts: list[str] = []
                for part in self.at_special(text):
                    parts += [part] if part in self.special else self._pieces(part) if part else []
                split.append(parts)
            else:
                split.append(self._pieces(text))
        if len(self.words) > REMEMBERED:  # words that come again within a generation live on
            self.former, self.words = self.words, {}
        known, former = self.words, self.former
        for s, i in self.special.items():
            known[s] = self.packed[i]
        new = {w for parts in split for w in parts if w not in known}
        packed = self.packed
        for w, ids in self.encode_words([w.encode() for w in new]):
            known[w.decode()] = b"".join([packed[i] for i in ids])
        return [b"".join(map(known.__getitem__, parts)) for parts in split]

    def decode(self, ids: bytes) -> str:
        """The text of packed ids; bytes that are no UTF-8 become replacement characters."""
        return b"".join(map(self.bytes.__getitem__, array("I", ids))).decode("utf-8", "replace")


@lru_cache(maxsize=4)
def load(path: str) -> ByteBpe:
    """The vocabulary at ``path``, read once by each worker."""
    return ByteBpe(path)


DIGESTS = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def digests(df: DataFrame, path: str, text: str = "text") -> DataFrame:
    """Token count and digests of the ids and of the decoded text, for each row of ``df``.

    Special strings inside a text become their own ids, as the library has it. Null texts count as
    empty, an empty text has no token; repeated rows give repeated results, an empty table gives an empty
    table. ``path`` names the vocabulary file on every executor.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe, names = load(path), [f.split()[0] for f in DIGESTS.split(", ")]
        for whole in batches:
            for b in slices(whole, "text"):
                ids = bpe.encode_batch(b.column("text").to_pylist())
                yield pa.RecordBatch.from_arrays([
                    b.column("doc_id"), pa.array([len(x) // 4 for x in ids], pa.int64()),
                    pa.array([hashlib.sha256(x).hexdigest() for x in ids], pa.string()),
                    pa.array([hashlib.sha256(bpe.decode(x).encode()).hexdigest() for x in ids], pa.string()),
                ], names)

    return map_batches(text_of(df, "doc_id", text=text), run, DIGESTS)


def encode(df: DataFrame, path: str, text: str = "text") -> DataFrame:
    """(doc_id, ids array<int>) of each text; a null text has none, an empty table gives an empty table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for whole in batches:
            for b in slices(whole, "text"):
                ids = [array("i", x).tolist() for x in bpe.encode_batch(b.column("text").to_pylist())]
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    return map_batches(text_of(df, "doc_id", text=text), run, "doc_id long, ids array<int>")


def decode(df: DataFrame, path: str, ids: str = "ids") -> DataFrame:
    """(doc_id, text) of each row's ids; null ids give a null text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for b in batches:
            texts = [None if x is None else bpe.decode(array("I", x).tobytes()) for x in b.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(texts, pa.string())], ["doc_id", "text"])

    return map_batches(df.selectExpr("doc_id", f"`{ids}` as ids"), run, "doc_id long, text string")
