"""Media columns: AVI files of losslessly coded motion-JPEG frames.

A payload becomes 8-bit grey frames, each a JPEG of the lossless kind (SOF3, predictor
1), in an AVI file with an ``idx1`` index. The Huffman table gives the difference of
category s a code of 9 - s bits, so that each sample takes nine bits, code and
extra bits together: a regular JPEG table that numpy can write and read without a loop over
samples. The length of the payload stands in an INFO chunk.

Frames of other writers are read as well, sample by sample: lossless ones with any Huffman table and predictor, and baseline or
extended sequential ones. Reading walks the RIFF tree, takes the frames through the index, decodes them and cuts shots
where the difference of successive histograms stands out from its surroundings.
"""

from __future__ import annotations

import hashlib
import math
import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eventpulse.llm.arrow import map_batches, text_of

WIDTH, MOST_ROWS, FPS = 64, 64, 25
#: Shots: histogram bins, frames on either side that set the threshold, and its factors.
BINS, AROUND, SIGMAS, LEAST = 16, 8, 2.5, 0.15
#: Fixed values of the JPEG format: markers.
SOI, EOI, SOF3, DHT, SOS, DQT, DRI, SOF_DCT = b"\xff\xd8", b"\xff\xd9", 0xC3, 0xC4, 0xDA, 0xDB, 0xDD, (0xC0, 0xC1)
_CODES = np.array([(1 << (9 - s)) - 2 for s in range(9)], dtype=np.int64)  # category s: 8 - s ones, then a zero
_TABLE = bytes([0, *[1] * 9, *[0] * 7, *range(8, -1, -1)])


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def _residuals(frame: np.ndarray) -> np.ndarray:
    x = frame.astype(np.int16)
    d = np.empty_like(x)
    d[:, 1:] = x[:, 1:] - x[:, :-1]
    d[1:, 0] = x[1:, 0] - x[:-1, 0]
    d[0, 0] = x[0, 0] - 128
    return d


#: Nine-bit word of each difference from -255 to 255.
_WORD = np.empty(511, dtype=np.uint16)
for _d in range(-255, 256):
    _s = abs(_d).bit_length()
    _WORD[_d + 255] = (int(_CODES[_s]) << _s | (_d if _d >= 0 else _d + (1 << _s) - 1)) if _s else int(_CODES[0])
_DIFF = np.zeros(512, dtype=np.int16)
_DIFF[_WORD] = np.arange(-255, 256)
_SHIFTS = np.arange(8, -1, -1, dtype=np.uint16)


def encode_jpeg(frame: np.ndarray) -> bytes:
    """A lossless JPEG of an 8-bit grey frame."""
    rows, cols = frame.shape
    words = _WORD[_residuals(frame).ravel() + 255]
    bits = ((words[:, None] >> _SHIFTS) & 1).astype(np.uint8).ravel()
    pad = -len(bits) % 8
    scan = np.packbits(np.concatenate([bits, np.ones(pad, np.uint8)])).tobytes().replace(b"\xff", b"\xff\x00")
    return b"".join([
        SOI, _segment(SOF3, struct.pack(">BHHB", 8, rows, cols, 1) + b"\x01\x11\x00"), _segment(DHT, _TABLE),
        _segment(SOS, b"\x01\x01\x00\x01\x00\x00"), scan, EOI,
    ])


class _Bits:
    """The bits of an entropy-coded segment, from the first; ones follow its end."""

    def __init__(self, scan: bytes):
        self.data, self.at, self.held, self.n = scan.replace(b"\xff\x00", b"\xff"), 0, 0, 0

    def take(self, n: int) -> int:
        while self.n < n:
            self.held = self.held << 8 | (self.data[self.at] if self.at < len(self.data) else 255)
            self.at, self.n = self.at + 1, self.n + 8
        self.n -= n
        out = self.held >> self.n
        self.held &= (1 << self.n) - 1
        return out

    def symbol(self, table: dict[tuple[int, int], int]) -> int:
        code = 0
        for size in range(1, 17):
            code = code << 1 | self.take(1)
            if (size, code) in table:
                return table[size, code]
        raise ValueError("no code of the Huffman table")

    def signed(self, size: int) -> int:
        """A difference of category ``size``."""
        if size == 16:
            return 1 << 15
        v = self.take(size)
        return v if not size or v >> (size - 1) else v + 1 - (1 << size)


def _huffman(body: bytes) -> dict[int, dict[tuple[int, int], int]]:
    """{class and place of a table: {(length, code): symbol}} of a DHT segment."""
    out, at = {}, 0
    while at < len(body):
        which, counts, at = body[at], body[at + 1 : at + 17], at + 17
        table, code = {}, 0
        for size, n in enumerate(counts, 1):
            for _ in range(n):
                table[size, code] = body[at]
                code, at = code + 1, at + 1
            code <<= 1
        out[which] = table
    return out


def _quantizers(body: bytes) -> dict[int, np.ndarray]:
    out, at = {}, 0
    while at < len(body):
        wide, which = divmod(body[at], 16)
        out[which] = np.frombuffer(body, ">u2" if wide else "u1", 64, at + 1).astype(np.int64)
        at += 129 if wide else 65
    return out


def _parse(data: bytes) -> dict:
    """The segments of a JPEG up to its scan, and the scan's entropy-coded segments between restart markers."""
    if data[:2] != SOI:
        raise ValueError("no JPEG")
    out: dict = {"huffman": {}, "quantizers": {}, "restart": 0, "tables": b""}
    at = 2
    while "scan" not in out:
        ff, marker, size = struct.unpack_from(">BBH", data, at)
        if ff != 0xFF:
            raise ValueError("no JPEG marker")
        body = data[at + 4 : at + 2 + size]
        at += 2 + size
        if marker == DHT:
            out["tables"] += body
            out["huffman"] |= _huffman(body)
        elif marker == DQT:
            out["quantizers"] |= _quantizers(body)
        elif marker == DRI:
            out["restart"] = struct.unpack(">H", body)[0]
        elif 0xC0 <= marker <= 0xCF and marker not in (0xC8, 0xCC):
            if marker not in (*SOF_DCT, SOF3):
                raise ValueError("neither a sequential nor a lossless frame with Huffman codes")
            precision, rows, cols, n = struct.unpack_from(">BHHB", body)
            parts = [(body[6 + 3 * k], *divmod(body[7 + 3 * k], 16), body[8 + 3 * k]) for k in range(n)]
            out |= {"kind": marker, "precision": precision, "shape": (rows, cols), "parts": parts}
        elif marker == SOS:
            n = body[0]
            out["scan"] = {body[1 + 2 * k]: divmod(body[2 + 2 * k], 16) for k in range(n)}
            out["first"], out["shift"] = body[1 + 2 * n], body[3 + 2 * n] & 15
    coded = data[at : data.rindex(EOI)]
    out["coded"] = re.split(rb"\xff[\xd0-\xd7]", coded) if out["restart"] else [coded]
    return out


def _lossless(head: dict) -> np.ndarray:
    """Samples of a lossless grey frame: any Huffman table, predictors 1 to 7, point transform, restarts at row ends."""
    rows, cols = head["shape"]
    if len(head["parts"]) != 1 or head["precision"] > 8:
        raise ValueError("only grey lossless frames of at most 8 bits are read")
    table = head["huffman"][head["scan"][head["parts"][0][0]][0]]
    kind, x = head["first"], np.zeros((rows, cols), dtype=np.int64)
    step = head["restart"] // cols or rows
    for part, top in enumerate(range(0, rows, step)):
        bits = _Bits(head["coded"][part])
        for r in range(top, min(top + step, rows)):
            for c in range(cols):
                if r == top:
                    guess = x[r, c - 1] if c else 1 << (head["precision"] - head["shift"] - 1)
                elif not c:
                    guess = x[r - 1, 0]
                else:
                    left, up, corner = x[r, c - 1], x[r - 1, c], x[r - 1, c - 1]
                    guess = (left, up, corner, left + up - corner, left + ((up - corner) >> 1), up + ((left - corner) >> 1), (left + up) >> 1)[kind - 1]
                x[r, c] = (guess + bits.signed(bits.symbol(table))) & 0xFFFF
    return (x << head["shift"] & 255).astype(np.uint8)


#: Columns of the cosine transform of eight samples.
_COSINES = np.array([[math.cos((2 * x + 1) * u * math.pi / 16) * (math.sqrt(0.125) if u == 0 else 0.5) for u in range(8)] for x in range(8)])
#: Places of the 64 coefficients: along the anti-diagonals, in turn up and down.
_ZIGZAG = np.array([r * 8 + c for r, c in sorted(((r, c) for r in range(8) for c in range(8)), key=lambda p: (sum(p), p[0] if sum(p) % 2 else p[1]))])


def _sequential(head: dict) -> np.ndarray:
    """Luma samples of a baseline or extended sequential frame with 8 bits."""
    rows, cols = head["shape"]
    parts = head["parts"]
    if head["precision"] != 8 or len(head["scan"]) != len(parts):
        raise ValueError("only frames of 8 bits with one scan are read")
    one = len(parts) == 1
    sizes = [(1, 1) if one else (h, v) for _, h, v, _ in parts]
    most = max(h for h, _ in sizes), max(v for _, v in sizes)
    across, down = -(-cols // (8 * most[0])), -(-rows // (8 * most[1]))
    luma = np.zeros((down * sizes[0][1] * 8, across * sizes[0][0] * 8))
    step, last, bits = head["restart"] or across * down, [0] * len(parts), None
    for mcu in range(across * down):
        if mcu % step == 0:
            bits, last = _Bits(head["coded"][mcu // step]), [0] * len(parts)
        for k, ((name, _, _, quantizer), (h, v)) in enumerate(zip(parts, sizes, strict=True)):
            dc, ac = (head["huffman"][t] for t in (head["scan"][name][0], 16 + head["scan"][name][1]))
            for block in range(h * v):
                last[k] += bits.signed(bits.symbol(dc))
                z, at = np.zeros(64, dtype=np.int64), 1
                z[0] = last[k]
                while at < 64:
                    skip, size = divmod(bits.symbol(ac), 16)
                    if not size and skip < 15:
                        break
                    at += skip
                    if size:
                        z[at] = bits.signed(size)
                    at += 1
                if k == 0:
                    full = np.zeros(64)
                    full[_ZIGZAG] = z * head["quantizers"][quantizer]
                    y, x = (mcu // across * v + block // h) * 8, (mcu % across * h + block % h) * 8
                    luma[y : y + 8, x : x + 8] = _COSINES @ full.reshape(8, 8) @ _COSINES.T + 128
    tall, wide = (np.arange(n) * size // full for n, size, full in ((rows, sizes[0][1], most[1]), (cols, sizes[0][0], most[0])))
    return np.clip(np.rint(luma[np.ix_(tall, wide)]), 0, 255).astype(np.uint8)


def decode_jpeg(data: bytes) -> np.ndarray:
    """The grey frame of a JPEG: lossless or sequential with Huffman codes, with the tables in the file; of a colour
    frame its luma. What :func:`encode_jpeg` writes is read without a loop over samples."""
    head = _parse(data)
    if head["kind"] != SOF3:
        return _sequential(head)
    if (head["tables"], head["first"], head["shift"], head["restart"], head["precision"], len(head["parts"])) != (_TABLE, 1, 0, 0, 8, 1):
        return _lossless(head)
    rows, cols = head["shape"]
    bits = np.unpackbits(np.frombuffer(head["coded"][0].replace(b"\xff\x00", b"\xff"), dtype=np.uint8), count=rows * cols * 9)
    words = bits.reshape(-1, 9).astype(np.uint16) @ (1 << _SHIFTS)
    d = _DIFF[words].reshape(rows, cols).astype(np.int32)
    d[0, 0] += 128
    d[:, 0] = np.cumsum(d[:, 0])
    return (np.cumsum(d, axis=1) & 255).astype(np.uint8)


def _chunk(tag: bytes, body: bytes) -> bytes:
    return tag + struct.pack("<I", len(body)) + body + b"\0" * (len(body) & 1)


def _list(kind: bytes, *chunks: bytes) -> bytes:
    return _chunk(b"LIST", kind + b"".join(chunks))


def write_avi(payload: bytes, width: int = WIDTH, most_rows: int = MOST_ROWS) -> bytes:
    """An AVI file that holds ``payload``; its length must be a positive multiple of ``width``."""
    if not payload or len(payload) % width:
        raise ValueError(f"a payload has a positive multiple of {width} bytes")
    rows = min(len(payload) // width, most_rows)
    a = np.frombuffer(payload, dtype=np.uint8)
    a = np.concatenate([a, np.zeros(-len(a) % (rows * width), np.uint8)]).reshape(-1, rows, width)
    frames = [_chunk(b"00dc", encode_jpeg(f)) for f in a]
    index, at = [], 4
    for f in frames:
        index.append(b"00dc" + struct.pack("<III", 0x10, at, struct.unpack_from("<I", f, 4)[0]))
        at += len(f)
    largest = max(map(len, frames))
    avih = struct.pack("<14I", 1_000_000 // FPS, largest * FPS, 0, 0x10, len(a), 0, 1, largest, width, rows, 0, 0, 0, 0)
    strh = b"vidsMJPG" + struct.pack("<IHHIIIIIIIIHHHH", 0, 0, 0, 0, 1, FPS, 0, len(a), largest, 0xFFFFFFFF, 0, 0, 0, width, rows)
    strf = struct.pack("<IiiHH4sIiiII", 40, width, rows, 1, 8, b"MJPG", width * rows, 0, 0, 0, 0)
    body = b"AVI " + _list(b"hdrl", _chunk(b"avih", avih), _list(b"strl", _chunk(b"strh", strh), _chunk(b"strf", strf)))
    body += _list(b"INFO", _chunk(b"ICMT", b"payload=%d" % len(payload))) + _list(b"movi", *frames) + _chunk(b"idx1", b"".join(index))
    return _chunk(b"RIFF", body)


def parse_avi(data: bytes) -> dict:
    """Headers, comment and the (offset, size) of each frame that the index lists."""
    if data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("no AVI file")
    out: dict = {"fps": float(FPS), "payload": None, "frames": []}
    movi, index = 0, b""
    todo = [(12, min(len(data), 8 + struct.unpack_from("<I", data, 4)[0]))]
    while todo:
        at, end = todo.pop()
        while at + 8 <= end:
            tag, size = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
            if tag == b"LIST":
                kind = data[at + 8 : at + 12]
                if kind == b"movi":
                    movi = at + 8
                else:
                    todo.append((at + 12, at + 8 + size))
            elif tag == b"strh":
                scale, rate = struct.unpack_from("<II", data, at + 8 + 20)
                out["fps"] = rate / max(scale, 1)
            elif tag == b"ICMT":
                out["payload"] = int(data[at + 16 : at + 8 + size])
            elif tag == b"idx1":
                index = data[at + 8 : at + 8 + size]
            at += 8 + size + (size & 1)
    for k in range(0, len(index), 16):
        if index[k + 2 : k + 4] in (b"dc", b"db"):
            offset, size = struct.unpack_from("<II", index, k + 8)
            out["frames"].append((movi + offset + 8, size))
    return out


def read_avi(data: bytes) -> tuple[np.ndarray, bytes, float]:
    """The frames (n, rows, width), the payload they hold and the frame rate."""
    head = parse_avi(data)
    frames = np.stack([decode_jpeg(data[at : at + n]) for at, n in head["frames"]])
    flat = frames.tobytes()
    return frames, flat[: len(flat) if head["payload"] is None else head["payload"]], head["fps"]


def histograms(frames: np.ndarray, bins: int = BINS) -> np.ndarray:
    """Grey-level shares of each frame."""
    n = len(frames)
    level = (frames.reshape(n, -1) >> (8 - bins.bit_length() + 1)).astype(np.int64) + np.arange(n)[:, None] * bins
    return np.bincount(level.ravel(), minlength=n * bins).reshape(n, bins) / frames[0].size


def shots(frames: np.ndarray, around: int = AROUND, sigmas: float = SIGMAS, least: float = LEAST) -> list[tuple[int, int]]:
    """[first, last) of each shot. A cut lies where half the L1 distance of successive
    histograms exceeds ``least`` and the mean of the ``around`` distances on either side (its own
    left out) by ``sigmas`` deviations."""
    n = len(frames)
    if n == 1:
        return [(0, 1)]
    h = histograms(frames)
    d = np.abs(np.diff(h, axis=0)).sum(axis=1) / 2
    c1, c2 = np.concatenate([[0], np.cumsum(d)]), np.concatenate([[0], np.cumsum(d * d)])
    lo, hi = np.maximum(np.arange(n - 1) - around, 0), np.minimum(np.arange(n - 1) + around + 1, n - 1)
    m = hi - lo - 1
    mean = (c1[hi] - c1[lo] - d) / np.maximum(m, 1)
    var = np.maximum((c2[hi] - c2[lo] - d * d) / np.maximum(m, 1) - mean * mean, 0)
    cut = 1 + np.flatnonzero(d > np.maximum(least, mean + sigmas * np.sqrt(var) + 1e-9))
    edge = [0, *cut.tolist(), n]
    return list(zip(edge[:-1], edge[1:], strict=True))


def payload_of(text: str | None, unit: int = WIDTH) -> tuple[int, bytes]:
    """UTF-8 length and the bytes, filled with zeros to a positive multiple of ``unit``."""
    raw = (text or "").encode()
    return len(raw), raw + b"\0" * (-len(raw) % unit or (0 if raw else unit))


CLIPS = "doc_id long, clip int, first_frame int, last_frame int, start_s double, end_s double, mean_level double"
DIGESTS = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def store(df: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(doc_id, media): the AVI file of each text's payload. Null texts count as empty; equal texts give equal files;
    an empty table gives an empty table. ``key`` becomes doc_id, whatever other columns are called."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            files = (write_avi(payload_of(t.as_py())[1]) for t in b.column("text"))
            for i, f in enumerate(files):
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(i, 1), pa.array([f], pa.binary())], ["doc_id", "media"])

    return map_batches(text_of(df.select(F.col(key).alias("doc_id"), F.col(text).alias("text")), "doc_id"), run, "doc_id long, media binary")


def clips(media: DataFrame) -> DataFrame:
    """A row for each shot of each (doc_id, media) file: frames [first, last) and their times. Null
    files give no row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [f.split()[0] for f in CLIPS.split(", ")]
        for b in batches:
            rows = []
            for k, m in zip(b.column("doc_id"), b.column("media"), strict=True):
                if m.is_valid:
                    frames, _, fps = read_avi(m.as_py())
                    rows += [(k.as_py(), i, a, z, a / fps, z / fps, float(frames[a:z].mean())) for i, (a, z) in enumerate(shots(frames))]
            types = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.float64(), pa.float64()]
            cols = list(zip(*rows, strict=True)) or [[] for _ in names]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)

    return map_batches(media, run, CLIPS)


def _digest(text: str) -> tuple:
    n, payload = payload_of(text)
    media = write_avi(payload)
    frames, back, fps = read_avi(media)
    feature = ";".join(f"{a}-{z}@{a / fps:.2f}-{z / fps:.2f}:{frames[a:z].mean():.3f}" for a, z in shots(frames))
    return n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), feature


def digests(df: DataFrame, text: str = "text") -> DataFrame:
    """Each text stored, read back and described: sizes, digests and its shots as a string. Null texts count as empty;
    repeated rows give repeated results; an empty table gives an empty table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        names = [f.split()[0] for f in DIGESTS.split(", ")]
        for b in batches:
            rows = [_digest(t.as_py()) for t in b.column("text")]
            cols = list(zip(*rows, strict=True)) or [[] for _ in types]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *[pa.array(c, t) for c, t in zip(cols, types, strict=True)]], names)

    return map_batches(text_of(df, "doc_id", text=text), run, DIGESTS)
