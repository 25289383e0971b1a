"""Media columns: AVI with lossless JPEG frames, read back through its index.

A payload becomes grey frames 64 samples wide. Each frame is a lossless JPEG (process 14,
first predictor): differences of neighbours, Huffman coded. The Huffman table gives the
category of s extra bits a code of 9 - s bits, so every sample takes exactly 9 bits and
frames are packed and unpacked without a loop over samples. Frames are the ``00dc`` chunks
of a RIFF file whose ``idx1`` index lists them; reading follows the index. Frames with any
other table, and baseline frames of motion JPEG made elsewhere, go to the general decoder.

Writing and reading work through a file by SLAB rows and frame by frame: beside the payload
and its file, memory does not grow with a text.

Shots: the histogram distance of each frame to the one before starts a new shot where it
is over the mean of the shot's distances so far plus SPREAD standard deviations, and over
LEAST. A shot is a clip row with its first frame, frames, start and end in seconds.

Edge cases: null and empty texts are one block of 64 zero bytes; a payload of any length
is stored whole, in frames of at most ROWS rows; broken files raise ValueError; an empty
table gives no rows; repeated rows and null ids are like others.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from . import jpeg
from .common import annotate

WIDTH, ROWS, FPS = 64, 16, 25
#: Rows that are coded at once; whole frames.
SLAB = 1024 * ROWS
BINS, SPREAD, LEAST = 32, 3.0, 0.25

#: Codes of 9 - s bits for categories s: lengths 1 to 9 have one code each, for 8, 7, ... 0.
_TABLE = bytes([1] * 9 + [0] * 7) + bytes(range(8, -1, -1))


def _symbols() -> tuple[np.ndarray, np.ndarray]:
    """The 9-bit pattern of every difference from -255 to 255 (at 255 + difference), and its inverse."""
    forth = np.zeros(511, np.uint16)
    back = np.zeros(512, np.int16)
    for d in range(-255, 256):
        s = abs(d).bit_length()
        code = (1 << (9 - s)) - 2  # s ones less one, then a nought: the canonical codes
        bits = d if d > 0 else d + (1 << s) - 1
        forth[d + 255] = (code << s) | bits
        back[forth[d + 255]] = d
    return forth, back


_FORTH, _BACK = _symbols()
_WEIGHTS = (1 << np.arange(8, -1, -1)).astype(np.uint16)


def _head(rows: int) -> bytes:
    frame = struct.pack(">HBHHBBBB", 11, 8, rows, WIDTH, 1, 1, 0x11, 0)
    table = struct.pack(">HB", 3 + len(_TABLE), 0) + _TABLE
    scan = struct.pack(">HBBBBBB", 8, 1, 1, 0, 1, 0, 0)
    return b"\xff\xd8\xff\xc3" + frame + b"\xff\xc4" + table + b"\xff\xda" + scan


def encode_frames(samples: np.ndarray) -> Iterator[bytes]:
    """JPEG files of ``samples`` (rows x WIDTH, 8 bits), ROWS rows each."""
    for slab in range(0, len(samples), SLAB):
        x = samples[slab : slab + SLAB].astype(np.int16)
        left = np.empty_like(x)
        left[:, 1:] = x[:, :-1]
        left[1:, 0] = x[:-1, 0]
        left[::ROWS, 0] = 128
        symbols = _FORTH[x - left + 255]
        bits = np.unpackbits(symbols.astype(">u2").view(np.uint8).reshape(-1, 2), axis=1)[:, 7:]
        packed = np.packbits(bits.reshape(-1, 9 * WIDTH), axis=1)
        for at in range(0, len(x), ROWS):
            part = packed[at : at + ROWS]
            yield _head(len(part)) + part.tobytes().replace(b"\xff", b"\xff\x00") + b"\xff\xd9"


_OWN = {rows: _head(rows) for rows in range(1, ROWS + 1)}
_OWN_SIZE = len(_OWN[1])


def decode_frame(data: bytes) -> np.ndarray:
    """Grey samples of one frame: those that ``encode_frames`` writes at once, all others by the general decoder."""
    rows = int.from_bytes(data[7:9], "big")
    if data[:_OWN_SIZE] != _OWN.get(rows) or data[-2:] != b"\xff\xd9":
        return jpeg.luma(data)
    coded = np.frombuffer(data[_OWN_SIZE:-2].replace(b"\xff\x00", b"\xff"), np.uint8)
    n = rows * WIDTH
    if len(coded) * 8 < 9 * n:
        raise ValueError("the frame's data end early")
    bits = np.unpackbits(coded)[: 9 * n].reshape(n, 9)
    d = _BACK[(bits * _WEIGHTS).sum(axis=1, dtype=np.uint16)].astype(np.int64).reshape(rows, WIDTH)
    first = np.cumsum(d[:, 0]) + 128
    d[:, 0] = first
    return np.cumsum(d, axis=1).astype(np.uint8)


def _chunk(kind: bytes, body: bytes) -> bytes:
    return kind + struct.pack("<I", len(body)) + body + b"\0" * (len(body) & 1)


def write_avi(samples: np.ndarray) -> bytes:
    """An AVI file of the frames of ``samples``."""
    movie, sizes = bytearray(b"movi"), []
    for f in encode_frames(samples):
        sizes.append(len(f))
        movie += _chunk(b"00dc", f)
    most = max(sizes)
    height = min(ROWS, len(samples))
    main = struct.pack("<14I", 1_000_000 // FPS, most * FPS, 0, 0x10, len(sizes), 0, 1, most, WIDTH, height, 0, 0, 0, 0)
    stream = b"vidsMJPG" + struct.pack("<IHHIIIIIIIIHHHH", 0, 0, 0, 0, 1, FPS, 0, len(sizes), most, 0xFFFFFFFF, 0, 0, 0, WIDTH, height)
    form = struct.pack("<IIIHH4sIIIII", 40, WIDTH, height, 1, 8, b"MJPG", WIDTH * height, 0, 0, 0, 0)
    header = _chunk(b"LIST", b"hdrl" + _chunk(b"avih", main) + _chunk(b"LIST", b"strl" + _chunk(b"strh", stream) + _chunk(b"strf", form)))
    size = np.array(sizes, np.uint32)
    table = np.zeros(len(sizes), [("kind", "S4"), ("flags", "<u4"), ("at", "<u4"), ("size", "<u4")])
    table["kind"], table["flags"], table["size"] = b"00dc", 0x10, size
    step = 8 + size.astype(np.int64) + (size & 1)
    table["at"] = 4 + np.cumsum(step) - step
    index = _chunk(b"idx1", table.tobytes())
    whole = 4 + len(header) + 8 + len(movie) + len(index)
    return b"".join([b"RIFF", struct.pack("<I", whole), b"AVI ", header, b"LIST", struct.pack("<I", len(movie)), movie, index])


def read_avi(data: bytes) -> tuple[list[tuple[int, int]], float]:
    """(start, size) of the frames of an AVI file in the order of its index, and the seconds of a frame.

    Places in the index may count from the list of frames or from the file's begin.
    """
    if data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("not an AVI file")
    at, movie, index, seconds = 12, None, b"", 1 / FPS
    while at + 8 <= len(data):
        kind, size = data[at : at + 4], struct.unpack("<I", data[at + 4 : at + 8])[0]
        if kind == b"LIST" and data[at + 8 : at + 12] == b"movi":
            movie = at + 8
        elif kind == b"LIST" and data[at + 8 : at + 12] == b"hdrl":
            seconds = struct.unpack("<I", data[at + 20 : at + 24])[0] / 1e6 or seconds
        elif kind == b"idx1":
            index = data[at + 8 : at + 8 + size]
        at += 8 + size + (size & 1)
    if movie is None or not index or len(index) % 16:
        raise ValueError("no frames or no index")
    frames, base = [], None
    for kind, _, place, size in struct.iter_unpack("<4sIII", index):
        if kind[2:] not in (b"dc", b"db") or not size:
            continue
        if base is None:
            base = movie if data[movie + place : movie + place + 4] == kind else 0
        start = base + place
        if data[start : start + 4] != kind or start + 8 + size > len(data):
            raise ValueError("the index points past a frame")
        frames.append((start + 8, size))
    return frames, seconds


def histogram(frame: np.ndarray) -> np.ndarray:
    """How many samples have each value."""
    return np.bincount(frame.ravel(), minlength=256)


def shots_of(counts: np.ndarray) -> list[int]:
    """First frames of the shots, from the frames' histograms over BINS."""
    hist = counts / counts.sum(axis=1, keepdims=True)
    apart = np.abs(np.diff(hist, axis=0)).sum(axis=1) / 2
    firsts, count, total, squares = [0], 0, 0.0, 0.0
    for k, d in enumerate(apart.tolist(), 1):
        mean = total / count if count else 0.0
        spread = max(0.0, squares / count - mean * mean) ** 0.5 if count else 0.0
        if d > LEAST and d > mean + SPREAD * spread:
            firsts.append(k)
            count, total, squares = 0, 0.0, 0.0
        else:
            count, total, squares = count + 1, total + d, squares + d * d
    return firsts


def shots(frames: list[np.ndarray]) -> list[int]:
    return shots_of(np.array([_binned(histogram(f)) for f in frames]))


def _binned(counts: np.ndarray) -> np.ndarray:
    return counts.reshape(BINS, -1).sum(axis=1)


def payload(text: bytes | None) -> bytes:
    raw = text or b""
    return raw + b"\0" * ((-len(raw)) % 64 or (0 if raw else 64))


class Reading:
    """An AVI file read once, frame by frame: digests of its samples, their histogram, its timed clips."""

    def __init__(self, data: bytes, each=None):
        places, seconds = read_avi(data)
        digest, self.size, self.tail, self.counts, binned = hashlib.sha256(), 0, b"", np.zeros(256, np.int64), []
        for start, size in places:
            frame = decode_frame(data[start : start + size])
            raw, counts = frame.tobytes(), histogram(frame)
            digest.update(raw)
            self.size += len(raw)
            self.tail = (self.tail + raw[-64:])[-64:]
            self.counts += counts
            binned.append(_binned(counts))
            if each:
                each(raw)
        self.sha256, self.frames, self.clips = digest.hexdigest(), len(binned), []
        firsts = shots_of(np.array(binned)) if binned else []
        for a, b in zip(firsts, [*firsts[1:], len(binned)]):
            self.clips.append({"first_frame": a, "frames": b - a, "start_s": round(a * seconds, 6), "end_s": round(b * seconds, 6)})

    def moments(self) -> tuple[float, float]:
        """Mean and standard deviation of the samples."""
        values, n = np.arange(256), max(1, self.size)
        mean = float((self.counts * values).sum() / n)
        return mean, float(max(0.0, (self.counts * values * values).sum() / n - mean * mean) ** 0.5)


def clips(data: bytes) -> tuple[bytes, list[dict], int]:
    """The samples of an AVI file as bytes, its timed clips, and the number of its frames."""
    back = bytearray()
    found = Reading(data, back.extend)
    return bytes(back), found.clips, found.frames


_CLIPS = T.ArrayType(T.StructType([T.StructField("first_frame", T.LongType()), T.StructField("frames", T.LongType()), T.StructField("start_s", T.DoubleType()), T.StructField("end_s", T.DoubleType())]))


def to_video(docs: DataFrame, text: str = "text", keep=None) -> DataFrame:
    """Rows of ``docs`` with ``media``: the AVI file of the text."""

    def start():
        def work(texts):
            return [[write_avi(np.frombuffer(payload(t), np.uint8).reshape(-1, WIDTH)) for t in texts]]

        return work

    return annotate(docs, [text], [("media", T.BinaryType())], start, keep)


def clip_rows(videos: DataFrame, media: str = "media", keep=None) -> DataFrame:
    """One row for each shot of each video, with its times."""
    kept = list(videos.columns) if keep is None else list(keep)

    def start():
        return lambda media: [[clips(m)[1] if m else [] for m in media]]

    found = annotate(videos, [media], [("clips", _CLIPS)], start, kept)
    name = found.columns[-1]
    return found.select(*[F.col(f"`{c}`") for c in kept], F.inline(F.col(f"`{name}`")))


def digests(docs: DataFrame, text: str = "text", keep=None) -> DataFrame:
    """Rows of ``docs`` with sizes and digests of payload and AVI file, read back from the file, and a line of features."""

    def start():
        def work(texts):
            out = []
            for t in texts:
                media = write_avi(np.frombuffer(payload(t), np.uint8).reshape(-1, WIDTH))
                found = Reading(media)
                mean, spread = found.moments()
                ends = "|".join(f"{r['start_s']:.2f}-{r['end_s']:.2f}" for r in found.clips)
                feature = f"frames={found.frames};shots={len(found.clips)};mean={mean:.4f};std={spread:.4f};clips={ends}"
                out.append((len(t or b""), found.size, found.sha256, zlib.crc32(found.tail), len(media), hashlib.sha256(media).hexdigest(), feature))
            return list(zip(*out))

        return work

    long, string = T.LongType(), T.StringType()
    fields = [("n_bytes", long), ("payload_bytes", long), ("payload_sha256", string), ("tail_crc32", long), ("media_bytes", long), ("media_sha256", string), ("feature", string)]
    return annotate(docs, [text], fields, start, keep)


def op9_media(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return digests(docs, keep=["doc_id"])
