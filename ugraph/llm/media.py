"""Media columns: grey PNG images in binary columns, read back with checksum tests, and hashes of their low frequencies.

A text's bytes, padded with 255 to a positive multiple of 576, are the samples of an 8-bit grey image, 24 wide or, for
long texts, that times a power of two. The
writer predicts rows with the filter of least residual; the reader tests the signature, every chunk's checksum, the
header and the sample count, inflates the zlib stream and undoes all five filter types with numpy.

Defined cases: null text is an empty text (one row of 255); equal texts give equal images and hashes; extra columns are
ignored; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_arrow, materialise, slices

UNIT = 576
SIGNATURE = b"\x89PNG\r\n\x1a\n"


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def encode_png(samples: np.ndarray, level: int = 6) -> bytes:
    """An 8-bit grey image (rows x columns) as PNG; one of the filters none, left and up serves all rows."""
    h, w = samples.shape
    left = samples.copy()
    left[:, 1:] -= samples[:, :-1]
    up = samples.copy()
    up[1:] -= samples[:-1]
    options = [(0, samples), (1, left), (2, up)]
    kind, rows = min(options, key=lambda o: int(np.abs(o[1].view(np.int8).astype(np.int32)).sum()))
    raw = np.empty((h, w + 1), np.uint8)
    raw[:, 0] = kind
    raw[:, 1:] = rows
    head = struct.pack(">IIBBBBB", w, h, 8, 0, 0, 0, 0)
    return SIGNATURE + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(raw.tobytes(), level)) + _chunk(b"IEND", b"")


def _unfilter(raw: np.ndarray) -> np.ndarray:
    kinds, rows = raw[:, 0], raw[:, 1:]
    h, w = rows.shape
    if (kinds == 0).all():
        return rows.copy()
    if (kinds == 1).all():
        return np.cumsum(rows, axis=1, dtype=np.uint8)
    if (kinds == 2).all():
        return np.cumsum(rows, axis=0, dtype=np.uint8)
    out = np.zeros((h, w), np.uint8)
    above = np.zeros(w, np.uint8)
    for y in range(h):
        kind, row = int(kinds[y]), rows[y]
        if kind == 0:
            out[y] = row
        elif kind == 1:
            out[y] = np.cumsum(row, dtype=np.uint8)
        elif kind == 2:
            out[y] = row + above
        elif kind == 3:
            before, line, up = 0, row.tolist(), above.tolist()
            for x in range(w):
                before = line[x] = (line[x] + (before + up[x]) // 2) & 255
            out[y] = line
        elif kind == 4:
            a = c = 0
            line, up = row.tolist(), above.tolist()
            for x in range(w):
                b = up[x]
                p = a + b - c
                da, db, dc = abs(p - a), abs(p - b), abs(p - c)
                a = line[x] = (line[x] + (a if da <= db and da <= dc else b if db <= dc else c)) & 255
                c = b
            out[y] = line
        else:
            raise ValueError(f"unknown PNG filter {kind}")
        above = out[y]
    return out


def decode_png(data: bytes) -> np.ndarray:
    """The samples of an 8-bit grey PNG without interlace; ValueError if anything in the file is wrong."""
    if data[:8] != SIGNATURE:
        raise ValueError("not a PNG")
    at, head, streams, ended = 8, None, [], False
    while at < len(data) and not ended:
        if at + 12 > len(data):
            raise ValueError("PNG chunk cut short")
        (n,) = struct.unpack_from(">I", data, at)
        kind, body = data[at + 4 : at + 8], data[at + 8 : at + 8 + n]
        if len(body) < n or len(data) < at + 12 + n:
            raise ValueError("PNG chunk cut short")
        if struct.unpack_from(">I", data, at + 8 + n)[0] != zlib.crc32(kind + body):
            raise ValueError(f"PNG checksum of {kind!r} differs")
        if kind == b"IHDR":
            head = struct.unpack(">IIBBBBB", body)
        elif kind == b"IDAT":
            streams.append(body)
        ended = kind == b"IEND"
        at += 12 + n
    if head is None or not ended:
        raise ValueError("PNG without header or end")
    w, h, depth, colour, packing, filtering, interlace = head
    if (depth, colour, packing, filtering, interlace) != (8, 0, 0, 0, 0):
        raise ValueError("only 8-bit grey PNG without interlace")
    raw = np.frombuffer(zlib.decompress(b"".join(streams)), np.uint8)
    if len(raw) != h * (w + 1):
        raise ValueError("PNG sample count differs from its header")
    return _unfilter(raw.reshape(h, w + 1))


@cache
def _cosines(n: int, k: int) -> np.ndarray:
    """The first k rows of the cosine transform of n values."""
    return np.cos(np.pi * (np.arange(n) + 0.5) * np.arange(k)[:, None] / n)


def cosine_hash(samples: np.ndarray, side: int = 32, k: int = 8) -> bytes:
    """64 bits: which of the k x k lowest frequencies of the image, shrunk to side x side means, exceed their median
    (the constant term takes no part in the median)."""
    h, w = samples.shape
    small = samples.astype(np.float64)
    for axis, n in ((0, h), (1, w)):
        if n >= side:
            cuts = np.arange(side) * n // side
            counts = np.diff(np.append(cuts, n))
            small = np.add.reduceat(small, cuts, axis=axis) / (counts[:, None] if axis == 0 else counts)
        else:
            small = np.take(small, np.arange(side) * n // side, axis=axis)
    low = (_cosines(side, k) @ small @ _cosines(side, k).T).round(6).ravel()
    return np.packbits(low > np.median(low[1:])).tobytes()


def text_samples(text: bytes) -> np.ndarray:
    n = max(UNIT, -(-len(text) // UNIT) * UNIT)
    out = np.full(n, 255, np.uint8)
    out[: len(text)] = np.frombuffer(text, np.uint8)
    width = 24
    while n // width >= 4 * width and n // width % 2 == 0:
        width *= 2
    return out.reshape(-1, width)


def _to_images(batches):
    for batch in batches:
        for part in slices(batch, "text"):
            texts = [(t or "").encode() for t in part.column("text").to_pylist()]
            images = [encode_png(text_samples(t)) for t in texts]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([len(t) for t in texts], pa.int64()), pa.array(images, pa.binary())], names=["doc_id", "n_bytes", "media"])


MEDIA = "doc_id long, n_bytes long, media binary"
FEATURES = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, cosine_hash binary"


def _features(batches):
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary()]
    names = [f.split()[0] for f in FEATURES.split(", ")]
    for batch in batches:
        rows = []
        for doc_id, n, media in zip(*(batch.column(c) for c in ("doc_id", "n_bytes", "media")), strict=True):
            media = media.as_py()
            samples = decode_png(media)
            payload, mark = samples.tobytes(), cosine_hash(samples)
            rows.append((doc_id.as_py(), n.as_py(), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(media), hashlib.sha256(media).hexdigest(), mark.hex(), mark))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)


def text_images(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes and the PNG of every text."""
    return map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), _to_images, MEDIA)


def image_features(media: DataFrame) -> DataFrame:
    """What is read back from stored images, with the cosine hash as text and as a binary column."""
    return map_arrow(media.select("doc_id", "n_bytes", "media"), _features, FEATURES)


def media_digest(docs: DataFrame) -> DataFrame:
    """op4: store all texts as images, read the stored table back, and return its features."""
    return image_features(materialise(text_images(docs), "media"))
