"""A minimal PNG writer and reader (8-bit RGB, no interlace), and charts as image files."""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .tables import read_images

MAGIC = b"\x89PNG\r\n\x1a\n"


def encode(img: np.ndarray) -> bytes:
    """PNG bytes of an H x W x 3 array."""
    h, w, _ = img.shape
    raw = np.hstack((np.zeros((h, 1), np.uint8), img.reshape(h, w * 3))).tobytes()
    chunk = lambda kind, body: struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))
    return MAGIC + chunk(b"IHDR", struct.pack(">IIBBBBB", w, h, 8, 2, 0, 0, 0)) + chunk(b"IDAT", zlib.compress(raw, 6)) + chunk(b"IEND", b"")


def decode(data: bytes) -> np.ndarray:
    """The array of PNG bytes as ``encode`` writes them, any of the five row filters."""
    if data[:8] != MAGIC:
        raise ValueError("not a PNG file")
    at, body, size = 8, b"", None
    while at < len(data):
        n, kind = struct.unpack(">I4s", data[at : at + 8])
        part = data[at + 8 : at + 8 + n]
        if kind == b"IHDR":
            w, h, depth, colour, _, _, lace = struct.unpack(">IIBBBBB", part)
            if (depth, colour, lace) != (8, 2, 0):
                raise ValueError("only 8-bit RGB without interlace")
            size = (h, w)
        elif kind == b"IDAT":
            body += part
        at += 12 + n
    h, w = size
    rows = np.frombuffer(zlib.decompress(body), np.uint8).reshape(h, w * 3 + 1)
    out = np.zeros((h, w * 3), np.int64)
    for y in range(h):
        kind, line = int(rows[y, 0]), rows[y, 1:].astype(np.int64)
        up = out[y - 1] if y else np.zeros(w * 3, np.int64)
        if kind == 0:
            out[y] = line
        elif kind == 2:
            out[y] = (line + up) % 256
        else:
            for x in range(w * 3):
                a, c = (out[y, x - 3], up[x - 3]) if x >= 3 else (0, 0)
                b = up[x]
                if kind == 1:
                    p = a
                elif kind == 3:
                    p = (a + b) // 2
                else:
                    d = (abs(b - c), abs(a - c), abs(a + b - 2 * c))
                    p = (a, b, c)[d.index(min(d))]
                out[y, x] = (line[x] + p) % 256
    return out.astype(np.uint8).reshape(h, w, 3)


def as_png(images: DataFrame) -> DataFrame:
    """chart_id, png of packed images."""

    def run(batches):
        for batch in batches:
            got = [encode(np.frombuffer(d, np.uint8).reshape(h, w, 3)) for w, h, d in zip(*(batch.column(n).to_pylist() for n in ("width", "height", "data")))]
            yield pa.RecordBatch.from_arrays([batch.column("chart_id"), pa.array(got, pa.binary())], names=["chart_id", "png"])

    return images.select("chart_id", "width", "height", "data").mapInArrow(run, "chart_id long, png binary")


def from_files(spark: SparkSession, path: str) -> DataFrame:
    """Packed images from PNG files named <chart_id>.png, decoded on the executors."""
    return unpacked(read_images(spark, path, glob="*.png"))


def unpacked(files: DataFrame) -> DataFrame:
    """Packed images of (path, data) rows."""

    def run(batches):
        for batch in batches:
            imgs = [decode(d) for d in batch.column("data").to_pylist()]
            ids = [int(p.rsplit("/", 1)[-1].split(".")[0]) for p in batch.column("path").to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([i.shape[1] for i in imgs], pa.int32()), pa.array([i.shape[0] for i in imgs], pa.int32()), pa.array([3] * len(imgs), pa.int32()), pa.array([i.tobytes() for i in imgs], pa.binary())], names=["chart_id", "width", "height", "channels", "data"])

    return files.select("path", "data").mapInArrow(run, "chart_id long, width int, height int, channels int, data binary")
