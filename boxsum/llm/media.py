"""Media columns: bytes kept losslessly as PNG images in a binary column, and low-frequency hashes of them.

A payload is padded with zero bytes to a positive multiple of `width` and laid out as rows of an 8-bit grey
image. It is compressed unfiltered and with the better of the types None, Sub and Up for each row by least
absolute sum; the shorter stream is kept and written as zlib chunks, each chunk with its CRC. Reading tests the signature, every chunk's CRC, the header's limits, the
stream's checksum and the filter types; unfiltering is done on whole rows, or on whole anti-diagonals where a
sample depends on its left neighbour too. The hash takes the image's means on a small grid, their cosine
transform, and one bit for each low frequency above the median.

Null payloads count as empty; equal payloads give equal images and hashes. Damaged images raise `PngError`.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.llm.shared import blocks

SIGNATURE = b"\x89PNG\r\n\x1a\n"
WIDTH, CHUNK, LEVEL, GRID, LOW = 64, 1 << 16, 1, 32, 8


class PngError(ValueError):
    pass


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def _paeth(a: np.ndarray, b: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Of left, up and upper left, the one nearest to a + b - c."""
    p = a + b - c
    da, db, dc = abs(p - a), abs(p - b), abs(p - c)
    return np.where((da <= db) & (da <= dc), a, np.where(db <= dc, b, c))


def filter_rows(rows: np.ndarray, kinds_tried: tuple[int, ...] = (0, 1, 2)) -> np.ndarray:
    """Rows of samples to rows of a filter type, the first of least absolute sum among those tried, and filtered samples."""
    x = rows.astype(np.int16)
    left, up, corner = np.zeros_like(x), np.zeros_like(x), np.zeros_like(x)
    left[:, 1:], up[1:], corner[1:, 1:] = x[:, :-1], x[:-1], x[:-1, :-1]
    best = None
    predictions = (lambda: np.int16(0), lambda: left, lambda: up, lambda: (left + up) >> 1, lambda: _paeth(left, up, corner))
    for kind in kinds_tried:
        predicted = predictions[kind]()
        residue = ((x - predicted) & 255).astype(np.uint8)
        score = np.abs(residue.view(np.int8).astype(np.int16)).sum(axis=1, dtype=np.int64)
        if best is None:
            best, out, kinds = score, residue, np.full(len(x), kind, np.uint8)
        else:
            better = score < best
            best = np.where(better, score, best)
            out[better], kinds[better] = residue[better], kind
    return np.column_stack([kinds, out])


def unfilter(kinds: np.ndarray, data: np.ndarray) -> np.ndarray:
    """The samples of filtered rows, by wrapping bytes."""
    height, width = data.shape
    if kinds.max(initial=0) > 4:
        raise PngError("unknown filter type")
    out = data.copy()
    if not kinds.any():
        return out
    row = 0
    while row < height:
        kind = kinds[row]
        end = row + 1
        if kind <= 1:
            while end < height and kinds[end] == kind:
                end += 1
            if kind == 1:
                out[row:end] = np.cumsum(data[row:end], axis=1, dtype=np.uint8)
        elif kind == 2:
            while end < height and kinds[end] == 2:
                end += 1
            part = data[row:end].copy()
            if row:
                part[0] += out[row - 1]
            out[row:end] = np.cumsum(part, axis=0, dtype=np.uint8)
        else:
            while end < height and kinds[end] > 2:
                end += 1
            _unfilter_diagonals(kinds, data, out, row, end)
        row = end
    return out


def _unfilter_diagonals(kinds: np.ndarray, data: np.ndarray, out: np.ndarray, first: int, end: int) -> None:
    """Rows of the average and Paeth types: sample (y, x) needs (y, x-1) and row y-1 to x, all on earlier diagonals."""
    width = data.shape[1]
    work = np.zeros((end - first + 1, width + 1), np.int16)
    if first:
        work[0, 1:] = out[first - 1]
    paeth = kinds[first:end] == 4
    n = end - first
    for d in range(n + width - 1):
        y = np.arange(max(0, d - width + 1), min(n, d + 1))
        x = d - y
        a, b, c = work[y + 1, x], work[y, x + 1], work[y, x]
        work[y + 1, x + 1] = (data[first + y, x] + np.where(paeth[y], _paeth(a, b, c), (a + b) >> 1)) & 255
    out[first:end] = work[1:, 1:].astype(np.uint8)


def write_png(payload: bytes, width: int = WIDTH, filters: tuple[tuple[int, ...], ...] = ((0,), (0, 1, 2))) -> bytes:
    """The payload, a positive multiple of width bytes, as an 8-bit grey image; filters: the choices for its rows, the shortest wins."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, width)
    stream = min((zlib.compress(filter_rows(rows, kinds).tobytes(), LEVEL) for kinds in filters), key=len)
    head = struct.pack(">IIBBBBB", width, len(rows), 8, 0, 0, 0, 0)
    parts = [_chunk(b"IDAT", stream[i : i + CHUNK]) for i in range(0, len(stream), CHUNK)]
    return b"".join([SIGNATURE, _chunk(b"IHDR", head), *parts, _chunk(b"IEND", b"")])


def read_png(image: bytes) -> np.ndarray:
    """The samples of an 8-bit grey image without interlace, all checksums tested."""
    if image[:8] != SIGNATURE:
        raise PngError("no PNG signature")
    at, stream, head, done = 8, [], None, False
    while at < len(image) and not done:
        if at + 12 > len(image):
            raise PngError("cut off")
        (size,) = struct.unpack_from(">I", image, at)
        kind, data = image[at + 4 : at + 8], image[at + 8 : at + 8 + size]
        if at + 12 + size > len(image):
            raise PngError("cut off")
        if struct.unpack_from(">I", image, at + 8 + size)[0] != zlib.crc32(kind + data):
            raise PngError(f"checksum of {kind!r}")
        if kind == b"IHDR":
            head = struct.unpack(">IIBBBBB", data)
        elif kind == b"IDAT":
            stream.append(data)
        elif kind == b"IEND":
            done = True
        elif not kind[0] & 32:
            raise PngError(f"unknown critical chunk {kind!r}")
        at += 12 + size
    if head is None or not done or head[2:] != (8, 0, 0, 0, 0) or not head[0] or not head[1]:
        raise PngError("not a whole 8-bit grey image")
    width, height = head[:2]
    inflate = zlib.decompressobj()
    try:
        raw = inflate.decompress(b"".join(stream), height * (width + 1) + 1)
    except zlib.error as e:
        raise PngError(str(e)) from e
    if len(raw) != height * (width + 1) or not inflate.eof:
        raise PngError("stream's length")
    rows = np.frombuffer(raw, np.uint8).reshape(height, width + 1)
    return unfilter(rows[:, 0], rows[:, 1:])


@lru_cache(maxsize=4)
def _cosines(n: int, low: int) -> np.ndarray:
    k, x = np.arange(low)[:, None], np.arange(n)[None, :]
    return np.cos(np.pi * k * (2 * x + 1) / (2 * n))


def low_frequency_hash(samples: np.ndarray, grid: int = GRID, low: int = LOW) -> str:
    """Bits of the low frequencies but the mean, row by row, in hexadecimal; images of any size."""
    height, width = samples.shape
    ys, xs = (np.arange(grid + 1) * height) // grid, (np.arange(grid + 1) * width) // grid
    # means over cells, a cell of no row or column being the one it lies in
    total = np.zeros((height + 1, grid))
    columns = np.concatenate([np.zeros((height, 1)), np.cumsum(samples, axis=1, dtype=np.float64)], axis=1)
    x_end = np.maximum(xs[1:], xs[:-1] + 1)
    np.cumsum((columns[:, x_end] - columns[:, xs[:-1]]) / (x_end - xs[:-1]), axis=0, out=total[1:])
    y_end = np.maximum(ys[1:], ys[:-1] + 1)
    cells = (total[y_end] - total[ys[:-1]]) / (y_end - ys[:-1])[:, None]
    c = _cosines(grid, low)
    f = np.round((c @ cells @ c.T).ravel()[1:], 6)
    bits = np.concatenate([[False], f > np.median(f)])
    return np.packbits(bits).tobytes().hex()


def pad(raw: bytes, width: int = WIDTH) -> bytes:
    return raw + bytes(-len(raw) % width or (0 if raw else width))


def store(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH) -> DataFrame:
    """(id, n_bytes, media): each whole text as an image; n_bytes is its length without padding."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "text"):
            raw = [(t or "").encode("utf-8", "surrogatepass") for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(map(len, raw), pa.int64()), pa.array([write_png(pad(r, width), width) for r in raw], pa.binary())], ["id", "n_bytes", "media"])

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, n_bytes long, media binary").withColumnRenamed("id", id_col)


def features(media: DataFrame, id_col: str = "doc_id", media_col: str = "media", size_col: str = "n_bytes") -> DataFrame:
    """(id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature), from the stored bytes alone."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "media"):
            out = []
            for image in b.column("media").to_pylist():
                samples = read_png(image)
                payload = samples.tobytes()
                out.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(image), hashlib.sha256(image).hexdigest(), low_frequency_hash(samples)))
            size, digest, tail, stored, stored_digest, feature = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("n_bytes"), pa.array(size, pa.int64()), pa.array(digest), pa.array(tail, pa.int64()), pa.array(stored, pa.int64()), pa.array(stored_digest), pa.array(feature)], ["id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    rows = media.select(F.col(id_col).alias("id"), F.col(size_col).alias("n_bytes"), F.col(media_col).alias("media"))
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string").withColumnRenamed("id", id_col)
