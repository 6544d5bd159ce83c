"""Media columns: 8-bit grey PNG in binary columns, and hashes of low-frequency cosine coefficients.

A payload of bytes is stored as an image 64 samples wide, one filter a row chosen by the least sum of absolute differences,
deflated and split into IDAT chunks. Reading tests the signature, every chunk's CRC-32, the deflate stream's own Adler-32
and the sizes, then undoes the five filters in numpy: rows of None, Sub and Up in one vectorised pass, images that hold
Average or Paeth rows row by row. The hash shrinks the image to 32 x 32 means, takes its cosine transform and sets one bit
for each of the 64 lowest frequencies but the constant one (the last bit is the 65th's) above their median.

Edge cases: a null text is an empty one; an empty text becomes one row of zeros; texts of any length keep every byte;
equal texts give equal bytes, images and hashes; repeated rows give repeated results; an empty table gives an empty result;
null and broken images give rows with nulls and end no job.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

WIDTH = 64
SIGNATURE = b"\x89PNG\r\n\x1a\n"
IDAT_BYTES = 1 << 16


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(data, zlib.crc32(kind)))


def encode_png(pixels: np.ndarray, level: int = 1) -> bytes:
    """A height x width array of uint8 as a grey PNG."""
    height, width = pixels.shape
    left, up = np.zeros_like(pixels), np.zeros_like(pixels)
    left[:, 1:], up[1:] = pixels[:, :-1], pixels[:-1]
    kinds = np.stack([pixels, pixels - left, pixels - up])
    cost = np.minimum(kinds, 0 - kinds).sum(2, dtype=np.uint32)  # bytes read as signed
    best = cost.argmin(0)
    rows = np.empty((height, width + 1), np.uint8)
    rows[:, 0] = best
    rows[:, 1:] = kinds[best, np.arange(height)]
    data = zlib.compress(rows.tobytes(), level)
    parts = [_chunk(b"IDAT", data[i : i + IDAT_BYTES]) for i in range(0, len(data), IDAT_BYTES)]
    return SIGNATURE + _chunk(b"IHDR", struct.pack(">IIBBBBB", width, height, 8, 0, 0, 0, 0)) + b"".join(parts) + _chunk(b"IEND", b"")


def unfilter(kind: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Undo PNG's row filters for one byte a pixel."""
    if len(kind) and kind.max() > 4:
        raise ValueError("unknown PNG filter")
    if not len(kind) or kind.max() <= 2:
        out = rows.copy()
        sub = kind == 1
        out[sub] = np.add.accumulate(rows[sub], axis=1, dtype=np.uint8)
        total = np.add.accumulate(out, axis=0, dtype=np.uint8)
        start = np.maximum.accumulate(np.where(kind != 2, np.arange(len(kind)), 0))  # the row that an Up row's sum starts at
        before = np.zeros_like(out)
        before[start > 0] = total[start[start > 0] - 1]
        return total - before
    out, above = np.zeros_like(rows), np.zeros(rows.shape[1], np.uint8)
    for i, k in enumerate(kind):
        if k <= 2:
            out[i] = (rows[i], np.add.accumulate(rows[i], dtype=np.uint8), rows[i] + above)[k]
        else:
            a = c = 0
            for j, (x, b) in enumerate(zip(rows[i].tolist(), above.tolist(), strict=True)):
                if k == 3:
                    a = (x + ((a + b) >> 1)) & 255
                else:
                    pa_, pb, pc = abs(b - c), abs(a - c), abs(a + b - 2 * c)
                    a = (x + (a if pa_ <= pb and pa_ <= pc else b if pb <= pc else c)) & 255
                c = b
                out[i, j] = a
        above = out[i]
    return out


def decode_png(data: bytes) -> np.ndarray:
    """The pixels of an 8-bit grey PNG; ValueError if a checksum, size or field is wrong."""
    if data[:8] != SIGNATURE:
        raise ValueError("not a PNG")
    at, head, body, ended = 8, None, [], False
    while at + 12 <= len(data) and not ended:
        n, kind = struct.unpack_from(">I4s", data, at)
        part = data[at + 8 : at + 8 + n]
        if len(part) != n or at + 12 + n > len(data) or zlib.crc32(part, zlib.crc32(kind)) != struct.unpack_from(">I", data, at + 8 + n)[0]:
            raise ValueError("PNG chunk broken")
        if kind == b"IHDR":
            if n != 13:
                raise ValueError("PNG header broken")
            head = struct.unpack(">IIBBBBB", part)
        elif kind == b"IDAT":
            body.append(part)
        ended = kind == b"IEND"
        at += 12 + n
    if head is None or not ended or head[2:] != (8, 0, 0, 0, 0):
        raise ValueError("PNG kind not supported or cut short")
    width, height = head[:2]
    size, stream = height * (width + 1), zlib.decompressobj()
    try:
        raw = stream.decompress(b"".join(body), size + 1)  # tests Adler-32; a stream that holds more isn't read further
    except zlib.error as e:
        raise ValueError("PNG data broken") from e
    if len(raw) != size or not stream.eof:
        raise ValueError("PNG size wrong")
    rows = np.frombuffer(raw, np.uint8).reshape(height, width + 1)
    return unfilter(rows[:, 0], rows[:, 1:])


SIDE = 32
_DCT = np.cos(np.pi * np.outer(np.arange(9), 2 * np.arange(SIDE) + 1) / (2 * SIDE))
_LOW = sorted(((i, j) for i in range(9) for j in range(9) if i or j), key=lambda p: (p[0] + p[1], p))[:64]
_LI, _LJ = (np.array(x) for x in zip(*_LOW, strict=True))


def cosine_hash(pixels: np.ndarray) -> bytes:
    """Eight bytes from the 64 lowest frequencies of the image shrunk to 32 x 32."""
    height, width = pixels.shape
    if height < SIDE:
        pixels, height = np.repeat(pixels, -(-SIDE // height), axis=0), height * -(-SIDE // height)
    if width < SIDE:
        pixels, width = np.repeat(pixels, -(-SIDE // width), axis=1), width * -(-SIDE // width)
    ys, xs = np.arange(SIDE + 1) * height // SIDE, np.arange(SIDE + 1) * width // SIDE
    small = np.add.reduceat(np.add.reduceat(pixels, xs[:-1], axis=1, dtype=np.int64), ys[:-1], axis=0) / np.outer(np.diff(ys), np.diff(xs))
    low = (_DCT @ small @ _DCT.T)[_LI, _LJ]
    return np.packbits(low > np.median(low)).tobytes()


def payload(data: bytes) -> np.ndarray:
    """Bytes padded with zeros to a positive multiple of the width, as pixels."""
    n = max(1, -(-len(data) // WIDTH)) * WIDTH
    return np.frombuffer(data + bytes(n - len(data)), np.uint8).reshape(-1, WIDTH)


def _encode(batches):
    for batch in batches:
        texts = [(t.as_py() or "").encode() for t in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array([encode_png(payload(t)) for t in texts], pa.binary())], ["doc_id", "n_bytes", "media"])


def to_media(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes and ``media``, the PNG that holds the text's UTF-8 bytes."""
    return df.select(df[id_col].cast("long").alias("doc_id"), df[text_col].cast("string").alias("text")).mapInArrow(_encode, "doc_id long, n_bytes long, media binary")


def _features(batches):
    for batch in batches:
        out = []
        for value in batch.column(2):
            data = value.as_py()
            if data is None:
                out.append((None,) * 6)
                continue
            try:
                pixels = decode_png(data)
            except ValueError:
                out.append((None, None, None, len(data), hashlib.sha256(data).hexdigest(), None))
                continue
            raw = pixels.tobytes()
            out.append((len(raw), hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-WIDTH:]), len(data), hashlib.sha256(data).hexdigest(), cosine_hash(pixels)))
        n, sha, tail, size, media, feature = zip(*out, strict=True) if out else [()] * 6
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(1), pa.array(n, pa.int64()), pa.array(sha, pa.string()), pa.array(tail, pa.int64()), pa.array(size, pa.int64()), pa.array(media, pa.string()), pa.array(feature, pa.binary())],
            ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "hash"])


def features(media: DataFrame) -> DataFrame:
    """Decode ``media`` and return its digests and the cosine ``hash`` (binary, 8 bytes). A null image gives nulls; of one
    that is broken, by any checksum, size or field, only size and digest of the stored bytes are known."""
    return media.mapInArrow(_features, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, hash binary")


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = features(to_media(docs))
    return out.selectExpr("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "lower(hex(hash)) AS feature")
