"""Shared pieces of the training-data operators: shared-folder tables, Arrow byte access, vectorised word hashes."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one numpy pass works on; bounds a Python worker's memory whatever the Arrow batch holds.
CHUNK_BYTES = 1 << 19
#: A side is broadcast only when its counted rows stay below this; otherwise the join shuffles.
BROADCAST_ROWS = 200_000

_U64 = np.uint64


def shared_dir(spark: SparkSession) -> str:
    """The shared folder of ``spark.checkpoint.dir``; a local temporary one only for a local master without the setting."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="rgsketch-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def materialize(df: DataFrame) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/rgsketch/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_written(spark: SparkSession) -> None:
    """Delete the tables that ``materialize`` has written in the shared folder. For the end of a job: results that weren't
    stored elsewhere are read from them."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/rgsketch")
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def maybe_broadcast(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Hint a broadcast only for a counted, bounded side."""
    return F.broadcast(df) if rows <= limit else df


#: Bits of a fixed-size filter (2 MB). It only spares work: a fuller filter lets more rows pass, results stay the same.
FILTER_BITS = 1 << 24


def filter_spot(col: F.Column | str) -> F.Column:
    """A value's bit in a filter of FILTER_BITS bits."""
    return F.pmod(F.xxhash64(col), F.lit(FILTER_BITS))


def bit_filter(df: DataFrame, col: str) -> np.ndarray:
    """The filter of df's values: FILTER_BITS / 64 words at most come to the driver, whatever df holds."""
    spot = filter_spot(col)
    cells = df.select(F.shiftright(spot, 6).cast("int").alias("cell"), F.expr(f"shiftleft(1L, cast(pmod(xxhash64({col}), {FILTER_BITS}L) & 63 as int))").alias("bit")).groupBy("cell").agg(F.bit_or("bit").alias("bits"))
    table = np.zeros(FILTER_BITS // 64, np.int64)
    got = cells.toArrow()
    table[got.column("cell").to_numpy()] = got.column("bits").to_numpy()
    return table


def in_filter(table: np.ndarray, spot: np.ndarray) -> np.ndarray:
    return ((table[spot >> 6] >> (spot & 63)) & 1).astype(bool)


def ascii_lower(col: F.Column) -> F.Column:
    """Lower-case A-Z alone; every other character stays."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def utf8(arr: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and its n + 1 offsets, without copying; nulls have no bytes."""
    if isinstance(arr, pa.ChunkedArray):
        arr = arr.combine_chunks()
    if arr.null_count:
        arr = arr.fill_null("")
    if len(arr) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    wide = pa.types.is_large_string(arr.type) or pa.types.is_large_binary(arr.type)
    _, off, data = arr.buffers()
    offsets = np.frombuffer(off, np.int64 if wide else np.int32)[arr.offset : arr.offset + len(arr) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(offsets: np.ndarray, size: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges whose bytes stay near ``size``; a longer row stands alone."""
    n, lo = len(offsets) - 1, 0
    while lo < n:
        hi = int(np.searchsorted(offsets, offsets[lo] + size, side="right")) - 1
        hi = min(n, max(hi, lo + 1))
        yield lo, hi
        lo = hi


def row_slices(batches: Iterator[pa.RecordBatch], rows: int = 500) -> Iterator[pa.RecordBatch]:
    """Batches of fewer rows, so that what Python holds besides the batch itself has a bound."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def mix64(x: np.ndarray) -> np.ndarray:
    """Avalanche a 64-bit hash in place of the caller's copy."""
    x = x ^ (x >> _U64(33))
    x = x * _U64(0xFF51AFD7ED558CCD)
    x ^= x >> _U64(33)
    x *= _U64(0xC4CEB9FE1A85EC53)
    x ^= x >> _U64(33)
    return x


_RNG = np.random.default_rng(20240229)
#: One odd base and one random value a byte: polynomial hashes modulo 2**64.
_BASE = int(_RNG.integers(1 << 62)) * 2 + 1
_INV = pow(_BASE, -1, 1 << 64)
BYTE_VALUE = _RNG.integers(0, 1 << 63, 256, dtype=np.uint64) * _U64(2) + _U64(1)
LOWER_VALUE = BYTE_VALUE.copy()
LOWER_VALUE[65:91] = BYTE_VALUE[97:123]
_WHITE = np.zeros(256, bool)
_WHITE[[0x20, 9, 10, 11, 12, 13]] = True
_POWERS: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n - 1) modulo 2**64, kept for the next call."""
    have = _POWERS.get(base)
    if have is None or len(have) < n:
        have = np.full(max(n, CHUNK_BYTES + 1), _U64(base), np.uint64)
        have[0] = 1
        have = np.multiply.accumulate(have)
        if len(have) <= 1 << 22:
            _POWERS[base] = have
    return have[:n]


def prefix_hash(raw: np.ndarray, values: np.ndarray = BYTE_VALUE) -> np.ndarray:
    """n + 1 prefix sums; ``span_hash`` of two of them depends on the bytes between alone."""
    out = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum(values[raw] * powers(_BASE, len(raw)), out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return mix64((prefix[end] - prefix[start]) * powers(_INV, len(prefix))[start])


def words(raw: np.ndarray, offsets: np.ndarray, white: np.ndarray = _WHITE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of every maximal run of non-separator bytes, and per row the index of its first word (n + 1)."""
    n = len(raw)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    inside = ~white[raw]
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    cut = offsets[:-1][offsets[:-1] < offsets[1:]]  # rows with bytes: a word never runs over a row's end
    first[cut] = inside[cut]
    last[cut[1:] - 1] = inside[cut[1:] - 1]
    start = np.flatnonzero(first)
    return start, np.flatnonzero(last) + 1, np.searchsorted(start, offsets)


def word_hashes(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """64-bit hashes of the words with A-Z lower-cased, their starts and ends, and each row's first word."""
    start, end, row = words(raw, offsets)
    return span_hash(prefix_hash(raw, LOWER_VALUE), start, end), start, end, row


_SHINGLE = [_U64(0x9E3779B97F4A7C15), _U64(0xC2B2AE3D27D4EB4F), _U64(0x165667B19E3779F9), _U64(0x27D4EB2F165667C5), _U64(0x85EBCA77C2B2AE63)]


def shingle_hashes(h: np.ndarray, width: int) -> np.ndarray:
    """Hash of each run of ``width`` consecutive word hashes; len(h) - width + 1 of them."""
    n = len(h) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = h[:n] * _SHINGLE[0]
    for i in range(1, width):
        out = mix64(out) + h[i : i + n] * _SHINGLE[i % len(_SHINGLE)]
    return mix64(out)
