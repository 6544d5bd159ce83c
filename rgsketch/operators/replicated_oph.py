"""The fast biased baseline: copies, one permutation, k bins, empty ones filled."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.functions.rng import DIGIT_BITS, PRIME, UNIT, bits52_of, mix32, scramble_digits, stream_word, universal_triple
from rgsketch.operators import replicate, unweighted


def sketch(v: DataFrame, k: int, seed: int, scale: float = 1.0, coin: str = "shared", densify: str = "rotate") -> DataFrame:
    """vec_id, hash_id, h. Copies are made and folded into bins in one stage."""
    bins = unweighted.oph(replicate.to_set(v, scale, coin, seed), k, seed)
    return unweighted.densify(bins, k, densify, seed).withColumnRenamed("bin", "hash_id")


def sketch_classic(v: DataFrame, k: int, seed: int, scale: float = 1.0, coin: str = "shared") -> DataFrame:
    """The same copies under k hash functions."""
    return unweighted.minhash(replicate.to_set(v, scale, coin, seed), k, seed)


@lru_cache(1 << 20)
def _coin(seed: int, *key: int) -> float:
    return bits52_of(seed, "coin", *key) / UNIT


def _bins(comps: np.ndarray, x: np.ndarray, k: int, seed: int, triple: tuple[int, int, int], vec: int | None = None) -> np.ndarray:
    """The k filled bins of one vector of scaled weights; PRIME everywhere if it has no copy. Coins are the vector's own if
    it is given."""
    a, c, b = triple
    width = -(-PRIME // k)
    whole = np.floor(x).astype(np.int64)
    part = x - whole
    some = np.flatnonzero(part)
    whole[some] += np.array([_coin(seed, j) if vec is None else _coin(seed, vec, j) for j in comps[some].tolist()]) < part[some]
    copy = np.arange(whole.sum()) - np.repeat(np.cumsum(whole) - whole, whole) + 1
    x = scramble_digits(copy, np.repeat(mix32((comps + stream_word(seed, "elem", 0)) & 0xFFFFFFFF), whole))
    h = ((x & ((1 << DIGIT_BITS) - 1)) * a + (x >> DIGIT_BITS) * c + b) % PRIME
    bins = np.full(k, PRIME, np.int64)
    np.minimum.at(bins, h // width, h % width)
    full = np.flatnonzero(bins < PRIME)
    if len(full):
        at = np.arange(k)
        to = np.searchsorted(full, at)
        near = np.where(to < len(full), full[np.minimum(to, len(full) - 1)], full[0] + k)
        bins = bins[near % k] + (near - at) * (width + 1)
    return bins


def sketcher(k: int, seed: int, scale: float = 1.0):
    """The function over Arrow batches (vec_id, comps, weights) that ``sketch_batches`` runs in the workers."""
    triple = universal_triple(seed)

    def run(batches):
        for batch in batches:
            ids, comps, weights = batch.columns
            edge = np.concatenate(([0], np.cumsum(np.asarray(comps.value_lengths().fill_null(0))))).astype(np.int64)
            c, x = np.asarray(comps.flatten()).astype(np.int64), np.asarray(weights.flatten(), float) * scale
            out = [_bins(c[lo:hi], x[lo:hi], k, seed, triple) for lo, hi in zip(edge[:-1], edge[1:], strict=True)]
            some = [i for i, bins in enumerate(out) if bins[0] < PRIME or bins.min() < PRIME]
            off = pa.array(np.arange(0, len(some) * k + 1, k, dtype=np.int32))
            flat = np.concatenate([out[i] for i in some]) if some else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(some, pa.int64())), pa.ListArray.from_arrays(off, pa.array(flat))], ["vec_id", "sketch"])

    return run


def sketch_batches(packed: DataFrame, k: int, seed: int, scale: float = 1.0) -> DataFrame:
    """vec_id, sketch ARRAY<BIGINT> in Arrow batches: shared coins, rotation, the same hashes as ``sketch``. Vectors without
    a copy give no row."""
    return packed.select("vec_id", "comps", "weights").mapInArrow(sketcher(k, seed, scale), "vec_id long, sketch array<long>")


def sketch_seeds(packed: DataFrame, k: int, seeds: range, scale: float = 1.0, coin: str = "shared") -> DataFrame:
    """vec_id, rep, hash_id, h: the sketches of ``sketch_batches`` under each of some seeds (rep counts them), for studies of
    few vectors; coins are shared or, ``independent``, each vector's own."""
    triples = [universal_triple(s) for s in seeds]

    def run(batches):
        for batch in batches:
            for vec, comps, weights in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                c, x = np.asarray(comps, np.int64), np.asarray(weights, float) * scale
                rows = [_bins(c, x, k, s, t, vec if coin == "independent" else None) for s, t in zip(seeds, triples, strict=True)]
                h = np.concatenate(rows)
                n = len(h)
                out = [pa.array(np.full(n, vec, np.int64)), pa.array(np.repeat(np.arange(len(rows), dtype=np.int32), k)), pa.array(np.tile(np.arange(k, dtype=np.int32), len(rows))), pa.array(h)]
                yield pa.RecordBatch.from_arrays(out, ["vec_id", "rep", "hash_id", "h"])

    got = packed.select("vec_id", "comps", "weights").mapInArrow(run, "vec_id long, rep int, hash_id int, h long")
    return got.where(F.col("h") != PRIME)  # a vector without a copy has no hash


def elements(v: DataFrame, scale: float = 1.0) -> DataFrame:
    """vec_id, copies: the expected work, to look at before a scale is chosen."""
    return v.groupBy("vec_id").agg(F.sum(F.col("weight") * scale).alias("copies"))
