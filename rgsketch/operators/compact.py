"""Fewer bits a hash: rehashing, lowest bits, and packing into bytes."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rgsketch.functions.rng import bits52


def rehash(hashes: DataFrame, bits: int, seed: int = 0, value: tuple[str, ...] = ("h",)) -> DataFrame:
    """vec_id, hash_id, v: each hash's value sent at random to 2**bits cells; different ones meet with chance 2**-bits."""
    v = F.pmod(bits52(seed, "re", F.col("hash_id"), *[F.col(c) for c in value]), F.lit(1 << bits))
    return hashes.select("vec_id", "hash_id", v.alias("v"))


def low_bits(hashes: DataFrame, bits: int) -> DataFrame:
    return hashes.select("vec_id", "hash_id", F.col("h").cast("long").bitwiseAND(F.lit((1 << bits) - 1)).alias("v"))


def debias_bits(est: Column, bits: int) -> Column:
    """Similarity from the agreement of ideal uniform bits."""
    floor = 2.0**-bits
    return (est - floor) / (1 - floor)


def pack(sketches: DataFrame, bits: int) -> DataFrame:
    """vec_id, packed BINARY: sketch values (up to 2**bits - 1, else it raises) in ``bits`` bits each."""

    @F.pandas_udf("binary")
    def run(s: pd.Series) -> pd.Series:
        def one(x):
            x = np.asarray(x, np.uint64)
            if len(x) and int(x.max()) >> bits:
                raise ValueError("a hash needs more bits")
            return np.packbits(((x[:, None] >> np.arange(bits, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8).ravel(), bitorder="little").tobytes()

        return s.map(one)

    return sketches.select("vec_id", run("sketch").alias("packed"))


def unpack(packed: DataFrame, bits: int, k: int) -> DataFrame:
    @F.pandas_udf("array<int>")
    def run(s: pd.Series) -> pd.Series:
        def one(b):
            x = np.unpackbits(np.frombuffer(b, np.uint8), count=bits * k, bitorder="little").reshape(k, bits)
            return (x.astype(np.int64) << np.arange(bits)).sum(1).astype(np.int32)

        return s.map(one)

    return packed.select("vec_id", run("packed").alias("sketch"))
