"""The exact consistent sampler with Gamma variates: a hash is the component of least key and its quantised log weight."""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.functions.rng import bits52, mix32, sql_mix32, stream_word

#: Logarithms of two engines may differ in the last digit; levels are cut this far from a whole number, keys rounded so.
GUARD = 1e-9
DIGITS = 9
#: Words of a (hash, component): two each for the Gamma variates r and c, one for the uniform beta.
STREAMS = ("r1", "r2", "c1", "c2", "b")
_WORD, _WORDS = (1 << 32) - 1, float(1 << 32)
#: Variates of components and hashes that one table in a worker's memory holds.
TABLE = 1 << 21


def sketch(v: DataFrame, k: int, seed: int) -> DataFrame:
    """vec_id, hash_id, comp, level. Variates hang on (seed, hash, component) and are made in the row from two mixed words:
    no table of k * D of them. All is one projection and a minimum; rows grow k-fold inside the stage only."""
    own = [mix32((F.col("comp").cast("long") + stream_word(seed, "comp", i)).bitwiseAND(F.lit(_WORD))).alias(f"m{i}") for i in range(5)]
    rows = v.select("vec_id", "comp", F.log("weight").alias("lw"), *own, F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("hash_id"))
    rows = rows.withColumns({f"h{i}": mix32((F.col("hash_id").cast("long") + stream_word(seed, "hash", i)).bitwiseAND(F.lit(_WORD))) for i in range(5)})
    rows = rows.withColumns({f"u{i}": (mix32((F.col(f"m{i}") + F.col(f"h{i}")).bitwiseAND(F.lit(_WORD))) + 0.5) / _WORDS for i in range(5)})
    rows = rows.select("vec_id", "hash_id", "comp", "lw", (-F.log(F.col("u0") * F.col("u1"))).alias("r"), F.log(-F.log(F.col("u2") * F.col("u3"))).alias("lc"), F.col("u4").alias("beta"))
    level = F.floor(F.col("lw") / F.col("r") + F.col("beta") + GUARD)
    rows = rows.select("vec_id", "hash_id", "comp", level.alias("level"), (F.col("lc") - F.col("r") * (level - F.col("beta") + 1)).alias("key"))
    best = F.min_by(F.struct("comp", "level"), F.struct(F.round("key", DIGITS), "comp")).alias("b")
    return rows.groupBy("vec_id", "hash_id").agg(best).select("vec_id", "hash_id", "b.comp", "b.level")


def variates(seed: int, comps: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """r, ln c and beta, components x hashes, as ``sketch`` makes them."""
    u = []
    for i in range(5):
        m = mix32((comps + stream_word(seed, "comp", i)) & _WORD)
        h = mix32((np.arange(k) + stream_word(seed, "hash", i)) & _WORD)
        u.append((mix32((m[:, None] + h) & _WORD) + 0.5) / _WORDS)
    return -np.log(u[0] * u[1]), np.log(-np.log(u[2] * u[3])), u[4]


def sketcher(k: int, seed: int):
    """The function over Arrow batches (vec_id, comps, weights) that ``sketch_batches`` runs in the workers."""
    block = max(1, TABLE // k // 4)

    def run(batches):
        for batch in batches:
            ids, comps, weights = batch.columns
            edge = np.concatenate(([0], np.cumsum(np.asarray(comps.value_lengths().fill_null(0))))).astype(np.int64)
            c, lw = np.asarray(comps.flatten()).astype(np.int64), np.log(np.asarray(weights.flatten(), float))
            names = np.unique(c)
            table = variates(seed, names, k) if len(names) * k <= TABLE else None
            at = np.searchsorted(names, c)
            n, every = batch.num_rows, np.arange(k)
            bc, bl = np.zeros((n, k), np.int32), np.zeros((n, k), np.int64)
            for i in range(n):
                best = np.full(k, np.inf)
                for lo in range(edge[i], edge[i + 1], block):  # components ascend, so the first of equal keys has the least
                    s = slice(lo, min(lo + block, edge[i + 1]))
                    r, lc, beta = (x[at[s]] for x in table) if table is not None else variates(seed, c[s], k)
                    level = np.floor(lw[s, None] / r + beta + GUARD)
                    key = np.round(lc - r * (level - beta + 1), DIGITS)
                    j = key.argmin(0)
                    m = key[j, every]
                    less = m < best
                    best[less], bl[i, less], bc[i, less] = m[less], level[j, every][less], c[s][j][less]
            off = pa.array(np.arange(0, n * k + 1, k, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(off, pa.array(bc.ravel())), pa.ListArray.from_arrays(off, pa.array(bl.ravel()))], ["vec_id", "comps", "levels"])

    return run


def sketch_batches(packed: DataFrame, k: int, seed: int) -> DataFrame:
    """vec_id, comps ARRAY<INT>, levels ARRAY<BIGINT> in Arrow batches, the same hashes as ``sketch``. The variates of a
    batch's components are one table where it stays below TABLE; otherwise they are made by blocks of a vector."""
    return packed.select("vec_id", "comps", "weights").mapInArrow(sketcher(k, seed), "vec_id long, comps array<int>, levels array<long>")


def compact(hashes: DataFrame, bits: int | None = None, mode: str = "pair", seed: int = 0) -> DataFrame:
    """vec_id, hash_id, v: ``component`` drops the level (a known approximation), ``pair`` hashes both; bits keeps so many.
    Of the packed hashes of ``sketch_batches``: vec_id, sketch, the same values in order of hash_id, without a row a hash."""
    if "levels" in hashes.columns:
        if mode == "component" and bits is None:
            return hashes.select("vec_id", F.col("comps").cast("array<long>").alias("sketch"))

        def one(e, i):
            v = bits52(seed, "v", i, *((e["comps"],) if mode == "component" else (e["comps"], e["levels"])))
            return F.pmod(v, F.lit(1 << bits)) if bits else v

        return hashes.select("vec_id", F.transform(F.arrays_zip("comps", "levels"), one).alias("sketch"))
    if mode == "component" and bits is None:
        return hashes.select("vec_id", "hash_id", F.col("comp").cast("long").alias("v"))
    part = (F.col("comp"),) if mode == "component" else (F.col("comp"), F.col("level"))
    v = bits52(seed, "v", F.col("hash_id"), *part)
    return hashes.select("vec_id", "hash_id", (F.pmod(v, F.lit(1 << bits)) if bits else v).alias("v"))


def active_index_one(weights: dict[int, int], k: int, seed: int) -> list[tuple[int, int]]:
    """The older sampler for whole weights, in plain Python for tests: the hash is the unit (component, index) of least
    value. Of a component's units only the record minima are visited; from one of value z at index i the next lies a
    geometric gap with chance z further on and is z times a uniform draw, both seeded by i, so that all weights share them."""

    def u(*key) -> float:
        return (int(hashlib.md5(":".join(map(str, key)).encode()).hexdigest()[:13], 16) + 0.5) / 2**52

    out = []
    for h in range(k):
        best = (math.inf, -1, -1)
        for c, w in weights.items():
            at, z = 1, u(seed, h, c, "first")
            while True:
                far = at + 1 + math.floor(math.log(u(seed, h, c, at, "gap")) / math.log1p(-z))
                if far > w:
                    break
                at, z = far, z * u(seed, h, c, at, "value")
            best = min(best, (z, c, at))
        out.append(best[1:])
    return out


def sql(k: int, seed: int, v: str = "v", name: str = "gam") -> str:
    col = lambda f: ", ".join(f(i) for i in range(5))
    return (
        f"{name}_w AS (SELECT vec_id, comp, ln(weight) AS lw, {col(lambda i: f'((comp::BIGINT + {stream_word(seed, "comp", i)}) & {_WORD}) AS c{i}')} FROM {v}), "
        f"{name}_h AS (SELECT hash_id::INT AS hash_id, {col(lambda i: f'((hash_id::BIGINT + {stream_word(seed, "hash", i)}) & {_WORD}) AS g{i}')} FROM range({k}) x(hash_id)), "
        f"{name}_c AS MATERIALIZED (SELECT vec_id, comp, lw, {col(lambda i: f'{sql_mix32(f"c{i}")} AS m{i}')} FROM {name}_w), "
        f"{name}_k AS MATERIALIZED (SELECT hash_id, {col(lambda i: f'{sql_mix32(f"g{i}")} AS h{i}')} FROM {name}_h), "
        f"{name}_x AS (SELECT vec_id, comp, lw, hash_id, {col(lambda i: f'((m{i} + h{i}) & {_WORD}) AS x{i}')} FROM {name}_c, {name}_k), "
        f"{name}_u AS (SELECT vec_id, comp, lw, hash_id, {col(lambda i: f'(({sql_mix32(f"x{i}")}) + 0.5::DOUBLE) / {_WORDS}::DOUBLE AS u{i}')} FROM {name}_x), "
        f"{name}_p AS (SELECT vec_id, comp, hash_id, lw, -ln(u0 * u1) AS r, ln(-ln(u2 * u3)) AS lc, u4 AS beta FROM {name}_u), "
        f"{name}_l AS (SELECT *, floor(lw / r + beta + {GUARD}) AS lev FROM {name}_p), "
        f"{name} AS (SELECT vec_id, hash_id, b.comp AS comp, b.lev::BIGINT AS level FROM (SELECT vec_id, hash_id, min_by(struct_pack(comp := comp, lev := lev), struct_pack(k := round(lc - r * (lev - beta + 1), {DIGITS}), comp := comp)) AS b FROM {name}_l GROUP BY ALL))"
    )
