"""Unweighted minwise hashing: k hash functions, or one permutation cut into k bins with empty ones filled."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rgsketch.functions.rng import DIGIT_BITS, PRIME, scramble, sql_scramble, sql_universal, two_universal, uniform, universal_triple
from rgsketch.sources.tables import materialize


def minhash(sets: DataFrame, k: int, seed: int) -> DataFrame:
    """vec_id, hash_id, h: the least of each of k 2-universal hashes over (vec_id, elem)."""
    rows = sets.select("vec_id", scramble(F.col("elem").cast("long"), seed).alias("x"))
    got = rows.groupBy("vec_id").agg(*[F.min(two_universal(F.col("x"), seed, salt=f":{i}")).alias(f"m{i}") for i in range(k)])
    return got.select("vec_id", F.posexplode(F.array(*[f"m{i}" for i in range(k)])).alias("hash_id", "h"))


def oph(sets: DataFrame, k: int, seed: int) -> DataFrame:
    """vec_id, bin, h: the least offset in every non-empty one of k bins of one hash."""
    width = -(-PRIME // k)
    h = two_universal(F.col("x"), seed)
    rows = sets.select("vec_id", scramble(F.col("elem").cast("long"), seed).alias("x")).select("vec_id", F.floor(h / width).cast("int").alias("bin"), F.pmod(h, F.lit(width)).alias("o"))
    return rows.groupBy("vec_id", "bin").agg(F.min("o").alias("h"))


def _ring(bins: DataFrame, k: int) -> DataFrame:
    got = bins.groupBy("vec_id").agg(F.map_from_entries(F.collect_list(F.struct("bin", "h"))).alias("m"))
    return got.select("vec_id", F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.try_element_at("m", i.cast("int"))).alias("b"))


def densify(bins: DataFrame, k: int, mode: str = "rotate", seed: int = 0) -> DataFrame:
    """vec_id, bin, h for all k bins. An empty bin borrows from the nearest full one to the right, ring-wise (``rotate``),
    to the side that a coin of the bin says (``direction``), each adding the way's length times an offset; or from the first
    full one of a sequence drawn for the bin (``probe``)."""
    width = -(-PRIME // k)
    if mode == "probe":
        return _probe(bins, k, seed)
    bins = materialize(bins)  # read twice; and no filter on a bin is inferred into the hashes' long expressions
    # two rounds of the ring by windows over full bins: the next full bin to the right and to the left of each
    grid = bins.select("vec_id").distinct().crossJoin(F.broadcast(bins.sparkSession.range(k).select(F.col("id").cast("int").alias("bin"))))
    rows = grid.join(bins, ["vec_id", "bin"], "left")
    ring = rows.select("vec_id", "h", F.explode(F.array(F.col("bin") - k, "bin", F.col("bin") + k)).alias("at"))
    own = F.when(F.col("h").isNotNull(), F.struct(F.col("at").alias("at"), F.col("h").alias("h")))
    w = Window.partitionBy("vec_id").orderBy("at")
    right = F.first(own, ignorenulls=True).over(w.rowsBetween(0, Window.unboundedFollowing))
    left = F.last(own, ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, 0))
    full = ring.select("vec_id", F.col("at").alias("bin"), right.alias("r"), left.alias("l")).where((F.col("bin") >= 0) & (F.col("bin") < k))
    step = width + 1
    by_right = F.col("r.h") + (F.col("r.at") - F.col("bin")) * F.lit(step)
    by_left = F.col("l.h") + (F.col("bin") - F.col("l.at")) * F.lit(step)
    h = by_right if mode == "rotate" else F.when(uniform(seed, "side", F.col("bin")) < 0.5, by_right).otherwise(by_left)
    return full.select("vec_id", "bin", h.cast("long").alias("h"))


def _probe(bins: DataFrame, k: int, seed: int) -> DataFrame:
    def run(batches):
        for batch in batches:
            out = []
            for row in batch.column(1).to_pylist():
                full = {i for i, x in enumerate(row) if x is not None}
                own = []
                for i, x in enumerate(row):
                    if x is None and full:
                        rng = np.random.default_rng([seed, i])
                        for _ in range(64 * k):
                            j = int(rng.integers(k))
                            if j in full:
                                break
                        else:
                            j = min(full)
                        x = row[j]
                    own.append(x)
                out.append(own)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.list_(pa.int64()))], ["vec_id", "b"])

    got = _ring(bins, k).mapInArrow(run, "vec_id long, b array<long>")
    return got.select("vec_id", F.posexplode("b").alias("bin", "h"))


def permute_exact(universe: DataFrame, seed: int) -> DataFrame:
    """elem, rank: a true random order of a small universe, ranked in one place."""
    return universe.select("elem").distinct().withColumn("rank", F.row_number().over(Window.orderBy(uniform(seed, "perm", F.col("elem")), "elem")) - 1)


def naive_sample(v: DataFrame, k: int, seed: int) -> DataFrame:
    """The control that must fail: each vector draws a component by weight on its own, without shared draws."""
    run = Window.partitionBy("vec_id").orderBy("comp").rowsBetween(Window.unboundedPreceding, 0)
    all_ = F.sum("weight").over(Window.partitionBy("vec_id"))
    rows = v.withColumn("up", F.sum("weight").over(run) / all_).withColumn("hash_id", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))
    rows = rows.where(F.col("up") >= uniform(seed, "own", F.col("vec_id"), F.col("hash_id")))
    return rows.groupBy("vec_id", "hash_id").agg(F.min_by("comp", "up").alias("h"))


def sql_minhash(k: int, seed: int, sets: str = "rep", name: str = "mh") -> str:
    rows = ", ".join(f"({i}, {a}::BIGINT, {c}::BIGINT, {b}::BIGINT)" for i in range(k) for a, c, b in [universal_triple(seed, f":{i}")])
    h = f"((x & {(1 << DIGIT_BITS) - 1}) * a + (x >> {DIGIT_BITS}) * c + b) % {PRIME}"
    return f"{name}_x AS MATERIALIZED (SELECT vec_id, {sql_scramble('elem', seed)} AS x FROM {sets}), {name} AS (SELECT vec_id, hash_id::INT AS hash_id, min({h})::BIGINT AS h FROM {name}_x, (VALUES {rows}) t(hash_id, a, c, b) GROUP BY ALL)"


def sql_oph(k: int, seed: int, sets: str = "rep", name: str = "oph") -> str:
    width = -(-PRIME // k)
    return f"{name}_x AS MATERIALIZED (SELECT vec_id, {sql_scramble('elem', seed)} AS y FROM {sets}), {name} AS (SELECT vec_id, (x // {width})::INT AS bin, min(x % {width})::BIGINT AS h FROM (SELECT vec_id, {sql_universal('y', seed)} AS x FROM {name}_x) GROUP BY ALL)"


def sql_densify(k: int, mode: str = "rotate", seed: int = 0, bins: str = "oph", name: str = "den") -> str:
    from rgsketch.functions.rng import sql_uniform

    step = -(-PRIME // k) + 1
    right = f"(SELECT min_by(o.h + (o.at - g.bin)::BIGINT * {step}, o.at) FROM {name}_o o WHERE o.vec_id = g.vec_id AND o.at >= g.bin)"
    left = f"(SELECT max_by(o.h + (g.bin - o.at)::BIGINT * {step}, o.at) FROM {name}_o o WHERE o.vec_id = g.vec_id AND o.at <= g.bin)"
    pick = right if mode == "rotate" else f"CASE WHEN {sql_uniform(f'{seed}', "'side'", 'g.bin')} < 0.5 THEN {right} ELSE {left} END"
    return (
        f"{name}_o AS (SELECT vec_id, h, bin + s * {k} AS at FROM {bins}, (VALUES (-1), (0), (1)) t(s)), "
        f"{name} AS (SELECT g.vec_id, g.bin, {pick}::BIGINT AS h FROM (SELECT vec_id, bin::INT AS bin FROM (SELECT DISTINCT vec_id FROM {bins}), range({k}) r(bin)) g)"
    )
