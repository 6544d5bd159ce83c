"""Cost, accuracy and storage measures."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.plans import layout as L


def dataset_stats(v: DataFrame) -> DataFrame:
    """n, d_avg, dim, total (whole widths), s_avg in one row, by aggregates alone."""
    caps = v.groupBy("comp").agg(F.greatest(F.lit(1.0), F.ceil(F.max("weight")).cast("double")).alias("cap")).agg(F.count("*").alias("dim"), F.sum("cap").alias("total"))
    per = v.groupBy("vec_id").agg(F.count("*").alias("d"), F.sum("weight").alias("l1")).agg(F.count("*").alias("n"), F.avg("d").alias("d_avg"), F.avg("l1").alias("l1"))
    return per.crossJoin(caps).select("n", "d_avg", "dim", "total", (F.col("l1") / F.col("total")).alias("s_avg"))


def hash_moments(hashes: DataFrame, fills: DataFrame) -> DataFrame:
    """Mean and variance of hashes against 1 / s and (1 - s) / s**2, by vector."""
    got = hashes.groupBy("vec_id").agg(F.avg("h").alias("mean_h"), F.var_samp("h").alias("var_h"))
    s = F.col("s")
    return got.join(fills, "vec_id").select("vec_id", "mean_h", "var_h", (1 / s).alias("mean_theory"), ((1 - s) / (s * s)).alias("var_theory"))


def tail_check(hashes: DataFrame, fills: DataFrame, steps: list[int]) -> DataFrame:
    """t, observed and expected share of hashes above t."""
    j = hashes.join(fills.select("vec_id", "s"), "vec_id").select("h", "s", F.explode(F.array(*[F.lit(t) for t in steps])).alias("t"))
    return j.groupBy("t").agg(F.avg((F.col("h") > F.col("t")).cast("double")).alias("observed"), F.avg(F.pow(1 - F.col("s"), F.col("t"))).alias("expected"))


def range_bits(hashes: DataFrame) -> DataFrame:
    """Mean, least and largest hash, and the bits that hold all."""
    return hashes.agg(F.avg("h").alias("mean_h"), F.min("h").alias("min_h"), F.max("h").alias("max_h"), F.ceil(F.log2(F.max("h") + 1)).cast("int").alias("bits"))


def bits_report(hashes: DataFrame, fills: DataFrame) -> DataFrame:
    """Mean log2 of hashes beside the bound log2(1/s), its second-order form and the entropy of the geometric law."""
    s = F.col("s")
    entropy = (-(1 - s) * F.log2(1 - s) - s * F.log2(s)) / s
    theory = fills.where("s < 1").agg(F.avg(F.log2(1 / s)).alias("bound"), F.avg(F.log2(1 / s) - (1 - s) / (2 * math.log(2))).alias("second_order"), F.avg(entropy).alias("entropy"))
    return hashes.agg(F.avg(F.log2("h")).alias("mean_log2")).crossJoin(theory)


def storage(hashes: DataFrame, k: int) -> DataFrame:
    """Bytes of a sketch at the bits it needs, and savings against 32, 64 and 96 bits (a pair) a hash."""
    b = F.col("bits")
    return range_bits(hashes).select("bits", F.ceil(b * k / 8).alias("bytes"), (32 / b).alias("saving_32"), (64 / b).alias("saving_64"), (96 / b).alias("saving_pair"))


def work(v: DataFrame, layout: L.Layout, k: int) -> DataFrame:
    """Per vector: expected draws (and membership tests) of the red-green sampler, variate sets of the gamma sampler, copies
    of the replicated one."""
    per = v.groupBy("vec_id").agg(F.count("*").alias("d"), F.sum("weight").alias("l1"))
    return per.select("vec_id", (F.lit(k) * layout.total / (F.col("l1") * layout.alpha)).alias("draws"), (F.lit(k) * F.col("d")).alias("variates"), F.col("l1").alias("copies"))


def draw_counts(hashes: DataFrame) -> DataFrame:
    return hashes.groupBy("vec_id").agg(F.sum("h").alias("draws"))


def position_correlation(agreed: DataFrame) -> DataFrame:
    """Correlation of agreement at neighbouring hash positions over repetitions: agreed has rep, hash_id, same (0 or 1)."""
    nxt = agreed.select("rep", (F.col("hash_id") - 1).alias("hash_id"), F.col("same").alias("next"))
    return agreed.join(nxt, ["rep", "hash_id"]).agg(F.corr(F.col("same").cast("double"), F.col("next").cast("double")).alias("corr"), F.count("*").alias("n"))
