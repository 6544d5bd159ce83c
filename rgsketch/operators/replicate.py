"""Weights to sets of copies, exactly for whole weights and with a bias for others."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.functions.rng import DIGIT_BITS, sql_uniform, uniform

#: An element is comp * SHIFT + copy: no two pairs share one while comps and copies stay below SHIFT.
SHIFT = 1 << DIGIT_BITS


def to_set(v: DataFrame, scale: float = 1.0, coin: str = "shared", seed: int = 0) -> DataFrame:
    """vec_id, comp, copy (from 1), elem. The fraction left decides on a last copy by a coin: one for each component
    (``shared``), one for each vector and component (``independent``), or none, where a fraction is an error (``none``).
    A component with SHIFT copies or more is an error."""
    x = F.col("weight") * F.lit(float(scale))
    whole = F.floor(x)
    if coin == "none":
        n = F.when(x == whole, whole).otherwise(F.raise_error(F.lit("a weight isn't whole")).cast("long"))
    else:
        u = uniform(seed, "coin", F.col("comp")) if coin == "shared" else uniform(seed, "coin", F.col("vec_id"), F.col("comp"))
        n = whole + (u < x - whole).cast("long")
    n = F.when(n < SHIFT, n).otherwise(F.raise_error(F.lit("too many copies of a component")).cast("long"))
    rows = v.select("vec_id", "comp", n.alias("n")).where("n > 0")
    rows = rows.select("vec_id", "comp", F.explode(F.sequence(F.lit(1), F.col("n").cast("int"))).alias("copy"))
    return rows.withColumn("elem", F.col("comp").cast("long") * SHIFT + F.col("copy"))


def quantize(v: DataFrame, layout, levels: int) -> DataFrame:
    """Weights as whole numbers of 1 / levels of their component's maximum; those rounded to 0 go."""
    q = F.round(F.col("weight") * levels / F.col("max_w"))
    return v.join(layout.df.select("comp", "max_w"), "comp").select("vec_id", "comp", q.alias("weight")).where("weight > 0")


def sql(v: str = "v", scale: float = 1.0, coin: str = "shared", seed: int = 0, name: str = "rep") -> str:
    u = {"shared": sql_uniform(f"'{seed}'", "'coin'", "comp"), "independent": sql_uniform(f"'{seed}'", "'coin'", "vec_id", "comp"), "none": "1.0"}[coin]
    return (
        f"{name}_n AS (SELECT vec_id, comp, floor(weight * {float(scale)}::DOUBLE)::BIGINT + CASE WHEN {u} < weight * {float(scale)}::DOUBLE - floor(weight * {float(scale)}::DOUBLE) THEN 1 ELSE 0 END AS n FROM {v}), "
        f"{name} AS (SELECT vec_id, comp, copy::INT AS copy, comp::BIGINT * {SHIFT} + copy AS elem FROM (SELECT vec_id, comp, unnest(range(1, n + 1)) AS copy FROM {name}_n WHERE n > 0))"
    )
