"""Exact and estimated similarity of pairs, and distances that follow from it."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rgsketch.operators import blocks


def exact_pairs(v: DataFrame, pairs: DataFrame | None = None) -> DataFrame:
    """id_a, id_b, j: sum of minima over sum of maxima. Without ``pairs``, all pairs a < b that share a component."""
    if pairs is None:
        return blocks.pairs(v)
    norm = v.groupBy("vec_id").agg(F.sum("weight").alias("l1"))
    a, b = (v.select(F.col("vec_id").alias(f"id_{x}"), "comp", F.col("weight").alias(f"w_{x}")) for x in "ab")
    pairs = pairs.select("id_a", "id_b").distinct()
    hit = pairs.join(a, "id_a").join(b, ["id_b", "comp"]).groupBy("id_a", "id_b").agg(F.sum(F.least("w_a", "w_b")).alias("lo"))
    both = pairs.join(hit, ["id_a", "id_b"], "left").withColumn("lo", F.coalesce("lo", F.lit(0.0)))
    na, nb = (norm.select(F.col("vec_id").alias(f"id_{x}"), F.col("l1").alias(f"l1_{x}")) for x in "ab")
    return both.join(na, "id_a").join(nb, "id_b").select("id_a", "id_b", (F.col("lo") / (F.col("l1_a") + F.col("l1_b") - F.col("lo"))).alias("j"), "l1_a", "l1_b")


def set_jaccard(a: Column, b: Column) -> Column:
    """Of two arrays of distinct values."""
    common = F.size(F.array_intersect(a, b))
    return common / (F.size(a) + F.size(b) - common)


def map_jaccard(a: Column, b: Column) -> Column:
    """Generalised similarity of two MAP<_, DOUBLE>."""
    keys = F.array_union(F.map_keys(a), F.map_keys(b))
    get = lambda m, k: F.coalesce(F.try_element_at(m, k), F.lit(0.0))
    total = lambda f: F.aggregate(keys, F.lit(0.0), lambda s, k: s + f(get(a, k), get(b, k)))
    return total(F.least) / total(F.greatest)


def agreement(a: Column, b: Column, upto: int | None = None) -> Column:
    """Share of equal values at equal positions of two sketches; 0 stands for an unresolved hash and equals nothing."""
    if upto is not None:
        a, b = F.slice(a, 1, upto), F.slice(b, 1, upto)
    same = F.zip_with(a, b, lambda x, y: ((x == y) & (x != 0)).cast("int"))
    return F.aggregate(same, F.lit(0), lambda s, x: s + F.coalesce(x, F.lit(0))) / F.size(a)


def estimate(sketches: DataFrame, pairs: DataFrame, upto: int | None = None) -> DataFrame:
    """id_a, id_b, est from packed sketches. Sketches with layout_id, method and seed must agree in them, else it raises."""
    tags = [c for c in ("method", "layout_id", "seed") if c in sketches.columns]
    a, b = (sketches.select(F.col("vec_id").alias(f"id_{x}"), F.col("sketch").alias(f"s_{x}"), *[F.col(t).alias(f"{t}_{x}") for t in tags]) for x in "ab")
    j = pairs.join(a, "id_a").join(b, "id_b")
    est = agreement(F.col("s_a"), F.col("s_b"), upto)
    for t in tags:
        est = F.when(F.col(f"{t}_a").eqNullSafe(F.col(f"{t}_b")), est).otherwise(F.raise_error(F.lit(f"sketches of different {t} don't compare")).cast("double"))
    return j.select("id_a", "id_b", est.alias("est"))


def estimate_long(hashes: DataFrame, pairs: DataFrame, k: int, value: tuple[str, ...] = ("h",)) -> DataFrame:
    """The same from long hashes, whose value may be several columns."""
    a, b = (hashes.select(F.col("vec_id").alias(f"id_{x}"), "hash_id", F.struct(*value).alias(f"v_{x}")) for x in "ab")
    j = pairs.join(a, "id_a").join(b, ["id_b", "hash_id"])
    return j.groupBy("id_a", "id_b").agg((F.sum((F.col("v_a") == F.col("v_b")).cast("int")) / F.lit(k)).alias("est"))


def std_error(j: Column, k: int) -> Column:
    return F.sqrt(j * (1 - j) / k)


def required_k(eps: float, delta: float) -> int:
    """Hashes after which the estimate is within eps but for probability delta, whatever the similarity."""
    return math.ceil(math.log(2 / delta) / (2 * eps * eps))


def required_k_of(eps: Column, delta: Column) -> Column:
    """The same of columns."""
    return F.ceil(F.log(F.lit(2) / delta) / (F.lit(2) * eps * eps))


def cap_correction(j: Column, union_fill: Column, steps: int) -> Column:
    """Similarity from the expected estimate of sketches capped at ``steps`` draws."""
    return j / (1 - F.pow(1 - union_fill, F.lit(steps)))


def l1_estimate(est: Column, l1_a: Column, l1_b: Column) -> Column:
    """L1 distance from similarity and norms."""
    return (l1_a + l1_b) * (1 - est) / (1 + est)


def exact_l1(v: DataFrame, pairs: DataFrame | None = None) -> DataFrame:
    """id_a, id_b, l1 of the given pairs, or of all that share a component."""
    return exact_pairs(v, pairs).select("id_a", "id_b", l1_estimate(F.col("j"), F.col("l1_a"), F.col("l1_b")).alias("l1"))


def cumulative(v: DataFrame) -> DataFrame:
    """Histograms over ordered components to their running shares: the L1 distance of two of these is the earth mover's
    distance in one dimension. Shares are taken at every component of the data set, so gaps keep the running value."""
    grid = v.select("vec_id").distinct().crossJoin(v.select("comp").distinct())
    total = v.groupBy("vec_id").agg(F.sum("weight").alias("all"))
    rows = grid.join(v, ["vec_id", "comp"], "left").join(total, "vec_id")
    run = Window.partitionBy("vec_id").orderBy("comp").rowsBetween(Window.unboundedPreceding, 0)
    return rows.select("vec_id", "comp", (F.sum(F.coalesce("weight", F.lit(0.0))).over(run) / F.col("all")).alias("weight")).where("weight > 0")


def grid_tree(v: DataFrame, side: int) -> DataFrame:
    """Histograms over a side x side grid (comp = row * side + column) to counts of nested squares weighted by their width;
    L1 distances bound the two-dimensional earth mover's distance within a logarithmic factor."""
    row, col = F.floor(F.col("comp") / side), F.pmod("comp", F.lit(side))
    parts, base, width = [], 0, 1
    while width <= side:
        across = -(-side // width)
        parts.append(F.struct((F.lit(base) + F.floor(row / width) * across + F.floor(col / width)).cast("int").alias("comp"), (F.col("weight") * width).alias("weight")))
        base, width = base + across * across, width * 2
    return v.select("vec_id", F.explode(F.array(*parts)).alias("p")).groupBy("vec_id", F.col("p.comp").alias("comp")).agg(F.sum("p.weight").alias("weight"))


def sql_exact(v: str = "v", name: str = "ex", where: str = "TRUE") -> str:
    return (
        f"{name}_l AS (SELECT vec_id, sum(weight) AS l1 FROM {v} GROUP BY vec_id), "
        f"{name}_s AS (SELECT a.vec_id AS id_a, b.vec_id AS id_b, sum(least(a.weight, b.weight)) AS lo FROM {v} a JOIN {v} b ON a.comp = b.comp AND a.vec_id < b.vec_id WHERE {where} GROUP BY ALL), "
        f"{name} AS (SELECT id_a, id_b, lo / (x.l1 + y.l1 - lo) AS j, x.l1 AS l1_a, y.l1 AS l1_b FROM {name}_s JOIN {name}_l x ON x.vec_id = id_a JOIN {name}_l y ON y.vec_id = id_b)"
    )
