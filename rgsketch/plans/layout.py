"""Layouts: components side by side on [0, total), each with a width at least its largest weight in the data set."""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, Row, SparkSession, Window
from pyspark.sql import functions as F

BLOCK = 4096


@dataclass(frozen=True)
class Layout:
    """df has comp, max_w, cap, lo; hashes compare only under one layout_id."""

    df: DataFrame
    total: float
    dim: int
    alpha: float = 1.0
    widths: int = 0

    @property
    def layout_id(self) -> str:
        """Of the scale and all (component, width) pairs; ``widths`` is their hash whatever the order of rows."""
        return hashlib.md5(f"{self.total}:{self.dim}:{self.alpha}:{self.widths}".encode()).hexdigest()[:12]

    def tag(self, sketches: DataFrame, seed: int, method: str = "redgreen") -> DataFrame:
        """Packed or long hashes with what two of them must have in common to compare."""
        return sketches.withColumns({"method": F.lit(method), "layout_id": F.lit(self.layout_id), "seed": F.lit(seed).cast("long")})


def component_caps(v: DataFrame, alpha: float = 1.0, rounding: str = "ceil") -> DataFrame:
    """comp, max_w, cap: the least whole width that holds alpha * max (``ceil``), or alpha * max itself (``exact``)."""
    top = v.groupBy("comp").agg(F.max("weight").alias("max_w")).where("max_w > 0")
    wide = F.col("max_w") * F.lit(float(alpha))
    cap = wide if rounding == "exact" else F.greatest(F.lit(1.0), F.ceil(wide).cast("double"))
    return top.select("comp", "max_w", cap.alias("cap"))


def build_layout(caps: DataFrame, alpha: float = 1.0) -> Layout:
    """Starts by prefix sums: within blocks of components, plus the blocks' own prefix (one row a block in one place)."""
    b = F.floor(F.col("comp") / BLOCK)
    sums = caps.groupBy(b.alias("block")).agg(F.sum("cap").alias("s"))
    before = sums.select("block", F.coalesce(F.sum("s").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)).alias("before"))
    run = F.coalesce(F.sum("cap").over(Window.partitionBy("block").orderBy("comp").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    df = caps.withColumn("block", b).join(before, "block").select("comp", "max_w", "cap", (F.col("before") + run).alias("lo"))
    r = caps.agg(F.sum("cap").alias("m"), F.count("*").alias("d"), F.bit_xor(F.xxhash64("comp", "cap")).alias("w")).first()
    return Layout(df, float(r["m"] or 0), r["d"], alpha, r["w"] or 0)


def of(v: DataFrame, alpha: float = 1.0, rounding: str = "ceil") -> Layout:
    return build_layout(component_caps(v, alpha, rounding), alpha)


def unit_layout(v: DataFrame) -> Layout:
    """Width 1 for each component of vectors whose weights are at most 1."""
    return build_layout(v.groupBy("comp").agg(F.max("weight").alias("max_w")).select("comp", "max_w", F.lit(1.0).alias("cap")))


def from_declared(spark: SparkSession, caps: dict[int, float]) -> Layout:
    return build_layout(spark.createDataFrame([(int(c), float(w), float(w)) for c, w in caps.items()], "comp int, max_w double, cap double"))


def estimate(v: DataFrame, fraction: float, margin: float, seed: int = 3) -> Layout:
    """Widths from a sample of the rows, widened by ``margin``; rows above them are for ``check_overflow``."""
    return build_layout(component_caps(v.sample(fraction=fraction, seed=seed), margin), 1.0)


def check_overflow(v: DataFrame, layout: Layout, policy: str = "error") -> DataFrame:
    """``report``: rows above their width or without one; ``clip``: weights cut to the width, unknown components dropped;
    ``error``: v, failing when a row overflows. For a new layout that holds all, see ``new_epoch``."""
    if policy not in ("report", "clip", "error"):
        raise ValueError(f"unknown overflow policy {policy!r}")
    j = v.join(layout.df.select("comp", "cap"), "comp", "left").select("vec_id", "comp", "weight", "cap")
    over = F.col("cap").isNull() | (F.col("weight") * layout.alpha > F.col("cap"))
    if policy == "report":
        return j.where(over)
    if policy == "clip":
        return j.where("cap IS NOT NULL").select("vec_id", "comp", F.least("weight", F.col("cap") / layout.alpha).alias("weight"))
    return j.select("vec_id", "comp", F.when(over, F.raise_error(F.lit("weight above its component's width")).cast("double")).otherwise(F.col("weight")).alias("weight"))


def new_epoch(v: DataFrame, layout: Layout) -> Layout:
    """The layout to go on with: the old one while no row overflows, else one whose widths also hold v's weights. A new
    layout has another layout_id, so hashes of two epochs refuse to compare and old vectors are sketched anew."""
    if check_overflow(v, layout, "report").isEmpty():
        return layout
    wide = component_caps(v, layout.alpha).unionByName(layout.df.select("comp", "max_w", "cap"))
    return build_layout(wide.groupBy("comp").agg(F.max("max_w").alias("max_w"), F.max("cap").alias("cap")), layout.alpha)


def cell_table(layout: Layout) -> DataFrame:
    """cell, comp: the component of every whole cell of [0, total)."""
    cells = F.sequence(F.col("lo").cast("long"), (F.col("lo") + F.col("cap") - 1).cast("long"))
    return layout.df.select(F.explode(cells).alias("cell"), "comp")


def start_table(layout: Layout) -> DataFrame:
    return layout.df.select("comp", "lo")


def intervals(v: DataFrame, layout: Layout) -> DataFrame:
    """The green and red stretch of each of a vector's components, for display and tests."""
    j = v.join(layout.df, "comp")
    mid = F.col("lo") + F.col("weight") * layout.alpha
    return j.select("vec_id", F.explode(F.array(F.struct(F.col("lo").alias("lo"), mid.alias("hi"), F.lit("green").alias("color")), F.struct(mid.alias("lo"), (F.col("lo") + F.col("cap")).alias("hi"), F.lit("red").alias("color")))).alias("i")).select("vec_id", "i.*").where("lo < hi")


def fill(v: DataFrame, layout: Layout) -> DataFrame:
    """vec_id, l1, s: the green share of each vector."""
    return v.groupBy("vec_id").agg(F.sum("weight").alias("l1")).withColumn("s", F.col("l1") * layout.alpha / layout.total)


def best_scale(v: DataFrame, grid: list[float], max_total: float | None = None) -> DataFrame:
    """alpha, total, fill (mean over vectors), place: best fill first; scales whose total is over the limit come last.
    Maxima are found once; the grid is crossed with them only."""
    caps = v.groupBy("comp").agg(F.max("weight").alias("m"))
    mean = v.groupBy("vec_id").agg(F.sum("weight").alias("l1")).agg(F.avg("l1").alias("l1"))
    alphas = v.sparkSession.createDataFrame([(float(a),) for a in grid], "alpha double")
    totals = caps.crossJoin(F.broadcast(alphas)).groupBy("alpha").agg(F.sum(F.greatest(F.lit(1.0), F.ceil(F.col("m") * F.col("alpha")).cast("double"))).alias("total"))
    out = totals.crossJoin(F.broadcast(mean)).select("alpha", "total", (F.col("l1") * F.col("alpha") / F.col("total")).alias("fill"))
    over = F.lit(False) if max_total is None else F.col("total") > max_total
    return out.withColumn("place", F.row_number().over(Window.orderBy(over, F.round("fill", 9).desc(), "total", "alpha")))


def horizon(s: float, delta: float) -> int:
    """Draws after which a vector of fill s is unresolved with probability delta at most."""
    return max(1, math.ceil(math.log(delta) / math.log1p(-s))) if s < 1 else 1


def recommend(v: DataFrame, layout: Layout, k: int, draw_cost: float = 1.0, gamma_cost: float = 8.0) -> Row:
    """The cheaper sampler by mean work a vector: k / s draws against k * d sets of variates; ``fold`` when both exceed a
    million units."""
    r = v.groupBy("vec_id").agg(F.sum("weight").alias("l1"), F.count("*").alias("d")).agg(F.avg(layout.total / (F.col("l1") * layout.alpha)).alias("inv_s"), F.avg("d").alias("d")).first()
    red, gam = k * (r["inv_s"] or 0.0) * draw_cost, k * (r["d"] or 0.0) * gamma_cost
    method = "fold" if min(red, gam) > 1e6 else "redgreen" if red <= gam else "gamma_cws"
    return Row(method=method, redgreen_work=red, gamma_work=gam)


def sql(v: str = "v", alpha: float = 1.0, rounding: str = "ceil", name: str = "lay") -> str:
    """DuckDB tables ``{name}`` (comp, max_w, cap, lo) and ``{name}_m`` (total, dim) of vectors ``v``."""
    wide = f"max(weight) * {float(alpha)}::DOUBLE"
    cap = wide if rounding == "exact" else f"greatest(1.0::DOUBLE, ceil({wide}))"
    return (
        f"{name}_c AS (SELECT comp, max(weight) AS max_w, {cap} AS cap FROM {v} GROUP BY comp), "
        f"{name} AS (SELECT *, coalesce(sum(cap) OVER (ORDER BY comp ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::DOUBLE AS lo FROM {name}_c), "
        f"{name}_m AS (SELECT sum(cap)::DOUBLE AS total, count(*) AS dim FROM {name}_c)"
    )
