"""Darts: the shared draws of all hashes, resolved once for a data set to a component and an offset in its width."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rgsketch.functions.rng import sql_uniform, uniform
from rgsketch.plans.layout import Layout

MULTIPLIER = 10**6


def draws(layout: Layout, k: int, steps: int, seed: int, first: int = 1) -> DataFrame:
    """hash_id 0 .. k - 1, step first .. first + steps - 1 and r, uniform on [0, total)."""
    spark = layout.df.sparkSession
    grid = spark.range(k * steps).select((F.col("id") % k).cast("int").alias("hash_id"), (F.floor(F.col("id") / k) + first).cast("int").alias("step"))
    return grid.withColumn("r", uniform(seed, F.col("hash_id"), F.col("step")) * F.lit(layout.total))


def resolve(points: DataFrame, layout: Layout) -> DataFrame:
    """Draws to (hash_id, step, comp, offset). A range join as an equi-join: widths are cut at coarse cells of about one
    component each, so that both sides meet on a cell; no side has to be small and no table of whole cells is made."""
    size = max(layout.total / max(layout.dim, 1), 1e-9)
    cells = F.sequence(F.floor(F.col("lo") / size), F.floor((F.col("lo") + F.col("cap")) / size))
    wide = layout.df.select("comp", "lo", "cap", F.explode(cells).alias("cell"))
    near = points.withColumn("cell", F.floor(F.col("r") / size)).join(wide, "cell")
    return near.where("lo <= r AND r < lo + cap").select("hash_id", "step", "comp", (F.col("r") - F.col("lo")).alias("offset"))


def build(layout: Layout, k: int, steps: int, seed: int, first: int = 1) -> DataFrame:
    return resolve(draws(layout, k, steps, seed, first), layout)


def prune(darts: DataFrame) -> DataFrame:
    """Only darts below all earlier ones of their hash and component: no other can be a vector's first green one."""
    earlier = Window.partitionBy("hash_id", "comp").orderBy("step").rowsBetween(Window.unboundedPreceding, -1)
    return darts.withColumn("m", F.min("offset").over(earlier)).where("m IS NULL OR offset < m").drop("m")


def drop_dead(darts: DataFrame, layout: Layout) -> DataFrame:
    """Without darts that are red for every vector of the data set. Not for sketches that will grow."""
    top = layout.df.select("comp", (F.col("max_w") * layout.alpha).alias("top"))
    return darts.join(top, "comp").where("offset < top").select("hash_id", "step", "comp", "offset")


def chained(layout: Layout, k: int, steps: int, seed: int, mult: int = MULTIPLIER) -> DataFrame:
    """The variant whose next draw is seeded by the last one: hash_id, step, r. Sequential along steps, so one row a hash
    folds over them; two hashes that draw one seed stay together from there on."""
    spark, total = layout.df.sparkSession, layout.total
    start = F.array(uniform(seed, "chain", F.col("hash_id")) * total)
    follow = lambda acc, _: F.concat(acc, F.array(uniform("next", F.ceil(F.element_at(acc, -1) * mult).cast("long")) * total))
    rows = spark.range(k).select(F.col("id").cast("int").alias("hash_id")).withColumn("all", F.aggregate(F.sequence(F.lit(2), F.lit(max(2, steps))), start, follow))
    return rows.select("hash_id", F.posexplode("all").alias("i", "r")).where(F.col("i") < steps).select("hash_id", (F.col("i") + 1).alias("step"), "r")


def save(darts: DataFrame, path: str) -> None:
    darts.write.mode("overwrite").parquet(path)


def load(spark, path: str) -> DataFrame:
    return spark.read.parquet(path)


def sql(k: int, steps: int, seed: int, lay: str = "lay", name: str = "darts", pruned: bool = False) -> str:
    """DuckDB table (hash_id, step, comp, off); pruned to the darts that are below all earlier ones of their component, from
    which any first green draw is found, so that a far horizon stays cheap."""
    u = sql_uniform(f"'{seed}'", "hash_id", "step")
    if pruned:
        return sql(k, steps, seed, lay, f"{name}_a") + f", {name} AS MATERIALIZED (SELECT hash_id, step, comp, off FROM (SELECT *, min(off) OVER (PARTITION BY hash_id, comp ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS m FROM {name}_a) WHERE m IS NULL OR off < m)"
    return (
        f"{name}_r AS (SELECT hash_id::INT AS hash_id, step::INT AS step, {u} * total AS r FROM range({k}) a(hash_id), range(1, {steps + 1}) b(step), {lay}_m), "
        f"{name} AS (SELECT hash_id, step, comp, r - lo AS off FROM {name}_r ASOF JOIN {lay} ON r >= lo WHERE r < lo + cap)"
    )
