"""The experiments: accuracy against k, time for k hashes, and the studies around them."""

from __future__ import annotations

import time
from statistics import median

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rgsketch.operators import blocks, gamma_cws, redgreen, replicated_oph, similarity
from rgsketch.plans import layout as L
from rgsketch.sources.families import pack
from rgsketch.sources.tables import materialize


def nine_pairs(v: DataFrame, levels: tuple[float, ...] = (0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9)) -> DataFrame:
    """pair (1 .. 9), id_a, id_b, j: of all pairs, the one nearest to each level, the smallest ids at a tie."""
    pairs = blocks.pairs(v, run=blocks.meet_levels(levels)).select("id_a", "id_b", "j")
    best = [F.min(F.struct(F.round(F.abs(F.col("j") - x), 9).alias("d"), "id_a", "id_b", "j")).alias(f"p{i + 1}") for i, x in enumerate(levels)]
    one = pairs.agg(*best).select(F.posexplode(F.array(*[f"p{i + 1}" for i in range(len(levels))])).alias("i", "p"))
    return one.select((F.col("i") + 1).alias("pair"), "p.id_a", "p.id_b", "p.j").where("id_a IS NOT NULL")


def agreements(v: DataFrame, pairs: DataFrame, method: str, k: int, seed: int, layout: L.Layout | None = None, steps: int | None = None, scale: float = 1.0) -> DataFrame:
    """pair, hash_id, same (0 or 1) of one repetition; pairs has pair, id_a, id_b. Only the pairs' vectors are sketched."""
    ids = pairs.select(F.col("id_a").alias("vec_id")).unionByName(pairs.select(F.col("id_b").alias("vec_id"))).distinct()
    own, value = v.join(F.broadcast(ids), "vec_id", "left_semi"), ("h",)
    if method == "redgreen":
        h = redgreen.sketch(own, layout, k, seed, steps=steps)
    elif method == "gamma_cws":
        h, value = gamma_cws.sketch(own, k, seed), ("comp", "level")
    else:
        h = replicated_oph.sketch(own, k, seed, scale)
    a, b = (h.select(F.col("vec_id").alias(f"id_{x}"), "hash_id", F.struct(*value).alias(f"v_{x}")) for x in "ab")
    j = pairs.select("pair", "id_a", "id_b").join(a, "id_a").join(b, ["id_b", "hash_id"])
    return j.select("pair", "hash_id", (F.col("v_a") == F.col("v_b")).cast("int").alias("same"))


def seed_agreements(v: DataFrame, pairs: DataFrame, k: int, seeds: range, scale: float = 1.0, coin: str = "shared") -> DataFrame:
    """pair, hash_id (repetition * k + bin), same of the replicated sketch under every seed."""
    ids = pairs.select(F.col("id_a").alias("vec_id")).unionByName(pairs.select(F.col("id_b").alias("vec_id"))).distinct()
    h = replicated_oph.sketch_seeds(pack(v.join(F.broadcast(ids), "vec_id", "left_semi")), k, seeds, scale, coin)
    h = materialize(h.select("vec_id", (F.col("rep") * k + F.col("hash_id")).alias("hash_id"), "h"))
    a, b = (h.select(F.col("vec_id").alias(f"id_{x}"), "hash_id", F.col("h").alias(f"h_{x}")) for x in "ab")
    j = pairs.select("pair", "id_a", "id_b").join(a, "id_a").join(b, ["id_b", "hash_id"])
    return j.select("pair", "hash_id", (F.col("h_a") == F.col("h_b")).cast("int").alias("same"))


def error_curve(v: DataFrame, pairs: DataFrame, method: str, k: int = 50, seeds: range = range(200), **kw) -> DataFrame:
    """pair, k, j, bias, mae, rmse of the first k hashes over repetitions. All repetitions are one plan: hash ids of a
    repetition are offset, so repetitions are independent blocks of one sketch of len(seeds) * k hashes."""
    n = len(seeds)
    if method == "replicated_oph":  # bins of one permutation aren't independent blocks: one sketch a seed
        same = seed_agreements(v, pairs, k, seeds, **kw)
    else:
        same = agreements(v, pairs, method, k * n, seeds[0], **kw)
    rep, pos = F.floor(F.col("hash_id") / k).alias("rep"), (F.pmod("hash_id", F.lit(k)) + 1).alias("k")
    full = pairs.select("pair", "j").crossJoin(F.broadcast(v.sparkSession.range(k * n).select(F.col("id").cast("int").alias("hash_id"))))
    rows = full.join(same, ["pair", "hash_id"], "left").select("pair", "j", rep, pos, F.coalesce("same", F.lit(0)).alias("same"))
    run = Window.partitionBy("pair", "rep").orderBy("k").rowsBetween(Window.unboundedPreceding, 0)
    e = rows.withColumn("e", F.avg("same").over(run) - F.col("j"))
    return e.groupBy("pair", "k").agg(F.first("j").alias("j"), F.avg("e").alias("bias"), F.avg(F.abs("e")).alias("mae"), F.sqrt(F.avg(F.col("e") * F.col("e"))).alias("rmse"))


def time_hashes(v: DataFrame, k: int = 500, methods: tuple[str, ...] = ("redgreen", "gamma_cws", "replicated_oph"), runs: int = 3, seed: int = 1, rounding: str = "exact", scale: float = 1.0) -> dict[str, float]:
    """Milliseconds a vector for k hashes: packed vectors cached, nothing kept of the result, the median of ``runs``."""
    packed = pack(v).cache()
    n = max(packed.count(), 1)
    lay = L.of(v, rounding=rounding)
    low = L.fill(v, lay).agg(F.percentile_approx("s", 0.5).alias("s")).first()["s"] or 1.0
    steps = L.horizon(min(low, 1.0), 1e-4)
    plans = {
        "redgreen": lambda: redgreen.sketch_batches(packed, lay, k, steps, seed),
        "gamma_cws": lambda: gamma_cws.sketch_batches(packed, k, seed),
        "replicated_oph": lambda: replicated_oph.sketch_batches(packed, k, seed, scale),
    }
    out = {}
    for m in methods:
        plan, took = plans[m](), []
        for _ in range(runs):
            t = time.perf_counter()
            plan.write.format("noop").mode("overwrite").save()
            took.append(time.perf_counter() - t)
        out[m] = 1000 * median(took) / n
    packed.unpersist()
    return out


def time_alone(v: DataFrame, k: int = 500, runs: int = 3, seed: int = 1, scale: float = 1.0, methods: tuple[str, ...] = ("redgreen", "gamma_cws", "replicated_oph"), rounding: str = "exact") -> dict[str, float]:
    """Milliseconds a vector for k hashes on one core, data in memory: the functions that the batch plans run in the workers,
    without a job's fixed cost. v is a study's table, packed into the driver: at most 4 million non-zeros."""
    if v.count() > 4_000_000:
        raise ValueError("too large to time in the driver; use time_hashes")
    batches = pack(v).select("vec_id", "comps", "weights").toArrow().combine_chunks().to_batches()
    n = max(sum(b.num_rows for b in batches), 1)
    lay = L.of(v, rounding=rounding)
    low = L.fill(v, lay).agg(F.min("s").alias("s")).first()["s"] or 1.0
    steps = L.horizon(min(low, 1.0), 1e-6)
    made = {"redgreen": lambda: redgreen.sketcher(lay, k, steps, seed), "gamma_cws": lambda: gamma_cws.sketcher(k, seed), "replicated_oph": lambda: replicated_oph.sketcher(k, seed, scale)}
    out = {}
    for m in methods:
        run, took = made[m](), []
        for _ in range(runs):
            t = time.perf_counter()
            for _ in run(iter(batches)):
                pass
            took.append(time.perf_counter() - t)
        out[m] = 1000 * median(took) / n
    return out


def copy_scale(v: DataFrame, copies: float = 100.0) -> float:
    """The one rule for the replicated sketch's scale: the largest weight of the data set counts as so many copies."""
    return copies / (v.agg(F.max("weight").alias("m")).first()["m"] or 1.0)


def speedups(times: dict[str, float], base: str = "redgreen") -> dict[str, float]:
    """How many times as long as ``base`` each other method takes."""
    return {m: t / times[base] for m, t in times.items() if m != base}


def scale_study(v: DataFrame, grid: list[float], k: int) -> DataFrame:
    """alpha, total, fill, draws: expected draws of k hashes of an average vector at each scale."""
    return L.best_scale(v, grid).withColumn("draws", k / F.col("fill"))


def replication_bias(v: DataFrame, pairs: DataFrame, k: int, seeds: range, scales: tuple[float, ...], coins: tuple[str, ...] = ("shared", "independent")) -> DataFrame:
    """scale, coin, pair, est, j: mean estimate of the replicated sketch over seeds. Coarse scales and coins of each vector's
    own lower the estimate."""
    out = None
    for s in scales:
        for coin in coins:
            e = error_curve(v, pairs, "replicated_oph", k, seeds, scale=s, coin=coin).where(F.col("k") == k)
            e = e.select(F.lit(float(s)).alias("scale"), F.lit(coin).alias("coin"), "pair", (F.col("j") + F.col("bias")).alias("est"), "j")
            out = e if out is None else out.unionByName(e)
    return out


def densify_variance(v: DataFrame, pairs: DataFrame, k: int, seeds: range, scale: float = 1.0) -> DataFrame:
    """mode, mae: error of the replicated sketch with each way to fill empty bins, over seeds and pairs."""
    ids = pairs.select(F.col("id_a").alias("vec_id")).unionByName(pairs.select(F.col("id_b").alias("vec_id"))).distinct()
    own, out = materialize(v.join(F.broadcast(ids), "vec_id", "left_semi")), None
    for mode in ("rotate", "direction", "probe"):
        for s in seeds:
            h = replicated_oph.sketch(own, k, s, scale, densify=mode).select("vec_id", "hash_id", "h")
            e = similarity.estimate_long(h, pairs.select("id_a", "id_b"), k).join(pairs, ["id_a", "id_b"]).select(F.lit(mode).alias("mode"), F.abs(F.col("est") - F.col("j")).alias("e"))
            out = e if out is None else out.unionByName(e)
    return out.groupBy("mode").agg(F.avg("e").alias("mae"))


def crossover(spark, families: dict[str, DataFrame], k: int = 500) -> DataFrame:
    """family, redgreen_work, gamma_work, method: which sampler does less, by fill and non-zeros."""
    rows = []
    for name, v in families.items():
        r = L.recommend(v, L.of(v), k)
        rows.append((name, float(r["redgreen_work"]), float(r["gamma_work"]), r["method"]))
    return spark.createDataFrame(rows, "family string, redgreen_work double, gamma_work double, method string")


def membership_ablation(v: DataFrame, layout: L.Layout, points: DataFrame) -> dict[str, float]:
    """Seconds of each membership test over all vectors and the given draws (a column r)."""
    packed = materialize(v.join(layout.df.select("comp", "lo"), "comp").groupBy("vec_id").agg(F.sort_array(F.collect_list(F.struct("lo", "weight"))).alias("e"), F.map_from_entries(F.collect_list(F.struct("comp", "weight"))).alias("m")))
    tables = layout.df.agg(F.sort_array(F.collect_list(F.struct("lo", "comp", "cap"))).alias("t")).first()["t"] if layout.total <= 100_000 else None
    rows = packed.crossJoin(F.broadcast(points.select("r")))
    tests = {"scan": redgreen.is_green_scan(F.col("r"), F.col("e.lo"), F.col("e.weight")), "search": redgreen.is_green_search(F.col("r"), F.col("e.lo"), F.col("e.weight"))}
    if tables is not None:
        starts = [0.0] * (max(c for _, c, _ in tables) + 1)
        cells: list[int] = []
        for lo, c, cap in tables:
            starts[c] = lo
            cells += [c] * int(cap)
        tests["table"] = redgreen.is_green_table(F.col("r"), F.array(*map(F.lit, cells)), F.array(*map(F.lit, starts)), F.col("m"))
    out = {}
    for name, test in tests.items():
        t = time.perf_counter()
        rows.select(F.sum(test.cast("int")).alias("n")).write.format("noop").mode("overwrite").save()
        out[name] = time.perf_counter() - t
    return out
