"""Linear features of the min-max kernel (the similarity itself) from sketches."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.evaluation import MulticlassClassificationEvaluator
from pyspark.ml.linalg import Vectors, VectorUDT
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.operators import blocks, similarity


def gram(sketches: DataFrame, ids: DataFrame) -> DataFrame:
    """id_a, id_b, value over all pairs id_a <= id_b of the given ids (their square is made, but neither exchanged nor kept)."""
    own = sketches.join(ids.select("vec_id").distinct(), "vec_id", "left_semi")
    size = own.agg(F.max(F.size("sketch")).alias("k")).first()["k"] or 1
    self_ = own.select(F.col("vec_id").alias("id_a"), F.col("vec_id").alias("id_b"), similarity.agreement(F.col("sketch"), F.col("sketch")).alias("value"))
    return blocks.pairs(None, own, (size,)).select("id_a", "id_b", F.col(f"est_{size}").alias("value")).unionByName(self_)


def slots(sketches: DataFrame, bits: int) -> DataFrame:
    """vec_id, slots ARRAY<INT>: for each hash position, one of 2**bits columns."""
    return sketches.select("vec_id", F.transform("sketch", lambda h, i: i * (1 << bits) + F.pmod(h, F.lit(1 << bits))).alias("slots"))


def features(sketches: DataFrame, k: int, bits: int) -> DataFrame:
    """vec_id, features: sparse vectors of k ones scaled so that inner products estimate the kernel."""
    size, value = k << bits, k**-0.5

    @F.udf(VectorUDT())
    def run(s):
        return Vectors.sparse(size, sorted(s), [value] * len(s))

    return slots(sketches, bits).select("vec_id", run("slots").alias("features"))


def evaluate(data: DataFrame, seed: int = 1, reg: float = 0.001) -> float:
    """Held-out accuracy (a quarter, by id) of a linear classifier on (vec_id, features, label)."""
    test = F.pmod(F.xxhash64(F.lit(seed), "vec_id"), F.lit(4)) == 0
    model = LogisticRegression(maxIter=60, regParam=reg).fit(data.where(~test))
    return MulticlassClassificationEvaluator(metricName="accuracy").evaluate(model.transform(data.where(test)))


def nearest(v: DataFrame, labels: DataFrame, seed: int = 1) -> DataFrame:
    """Held-out accuracy of the exact kernel's nearest neighbour."""
    test = F.pmod(F.xxhash64(F.lit(seed), "vec_id"), F.lit(4)) == 0
    pairs = blocks.pairs(v.where(test), keep=blocks.best_of_row, against=v.where(~test))
    best = pairs.groupBy("id_a").agg(F.max_by("id_b", F.struct("j", -F.col("id_b"))).alias("id_b"))
    la, lb = (labels.select(F.col("vec_id").alias(f"id_{x}"), F.col("label").alias(f"l_{x}")) for x in "ab")
    return best.join(la, "id_a").join(lb, "id_b").agg(F.avg((F.col("l_a") == F.col("l_b")).cast("double")).alias("accuracy"))


def pandas_agreement():
    """Arrow form of the estimator for SQL users."""

    @F.pandas_udf("double")
    def sketch_similarity(a: pd.Series, b: pd.Series) -> pd.Series:
        sizes = np.array([len(x) for x in a], np.int64)
        if (sizes != np.array([len(x) for x in b], np.int64)).any():
            raise ValueError("sketches differ in length")
        x, y = (np.concatenate([np.asarray(v) for v in s]) if sizes.sum() else np.zeros(0) for s in (a, b))
        same = np.concatenate(([0], np.cumsum((x == y) & (x != 0))))
        end = np.cumsum(sizes)
        return pd.Series((same[end] - same[end - sizes]) / np.maximum(sizes, 1))

    return sketch_similarity
