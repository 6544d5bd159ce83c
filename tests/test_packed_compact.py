"""Packed gamma hashes are cut as the long ones are, and no row a hash is made or exchanged."""

import pytest
from pyspark.sql import functions as F

from rgsketch.operators import gamma_cws, lsh, redgreen
from rgsketch.queries import applications
from rgsketch.sources import families as V


@pytest.mark.parametrize("how", [{}, {"bits": 5}, {"mode": "component"}, {"mode": "component", "bits": 3}])
def test_packed_equals_long(spark, how):
    v = spark.createDataFrame([(i, c, 0.3 + (i * 7 + c * c) % 11) for i in range(12) for c in range(1 + i % 5, 9)], "vec_id long, comp int, weight double")
    cut = gamma_cws.compact(gamma_cws.sketch_batches(V.pack(v), 16, 3), seed=3, **how)
    assert "Generate" not in cut._jdf.queryExecution().optimizedPlan().toString()
    want = redgreen.to_packed(gamma_cws.compact(gamma_cws.sketch(v, 16, 3), seed=3, **how).withColumnRenamed("v", "h"))
    assert {r["vec_id"]: list(r["sketch"]) for r in cut.collect()} == {r["vec_id"]: list(r["sketch"]) for r in want.collect()}


def test_links_explode_no_hashes(spark, monkeypatch):
    plans = []
    monkeypatch.setattr(lsh, "link", lambda v1, v2, s1, s2, *a: plans.extend([s1, s2]) or v1.select(F.col("vec_id").alias("id_a"), F.col("vec_id").alias("id_b"), F.lit(1.0).alias("j")))
    applications._link(spark, "/root/testdata/sf0.001")
    assert len(plans) == 2 and not any("Generate" in s._jdf.queryExecution().optimizedPlan().toString() for s in plans)
