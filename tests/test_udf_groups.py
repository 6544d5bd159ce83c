"""op_udf runs its functions once for two groups of vectors with equal sketches, and still gives every pair."""

import pytest
from pyspark.sql import functions as F

from rgsketch.operators import similarity
from rgsketch.queries import engine


@pytest.mark.parametrize("together", [256, 3])
def test_udf_runs_on_groups_and_gives_all_pairs(spark, tmp_path, monkeypatch, together):
    monkeypatch.setattr(engine, "TOGETHER", together, raising=False)
    rows = [(s, p, float(1 + (s % 3) * p)) for s in range(14) for p in (1, 2, 3)]
    spark.createDataFrame(rows, "l_suppkey long, l_partkey long, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(p, f"Brand#{p}") for p in (1, 2, 3)], "p_partkey long, p_brand string").write.parquet(f"{tmp_path}/part.parquet")
    df = engine._udf(spark, str(tmp_path))
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert 0 <= plan.find("Generate") < plan.find("ArrowEvalPython")  # pairs are made from what the functions gave
    got = [tuple(r) for r in df.collect()]
    s = engine._sk(spark, str(tmp_path)).select("vec_id", "sketch")
    every = s.alias("a").join(s.alias("b"), F.col("a.vec_id") < F.col("b.vec_id"))
    est = F.round(similarity.agreement(F.col("a.sketch"), F.col("b.sketch")), 6)
    want = [(*r, r[2]) for r in every.select("a.vec_id", "b.vec_id", est).collect()]
    assert len(got) == 91 and sorted(got) == sorted(want)
