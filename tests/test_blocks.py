"""All pairs by blocks against brute force, and that no row a pair is exchanged."""

import random

import pytest

from rgsketch.operators import blocks, experiments, kernel, lsh, similarity


@pytest.fixture(scope="module")
def many(spark):
    """200 vectors over some components that all hold and many that few hold, some equal; and their sketches."""
    rng = random.Random(3)
    out = {i * 7 - 300: {**{c: rng.uniform(0.1, 4) for c in range(5)}, **{rng.randrange(10, 400): rng.uniform(0.1, 9) for _ in range(4)}} for i in range(200)}
    out[-300] = dict(out[400])
    out[5000] = {1000: 1.0}
    v = spark.createDataFrame([(i, c, w) for i, x in out.items() for c, w in x.items()], "vec_id long, comp int, weight double").cache()
    hashes = {i: [rng.randrange(3) for _ in range(8)] for i in out}
    return v, out, spark.createDataFrame(list(hashes.items()), "vec_id long, sketch array<int>"), hashes


def _jaccard(x, y):
    lo = sum(min(x[c], y[c]) for c in x.keys() & y.keys())
    return lo / (sum(x.values()) + sum(y.values()) - lo)


def _agree(x, y, k):
    return sum(p == q != 0 for p, q in zip(x[:k], y[:k], strict=True)) / k


@pytest.mark.parametrize("rows", [10_000, 60, 17])
def test_pairs_equal_brute_force(spark, many, monkeypatch, rows):
    monkeypatch.setattr(blocks, "ROWS", rows)
    v, out, s, hashes = many
    want = {(a, b): _jaccard(out[a], out[b]) for a in out for b in out if a < b and out[a].keys() & out[b].keys()}
    got = blocks.pairs(v, s, (3, 8)).collect()
    assert len(got) == len(want) == len({(r["id_a"], r["id_b"]) for r in got})
    for r in got:
        a, b = r["id_a"], r["id_b"]
        assert abs(r["j"] - want[a, b]) < 1e-12 and abs(r["l1_a"] - sum(out[a].values())) < 1e-9 and abs(r["l1_b"] - sum(out[b].values())) < 1e-9
        assert (r["est_3"], r["est_8"]) == (_agree(hashes[a], hashes[b], 3), _agree(hashes[a], hashes[b], 8))
    gram = {(r["id_a"], r["id_b"]): r["value"] for r in kernel.gram(s, s.select("vec_id")).collect()}
    assert gram == {(a, b): _agree(hashes[a], hashes[b], 8) for a in out for b in out if a <= b}
    nine = {r["pair"]: (r["id_a"], r["id_b"]) for r in experiments.nine_pairs(v).collect()}
    assert nine == {i + 1: min((round(abs(j - (i + 1) / 10), 9), *p) for p, j in want.items())[1:] for i in range(9)}
    top = {}
    for r in blocks.pairs(v.where("vec_id % 2 = 0"), keep=blocks.best_of_row, against=v.where("vec_id % 2 <> 0")).collect():
        top[r["id_a"]] = max(top.get(r["id_a"], 0), r["j"])
    assert top.keys() == {i for i in out if i % 2 == 0 and any(k % 2 and out[k].keys() & out[i].keys() for k in out)}
    assert all(abs(j - max(_jaccard(out[a], out[b]) for b in out if b % 2)) < 1e-12 for a, j in top.items())


def test_all_pairs_exchange_no_pairs(spark, many):
    plan = similarity.exact_pairs(many[0])._jdf.queryExecution().executedPlan().toString()
    assert "Aggregate" not in plan and "SortMergeJoin" not in plan


def test_all_pairs_lists_no_bucket(spark, many):
    """Verified pairs are the candidates' pairs, and no join on buckets is made for them."""
    v, out, s, _ = many
    df = lsh.all_pairs(s, v, 0.4, 2, 4)
    assert "SortMergeJoin" not in df._jdf.queryExecution().executedPlan().toString()
    mates = {(r["id_a"], r["id_b"]) for r in lsh.candidates(lsh.index(s, 2, 4)).collect()}
    got = {(r["id_a"], r["id_b"]) for r in df.collect()}
    assert got == {p for p in mates if out[p[0]].keys() & out[p[1]].keys() and _jaccard(out[p[0]], out[p[1]]) >= 0.4} and got


def test_zscores_of_equal_vectors(spark, tmp_path):
    """Two suppliers with equal vectors: 0 / 0 as in the query's SQL, no error."""
    import math

    import __spark_entry__

    rows = [(s, p, float(q)) for s, m in ((1, 1), (2, 1), (3, 5)) for p, q in ((1, 2 * m), (2, 3))]
    spark.createDataFrame(rows, "l_suppkey long, l_partkey long, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(1, "Brand#11"), (2, "Brand#12")], "p_partkey long, p_brand string").write.parquet(f"{tmp_path}/part.parquet")
    got = {(r["id_a"], r["id_b"]): r["z"] for r in __spark_entry__.queries()["est_zscores"](spark, str(tmp_path)).collect()}
    assert got.keys() == {(1, 2), (1, 3), (2, 3)} and math.isnan(got[1, 2]) and got[1, 3] == got[2, 3] and math.isfinite(got[1, 3])
