"""Worked examples, equivalences, invariants and laws of the samplers."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from rgsketch.functions import sql as SQL
from rgsketch.functions.rng import two_universal
from rgsketch.operators import compact, experiments, gamma_cws, kernel, lsh, measures, redgreen, replicate, replicated_oph, similarity, unweighted
from rgsketch.plans import darts as D
from rgsketch.plans import layout as L
from rgsketch.sources import families as V
from rgsketch.sources import tables
from rgsketch.streaming import histograms

X, Y = {0: 1.5, 2: 2.0, 3: 1.0}, {0: 0.5, 1: 1.0, 2: 3.0}
CAPS = {0: 2.0, 1: 1.0, 2: 3.0, 3: 1.0}


def long(spark, *vectors):
    return spark.createDataFrame([(i, c, float(w)) for i, v in enumerate(vectors) for c, w in v.items()], "vec_id long, comp int, weight double")


@pytest.fixture(scope="module")
def few(spark):
    """Twelve random vectors over twenty components, some close."""
    rng = random.Random(5)
    base = {c: rng.uniform(0.1, 4) for c in range(20)}
    out = [{c: w * rng.choice([1, 1, 0.5]) for c, w in base.items() if rng.random() < 0.8} for _ in range(12)]
    return long(spark, *out).cache(), out


def jaccard(x, y):
    keys = set(x) | set(y)
    return sum(min(x.get(k, 0), y.get(k, 0)) for k in keys) / sum(max(x.get(k, 0), y.get(k, 0)) for k in keys)


def test_worked_example(spark):
    lay = L.from_declared(spark, CAPS)
    assert (lay.total, lay.dim) == (7.0, 4)
    assert [r["lo"] for r in lay.df.orderBy("comp").collect()] == [0, 2, 3, 6]
    assert [r["comp"] for r in L.cell_table(lay).orderBy("cell").collect()] == [0, 0, 1, 2, 2, 2, 3]
    v = long(spark, X, Y)
    green = {(r["vec_id"], r["lo"], r["hi"]) for r in L.intervals(v, lay).where("color = 'green'").collect()}
    assert green == {(0, 0, 1.5), (0, 3, 5), (0, 6, 7), (1, 0, 0.5), (1, 2, 3), (1, 3, 6)}
    assert all(abs(r["s"] - 9 / 14) < 1e-12 for r in L.fill(v, lay).collect())
    r = similarity.exact_pairs(v).first()
    assert abs(r["j"] - 5 / 13) < 1e-12
    assert abs(similarity.exact_l1(v, v.sparkSession.createDataFrame([(0, 1)], "id_a long, id_b long")).first()["l1"] - 4) < 1e-12
    points = spark.createDataFrame([(0, i + 1, r) for i, r in enumerate([5.5, 2.2, 1.0, 0.2])] + [(1, i + 1, r) for i, r in enumerate([1.9, 4.0])], "hash_id int, step int, r double")
    got = {(r["vec_id"], r["hash_id"]): r["h"] for r in redgreen.sketch_relational(v, D.resolve(points, lay)).collect()}
    assert got == {(0, 0): 3, (1, 0): 1, (0, 1): 2, (1, 1): 2}


def test_membership_tests_agree_at_the_edges(spark):
    lay = L.from_declared(spark, CAPS)
    rows = [(lo, c, cap) for c, cap, lo in lay.df.select("comp", "cap", "lo").orderBy("lo").collect()]
    starts = F.array(*[F.lit(lo) for lo, c, _ in rows if c in X])
    weights = F.array(*[F.lit(X[c]) for _, c, _ in rows if c in X])
    cells = F.array(*[F.lit(c) for _, c, cap in rows for _ in range(int(cap))])
    m = F.create_map(*[F.lit(x) for c, w in X.items() for x in (c, w)])
    at = [0.0, 1.4999, 1.5, 2.0, 2.5, 3.0, 4.9999, 5.0, 5.5, 6.0, 6.9999]
    df = spark.createDataFrame([(r,) for r in at], "r double").select("r", redgreen.is_green_scan(F.col("r"), starts, weights).alias("a"), redgreen.is_green_search(F.col("r"), starts, weights).alias("b"), redgreen.is_green_table(F.col("r"), cells, F.array(*[F.lit(lo) for lo, _, _ in rows]), m).alias("c"))
    want = [True, True, False, False, False, True, True, False, False, True, True]
    got = df.orderBy("r").collect()
    assert [r["a"] for r in got] == [r["b"] for r in got] == [r["c"] for r in got] == want


def test_plans_agree_and_prefixes_hold(spark, few):
    v, out = few
    lay = L.of(v)
    table = [(r["comp"], r["cap"], r["lo"]) for r in lay.df.orderBy("lo").collect()]
    one = {i: redgreen.sketch_one(list(x), list(x.values()), table, 8, 3) for i, x in enumerate(out)}
    assert one == {i: redgreen.sketch_one(list(x), list(x.values()), table, 8, 3, test="scan") for i, x in enumerate(out)} == {i: redgreen.sketch_one(list(x), list(x.values()), table, 8, 3, test="table") for i, x in enumerate(out)}
    steps = max(max(h) for h in one.values())
    get = lambda df: {r["vec_id"]: list(r["sketch"]) for r in df.collect()}
    assert get(redgreen.to_packed(redgreen.sketch_relational(v, D.build(lay, 8, steps, 3)))) == one
    assert get(redgreen.to_packed(redgreen.sketch_relational(v, D.drop_dead(D.prune(D.build(lay, 8, steps, 3)), lay), small=False))) == one
    assert get(redgreen.sketch_batches(V.pack(v.repartition(5)), lay, 8, steps, 3, rows=5)) == one
    assert get(redgreen.to_packed(redgreen.sketch(v, lay, 8, 3, steps=1))) == one  # extended by doubling
    assert get(redgreen.to_packed(redgreen.sketch(v, lay, 4, 3, steps=steps, unresolved="cap"))) == {i: h[:4] for i, h in one.items()}


def test_merge_growth_and_disjoint(spark, few):
    v, out = few
    lay = L.of(v)
    darts = D.build(lay, 16, 64, 9)
    h = redgreen.sketch_relational(v, darts)
    top = {c: max(x.get(c, 0) for x in out) for c in range(20)}
    whole = redgreen.sketch_relational(long(spark, {c: w for c, w in top.items() if w}), darts)
    merged = redgreen.merge_max(h, v.select("vec_id", F.lit(0).cast("long").alias("group_id")).distinct())
    assert sorted(map(tuple, merged.collect())) == sorted(map(tuple, whole.collect()))
    half = v.withColumn("weight", F.col("weight") / 2)
    grown = v.select("vec_id", "comp", (F.col("weight") / 2).alias("old_weight"), F.col("weight").alias("new_weight"))
    assert sorted(map(tuple, redgreen.update(redgreen.sketch_relational(half, darts), grown, darts).collect())) == sorted(map(tuple, h.collect()))
    two = long(spark, {0: 1.0}, {1: 1.0})
    a = redgreen.sketch(two, L.of(two), 64, 1)
    assert a.groupBy("hash_id").agg(F.countDistinct("h").alias("n")).where("n < 2").count() == 0


def test_laws_of_the_sampler(spark):
    """Collision probability, mean, variance and tail, over hashes of fixed seeds."""
    v = long(spark, X, Y)
    lay, k = L.from_declared(spark, CAPS), 4000
    h = redgreen.to_packed(redgreen.sketch(v, lay, k, 11, steps=40))
    s = {r["vec_id"]: np.array(r["sketch"]) for r in h.collect()}
    j, fill = 5 / 13, 9 / 14
    assert abs((s[0] == s[1]).mean() - j) < 5 * math.sqrt(j * (1 - j) / k)
    assert abs(s[0].mean() - 1 / fill) < 5 * math.sqrt((1 - fill) / fill**2 / k)
    assert abs((s[0] > 2).mean() - (1 - fill) ** 2) < 0.03
    capped = redgreen.sketch(v, lay, k, 11, steps=1, unresolved="cap")
    c = {r["vec_id"]: np.array(r["sketch"]) for r in redgreen.to_packed(capped).collect()}
    est = ((c[0] == c[1]) & (c[0] > 0)).mean()
    assert abs(est / (1 - (1 - 6.5 / 7)) - j) < 0.04


def test_gamma_sampler(spark, few):
    v, out = few
    h = gamma_cws.sketch(v, 400, 3)
    s = {}
    for r in h.collect():
        s.setdefault(r["vec_id"], {})[r["hash_id"]] = (r["comp"], r["level"])
    errors = [np.mean([s[a][i] == s[b][i] for i in range(400)]) - jaccard(out[a], out[b]) for a in range(6) for b in range(a)]
    assert max(map(abs, errors)) < 0.12
    b = {r["vec_id"]: list(zip(r["comps"], r["levels"], strict=True)) for r in gamma_cws.sketch_batches(V.pack(v), 400, 3).collect()}
    errors = [np.mean([p == q for p, q in zip(b[x], b[y], strict=True)]) - jaccard(out[x], out[y]) for x in range(6) for y in range(x)]
    assert max(map(abs, errors)) < 0.12
    first = [c for c, _ in b[0]]
    l1 = sum(out[0].values())
    assert all(abs(first.count(c) / 400 - w / l1) < 0.12 for c, w in out[0].items())


def test_older_sampler_and_negative_control(spark):
    x, y = {0: 5, 1: 9, 2: 1}, {0: 7, 1: 3, 3: 4}
    a, b = gamma_cws.active_index_one(x, 3000, 1), gamma_cws.active_index_one(y, 3000, 1)
    assert abs(np.mean([p == q for p, q in zip(a, b, strict=True)]) - jaccard(x, y)) < 0.04
    v = long(spark, {c: 1.0 for c in range(40)}, {c: 1.0 for c in range(40)})
    n = unweighted.naive_sample(v, 300, 2)
    got = similarity.estimate_long(n, spark.createDataFrame([(0, 1)], "id_a long, id_b long"), 300).first()["est"]
    assert got < 0.2  # the vectors are equal


def test_replication_and_bins(spark):
    v = long(spark, {0: 3.0, 1: 2.0}, {0: 1.0, 2: 4.0})
    s = replicate.to_set(v, coin="none")
    assert s.count() == 10
    with pytest.raises(Exception, match="whole"):
        replicate.to_set(long(spark, X), coin="none").collect()
    real = long(spark, *[{c: 0.3 for c in range(400)} for _ in range(2)])
    shared, own = (replicate.to_set(real, coin=c).groupBy("comp").agg(F.countDistinct("vec_id").alias("n")).where("n = 2").count() for c in ("shared", "independent"))
    assert 80 < shared < 160 and 10 < own < 70
    for mode in ("rotate", "direction", "probe"):
        d = unweighted.densify(unweighted.oph(s, 32, 5), 32, mode, 5)
        assert d.count() == 64 and d.where("h IS NULL").count() == 0
    k = 256
    pair = spark.createDataFrame([(0, 1)], "id_a long, id_b long")
    big = long(spark, {c: 30.0 for c in range(20)}, {c: 30.0 for c in range(10, 30)})
    for sk in (replicated_oph.sketch(big, k, 3), replicated_oph.sketch_classic(big, k, 3)):
        assert abs(similarity.estimate_long(sk, pair, k).first()["est"] - 1 / 3) < 0.15


def test_elements_of_wide_vectors_differ(spark):
    """Components far apart and neighbouring copies never share an element, so disjoint vectors never agree."""
    far = long(spark, {c: 50.0 for c in range(100)}, {c + 512: 50.0 for c in range(100)}, {c * 9973: 50.0 for c in range(100)})
    s = replicate.to_set(far, coin="none")
    assert s.select("elem").distinct().count() == s.select("comp", "copy").distinct().count()
    pairs = spark.createDataFrame([(0, 1)], "id_a long, id_b long")
    for k, sk in ((256, replicated_oph.sketch(far, 256, 3)), (64, replicated_oph.sketch_classic(far, 64, 3))):
        got = similarity.estimate_long(sk, pairs, k).first()
        assert got is None or got["est"] < 0.1
    h = two_universal(F.col("x"), 5)
    x = spark.range(2000).select((F.col("id") * (1 << 31)).alias("x"))
    assert x.select(h.alias("h")).distinct().count() > 1990


def test_batch_plans_give_the_relational_hashes(spark, few):
    v, _ = few
    rows = lambda df: sorted(map(tuple, df.collect()))
    b = gamma_cws.sketch_batches(V.pack(v), 40, 3).select("vec_id", F.posexplode(F.arrays_zip("comps", "levels")).alias("hash_id", "x")).select("vec_id", "hash_id", "x.comps", "x.levels")
    assert rows(b) == rows(gamma_cws.sketch(v, 40, 3))
    for scale in (1.0, 7.3):
        want = rows(replicated_oph.sketch(v, 32, 3, scale).select("vec_id", "hash_id", "h"))
        assert rows(redgreen.to_long(replicated_oph.sketch_batches(V.pack(v), 32, 3, scale))) == want
        assert rows(replicated_oph.sketch_seeds(V.pack(v), 32, range(3, 5), scale).where("rep = 0").select("vec_id", "hash_id", "h")) == want
    own = replicated_oph.sketch_seeds(V.pack(v), 32, range(3, 4), 0.7, "independent").select("vec_id", "hash_id", "h")
    assert rows(own) == rows(replicated_oph.sketch(v, 32, 3, 0.7, coin="independent").select("vec_id", "hash_id", "h"))


def test_layout_identity_and_epochs(spark):
    a, b = L.from_declared(spark, {0: 1.0, 1: 3.0}), L.from_declared(spark, {0: 3.0, 1: 1.0})
    assert a.layout_id != b.layout_id and a.layout_id == L.from_declared(spark, {1: 3.0, 0: 1.0}).layout_id
    s = spark.createDataFrame([(0, [1, 2])], "vec_id long, sketch array<int>")
    both = a.tag(s, 1).unionByName(b.tag(s.withColumn("vec_id", F.lit(1).cast("long")), 1))
    with pytest.raises(Exception, match="compare"):
        similarity.estimate(both, spark.createDataFrame([(0, 1)], "id_a long, id_b long")).collect()
    inside, over = long(spark, {0: 0.5, 1: 2.0}), long(spark, {0: 2.5, 7: 1.0})
    assert L.new_epoch(inside, a) is a
    new = L.new_epoch(over, a)
    assert new.layout_id != a.layout_id and {r["comp"]: r["cap"] for r in new.df.collect()} == {0: 3.0, 1: 3.0, 7: 1.0}
    assert L.check_overflow(over, new, "report").isEmpty()
    with pytest.raises(ValueError, match="policy"):
        L.check_overflow(over, a, "epoch")


def test_sketches_are_complete(spark):
    """Vectors of very different fill get every hash, whatever horizon is first taken."""
    v = long(spark, {0: 0.01}, {c: 5.0 for c in range(30)}, {3: 1.0, 4: 0.02})
    lay = L.of(v)
    whole = sorted(map(tuple, redgreen.sketch(v, lay, 12, 3).collect()))
    assert len(whole) == 36 and whole == sorted(map(tuple, redgreen.sketch(v, lay, 12, 3, steps=7).collect()))


def test_growing_sketch_takes_a_batch_once(spark):
    rows = [(i, f"2024-01-01 0{i % 3}:00:00", i % 2, "click") for i in range(12)]
    e = spark.createDataFrame(rows, "event_id long, t string, user_id long, event_type string").withColumn("ts", F.to_timestamp("t"))
    names = spark.createDataFrame([(f"click|0{i}", i) for i in range(3)], "name string, comp int")
    lay = L.from_declared(spark, {0: 4.0, 1: 4.0, 2: 4.0})
    state = histograms.GrowingSketch(lay, D.prune(D.build(lay, 8, 200, 3)), names)
    for part, number in ((e.where("event_id < 6"), 0), (e.where("event_id < 6"), 0), (e.where("event_id >= 6"), 1)):
        state.add(part, number)
    whole = histograms.histogram(e).join(names, "name").select("vec_id", "comp", "weight")
    assert sorted(map(tuple, state.weights.collect())) == sorted(map(tuple, whole.collect()))
    assert sorted(map(tuple, state.hashes.select("vec_id", "hash_id", "h").collect())) == sorted(map(tuple, redgreen.sketch(whole, lay, 8, 3).collect()))
    with pytest.raises(Exception, match="no component"):
        state.add(e.withColumn("event_type", F.lit("view")), 2)


def test_letters_equal_a_plain_count(spark):
    texts = {0: "Aab Z", 1: None, 2: "", 3: "12 \u00e9\u00df!", 4: "xyz" * 400_000, 5: "Q"}
    spark.createDataFrame([(i, t) for i, t in texts.items()], "doc_id long, text string").createOrReplaceTempView("letters")
    got = {}
    for r in spark.table("letters").select(F.col("doc_id").alias("vec_id"), "text").mapInArrow(V._letter_shares, "vec_id long, comp int, weight double").collect():
        got.setdefault(r["vec_id"], {})[r["comp"]] = r["weight"]
    want = {}
    for i, t in texts.items():
        n = [sum(ch in (chr(97 + c), chr(65 + c)) for ch in (t or "")[:1200] or []) for c in range(26)]
        if sum(n):
            want[i] = {c: pytest.approx(x / sum(n)) for c, x in enumerate(n) if x}
    assert got == want


def test_written_tables_can_be_dropped(spark):
    df = tables.materialize(spark.range(3))
    assert df.count() == 3
    path = df.inputFiles()[0]
    tables.drop_written(spark)
    with pytest.raises(Exception, match="(?i)not.exist|path"):
        spark.read.parquet(path).count()


def test_equal_vectors_are_one_class(spark):
    v = long(spark, *[{c: 1.0 + (c % 3) for c in range(12)} for _ in range(20)], {50: 1.0}, {c: 1.0 for c in range(60, 70)})
    s = redgreen.sketch_batches(V.pack(v), L.of(v, rounding="exact"), 16, 400, 3)
    got = {r["vec_id"]: r["cluster"] for r in lsh.near_duplicates(s, v, 0.9, 2, 8).collect()}
    assert got == {**{i: 0 for i in range(20)}, 20: 20, 21: 21}


def test_bits_and_packing(spark, few):
    v, _ = few
    lay = L.of(v)
    s = redgreen.sketch_batches(V.pack(v), lay, 50, 300, 3)
    back = compact.unpack(compact.pack(s, 9), 9, 50)
    assert sorted(map(str, back.collect())) == sorted(map(str, s.collect()))
    with pytest.raises(Exception, match="bits"):
        compact.pack(s.select("vec_id", F.transform("sketch", lambda x: x + 4096).alias("sketch")), 9).collect()
    h = redgreen.to_long(s)
    r = measures.range_bits(h).first()
    assert r["bits"] == math.ceil(math.log2(r["max_h"] + 1))


def test_edge_rows(spark):
    for bad in (None, float("nan"), -1.0, float("inf")):
        with pytest.raises(Exception, match="finite"):
            V.clean(spark.createDataFrame([(0, 0, bad)], "vec_id long, comp int, weight double")).collect()
    rows = spark.createDataFrame([(0, 0, 1.0), (0, 0, 2.0), (0, 1, 0.0), (1, 1, 1e-12)], "vec_id long, comp int, weight double")
    assert sorted(map(tuple, V.clean(rows).collect())) == [(0, 0, 3.0), (1, 1, 1e-12)]
    split = V.clean(spark.createDataFrame([(0, 3, -2.0), (0, 4, 2.0)], "vec_id long, comp int, weight double"), "split_sign")
    assert sorted(map(tuple, split.collect())) == [(0, 7, 2.0), (0, 8, 2.0)]
    lay = L.from_declared(spark, {0: 2.0})
    over = long(spark, {0: 5.0}, {0: 1.0, 9: 1.0})
    assert L.check_overflow(over, lay, "report").count() == 2
    assert sorted(map(tuple, L.check_overflow(over, lay, "clip").collect())) == [(0, 0, 2.0), (1, 0, 1.0)]
    with pytest.raises(Exception, match="above"):
        L.check_overflow(over, lay).collect()
    e = redgreen.with_empty(redgreen.sketch(over.where("vec_id = 1 AND comp = 0"), lay, 2, 1), spark.createDataFrame([(1,), (2,)], "vec_id long"))
    assert [r["vec_id"] for r in e.where("h IS NULL").collect()] == [2]
    none = long(spark)
    assert L.of(none).dim == 0 and redgreen.sketch_relational(none, spark.createDataFrame([], "hash_id int, step int, comp int, offset double")).count() == 0


def test_layout_prefix_over_blocks_equals_one_window(spark):
    caps = spark.range(10_000).select(F.col("id").cast("int").alias("comp"), F.lit(1.0).alias("max_w"), (F.pmod("id", F.lit(5)) + 1).cast("double").alias("cap"))
    lay = L.build_layout(caps)
    lo = np.array([r["lo"] for r in lay.df.orderBy("comp").collect()])
    assert (lo == np.concatenate(([0], np.cumsum(np.arange(9_999) % 5 + 1)))).all()
    assert L.horizon(0.05, 1e-6) == 270


def test_plan_shapes(spark, few):
    v, _ = few
    lay = L.of(v)
    plan = redgreen.sketch_relational(v, D.build(lay, 8, 16, 3))._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "partial_min" in plan and "Python" not in plan and "CartesianProduct" not in plan
    assert "NestedLoop" not in D.build(lay, 8, 16, 3)._jdf.queryExecution().executedPlan().toString()


def test_lsh_clusters_and_estimates(spark):
    rng = random.Random(1)
    base = [{c: rng.uniform(1, 3) for c in rng.sample(range(60), 30)} for _ in range(6)]
    out = [{c: w * rng.uniform(0.99, 1.0) for c, w in b.items()} for b in base for _ in range(3)]
    v = long(spark, *out)
    s = redgreen.sketch_batches(V.pack(v), L.of(v, rounding="exact"), 64, 200, 3)
    got = {r["vec_id"]: r["cluster"] for r in lsh.near_duplicates(s, v, 0.9, 4, 16).collect()}
    assert got == {i: i // 3 * 3 for i in range(18)}
    top = lsh.query(lsh.index(s, 4, 16), lsh.index(s, 4, 16), v, v, 1).collect()
    assert all(r["query_id"] == r["vec_id"] and abs(r["j"] - 1) < 1e-9 for r in top)
    assert kernel.gram(s, s.select("vec_id")).where("id_a = id_b AND value < 1").count() == 0
    with pytest.raises(Exception, match="compare"):
        t = s.withColumn("layout_id", F.when(F.col("vec_id") == 0, "a").otherwise("b"))
        similarity.estimate(t, spark.createDataFrame([(0, 1)], "id_a long, id_b long")).collect()


def test_sql_functions(spark):
    SQL.register(spark)
    assert spark.sql("SELECT weighted_jaccard(map('a', 1D, 'b', 2D), map('a', 2D, 'c', 1D)) AS j").first()["j"] == pytest.approx(1 / 5)
    assert spark.sql("SELECT sketch_similarity(array(1, 2, 0), array(1, 3, 0)) AS j").first()["j"] == pytest.approx(1 / 3)
    assert spark.sql("SELECT count(*) AS n FROM red_green_draws(10D, 3, 4, 1)").first()["n"] == 12
    assert spark.sql("SELECT * FROM lsh_buckets(array(1, 2, 3, 0), 2, 2)").count() == 1


def test_accuracy_order_of_the_methods(spark, few):
    """Red-green and gamma errors are alike; the replicated sketch is biased on real weights."""
    v, _ = few
    pairs = experiments.nine_pairs(v)
    mae = {}
    for m, kw in (("redgreen", {"layout": L.of(v), "steps": 200}), ("gamma_cws", {}), ("replicated_oph", {})):
        mae[m] = experiments.error_curve(v, pairs, m, 50, range(200), **kw).where("k = 50").agg(F.avg("mae")).first()[0]
    assert abs(mae["redgreen"] - mae["gamma_cws"]) < 0.02 and mae["replicated_oph"] > mae["redgreen"]
