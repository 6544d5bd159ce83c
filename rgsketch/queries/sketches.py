"""Queries of vectors, layouts, draws, samplers and baselines, each with its DuckDB equivalent where there is one."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from rgsketch.functions import rng
from rgsketch.operators import compact, gamma_cws, measures, redgreen, replicate, replicated_oph, similarity, unweighted
from rgsketch.plans import darts as D
from rgsketch.plans import layout as L
from rgsketch.sources import families as V
from rgsketch.sources.tables import materialize, shared_dir, table

SEED = 7
#: Hashes of each family's relational sketch, widths, and the horizon of its SQL, far enough for every hash of the given
#: tables; the sketch itself draws on until no hash is open.
PLAN = {
    "embeddings": (32, "ceil", 512), "customer_brand": (32, "ceil", 100_000), "supplier_brand": (64, "ceil", 256), "supplier_month": (64, "ceil", 256),
    "part_supplier": (16, "ceil", 4096), "user_hours": (32, "ceil", 1024), "doc_letters": (32, "exact", 512), "page_tags": (32, "ceil", 4096),
}
_GROUP = "SELECT vec_id, comp, round(weight, 6) AS weight FROM v"


def _r(name: str, d: int = 6):
    return F.round(name, d).alias(name)


def _with(*parts: str) -> str:
    return "WITH " + ", ".join(parts) + " "


def _family(name):
    def run(spark, d):
        return V.BUILDERS[name](spark, d).select("vec_id", "comp", _r("weight"))

    return run, _with(V.sql(name)) + _GROUP


def _stats(spark, d):
    out = None
    for name, build in V.BUILDERS.items():
        s = measures.dataset_stats(build(spark, d)).select(F.lit(name).alias("family"), F.col("n"), _r("d_avg"), "dim", _r("total"), _r("s_avg", 9))
        out = s if out is None else out.unionByName(s)
    return out


_STATS = " UNION ALL ".join(
    f"(WITH {V.sql(f)}, c AS (SELECT count(*) AS dim, sum(cap) AS total FROM (SELECT greatest(1.0::DOUBLE, ceil(max(weight))) AS cap FROM v GROUP BY comp)), "
    f"p AS (SELECT count(*) AS n, avg(d) AS d_avg, avg(l1) AS l1 FROM (SELECT count(*) AS d, sum(weight) AS l1 FROM v GROUP BY vec_id)) "
    f"SELECT '{f}' AS family, n, round(d_avg, 6) AS d_avg, dim, round(total, 6) AS total, round(l1 / total, 9) AS s_avg FROM p, c)"
    for f in V.BUILDERS
)


def _complete(spark, d, name, k=None, rounding=None):
    """A family's vectors (made once), their layout and all their hashes."""
    own, wide, _ = PLAN[name]
    v = materialize(V.BUILDERS[name](spark, d))
    lay = L.of(v, rounding=rounding or wide)
    return v, lay, redgreen.sketch(v, lay, k or own, SEED)


def _complete_sql(name, k=None, rounding=None):
    own, wide, steps = PLAN[name]
    return V.sql(name), L.sql(rounding=rounding or wide), D.sql(k or own, steps, SEED, pruned=True), redgreen.sql()


def _rg(name: str, rounding: str | None = None):
    return lambda spark, d: _complete(spark, d, name, rounding=rounding)[2], _with(*_complete_sql(name, rounding=rounding)) + "SELECT * FROM rg"


def _emb(spark, d):
    v = V.embeddings(spark, d)
    return v, L.of(v)


_EMB = (V.sql("embeddings"), L.sql())
_K, _, _T = PLAN["embeddings"]
_RG_EMB = _with(*_complete_sql("embeddings")) + "SELECT * FROM rg"


def _caps(spark, d):
    return L.component_caps(V.supplier_brand(spark, d))


def _exact_caps(spark, d):
    return L.of(V.embeddings(spark, d), rounding="exact").df.select("comp", _r("max_w"), _r("cap"), _r("lo"))


def _cells(spark, d):
    return L.cell_table(L.of(V.supplier_brand(spark, d)))


def _starts(spark, d):
    return L.start_table(L.of(V.supplier_month(spark, d)))


def _unit(spark, d):
    return L.unit_layout(V.doc_letters(spark, d)).df.select("comp", "cap", "lo")


def _overflow(spark, d):
    """Hourly counts of users against widths of 8, declared for all components."""
    v = V.user_hours(spark, d)
    lay = L.Layout(v.select("comp").distinct().withColumn("cap", F.lit(8.0)), 8.0, 1)
    return L.check_overflow(v, lay, "report").select("vec_id", "comp", "weight", "cap")


def _estimate(spark, d):
    return L.estimate(V.user_hours(spark, d), 0.5, 1.5).df.select("comp", "cap")


def _fill(name):
    def run(spark, d):
        v = V.BUILDERS[name](spark, d)
        return L.fill(v, L.of(v)).select("vec_id", _r("l1"), _r("s", 9))

    return run, _with(V.sql(name), L.sql()) + "SELECT vec_id, round(sum(weight), 6) AS l1, round(sum(weight) / any_value(total), 9) AS s FROM v, lay_m GROUP BY vec_id"


GRID = [0.5, 1.0, 2.0, 5.0, 10.0, 100.0, 1000.0]


def _scale(spark, d):
    return L.best_scale(V.doc_letters(spark, d), GRID).select("alpha", "total", _r("fill", 9), "place")


_SCALE = _with(V.sql("doc_letters"), "c AS (SELECT comp, max(weight) AS m FROM v GROUP BY comp)", "a AS (SELECT avg(l1) AS l1 FROM (SELECT sum(weight) AS l1 FROM v GROUP BY vec_id))", f"t AS (SELECT alpha, sum(greatest(1.0::DOUBLE, ceil(m * alpha))) AS total FROM c, (SELECT unnest({GRID})::DOUBLE AS alpha) GROUP BY alpha)") + "SELECT alpha, total, round(l1 * alpha / total, 9) AS fill, row_number() OVER (ORDER BY round(l1 * alpha / total, 9) DESC, total, alpha)::INT AS place FROM t, a"


def _choice(spark, d):
    from rgsketch.operators.experiments import crossover

    return crossover(spark, {n: b(spark, d) for n, b in V.BUILDERS.items()}).select("family", _r("redgreen_work", 3), _r("gamma_work", 3), "method")


_CHOICE = " UNION ALL ".join(
    f"(WITH {V.sql(f)}, {L.sql()}, p AS (SELECT sum(weight) AS l1, count(*) AS d FROM v GROUP BY vec_id), r AS (SELECT 500 * avg(total / l1) AS a, 500 * avg(d) * 8.0::DOUBLE AS b FROM p, lay_m) "
    f"SELECT '{f}' AS family, round(a, 3) AS redgreen_work, round(b, 3) AS gamma_work, CASE WHEN least(a, b) > 1e6 THEN 'fold' WHEN a <= b THEN 'redgreen' ELSE 'gamma_cws' END AS method FROM r)"
    for f in V.BUILDERS
)


def _uniform(spark, d):
    return table(spark, d, "orders", "o_orderkey").select("o_orderkey", rng.uniform(SEED, F.col("o_orderkey"), 3).alias("u"))


def _universal(spark, d):
    return table(spark, d, "orders", "o_orderkey").select("o_orderkey", rng.two_universal(F.col("o_orderkey"), SEED, 1000).alias("h"))


def _darts(spark, d):
    return D.build(_emb(spark, d)[1], _K, _T, SEED).select("hash_id", "step", "comp", _r("offset", 9))


def _saved(spark, d):
    """Darts written to the shared folder and read back."""
    path = f"{shared_dir(spark)}/rgsketch/{uuid.uuid4().hex}"
    D.save(D.build(_emb(spark, d)[1], _K, _T, SEED), path)
    return D.load(spark, path).select("hash_id", "step", "comp", _r("offset", 9))


def _pruned(spark, d):
    return D.prune(D.build(_emb(spark, d)[1], _K, _T, SEED)).select("hash_id", "step", "comp", _r("offset", 9))


def _live(spark, d):
    lay = _emb(spark, d)[1]
    return D.drop_dead(D.prune(D.build(lay, _K, _T, SEED)), lay).select("hash_id", "step", "comp", _r("offset", 9))


_DARTS = (*_EMB, D.sql(_K, _T, SEED))
_PRUNED = "pr AS (SELECT * FROM (SELECT *, min(off) OVER (PARTITION BY hash_id, comp ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS m FROM darts) WHERE m IS NULL OR off < m)"


def _chained(spark, d):
    return D.chained(_emb(spark, d)[1], 16, 24, SEED).select("hash_id", "step", _r("r", 9))


_CHAINED = (
    "WITH RECURSIVE " + ", ".join(_EMB) + f", ch(hash_id, step, r) AS (SELECT h::INT, 1, {rng.sql_uniform(f"'{SEED}'", "'chain'", 'h')} * total FROM range(16) t(h), lay_m "
    f"UNION ALL SELECT hash_id, step + 1, {rng.sql_uniform("'next'", f'ceil(r * {D.MULTIPLIER})::BIGINT')} * total FROM ch, lay_m WHERE step < 24) SELECT hash_id, step, round(r, 9) AS r FROM ch"
)


def _rg_pruned(spark, d):
    v, lay = _emb(spark, d)
    return redgreen.sketch_relational(v, D.drop_dead(D.prune(D.build(lay, _K, _T, SEED)), lay))


def _rg_batches(spark, d):
    v, lay = _emb(spark, d)
    return redgreen.to_long(redgreen.sketch_batches(V.pack(v), lay, _K, _T, SEED)).where("h > 0").select("vec_id", F.col("hash_id").cast("int").alias("hash_id"), "h")


def _rg_scalar(spark, d):
    """The plain Python function on every vector, for comparison only."""
    v, lay = _emb(spark, d)
    rows = [(r["comp"], r["cap"], r["lo"]) for r in lay.df.orderBy("lo").collect()]  # one row a component of 128

    @F.udf("array<int>")
    def one(comps, weights):
        return redgreen.sketch_one(comps, weights, rows, 8, SEED)

    return redgreen.to_long(V.pack(v).select("vec_id", one("comps", "weights").alias("sketch"))).select("vec_id", F.col("hash_id").cast("int").alias("hash_id"), "h")


def _rg_extended(spark, d):
    v, lay = _emb(spark, d)
    return redgreen.sketch(v, lay, 16, SEED, steps=32, unresolved="extend")


def _rg_capped(spark, d):
    v, lay = _emb(spark, d)
    return redgreen.sketch(v, lay, 16, SEED, steps=32, unresolved="cap")


_LONG = lambda k, t: _with(*_EMB, D.sql(k, t, SEED), redgreen.sql()) + "SELECT * FROM rg"
_CAPPED = _with(*_EMB, D.sql(16, 32, SEED), redgreen.sql()) + "SELECT i.vec_id, x.hash_id::INT AS hash_id, coalesce(h, 0)::INT AS h FROM (SELECT DISTINCT vec_id FROM v) i CROSS JOIN range(16) x(hash_id) LEFT JOIN rg ON rg.vec_id = i.vec_id AND rg.hash_id = x.hash_id"


def _sets(spark, d):
    """The sets of suppliers of each part, whatever the quantity."""
    s = table(spark, d, "lineitem", "l_partkey", "l_suppkey").groupBy(F.col("l_partkey").alias("vec_id")).agg(F.collect_set("l_suppkey").alias("items"))
    return redgreen.sketch_sets(s, 16, 64, SEED)[0]


_SETS = _with("v AS (SELECT DISTINCT l_partkey AS vec_id, l_suppkey::INT AS comp, 1.0::DOUBLE AS weight FROM lineitem)", L.sql(), D.sql(16, 64, SEED), redgreen.sql()) + "SELECT i.vec_id, x.hash_id::INT AS hash_id, coalesce(h, 0)::INT AS h FROM (SELECT DISTINCT vec_id FROM v) i CROSS JOIN range(16) x(hash_id) LEFT JOIN rg ON rg.vec_id = i.vec_id AND rg.hash_id = x.hash_id"


def _empty(spark, d):
    """Letters' sketches with a null row for each document without a letter."""
    h = _complete(spark, d, "doc_letters", 4)[2]
    return redgreen.with_empty(h, table(spark, d, "documents", F.col("doc_id").alias("vec_id")))


_EMPTY = _with(*_complete_sql("doc_letters", 4)) + "SELECT * FROM rg UNION ALL SELECT DISTINCT doc_id, NULL::INT, NULL::INT FROM documents WHERE doc_id NOT IN (SELECT vec_id FROM rg)"


def _merge(spark, d):
    """Customers' sketches merged by nation: the sketch of each nation's element-wise maximum."""
    h = _complete(spark, d, "customer_brand")[2]
    return redgreen.merge_max(h, table(spark, d, "customer", F.col("c_custkey").alias("vec_id"), F.col("c_nationkey").alias("group_id")))


_MERGE = _with(*_complete_sql("customer_brand")[:3], "g AS (SELECT c_nationkey AS vec_id, comp, max(weight) AS weight FROM v JOIN customer ON c_custkey = vec_id GROUP BY ALL)", redgreen.sql("g")) + "SELECT * FROM rg"


def _growth(spark, d):
    """Suppliers' sketches on half of each weight, grown to the whole one."""
    v = V.supplier_brand(spark, d)
    darts = D.build(L.of(v), 64, 64, SEED)
    half = v.withColumn("weight", F.floor(F.col("weight") / 2).cast("double"))
    grown = v.select("vec_id", "comp", F.floor(F.col("weight") / 2).cast("double").alias("old_weight"), F.col("weight").alias("new_weight"))
    return redgreen.update(redgreen.sketch_relational(half, darts), grown, darts)


_GROWTH = _with(V.sql("supplier_brand"), L.sql(), D.sql(64, 64, SEED), redgreen.sql()) + "SELECT * FROM rg"


def _green(test):
    """Membership of the first draws of four hashes in every vector."""

    def run(spark, d):
        v = V.supplier_month(spark, d) if test != "table" else V.page_tags(spark, d)
        lay = L.of(v)
        rows = v.join(lay.df.select("comp", "lo"), "comp").groupBy("vec_id").agg(F.sort_array(F.collect_list(F.struct("lo", "weight"))).alias("e"), F.map_from_entries(F.collect_list(F.struct("comp", "weight"))).alias("m"))
        j = rows.crossJoin(F.broadcast(D.draws(lay, 4, 8, SEED)))
        if test == "table":
            t = lay.df.orderBy("lo").select("lo", "comp", "cap").collect()  # a row a tag
            starts, cells = [0.0] * len(t), []
            for lo, c, cap in t:
                starts[c] = lo
                cells += [c] * int(cap)
            green = redgreen.is_green_table(F.col("r"), F.array(*map(F.lit, cells)), F.array(*map(F.lit, starts)), F.col("m"))
        else:
            green = {"scan": redgreen.is_green_scan, "search": redgreen.is_green_search}[test](F.col("r"), F.col("e.lo"), F.col("e.weight"))
        return j.select("vec_id", "hash_id", "step", green.alias("green"))

    f = "page_tags" if test == "table" else "supplier_month"
    return run, _with(V.sql(f), L.sql(), D.sql(4, 8, SEED)) + "SELECT i.vec_id, d.hash_id, d.step, coalesce(d.off < v.weight, false) AS green FROM (SELECT DISTINCT vec_id FROM v) i CROSS JOIN darts d LEFT JOIN v ON v.vec_id = i.vec_id AND v.comp = d.comp"


def _gamma(name, k):
    def run(spark, d):
        return gamma_cws.sketch(V.BUILDERS[name](spark, d), k, SEED)

    return run, _with(V.sql(name), gamma_cws.sql(k, SEED)) + "SELECT * FROM gam"


def _gamma_batches(spark, d):
    s = gamma_cws.sketch_batches(V.pack(V.embeddings(spark, d)), 64, SEED)
    return s.select("vec_id", F.posexplode(F.arrays_zip("comps", "levels")).alias("hash_id", "x")).select("vec_id", "hash_id", F.col("x.comps").alias("comp"), F.col("x.levels").alias("level"))


def _gamma_bits(spark, d):
    return gamma_cws.compact(gamma_cws.sketch(V.embeddings(spark, d), 16, SEED), 8, "pair", SEED)


_GAMMA_BITS = _with(V.sql("embeddings"), gamma_cws.sql(16, SEED)) + f"SELECT vec_id, hash_id, {rng.sql_bits(f"'{SEED}'", "'v'", 'hash_id', 'comp', 'level')} % 256 AS v FROM gam"


def _gamma_component(spark, d):
    return gamma_cws.compact(gamma_cws.sketch(V.embeddings(spark, d), 16, SEED), mode="component")


def _repl(name, **kw):
    def run(spark, d):
        return replicate.to_set(V.BUILDERS[name](spark, d), seed=SEED, **kw).groupBy("vec_id", "comp").agg(F.count("*").alias("copies"))

    return run, _with(V.sql(name), replicate.sql(seed=SEED, **kw)) + "SELECT vec_id, comp, count(*) AS copies FROM rep GROUP BY ALL"


def _repl_quantized(spark, d):
    v = V.embeddings(spark, d)
    return replicate.quantize(v, L.of(v), 8)


_QUANT = _with(*_EMB) + "SELECT vec_id, comp, round(weight * 8 / max_w) AS weight FROM v JOIN lay USING (comp) WHERE round(weight * 8 / max_w) > 0"
_REP = (V.sql("supplier_brand"), replicate.sql(scale=0.05, coin="shared", seed=SEED))


def _rep(spark, d):
    return replicate.to_set(V.supplier_brand(spark, d), 0.05, "shared", SEED)


def _minhash(spark, d):
    return unweighted.minhash(_rep(spark, d), 32, SEED)


def _oph(spark, d):
    return unweighted.oph(_rep(spark, d), 64, SEED)


def _dense(mode):
    def run(spark, d):
        return unweighted.densify(_oph(spark, d), 64, mode, SEED).select("vec_id", F.col("bin").cast("int").alias("bin"), "h")

    return run, None if mode == "probe" else _with(*_REP, unweighted.sql_oph(64, SEED), unweighted.sql_densify(64, mode, SEED)) + "SELECT * FROM den"


def _replicated_oph(spark, d):
    return replicated_oph.sketch(V.supplier_brand(spark, d), 64, SEED, 0.05).select("vec_id", F.col("hash_id").cast("int").alias("hash_id"), "h")


def _replicated_batches(spark, d):
    s = replicated_oph.sketch_batches(V.pack(V.supplier_brand(spark, d)), 64, SEED, 0.05)
    return redgreen.to_long(s).select("vec_id", F.col("hash_id").cast("int").alias("hash_id"), "h")


def _wide(spark, d):
    """The whole terms of the documents, a dimension of tens of thousands, as replicated sketches."""
    return replicated_oph.sketch(V.doc_terms(spark, d), 64, SEED).select("vec_id", F.col("hash_id").cast("int").alias("hash_id"), "h")


def _classic(spark, d):
    return replicated_oph.sketch_classic(V.supplier_brand(spark, d), 32, SEED, 0.05)


def _permutation(spark, d):
    return unweighted.permute_exact(table(spark, d, "part", F.col("p_partkey").alias("elem")), SEED)


_PERM = f"SELECT p_partkey AS elem, (row_number() OVER (ORDER BY {rng.sql_uniform(f"'{SEED}'", "'perm'", 'p_partkey')}, p_partkey) - 1)::INT AS rank FROM part"


def _naive(spark, d):
    return unweighted.naive_sample(V.supplier_brand(spark, d), 16, SEED)


_NAIVE = _with(V.sql("supplier_brand")) + f"SELECT vec_id, hash_id::INT AS hash_id, min_by(comp, up) AS h FROM (SELECT vec_id, comp, sum(weight) OVER (PARTITION BY vec_id ORDER BY comp) / sum(weight) OVER (PARTITION BY vec_id) AS up FROM v), range(16) x(hash_id) WHERE up >= {rng.sql_uniform(f"'{SEED}'", "'own'", 'vec_id', 'hash_id')} GROUP BY vec_id, hash_id"


def _moments(name):

    def run(spark, d):
        v, lay, h = _complete(spark, d, name)
        out = measures.hash_moments(h, L.fill(v, lay))
        return out.select("vec_id", *[_r(c) for c in ("mean_h", "var_h", "mean_theory", "var_theory")])

    return run, _with(*_complete_sql(name), "f AS (SELECT vec_id, sum(weight) / any_value(total) AS s FROM v, lay_m GROUP BY vec_id)") + "SELECT vec_id, round(avg(h), 6) AS mean_h, round(var_samp(h), 6) AS var_h, round(1 / any_value(s), 6) AS mean_theory, round((1 - any_value(s)) / (any_value(s) * any_value(s)), 6) AS var_theory FROM rg JOIN f USING (vec_id) GROUP BY vec_id"


def _of_rg(name, use, cols):

    def run(spark, d):
        v, lay, h = _complete(spark, d, name)
        return use(h, L.fill(v, lay), PLAN[name][0]).select(*[_r(c) if r else c for c, r in cols])

    return run


_FILL = "f AS (SELECT vec_id, sum(weight) / any_value(total) AS s FROM v, lay_m GROUP BY vec_id)"
_EMB_RG = (*_complete_sql("embeddings"), _FILL)
_TAIL = _with(*_EMB_RG) + "SELECT t, round(avg(CASE WHEN h > t THEN 1.0::DOUBLE ELSE 0.0 END), 6) AS observed, round(avg(pow(1 - s, t)), 6) AS expected FROM rg JOIN f USING (vec_id), (SELECT unnest([1, 5, 10, 20, 50, 100])::INT AS t) GROUP BY t"
_RANGE = _with(*_EMB_RG) + "SELECT round(avg(h), 6) AS mean_h, min(h) AS min_h, max(h) AS max_h, ceil(log2(max(h) + 1))::INT AS bits FROM rg"
_BITS = _with(*_EMB_RG) + "SELECT round(a, 6) AS mean_log2, round(b, 6) AS bound, round(c, 6) AS second_order, round(e, 6) AS entropy FROM (SELECT avg(log2(h)) AS a FROM rg), (SELECT avg(log2(1 / s)) AS b, avg(log2(1 / s) - (1 - s) / (2 * ln(2))) AS c, avg((-(1 - s) * log2(1 - s) - s * log2(s)) / s) AS e FROM f WHERE s < 1)"
_STORE = _with(*_EMB_RG) + f"SELECT bits, ceil(bits * {_K} / 8.0)::BIGINT AS bytes, round(32.0::DOUBLE / bits, 6) AS saving_32, round(64.0::DOUBLE / bits, 6) AS saving_64, round(96.0::DOUBLE / bits, 6) AS saving_pair FROM (SELECT ceil(log2(max(h) + 1))::INT AS bits FROM rg)"


def _work(spark, d):
    v, lay = _emb(spark, d)
    return measures.work(v, lay, 500).select("vec_id", _r("draws", 3), "variates", _r("copies"))


_WORK = _with(*_EMB) + "SELECT vec_id, round(500 * any_value(total) / sum(weight), 3) AS draws, 500 * count(*) AS variates, round(sum(weight), 6) AS copies FROM v, lay_m GROUP BY vec_id"


def _draws(spark, d):
    return measures.draw_counts(_complete(spark, d, "embeddings")[2])


def _packed(spark, d):
    """Packed to the bits they need and back: equal to the sketches."""
    v, lay = _emb(spark, d)
    s = redgreen.sketch_batches(V.pack(v), lay, _K, _T, SEED)
    return redgreen.to_long(compact.unpack(compact.pack(s, 9), 9, _K)).where("h > 0").select("vec_id", F.col("hash_id").cast("int").alias("hash_id"), "h")


def queries() -> dict:
    """name -> (function, SQL or None)."""
    out = {"stats_families": (_stats, _STATS)}
    out |= {f"vec_{n}": _family(n) for n in V.BUILDERS}
    caps = "SELECT comp, max_w, cap FROM lay_c"
    out |= {
        "layout_caps": (_caps, _with(V.sql("supplier_brand"), L.sql()) + caps),
        "layout_exact_caps": (_exact_caps, _with(V.sql("embeddings"), L.sql(rounding="exact")) + "SELECT comp, round(max_w, 6) AS max_w, round(cap, 6) AS cap, round(lo, 6) AS lo FROM lay"),
        "layout_cells": (_cells, _with(V.sql("supplier_brand"), L.sql()) + "SELECT unnest(range(lo::BIGINT, (lo + cap)::BIGINT)) AS cell, comp FROM lay"),
        "layout_prefix": (_starts, _with(V.sql("supplier_month"), L.sql()) + "SELECT comp, lo FROM lay"),
        "layout_unit": (_unit, _with(V.sql("doc_letters")) + "SELECT comp, 1.0::DOUBLE AS cap, (row_number() OVER (ORDER BY comp) - 1)::DOUBLE AS lo FROM (SELECT DISTINCT comp FROM v)"),
        "layout_overflow": (_overflow, _with(V.sql("user_hours")) + "SELECT vec_id, comp, weight, 8.0::DOUBLE AS cap FROM v WHERE weight > 8"),
        "layout_estimate": (_estimate, None),
        "fill_vectors": _fill("embeddings"), "fill_letters": _fill("doc_letters"), "fill_parts": _fill("part_supplier"),
        "scale_search": (_scale, _SCALE), "method_choice": (_choice, _CHOICE),
        "rng_uniform": (_uniform, f"SELECT o_orderkey, {rng.sql_uniform(f"'{SEED}'", 'o_orderkey', '3')} AS u FROM orders"),
        "rng_two_universal": (_universal, f"SELECT o_orderkey, {rng.sql_universal('o_orderkey', SEED)} % 1000 AS h FROM orders"),
        "darts_build": (_darts, _with(*_DARTS) + 'SELECT hash_id, step, comp, round(off, 9) AS "offset" FROM darts'),
        "darts_saved": (_saved, _with(*_DARTS) + 'SELECT hash_id, step, comp, round(off, 9) AS "offset" FROM darts'),
        "darts_pruned": (_pruned, _with(*_DARTS, _PRUNED) + 'SELECT hash_id, step, comp, round(off, 9) AS "offset" FROM pr'),
        "darts_live": (_live, _with(*_DARTS, _PRUNED) + 'SELECT hash_id, step, comp, round(off, 9) AS "offset" FROM pr JOIN lay USING (comp) WHERE off < max_w'),
        "darts_chained": (_chained, _CHAINED),
        "rg_pruned": (_rg_pruned, _RG_EMB), "rg_batches": (_rg_batches, _RG_EMB), "rg_scalar": (_rg_scalar, _LONG(8, 2048)), "rg_extended": (_rg_extended, _LONG(16, 2048)), "rg_capped": (_rg_capped, _CAPPED),
        "rg_exact_caps": _rg("embeddings", "exact"),
        "rg_sets": (_sets, _SETS), "rg_empty_policy": (_empty, _EMPTY), "rg_merge_max": (_merge, _MERGE), "rg_growth": (_growth, _GROWTH), "rg_packed_bits": (_packed, _RG_EMB),
        "green_scan": _green("scan"), "green_search": _green("search"), "green_table": _green("table"),
        "gamma_embeddings": _gamma("embeddings", 16), "gamma_customer_brand": _gamma("customer_brand", 16), "gamma_batches": (_gamma_batches, _with(V.sql("embeddings"), gamma_cws.sql(64, SEED)) + "SELECT * FROM gam"),
        "gamma_bits": (_gamma_bits, _GAMMA_BITS), "gamma_component_only": (_gamma_component, _with(V.sql("embeddings"), gamma_cws.sql(16, SEED)) + "SELECT vec_id, hash_id, comp::BIGINT AS v FROM gam"),
        "repl_integer": _repl("customer_brand", coin="none"), "repl_shared_coin": _repl("embeddings", coin="shared", scale=20.0), "repl_independent_coin": _repl("embeddings", coin="independent", scale=20.0), "repl_quantized": (_repl_quantized, _QUANT),
        "minhash_sets": (_minhash, _with(*_REP, unweighted.sql_minhash(32, SEED)) + "SELECT * FROM mh"), "minhash_replicated": (_classic, _with(*_REP, unweighted.sql_minhash(32, SEED)) + "SELECT * FROM mh"),
        "oph_bins": (_oph, _with(*_REP, unweighted.sql_oph(64, SEED)) + "SELECT * FROM oph"), "oph_rotate": _dense("rotate"), "oph_direction": _dense("direction"), "oph_probe": _dense("probe"),
        "replicated_oph": (_replicated_oph, _with(*_REP, unweighted.sql_oph(64, SEED), unweighted.sql_densify(64, "rotate", SEED)) + "SELECT vec_id, bin AS hash_id, h FROM den"),
        "replicated_oph_batches": (_replicated_batches, _with(*_REP, unweighted.sql_oph(64, SEED), unweighted.sql_densify(64, "rotate", SEED)) + "SELECT vec_id, bin AS hash_id, h FROM den"),
        "replicated_oph_terms": (_wide, _with(V.sql("doc_terms"), replicate.sql(seed=SEED), unweighted.sql_oph(64, SEED), unweighted.sql_densify(64, "rotate", SEED)) + "SELECT vec_id, bin AS hash_id, h FROM den"),
        "permutation_exact": (_permutation, _PERM), "naive_sampler": (_naive, _NAIVE),
        "hash_moments": _moments("embeddings"), "hash_moments_letters": _moments("doc_letters"),
        "hash_tail": (_of_rg("embeddings", lambda h, f, k: measures.tail_check(h, f, [1, 5, 10, 20, 50, 100]), [("t", 0), ("observed", 1), ("expected", 1)]), _TAIL),
        "bits_range": (_of_rg("embeddings", lambda h, f, k: measures.range_bits(h), [("mean_h", 1), ("min_h", 0), ("max_h", 0), ("bits", 0)]), _RANGE),
        "bits_expected": (_of_rg("embeddings", lambda h, f, k: measures.bits_report(h, f), [("mean_log2", 1), ("bound", 1), ("second_order", 1), ("entropy", 1)]), _BITS),
        "storage_report": (_of_rg("embeddings", lambda h, f, k: measures.storage(h, k), [("bits", 0), ("bytes", 0), ("saving_32", 1), ("saving_64", 1), ("saving_pair", 1)]), _STORE),
        "work_counters": (_work, _WORK), "draw_counts": (_draws, _with(*_EMB_RG) + "SELECT vec_id, sum(h)::BIGINT AS draws FROM rg GROUP BY vec_id"),
    }
    return out | {f"rg_{n}": _rg(n) for n in PLAN}
