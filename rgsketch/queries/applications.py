"""Queries of estimates, errors, distances, searches, joins, clusters, kernels and studies."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from rgsketch.functions import rng
from rgsketch.operators import blocks, compact, experiments, gamma_cws, kernel, lsh, measures, redgreen, similarity
from rgsketch.plans import darts as D
from rgsketch.plans import layout as L
from rgsketch.queries.sketches import SEED, _r, _with
from rgsketch.sources import families as V
from rgsketch.sources.tables import materialize, table


def _exact(name):
    def run(spark, d):
        return similarity.exact_pairs(V.BUILDERS[name](spark, d)).select("id_a", "id_b", _r("j"))

    return run, _with(V.sql(name), similarity.sql_exact()) + "SELECT id_a, id_b, round(j, 6) AS j FROM ex"


def _set_jaccard(spark, d):
    """Of the suppliers' sets of parts, all pairs that share one: with weights of 1, minima count what is common."""
    v = table(spark, d, "lineitem", F.col("l_suppkey").alias("vec_id"), F.col("l_partkey").alias("comp")).distinct().withColumn("weight", F.lit(1.0))
    return similarity.exact_pairs(v).select("id_a", "id_b", _r("j"))


_SETJ = _with("v AS (SELECT DISTINCT l_suppkey AS vec_id, l_partkey AS comp, 1.0::DOUBLE AS weight FROM lineitem)", similarity.sql_exact()) + "SELECT id_a, id_b, round(j, 6) AS j FROM ex"


def _l1(spark, d):
    """Of all pairs that share a component."""
    return similarity.exact_l1(V.supplier_month(spark, d)).select("id_a", "id_b", _r("l1", 5))


_L1 = _with(V.sql("supplier_month"), similarity.sql_exact()) + "SELECT id_a, id_b, round((l1_a + l1_b) * (1 - j) / (1 + j), 5) AS l1 FROM ex"
_CUM = (
    "cu AS (SELECT * FROM (SELECT g.vec_id, g.comp, sum(coalesce(v.weight, 0)) OVER (PARTITION BY g.vec_id ORDER BY g.comp) / t.a AS weight FROM (SELECT DISTINCT vec_id FROM v) i CROSS JOIN (SELECT DISTINCT comp FROM v) c "
    "JOIN LATERAL (SELECT i.vec_id, c.comp) g ON TRUE LEFT JOIN v ON v.vec_id = g.vec_id AND v.comp = g.comp JOIN (SELECT vec_id, sum(weight) AS a FROM v GROUP BY vec_id) t ON t.vec_id = g.vec_id) WHERE weight > 0)"
)


def _months(spark, d):
    """Suppliers' money over months in order of time."""
    rows = table(spark, d, "lineitem", "l_suppkey", "l_shipdate", "l_extendedprice")
    comp = (F.year("l_shipdate") * 12 + F.month("l_shipdate")).alias("comp")
    return rows.groupBy(F.col("l_suppkey").alias("vec_id"), comp).agg((F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double") / 1000).alias("weight"))


_MONTHS = "v AS (SELECT l_suppkey AS vec_id, (year(l_shipdate) * 12 + month(l_shipdate))::INT AS comp, sum(l_extendedprice::DECIMAL(18,2))::DOUBLE / 1000 AS weight FROM lineitem GROUP BY ALL)"


def _emd(spark, d):
    c = materialize(similarity.cumulative(_months(spark, d)))
    return similarity.exact_l1(c).select("id_a", "id_b", F.round("l1", 4).alias("emd"))


_EMD = _with(_MONTHS, _CUM, similarity.sql_exact("cu")) + "SELECT id_a, id_b, round((l1_a + l1_b) * (1 - j) / (1 + j), 4) AS emd FROM ex"


def _packed(v, lay, k):
    """Packed sketches whose horizon follows the least filled vector."""
    return redgreen.sketch_batches(V.pack(v), lay, k, redgreen.full_horizon(v, lay, k), SEED)


def _sketch_estimates(name, k, rounding="ceil"):
    """Packed sketches of a family and the estimates of all its pairs beside the exact values."""

    def run(spark, d):
        v = materialize(V.BUILDERS[name](spark, d))
        s = _packed(v, L.of(v, rounding=rounding), k)
        return blocks.pairs(v, s, (k,)).withColumnRenamed(f"est_{k}", "est")

    return run


def _est_sql(name, k, steps=512):
    return (V.sql(name), L.sql(), D.sql(k, steps, SEED, pruned=True), redgreen.sql(), similarity.sql_exact(), f"es AS (SELECT id_a, id_b, coalesce(n, 0) / {k}.0::DOUBLE AS est, j, l1_a, l1_b FROM ex LEFT JOIN (SELECT a.vec_id AS id_a, b.vec_id AS id_b, count(*) AS n FROM rg a JOIN rg b ON a.hash_id = b.hash_id AND a.h = b.h AND a.vec_id < b.vec_id GROUP BY ALL) USING (id_a, id_b))")


def _est(spark, d):
    return _sketch_estimates("embeddings", 64)(spark, d).select("id_a", "id_b", _r("est"), _r("j"))


def _suppliers(spark, d):
    return _sketch_estimates("supplier_brand", 128)(spark, d)


def _l1_est(spark, d):
    e = _sketch_estimates("supplier_month", 128)(spark, d)
    return e.select("id_a", "id_b", F.round(similarity.l1_estimate(F.col("est"), F.col("l1_a"), F.col("l1_b")), 5).alias("est_l1"), F.round(similarity.l1_estimate(F.col("j"), F.col("l1_a"), F.col("l1_b")), 5).alias("l1"))


def _emd_est(spark, d):
    """Sketches with exact widths of the running shares."""
    c = materialize(similarity.cumulative(_months(spark, d)))
    s = _packed(c, L.of(c, rounding="exact"), 256)
    e = blocks.pairs(c, s, (256,)).withColumnRenamed("est_256", "est")
    return e.select("id_a", "id_b", F.round(similarity.l1_estimate(F.col("est"), F.col("l1_a"), F.col("l1_b")), 4).alias("est_emd"), F.round(similarity.l1_estimate(F.col("j"), F.col("l1_a"), F.col("l1_b")), 4).alias("emd"))


_EMD_EST = _with(_MONTHS, _CUM, similarity.sql_exact("cu"), L.sql("cu", rounding="exact"), D.sql(256, 512, SEED, pruned=True), redgreen.sql("cu"), "es AS (SELECT id_a, id_b, coalesce(n, 0) / 256.0::DOUBLE AS est, j, l1_a, l1_b FROM ex LEFT JOIN (SELECT a.vec_id AS id_a, b.vec_id AS id_b, count(*) AS n FROM rg a JOIN rg b ON a.hash_id = b.hash_id AND a.h = b.h AND a.vec_id < b.vec_id GROUP BY ALL) USING (id_a, id_b))") + "SELECT id_a, id_b, round((l1_a + l1_b) * (1 - est) / (1 + est), 4) AS est_emd, round((l1_a + l1_b) * (1 - j) / (1 + j), 4) AS emd FROM es"


def _errors(spark, d):
    """Mean errors over all pairs by the number of hashes used."""
    v = materialize(V.supplier_brand(spark, d))
    s = _packed(v, L.of(v), 128)
    ks = [2, 4, 8, 16, 32, 64, 128]
    p = blocks.pairs(v, s, tuple(ks))
    err = {k: F.col(f"est_{k}") - F.col("j") for k in ks}
    one = p.agg(*[F.struct(F.lit(k).alias("k"), F.round(F.avg(e), 6).alias("bias"), F.round(F.avg(F.abs(e)), 6).alias("mae"), F.round(F.sqrt(F.avg(e * e)), 6).alias("rmse")).alias(f"k{k}") for k, e in err.items()])
    return one.select(F.inline(F.array(*[f"k{k}" for k in ks])))


_ERRORS = _with(V.sql("supplier_brand"), L.sql(), D.sql(128, 512, SEED, pruned=True), redgreen.sql(), similarity.sql_exact(), "ks AS (SELECT unnest([2, 4, 8, 16, 32, 64, 128])::INT AS k)", "ag AS (SELECT a.vec_id AS id_a, b.vec_id AS id_b, a.hash_id FROM rg a JOIN rg b ON a.hash_id = b.hash_id AND a.h = b.h AND a.vec_id < b.vec_id)", "n AS (SELECT id_a, id_b, k, count(*) AS n FROM ag JOIN ks ON hash_id < k GROUP BY ALL)", "e AS (SELECT k, coalesce(n, 0) / k::DOUBLE - j AS e FROM ex CROSS JOIN ks LEFT JOIN n USING (id_a, id_b, k))") + "SELECT k, round(avg(e), 6) AS bias, round(avg(abs(e)), 6) AS mae, round(sqrt(avg(e * e)), 6) AS rmse FROM e GROUP BY k"


def _zscores(spark, d):
    """Equal vectors have no standard error: 0 / 0 is NaN, as in IEEE arithmetic."""
    off, err = F.col("est") - F.col("j"), similarity.std_error(F.col("j"), 128)
    z = F.when(err != 0, F.try_divide(off, err)).otherwise(F.when(off == 0, F.lit(float("nan"))).otherwise(F.signum(off) * F.lit(float("inf"))))
    return _suppliers(spark, d).select("id_a", "id_b", F.round(z, 6).alias("z"))


_ZSCORES = _with(*_est_sql("supplier_brand", 128)) + "SELECT id_a, id_b, round((est - j) / sqrt(j * (1 - j) / 128), 6) AS z FROM es"


def _required(spark, d):
    """Hashes for every accuracy and risk that lines have as discount and tax."""
    eps, delta = (F.col(c).cast("double").alias(n) for c, n in (("l_discount", "eps"), ("l_tax", "delta")))
    asked = table(spark, d, "lineitem", eps, delta).where("eps > 0 AND delta > 0").distinct()
    return asked.select("eps", "delta", similarity.required_k_of(F.col("eps"), F.col("delta")).cast("int").alias("k"))


_REQUIRED = "SELECT eps, delta, ceil(ln(2 / delta) / (2 * eps * eps))::INT AS k FROM (SELECT DISTINCT l_discount::DOUBLE AS eps, l_tax::DOUBLE AS delta FROM lineitem) WHERE eps > 0 AND delta > 0"


def _cap_correction(spark, d):
    """Suppliers' estimates under a horizon of three draws, corrected by the union's fill."""
    v = materialize(V.supplier_brand(spark, d))
    lay = L.of(v)
    s = redgreen.sketch_batches(V.pack(v), lay, 128, 3, SEED)
    e = blocks.pairs(v, s, (128,)).withColumnRenamed("est_128", "est")
    u = (F.col("l1_a") + F.col("l1_b")) / (1 + F.col("j")) / lay.total
    return e.select("id_a", "id_b", _r("est"), F.round(similarity.cap_correction(F.col("est"), u, 3), 6).alias("corrected"))


_CAPCOR = _with(*_est_sql("supplier_brand", 128, 3)) + "SELECT id_a, id_b, round(est, 6) AS est, round(est / (1 - pow(1 - (l1_a + l1_b) / (1 + j) / total, 3)), 6) AS corrected FROM es, lay_m"


def _bits(kind):
    """Estimates of gamma hashes kept to 1, 2, 4 and 8 bits, against whole ones (rehash), or of red-green low bits."""

    def run(spark, d):
        v = V.supplier_brand(spark, d)
        pairs = similarity.exact_pairs(v).select("id_a", "id_b")
        if kind == "rehash":
            h = gamma_cws.sketch(v, 32, SEED)
            cut = lambda b: compact.rehash(h, b, SEED, ("comp", "level"))
        else:
            h = redgreen.sketch(v, L.of(v), 32, SEED)
            cut = lambda b: compact.low_bits(h, b)
        out = None
        for b in (1, 2, 4, 8):
            e = similarity.estimate_long(cut(b), pairs, 32, ("v",)).select(F.lit(b).alias("bits"), "id_a", "id_b", _r("est"), F.round(compact.debias_bits(F.col("est"), b), 6).alias("debiased"))
            out = e if out is None else out.unionByName(e)
        return out

    src = gamma_cws.sql(32, SEED) if kind == "rehash" else f"{L.sql()}, {D.sql(32, 512, SEED, pruned=True)}, {redgreen.sql()}"
    val = f"{rng.sql_bits(f"'{SEED}'", "'re'", 'hash_id', 'comp', 'level')} % (1 << bits)" if kind == "rehash" else "h & ((1 << bits) - 1)"
    sql = _with(V.sql("supplier_brand"), src, f"c AS (SELECT vec_id, hash_id, bits, {val} AS x FROM {'gam' if kind == 'rehash' else 'rg'}, (SELECT unnest([1, 2, 4, 8])::INT AS bits))", "e AS (SELECT a.bits, a.vec_id AS id_a, b.vec_id AS id_b, sum((a.x = b.x)::INT) / 32.0::DOUBLE AS est FROM c a JOIN c b ON a.bits = b.bits AND a.hash_id = b.hash_id AND a.vec_id < b.vec_id GROUP BY ALL)")
    return run, sql + "SELECT bits, id_a, id_b, round(est, 6) AS est, round((est - pow(2.0::DOUBLE, -bits)) / (1 - pow(2.0::DOUBLE, -bits)), 6) AS debiased FROM e"


def _poscorr(spark, d):
    """Over all pairs of suppliers as repetitions: neighbouring positions agree independently."""
    v = V.supplier_brand(spark, d)
    h = redgreen.sketch(v, L.of(v), 64, SEED)
    a, b = (h.select(F.col("vec_id").alias(f"id_{x}"), "hash_id", F.col("h").alias(f"h_{x}")) for x in "ab")
    same = a.join(b, "hash_id").where("id_a < id_b").select((F.col("id_a") * 100000 + F.col("id_b")).alias("rep"), "hash_id", (F.col("h_a") == F.col("h_b")).cast("int").alias("same"))
    return measures.position_correlation(same).select(_r("corr"), "n")


_POSCORR = _with(V.sql("supplier_brand"), L.sql(), D.sql(64, 512, SEED, pruned=True), redgreen.sql(), "s AS (SELECT a.vec_id AS i, b.vec_id AS k, a.hash_id, (a.h = b.h)::INT AS same FROM rg a JOIN rg b ON a.hash_id = b.hash_id AND a.vec_id < b.vec_id)") + "SELECT round(corr(x.same::DOUBLE, y.same::DOUBLE), 6) AS corr, count(*) AS n FROM s x JOIN s y ON x.i = y.i AND x.k = y.k AND y.hash_id = x.hash_id + 1"


# --- searches and joins ------------------------------------------------------------------------------------------

ROWS, TABLES = 2, 16
_K = ROWS * TABLES


def _letters(spark, d):
    """Letters' shares of documents (made once) and their packed sketches, with exact widths: all vectors have norm 1 and so
    one fill, about 0.2, whose horizon leaves a hash open with probability 1e-9."""
    v = materialize(V.doc_letters(spark, d))
    lay = L.of(v, rounding="exact")
    return v, lay, redgreen.sketch_batches(V.pack(v), lay, _K, redgreen.full_horizon(v, lay, _K), SEED)


_LET = (V.sql("doc_letters"), L.sql(rounding="exact"), D.sql(_K, 512, SEED, pruned=True), redgreen.sql())
_PART = f"SELECT vec_id, (hash_id // {ROWS})::INT AS table_id, {rng.sql_bits("'lsh'", f'hash_id // {ROWS}', "string_agg(h::VARCHAR, ',' ORDER BY hash_id)")} AS bucket FROM rg GROUP BY vec_id, hash_id // {ROWS} HAVING count(*) = {ROWS}"
_CAND = (f"ix AS ({_PART})", "cand AS (SELECT DISTINCT a.vec_id AS id_a, b.vec_id AS id_b FROM ix a JOIN ix b ON a.table_id = b.table_id AND a.bucket = b.bucket AND a.vec_id < b.vec_id)")


def _buckets(spark, d):
    return lsh.index(_letters(spark, d)[2], ROWS, TABLES)


def _candidates(spark, d):
    return lsh.candidates(lsh.index(_letters(spark, d)[2], ROWS, TABLES))


def _all_pairs(spark, d):
    v, _, s = _letters(spark, d)
    return lsh.all_pairs(s, v, 0.9, ROWS, TABLES).select("id_a", "id_b", _r("j"))


_ALL = _with(*_LET, *_CAND, "l1 AS (SELECT vec_id, sum(weight) AS l FROM v GROUP BY vec_id)", "lo AS (SELECT id_a, id_b, sum(least(a.weight, b.weight)) AS lo FROM cand JOIN v a ON a.vec_id = id_a JOIN v b ON b.vec_id = id_b AND a.comp = b.comp GROUP BY ALL)", "vp AS (SELECT id_a, id_b, lo / (x.l + y.l - lo) AS j FROM lo JOIN l1 x ON x.vec_id = id_a JOIN l1 y ON y.vec_id = id_b)")


def _clusters(spark, d):
    v, _, s = _letters(spark, d)
    return lsh.near_duplicates(s, v, 0.98, ROWS, TABLES)


_CLUST = _ALL.replace("WITH ", "WITH RECURSIVE ", 1).rstrip() + ", e AS (SELECT id_a AS a, id_b AS b FROM vp WHERE j >= 0.98 UNION SELECT id_b, id_a FROM vp WHERE j >= 0.98), w(x, r) AS (SELECT vec_id, vec_id FROM l1 UNION SELECT w.x, e.b FROM w JOIN e ON e.a = w.r) SELECT x AS vec_id, min(r) AS cluster FROM w GROUP BY x"


def _top(spark, d):
    """For every benchmark item, the five most similar documents by letters among its candidates."""
    v, lay, s = _letters(spark, d)
    q = V.kmers(table(spark, d, "benchmark"), "item_id", "text", 1).join(_names(spark), "name")
    q = q.withColumn("weight", F.col("weight") / F.sum("weight").over(Window.partitionBy("vec_id"))).select("vec_id", "comp", "weight")
    q = q.where("weight > 0")
    sq = redgreen.sketch_batches(V.pack(L.check_overflow(q, lay, "clip")), lay, _K, redgreen.full_horizon(v, lay, _K), SEED)
    return lsh.nearest(sq, s, q, v, 5, ROWS, TABLES).select("query_id", "vec_id", _r("j"), "place")


def _names(spark):
    return F.broadcast(spark.createDataFrame([(c, i) for i, c in enumerate(V.LOWER)], "name string, comp int"))


def _l1_top(spark, d):
    """For every supplier, the three nearest by L1 distance of the money over months, among its candidates but itself."""
    v = V.supplier_month(spark, d)
    s = _packed(v, L.of(v), _K)
    ix = lsh.index(s, ROWS, TABLES)
    return lsh.query_l1(ix, ix, v, v, 4).where("query_id <> vec_id").select("query_id", "vec_id", _r("l1", 5))


#: The source whose documents are linked to those of all others.
LINKED = "src0"


def _link(spark, d):
    """Documents of one source and of all others with nearly equal terms (a shared dictionary). Terms are sparse, a document
    fills a part in ten thousand of all widths or less, so the gamma sampler does the hashing (see ``method_choice``), vector by
    vector: its relational plan would sort and spill a row for each term and hash."""
    docs = table(spark, d, "documents", "doc_id", "text", "source")
    mine = F.coalesce(F.col("source") == LINKED, F.lit(False))
    named = [V.term_counts(docs.where(c), "doc_id", "text") for c in (mine, ~mine)]
    words = V.dictionary(named[0].select("name").unionByName(named[1].select("name")))
    va, vb = (materialize(x.join(words, "name").select("vec_id", "comp", "weight")) for x in named)
    sa, sb = (gamma_cws.compact(gamma_cws.sketch_batches(V.pack(x), 64, SEED), seed=SEED) for x in (va, vb))
    return lsh.link(va, vb, sa, sb, 0.5, 2, 32).select("id_a", "id_b", _r("j"))


_TERMS = r"regexp_extract_all(lower(coalesce(text, '')), '[^\x20\x09-\x0D]+')"


def _index_sql(rg, name, rows):
    return f"{name} AS (SELECT vec_id, (hash_id // {rows})::INT AS table_id, {rng.sql_bits("'lsh'", f'hash_id // {rows}', "string_agg(h::VARCHAR, ',' ORDER BY hash_id)")} AS bucket FROM {rg} GROUP BY vec_id, hash_id // {rows} HAVING count(*) = {rows})"


def _cross_sql(a, b, ia, ib):
    """Distinct pairs of two indexes and their exact similarity (pairs without a common component have 0)."""
    return (
        f"cx AS (SELECT DISTINCT x.vec_id AS id_a, y.vec_id AS id_b FROM {ia} x JOIN {ib} y USING (table_id, bucket))",
        f"cs AS (SELECT id_a, id_b, sum(least(x.weight, coalesce(y.weight, 0))) AS lo FROM cx JOIN {a} x ON x.vec_id = id_a LEFT JOIN {b} y ON y.vec_id = id_b AND y.comp = x.comp GROUP BY ALL)",
        f"cj AS (SELECT id_a, id_b, lo / (p.l + q.l - lo) AS j, p.l AS l1_a, q.l AS l1_b FROM cs JOIN (SELECT vec_id, sum(weight) AS l FROM {a} GROUP BY ALL) p ON p.vec_id = id_a JOIN (SELECT vec_id, sum(weight) AS l FROM {b} GROUP BY ALL) q ON q.vec_id = id_b)",
    )


def _compact_sql(gam, name):
    return f"{name} AS (SELECT vec_id, hash_id, {rng.sql_bits(f"'{SEED}'", "'v'", 'hash_id', 'comp', 'level')} AS h FROM {gam})"


_LINK = _with(
    f"n AS (SELECT s, vec_id, name, count(*)::DOUBLE AS weight FROM (SELECT coalesce(source = '{LINKED}', false) AS s, doc_id AS vec_id, unnest({_TERMS}) AS name FROM documents) GROUP BY ALL)",
    "dict AS (SELECT name, (row_number() OVER (ORDER BY substr(md5(name), 1, 2), name) - 1)::INT AS comp FROM (SELECT DISTINCT name FROM n))", "v AS (SELECT s, vec_id, comp, weight FROM n JOIN dict USING (name))",
    "va AS (SELECT vec_id, comp, weight FROM v WHERE s)", "vb AS (SELECT vec_id, comp, weight FROM v WHERE NOT s)", gamma_cws.sql(64, SEED, "va", "ga"), gamma_cws.sql(64, SEED, "vb", "gb"),
    _compact_sql("ga", "rga"), _compact_sql("gb", "rgb"), _index_sql("rga", "ixa", 2), _index_sql("rgb", "ixb", 2), *_cross_sql("va", "vb", "ixa", "ixb"),
) + "SELECT id_a, id_b, round(j, 6) AS j FROM cj WHERE j >= 0.5"
_L1TOP = _with(V.sql("supplier_month"), L.sql(), D.sql(_K, 512, SEED, pruned=True), redgreen.sql(), _index_sql("rg", "ix", ROWS), *_cross_sql("v", "v", "ix", "ix")) + "SELECT id_a AS query_id, id_b AS vec_id, round(l1, 5) AS l1 FROM (SELECT *, row_number() OVER (PARTITION BY id_a ORDER BY l1, id_b) AS place FROM (SELECT *, (l1_a + l1_b) * (1 - j) / (1 + j) AS l1 FROM cj)) WHERE place <= 4 AND id_a <> id_b"
_TOP = _with(
    V.sql("doc_letters"), L.sql(rounding="exact"), D.sql(_K, 512, SEED, pruned=True), redgreen.sql(),
    "q0 AS (SELECT vec_id, comp, n / sum(n) OVER (PARTITION BY vec_id) AS weight FROM (SELECT item_id AS vec_id, i::INT AS comp, (length(t) - length(replace(t, chr((97 + i)::INT), '')))::DOUBLE AS n FROM (SELECT item_id, lower(coalesce(text, '')) AS t FROM benchmark), range(26) r(i)) WHERE n > 0)",
    "q AS (SELECT vec_id, comp, weight FROM q0)", "qc AS (SELECT vec_id, comp, least(weight, cap) AS weight FROM q JOIN lay USING (comp))", redgreen.sql("qc", name="rgq"),
    _index_sql("rg", "ix", ROWS), _index_sql("rgq", "ixq", ROWS), *_cross_sql("q", "v", "ixq", "ix"),
) + "SELECT id_a AS query_id, id_b AS vec_id, round(j, 6) AS j, place::INT AS place FROM (SELECT *, row_number() OVER (PARTITION BY id_a ORDER BY round(j, 9) DESC, id_b) AS place FROM cj) WHERE place <= 5"


def _contamination(spark, d):
    """Share of each benchmark item's terms that a document holds, half or more. An item meets only the documents that hold
    one of its rarest terms: those that together have more than half of its weight, so that nothing is lost."""
    a, b = V.term_counts(table(spark, d, "benchmark"), "item_id", "text"), V.term_counts(table(spark, d, "documents"), "doc_id", "text")
    words = V.dictionary(a.select("name"))
    va, vb = (x.join(words, "name").select("vec_id", "comp", "weight") for x in (a, b))
    va, vb = materialize(va), materialize(vb)
    held = va.join(vb.groupBy("comp").agg(F.count("*").alias("df")), "comp", "left").withColumn("df", F.coalesce("df", F.lit(0)))
    own = Window.partitionBy("vec_id")
    before = F.coalesce(F.sum("weight").over(own.orderBy("df", "comp").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    rare = held.withColumn("before", before).withColumn("all", F.sum("weight").over(own)).where(F.col("before") <= F.col("all") / 2)
    meet = rare.select(F.col("vec_id").alias("item_id"), "comp").join(vb.select(F.col("vec_id").alias("doc_id"), "comp"), "comp").select("item_id", "doc_id").distinct()
    both = meet.join(va.select(F.col("vec_id").alias("item_id"), "comp", F.col("weight").alias("wa")), "item_id").join(vb.select(F.col("vec_id").alias("doc_id"), "comp", F.col("weight").alias("wb")), ["doc_id", "comp"])
    na, nb = (x.groupBy("vec_id").agg(F.sum("weight").alias("l")) for x in (va, vb))
    lo = both.groupBy("item_id", "doc_id").agg(F.sum(F.least("wa", "wb")).alias("lo"))
    j = lo.join(na.select(F.col("vec_id").alias("item_id"), F.col("l").alias("la")), "item_id").join(nb.select(F.col("vec_id").alias("doc_id"), F.col("l").alias("lb")), "doc_id")
    c = lsh.containment(F.col("lo") / (F.col("la") + F.col("lb") - F.col("lo")), F.col("la"), F.col("lb"))
    return j.select("item_id", "doc_id", F.round(c, 6).alias("containment")).where("containment >= 0.5")


_TOK = "regexp_extract_all(lower(coalesce(text, '')), '[^\\x20\\x09-\\x0D]+')"
_CONT = f"WITH a AS (SELECT i, w, count(*)::DOUBLE AS n FROM (SELECT item_id AS i, unnest({_TOK}) AS w FROM benchmark) GROUP BY ALL), b AS (SELECT i, w, count(*)::DOUBLE AS n FROM (SELECT doc_id AS i, unnest({_TOK}) AS w FROM documents) GROUP BY ALL) SELECT a.i AS item_id, b.i AS doc_id, round(sum(least(a.n, b.n)) / any_value(t.n), 6) AS containment FROM a JOIN b USING (w) JOIN (SELECT i, sum(n) AS n FROM a GROUP BY i) t ON t.i = a.i GROUP BY ALL HAVING round(sum(least(a.n, b.n)) / any_value(t.n), 6) >= 0.5"


def _curve(spark, d):
    """Chance that a supplier's vector and the widths, the least vector above all (whose similarity is the fill), become a
    candidate pair."""
    v = materialize(V.supplier_brand(spark, d))
    rows = [(a, b) for a in (1, 2, 4, 8) for b in (4, 16, 64)]
    out = L.fill(v, L.of(v)).select("vec_id", F.col("s").alias("j")).crossJoin(F.broadcast(spark.createDataFrame(rows, "k int, l int")))
    return out.select("vec_id", _r("j", 9), "k", "l", F.round(lsh.curve(F.col("j"), F.col("k"), F.col("l")), 9).alias("p"))


_CURVE = _with(V.sql("supplier_brand"), L.sql()) + "SELECT vec_id, round(j, 9) AS j, k::INT AS k, l::INT AS l, round(1 - pow(1 - pow(j, k), l), 9) AS p FROM (SELECT vec_id, sum(weight) / any_value(total) AS j FROM v, lay_m GROUP BY vec_id), (VALUES (1), (2), (4), (8)) a(k), (VALUES (4), (16), (64)) b(l)"


def _lsh_quality(spark, d):
    """Precision and recall of the candidates for pairs of similarity 0.9 or more."""
    v, _, s = _letters(spark, d)
    truth = similarity.exact_pairs(v).where("j >= 0.9")
    return lsh.evaluate(lsh.candidates(lsh.index(s, ROWS, TABLES)), truth).select(_r("precision"), _r("recall"), "candidates")


_QUALITY = _with(*_LET, *_CAND, similarity.sql_exact()) + "SELECT round(count(*) FILTER (WHERE c AND t) / count(*) FILTER (WHERE c)::DOUBLE, 6) AS precision, round(count(*) FILTER (WHERE c AND t) / count(*) FILTER (WHERE t)::DOUBLE, 6) AS recall, count(*) FILTER (WHERE c) AS candidates FROM (SELECT x.id_a IS NOT NULL AS c, y.id_a IS NOT NULL AS t FROM cand x FULL JOIN (SELECT * FROM ex WHERE j >= 0.9) y ON x.id_a = y.id_a AND x.id_b = y.id_b)"

# --- kernels and studies -----------------------------------------------------------------------------------------


def _emb_sketch(spark, d, k):
    v = V.embeddings(spark, d)
    lay = L.of(v, rounding="exact")
    return v, redgreen.sketch_batches(V.pack(v), lay, k, 128, SEED)


def _gram(spark, d):
    v = V.supplier_brand(spark, d)
    s = _packed(v, L.of(v), 128)
    return kernel.gram(s, s.select("vec_id")).where("id_a < id_b").select("id_a", "id_b", _r("value"))


_GRAM = _with(*_est_sql("supplier_brand", 128)) + "SELECT id_a, id_b, round(est, 6) AS value FROM es"


def _slots(spark, d):
    v = V.embeddings(spark, d)
    s = _packed(v, L.of(v), 32)
    return kernel.slots(s, 6).select("vec_id", F.explode("slots").alias("slot"))


_SLOTS = _with(V.sql("embeddings"), L.sql(), D.sql(32, 512, SEED, pruned=True), redgreen.sql()) + "SELECT i.vec_id, (x.hash_id * 64 + coalesce(h, 0) % 64)::INT AS slot FROM (SELECT DISTINCT vec_id FROM v) i CROSS JOIN range(32) x(hash_id) LEFT JOIN rg ON rg.vec_id = i.vec_id AND rg.hash_id = x.hash_id"


def _classifier(spark, d):
    """Held-out accuracy of linear learning on sketch features of the embeddings' labels, by number of hashes."""
    rows = []
    for k in (16, 64, 256):
        _, s = _emb_sketch(spark, d, k)
        f = kernel.features(s, k, 5).join(table(spark, d, "embeddings", "vec_id", "label"), "vec_id")
        rows.append((k, kernel.evaluate(f.select("vec_id", "features", F.col("label").cast("double").alias("label")))))
    return spark.createDataFrame(rows, "k int, accuracy double")


def _nearest(spark, d):
    return kernel.nearest(V.embeddings(spark, d), table(spark, d, "embeddings", "vec_id", "label"))


def _drop_rare(spark, d):
    """Terms of each document, and those that two documents or more hold (their effect on similarity: drop_rare_error)."""
    v = V.doc_terms(spark, d)
    kept = V.drop_rare(v, 2)
    a, b = v.groupBy("vec_id").agg(F.count("*").alias("d_all")), kept.groupBy("vec_id").agg(F.count("*").alias("d_kept"))
    return a.join(b, "vec_id", "left").select("vec_id", "d_all", F.coalesce("d_kept", F.lit(0)).alias("d_kept"))


_RARE = _with(V.sql("doc_terms"), "k AS (SELECT comp FROM v GROUP BY comp HAVING count(*) >= 2)") + "SELECT vec_id, count(*) AS d_all, count(k.comp) AS d_kept FROM v LEFT JOIN k USING (comp) GROUP BY vec_id"


def _fold_error(spark, d):
    """Exact similarity of benchmark items before and after folding the terms to 64 buckets."""
    named = V.term_counts(table(spark, d, "benchmark"), "item_id", "text")
    ex, fo = similarity.exact_pairs(V.encode(named)), similarity.exact_pairs(V.fold(named, 64, name_col="name"))
    return fo.select("id_a", "id_b", F.col("j").alias("folded")).join(ex.select("id_a", "id_b", "j"), ["id_a", "id_b"], "left").select("id_a", "id_b", F.round(F.coalesce("j", F.lit(0.0)), 6).alias("j"), _r("folded"))


_FOLD = _with(V.sql("benchmark_terms"), "g AS (SELECT vec_id, (('0x' || substr(md5(concat_ws(':', '0', name)), 1, 13))::BIGINT % 64)::INT AS comp, sum(weight) AS weight FROM v_n GROUP BY ALL)", similarity.sql_exact(), similarity.sql_exact("g", "fo")) + "SELECT fo.id_a, fo.id_b, round(coalesce(ex.j, 0), 6) AS j, round(fo.j, 6) AS folded FROM fo LEFT JOIN ex ON ex.id_a = fo.id_a AND ex.id_b = fo.id_b"


def _nine(spark, d):
    return experiments.nine_pairs(V.supplier_month(spark, d)).select("pair", "id_a", "id_b", _r("j"))


_NINE = _with(V.sql("supplier_month"), similarity.sql_exact()) + "SELECT (i + 1)::INT AS pair, b.id_a, b.id_b, round(b.j, 6) AS j FROM (SELECT i, min(struct_pack(d := round(abs(j - (i + 1) / 10.0::DOUBLE), 9), id_a := id_a, id_b := id_b, j := j)) AS b FROM ex, range(9) r(i) GROUP BY i)"


#: Repetitions, hashes and families of the accuracy study.
REPS, UPTO = 200, 50
STUDIED = ("supplier_brand", "supplier_month", "embeddings", "user_hours")


def _nine_of(spark, d, family):
    """A family's vectors and the nine pairs that all methods are studied on."""
    v = materialize(V.BUILDERS[family](spark, d))
    return v, experiments.materialize(experiments.nine_pairs(v))


def _curve_of(v, pairs, method):
    own = {"redgreen": lambda: {"layout": L.of(v)}, "gamma_cws": dict, "replicated_oph": lambda: {"scale": experiments.copy_scale(v)}}[method]()
    return experiments.error_curve(v, pairs, method, UPTO, range(REPS), **own)


def _accuracy(method):
    """Error curves on nine pairs: k = 1 .. 50 over 200 repetitions."""

    def run(spark, d):
        return _curve_of(*_nine_of(spark, d, "supplier_brand"), method).select("pair", "k", _r("j"), _r("bias"), _r("mae"), _r("rmse"))

    if method == "replicated_oph":
        return run, None
    n = REPS * UPTO
    hashes = (L.sql(), D.sql(n, 256, 0, pruned=True), redgreen.sql("w", name="hs")) if method == "redgreen" else (gamma_cws.sql(n, 0, "w", "hs"),)
    same = "a.h = b.h" if method == "redgreen" else "a.comp = b.comp AND a.level = b.level"
    nine = "pr AS (SELECT (i + 1)::INT AS pair, b.id_a AS id_a, b.id_b AS id_b, b.j AS j FROM (SELECT i, min(struct_pack(d := round(abs(j - (i + 1) / 10.0::DOUBLE), 9), id_a := id_a, id_b := id_b, j := j)) AS b FROM ex, range(9) r(i) GROUP BY i))"
    parts = (V.sql("supplier_brand"), similarity.sql_exact(), nine, "w AS (SELECT * FROM v WHERE vec_id IN (SELECT id_a FROM pr UNION SELECT id_b FROM pr))", *hashes)
    sm = f"sm AS (SELECT pair, j, a.hash_id // {UPTO} AS rep, a.hash_id % {UPTO} + 1 AS k, ({same})::INT AS s FROM pr JOIN hs a ON a.vec_id = id_a JOIN hs b ON b.vec_id = id_b AND b.hash_id = a.hash_id)"
    er = "er AS (SELECT pair, k, j, avg(s) OVER (PARTITION BY pair, rep ORDER BY k) - j AS e FROM sm)"
    return run, _with(*parts, sm, er) + "SELECT pair, k::INT AS k, round(any_value(j), 6) AS j, round(avg(e), 6) AS bias, round(avg(abs(e)), 6) AS mae, round(sqrt(avg(e * e)), 6) AS rmse FROM er GROUP BY pair, k"


def _accuracy_families(spark, d):
    """Mean error over nine pairs at 1, 10 and 50 hashes of every family and method."""
    out = None
    for f in STUDIED:
        v, pairs = _nine_of(spark, d, f)
        for m in ("redgreen", "gamma_cws", "replicated_oph"):
            e = _curve_of(v, pairs, m).where(F.col("k").isin(1, 10, UPTO)).groupBy("k").agg(F.avg("mae").alias("mae"), F.avg("bias").alias("bias"))
            e = e.select(F.lit(f).alias("family"), F.lit(m).alias("method"), "k", _r("mae"), _r("bias"))
            out = e if out is None else out.unionByName(e)
    return out


def _bias(spark, d):
    """Copies of embeddings' weights at coarse and fine scales, with shared coins and coins of each vector's own."""
    v = materialize(V.embeddings(spark, d))
    pairs = experiments.materialize(experiments.nine_pairs(v))
    return experiments.replication_bias(v, pairs, UPTO, range(REPS), (1.0, 5.0, 20.0)).select("scale", "coin", "pair", _r("est"), _r("j"))


def _densify(spark, d):
    v = materialize(V.supplier_brand(spark, d))
    return experiments.densify_variance(v, experiments.materialize(experiments.nine_pairs(v)), 256, range(4), 0.05).select("mode", _r("mae"))


#: Families, widths and SQL horizons of the table of hash ranges at 500 hashes.
RANGES = {"supplier_brand": ("ceil", 256), "supplier_month": ("ceil", 256), "embeddings": ("ceil", 1024), "doc_letters": ("exact", 512)}


def _ranges(spark, d):
    """Mean, range and bits of 500 hashes a vector, beside the mean that the fill lets expect."""
    out = None
    for f, (rounding, _) in RANGES.items():
        v = materialize(V.BUILDERS[f](spark, d))
        lay = L.of(v, rounding=rounding)
        r = measures.range_bits(redgreen.sketch(v, lay, 500, SEED)).select(F.lit(f).alias("family"), _r("mean_h"), "min_h", "max_h", "bits")
        r = r.crossJoin(L.fill(v, lay).agg(F.round(F.avg(1 / F.col("s")), 6).alias("mean_theory")))
        out = r if out is None else out.unionByName(r)
    return out


_RANGES = " UNION ALL ".join(
    "(" + _with(V.sql(f), L.sql(rounding=w), D.sql(500, t, SEED, pruned=True), redgreen.sql(), "f AS (SELECT avg(total / l) AS m FROM (SELECT sum(weight) AS l FROM v GROUP BY vec_id), lay_m)")
    + f"SELECT '{f}' AS family, round(avg(h), 6) AS mean_h, min(h) AS min_h, max(h) AS max_h, ceil(log2(max(h) + 1))::INT AS bits, round(any_value(m), 6) AS mean_theory FROM rg, f)"
    for f, (w, t) in RANGES.items()
)


def _work_ratio(spark, d):
    """What 500 hashes of an average vector take of each method, and the ratios: the machine-independent speed-ups."""
    out = None
    for f in STUDIED:
        v = materialize(V.BUILDERS[f](spark, d))
        w = measures.work(v, L.of(v, rounding="exact"), 500).agg(F.avg("draws").alias("draws"), F.avg("variates").alias("variates"), F.avg("copies").alias("l1"))
        w = w.withColumn("copies", F.col("l1") * experiments.copy_scale(v))
        w = w.select(F.lit(f).alias("family"), F.round("draws", 3).alias("draws"), F.round("variates", 3).alias("variates"), F.round("copies", 3).alias("copies"), F.round(F.col("variates") / F.col("draws"), 6).alias("over_gamma"), F.round(F.col("copies") / F.col("draws"), 6).alias("over_replicated"))
        out = w if out is None else out.unionByName(w)
    return out


_WORK_RATIO = " UNION ALL ".join(
    "(" + _with(V.sql(f), L.sql(rounding="exact"), "p AS (SELECT sum(weight) AS l, count(*) AS d FROM v GROUP BY vec_id)", "w AS (SELECT avg(500 * total / l) AS draws, avg(500 * d) AS variates, avg(l) * any_value((SELECT 100.0::DOUBLE / max(weight) FROM v)) AS copies FROM p, lay_m)")
    + f"SELECT '{f}' AS family, round(draws, 3) AS draws, round(variates, 3) AS variates, round(copies, 3) AS copies, round(variates / draws, 6) AS over_gamma, round(copies / draws, 6) AS over_replicated FROM w)"
    for f in STUDIED
)


def _speedups(spark, d):
    """Measured milliseconds of 500 hashes of a vector with thousands of non-zeros, and how many times the proposed method's
    each method takes. Made vectors: no given table has such; the larger ones run in bench.py."""
    n, nz, dim = V.WIDE["d1000"]
    v = materialize(V.synthetic(spark, n, nz, dim))
    t = experiments.time_alone(v, 500, runs=1, scale=experiments.copy_scale(v))
    return spark.createDataFrame([(m, float(x), float(x / t["redgreen"])) for m, x in t.items()], "method string, ms double, times double")


def _lsh_work(spark, d):
    """What the hashes of a query take in K x L tables: variates of the gamma sampler, draws of the red-green one, and the
    comparisons of a direct scan (d of each of n vectors)."""
    v = materialize(V.embeddings(spark, d))
    one = L.fill(v, L.of(v, rounding="exact")).agg(F.avg(1 / F.col("s")).alias("inv")).crossJoin(v.groupBy("vec_id").agg(F.count("*").alias("d")).agg(F.avg("d").alias("d")))
    grid = spark.createDataFrame([(a, b) for a in (1, 2, 4, 8) for b in (4, 16, 64)], "k int, l int")
    return one.crossJoin(F.broadcast(grid)).select("k", "l", F.round(F.col("k") * F.col("l") * F.col("inv"), 4).alias("redgreen"), F.round(F.col("k") * F.col("l") * F.col("d"), 4).alias("gamma"), F.round(F.col("d") / F.col("inv"), 6).alias("ratio"))


_LSH_WORK = _with(V.sql("embeddings"), L.sql(rounding="exact"), "p AS (SELECT sum(weight) AS l, count(*) AS d FROM v GROUP BY vec_id)", "o AS (SELECT avg(1 / (l / total)) AS inv, avg(d) AS d FROM p, lay_m)") + "SELECT k::INT AS k, l::INT AS l, round(k * l * inv, 4) AS redgreen, round(k * l * d, 4) AS gamma, round(d / inv, 6) AS ratio FROM o, (VALUES (1), (2), (4), (8)) a(k), (VALUES (4), (16), (64)) b(l)"


def _labels(spark, d):
    """Held-out accuracy on documents' quality and toxicity, by linear learning on sketches of their folded terms."""
    labels = table(spark, d, "labels", F.col("doc_id").alias("vec_id"), "quality", "toxic").where("quality IS NOT NULL AND toxic IS NOT NULL").dropDuplicates(["vec_id"])
    v = materialize(V.doc_folded(spark, d).join(labels.select("vec_id"), "vec_id", "left_semi"))
    s = materialize(gamma_cws.sketch_batches(V.pack(v), 1024, SEED).select("vec_id", F.zip_with("comps", "levels", lambda c, l: F.pmod(F.xxhash64(c, l), F.lit(1 << 20)).cast("int") + 1).alias("sketch")))
    rows = []
    for k in (16, 64, 256, 1024):
        f = kernel.features(s.select("vec_id", F.slice("sketch", 1, k).alias("sketch")), k, 5)
        for name in ("quality", "toxic"):
            data = f.join(labels.select("vec_id", F.col(name).cast("double").alias("label")), "vec_id")
            rows.append((name, k, kernel.evaluate(data.select("vec_id", "features", "label"))))
    return spark.createDataFrame(rows, "label string, k int, accuracy double")


def _membership(spark, d):
    """Seconds of each membership test of a draw over all vectors."""
    v = materialize(V.supplier_month(spark, d))
    lay = L.of(v)
    t = experiments.membership_ablation(v, lay, D.draws(lay, 4, 16, SEED))
    return spark.createDataFrame([(n, float(s)) for n, s in t.items()], "test string, seconds double")


GRID_SIDE = 24


def _week(spark, d):
    """Events of users over hours (rows) and days of the week (columns) of a square grid."""
    e = table(spark, d, "events", "user_id", "ts")
    comp = (F.hour("ts") * GRID_SIDE + F.weekday("ts")).cast("int")
    return e.groupBy(F.col("user_id").alias("vec_id"), comp.alias("comp")).agg(F.count("*").cast("double").alias("weight"))


def _emd_grid(spark, d):
    """A bound of the two-dimensional earth mover's distance of all pairs of users: the L1 distance of nested squares."""
    return similarity.exact_l1(materialize(similarity.grid_tree(_week(spark, d), GRID_SIDE))).select("id_a", "id_b", _r("l1"))


def _grid_sql(side):
    parts, base, width = [], 0, 1
    while width <= side:
        across = -(-side // width)
        parts.append(f"SELECT vec_id, ({base} + ((comp // {side}) // {width}) * {across} + (comp % {side}) // {width})::INT AS comp, weight * {width} AS weight FROM g")
        base, width = base + across * across, width * 2
    return "v AS (SELECT vec_id, comp, sum(weight) AS weight FROM (" + " UNION ALL ".join(parts) + ") GROUP BY ALL)"


_EMD_GRID = _with(f"g AS (SELECT user_id AS vec_id, (hour(ts) * {GRID_SIDE} + isodow(ts) - 1)::INT AS comp, count(*)::DOUBLE AS weight FROM events GROUP BY ALL)", _grid_sql(GRID_SIDE), similarity.sql_exact()) + "SELECT id_a, id_b, round((l1_a + l1_b) * (1 - j) / (1 + j), 6) AS l1 FROM ex"


def _rare_error(spark, d):
    """Similarity of benchmark items with all terms and with the terms of two items or more alone, and the error."""
    v = materialize(V.benchmark_terms(spark, d))
    ex, kept = similarity.exact_pairs(v), similarity.exact_pairs(V.drop_rare(v, 2))
    both = ex.select("id_a", "id_b", "j").join(kept.select("id_a", "id_b", F.col("j").alias("kept")), ["id_a", "id_b"])
    return both.select("id_a", "id_b", _r("j"), _r("kept"), F.round(F.col("kept") - F.col("j"), 6).alias("error"))


_RARE_ERROR = _with(V.sql("benchmark_terms"), "g AS (SELECT * FROM v WHERE comp IN (SELECT comp FROM v GROUP BY comp HAVING count(*) >= 2))", similarity.sql_exact(), similarity.sql_exact("g", "kp")) + "SELECT id_a, id_b, round(ex.j, 6) AS j, round(kp.j, 6) AS kept, round(kp.j - ex.j, 6) AS error FROM ex JOIN kp USING (id_a, id_b)"


def _scale_draws(spark, d):
    return experiments.scale_study(V.embeddings(spark, d), [0.5, 1.0, 2.0, 10.0, 100.0], 500).select("alpha", "total", _r("fill", 9), _r("draws", 4), "place")


_SCALED = _with(V.sql("embeddings"), "c AS (SELECT comp, max(weight) AS m FROM v GROUP BY comp)", "a AS (SELECT avg(l1) AS l1 FROM (SELECT sum(weight) AS l1 FROM v GROUP BY vec_id))", "t AS (SELECT alpha, sum(greatest(1.0::DOUBLE, ceil(m * alpha))) AS total FROM c, (SELECT unnest([0.5, 1.0, 2.0, 10.0, 100.0])::DOUBLE AS alpha) GROUP BY alpha)") + "SELECT alpha, total, round(l1 * alpha / total, 9) AS fill, round(500 / (l1 * alpha / total), 4) AS draws, row_number() OVER (ORDER BY round(l1 * alpha / total, 9) DESC, total, alpha)::INT AS place FROM t, a"


def queries() -> dict:
    return {
        "exact_jaccard": _exact("supplier_brand"), "exact_jaccard_embeddings": _exact("embeddings"), "exact_jaccard_users": _exact("user_hours"), "exact_set_jaccard": (_set_jaccard, _SETJ), "exact_l1": (_l1, _L1), "exact_emd": (_emd, _EMD),
        "est_jaccard": (_est, _with(*_est_sql("embeddings", 64)) + "SELECT id_a, id_b, round(est, 6) AS est, round(j, 6) AS j FROM es"),
        "est_errors_by_k": (_errors, _ERRORS), "est_zscores": (_zscores, _ZSCORES), "est_required_k": (_required, _REQUIRED), "est_cap_correction": (_cap_correction, _CAPCOR),
        "lowbits_estimate": _bits("low"), "rehash_estimate": _bits("rehash"), "position_corr": (_poscorr, _POSCORR),
        "l1_estimate": (_l1_est, _with(*_est_sql("supplier_month", 128)) + "SELECT id_a, id_b, round((l1_a + l1_b) * (1 - est) / (1 + est), 5) AS est_l1, round((l1_a + l1_b) * (1 - j) / (1 + j), 5) AS l1 FROM es"),
        "emd_estimate": (_emd_est, _EMD_EST),
        "lsh_buckets": (_buckets, _with(*_LET, *_CAND) + "SELECT table_id, bucket, vec_id FROM ix"), "lsh_candidates": (_candidates, _with(*_LET, *_CAND) + "SELECT id_a, id_b FROM cand"),
        "lsh_query_topm": (_top, _TOP), "lsh_query_l1": (_l1_top, _L1TOP), "lsh_curve": (_curve, _CURVE), "lsh_quality": (_lsh_quality, _QUALITY),
        "all_pairs_join": (_all_pairs, _ALL + "SELECT id_a, id_b, round(j, 6) AS j FROM vp WHERE j >= 0.9"), "near_dup_clusters": (_clusters, _CLUST), "link_records": (_link, _LINK), "contamination": (_contamination, _CONT),
        "kernel_gram": (_gram, _GRAM), "kernel_features": (_slots, _SLOTS), "kernel_classifier": (_classifier, None), "kernel_nearest": (_nearest, None),
        "drop_rare": (_drop_rare, _RARE), "fold_error": (_fold_error, _FOLD), "nine_pairs": (_nine, _NINE), "scale_study": (_scale_draws, _SCALED),
        "accuracy_redgreen": _accuracy("redgreen"), "accuracy_gamma": _accuracy("gamma_cws"), "accuracy_replicated": _accuracy("replicated_oph"), "accuracy_families": (_accuracy_families, None),
        "replication_bias": (_bias, None), "densify_variance": (_densify, None), "hash_ranges": (_ranges, _RANGES), "work_ratios": (_work_ratio, _WORK_RATIO), "speedups": (_speedups, None),
        "lsh_work": (_lsh_work, _LSH_WORK), "kernel_labels": (_labels, None), "membership_ablation": (_membership, None), "emd_grid": (_emd_grid, _EMD_GRID), "drop_rare_error": (_rare_error, _RARE_ERROR),
    }
