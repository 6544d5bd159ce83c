"""Queries of the relational surface around the methods, on the tables that feed them."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from rgsketch.functions import rng
from rgsketch.functions import sql as SQL
from rgsketch.operators import redgreen, similarity
from rgsketch.plans import darts as D
from rgsketch.plans import layout as L
from rgsketch.queries.sketches import SEED, _r, _with
from rgsketch.sources import families as V
from rgsketch.sources.tables import materialize, shared_dir, table


def _t(name, *columns):
    return lambda spark, d: table(spark, d, name, *columns)


def _round_trip(fmt, **options):
    """The parts table written to the shared folder in a format and read back with its schema."""

    def run(spark, d):
        p = table(spark, d, "part", "p_partkey", "p_brand", "p_size")
        path = f"{shared_dir(spark)}/rgsketch/{uuid.uuid4().hex}"
        p.write.format(fmt).options(**options).save(path)
        return spark.read.format(fmt).options(**options).schema(p.schema).load(path)

    return run, "SELECT p_partkey, p_brand, p_size FROM part"


def _bucketed(spark, d):
    """Two bucketed tables joined on their bucket key: no exchange."""
    from rgsketch.sources.tables import write_bucketed

    tag = uuid.uuid4().hex[:8]
    write_bucketed(table(spark, d, "orders", "o_orderkey", "o_custkey"), f"rg_o_{tag}", 8, "o_orderkey")
    write_bucketed(table(spark, d, "lineitem", "l_orderkey", "l_quantity"), f"rg_l_{tag}", 8, "l_orderkey")
    return spark.table(f"rg_o_{tag}").join(spark.table(f"rg_l_{tag}").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.sum("l_quantity").alias("q"))


def _join_broadcast(spark, d):
    n = table(spark, d, "nation", "n_nationkey", "n_name")  # 25 rows by its definition
    return table(spark, d, "customer", "c_custkey", "c_nationkey").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


def _join_merge(spark, d):
    o, l = table(spark, d, "orders", "o_orderkey", "o_custkey"), table(spark, d, "lineitem", "l_orderkey", "l_quantity")
    return o.hint("merge").join(l, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey").agg(F.sum("l_quantity").alias("q"))


def _join_range(spark, d):
    """Draws to components by start and width."""
    lay = L.of(V.supplier_month(spark, d))
    return D.resolve(D.draws(lay, 16, 64, SEED), lay).select("hash_id", "step", "comp")


_RANGE = _with(V.sql("supplier_month"), L.sql(), D.sql(16, 64, SEED)) + "SELECT hash_id, step, comp FROM darts"


def _join_asof(spark, d):
    """The last start that isn't above a draw, by one pass over both sides in order: within hashes of draws and a copy of
    the starts each, so no single task holds all."""
    lay = L.of(V.supplier_month(spark, d))
    p = D.draws(lay, 16, 64, SEED)
    starts = lay.df.select(F.explode(F.sequence(F.lit(0), F.lit(15))).alias("hash_id"), F.lit(None).cast("int").alias("step"), F.col("lo").alias("r"), "comp")
    both = p.withColumn("comp", F.lit(None).cast("int")).unionByName(starts)
    w = Window.partitionBy("hash_id").orderBy("r", F.col("step").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("comp", F.last("comp", ignorenulls=True).over(w)).where("step IS NOT NULL").select("hash_id", "step", "comp")


def _interval(spark, d):
    """Events within an hour after another event of the same user and type."""
    e = table(spark, d, "events", "event_id", "user_id", "event_type", "ts")
    a, b = (e.select(*[F.col(c).alias(f"{c}_{x}") for c in e.columns]) for x in "ab")
    on = (F.col("user_id_a") == F.col("user_id_b")) & (F.col("event_type_a") == F.col("event_type_b")) & (F.col("ts_b") > F.col("ts_a")) & (F.col("ts_b") <= F.col("ts_a") + F.expr("INTERVAL 1 HOUR"))
    return a.join(b, on).select("event_id_a", "event_id_b")


URGENT = "o_orderpriority = '1-URGENT'"


def _outer(kind):
    def run(spark, d):
        """Customers and the urgent orders: either side has rows without the other."""
        c, o = table(spark, d, "customer", "c_custkey"), table(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderpriority").where(URGENT)
        return c.join(o, F.col("c_custkey") == F.col("o_custkey"), kind).groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))

    how = {"left": "LEFT", "right": "RIGHT", "full": "FULL"}[kind]
    return run, f"SELECT c_custkey, count(o_orderkey) AS n FROM customer {how} JOIN (SELECT * FROM orders WHERE {URGENT}) ON c_custkey = o_custkey GROUP BY c_custkey"


def _semi(spark, d):
    return V.drop_rare(V.doc_terms(spark, d), 5)


def _anti(spark, d):
    return table(spark, d, "customer", "c_custkey").join(table(spark, d, "orders", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


def _salted(spark, d, salts: int = 8):
    """Terms shared by documents and benchmark items, counted with the hot terms' rows spread over salts."""
    a = V.term_counts(table(spark, d, "documents"), "doc_id", "text").select("name", F.pmod(F.xxhash64("vec_id"), F.lit(salts)).alias("salt"), F.col("vec_id").alias("doc_id"))
    b = V.term_counts(table(spark, d, "benchmark"), "item_id", "text").select("name", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"), F.col("vec_id").alias("item_id"))
    return a.join(b, ["name", "salt"]).groupBy("item_id").agg(F.count("*").alias("n"), F.countDistinct("doc_id").alias("docs"))


_TOK = V._TOKENS
_SALTED = f"WITH a AS (SELECT DISTINCT doc_id, unnest({_TOK}) AS w FROM documents), b AS (SELECT DISTINCT item_id, unnest({_TOK}) AS w FROM benchmark) SELECT item_id, count(*) AS n, count(DISTINCT doc_id) AS docs FROM a JOIN b USING (w) GROUP BY item_id"


def _grouping(kind):
    def run(spark, d):
        l = table(spark, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity")
        if kind == "sets":
            l.createOrReplaceTempView(v := f"rg_{uuid.uuid4().hex[:8]}")
            return spark.sql(f"SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q FROM {v} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
        g = l.cube("l_returnflag", "l_linestatus") if kind == "cube" else l.rollup("l_returnflag", "l_linestatus")
        return g.agg(F.sum("l_quantity").alias("q"))

    by = {"sets": "GROUPING SETS ((l_returnflag), (l_linestatus), ())", "cube": "CUBE (l_returnflag, l_linestatus)", "rollup": "ROLLUP (l_returnflag, l_linestatus)"}[kind]
    return run, f"SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q FROM lineitem GROUP BY {by}"


def _filters(spark, d):
    l = table(spark, d, "part", "p_partkey", "p_name", "p_brand", "p_size")
    return l.where(F.col("p_size").between(5, 20) & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#13", "Brand#21", "Brand#22") & F.col("p_name").isNotNull() & ~F.col("p_name").like("zz%") & F.col("p_brand").rlike("^Brand") & F.col("p_size").eqNullSafe(F.col("p_size")))


def _aggs(spark, d):
    l = table(spark, d, "lineitem", "l_suppkey", "l_partkey", "l_quantity", "l_orderkey", "l_linenumber")
    key = F.struct("l_quantity", "l_orderkey", "l_linenumber")
    return l.groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.min_by("l_orderkey", key).alias("first_order"), F.max_by("l_orderkey", key).alias("last_order"), F.round(F.stddev("l_quantity"), 6).alias("sd"), F.round(F.var_samp("l_quantity"), 6).alias("var"), F.round(F.corr("l_quantity", F.col("l_linenumber").cast("double")), 6).alias("corr"))


_AGGS = "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, min_by(l_orderkey, struct_pack(q := l_quantity, o := l_orderkey, n := l_linenumber)) AS first_order, max_by(l_orderkey, struct_pack(q := l_quantity, o := l_orderkey, n := l_linenumber)) AS last_order, round(stddev(l_quantity), 6) AS sd, round(var_samp(l_quantity), 6) AS var, round(corr(l_quantity, l_linenumber::DOUBLE), 6) AS corr FROM lineitem GROUP BY l_suppkey"


def _approx(spark, d):
    return table(spark, d, "lineitem", "l_suppkey", "l_partkey").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey").alias("parts"))


def _percentile(spark, d):
    return table(spark, d, "lineitem", "l_suppkey", "l_extendedprice").groupBy("l_suppkey").agg(F.percentile_approx("l_extendedprice", 0.5, 10000).alias("p50"), F.size(F.histogram_numeric("l_extendedprice", F.lit(8))).alias("bins"))


def _pivot(spark, d):
    return table(spark, d, "events", "user_id", "event_type").groupBy("user_id").pivot("event_type", ["click", "view", "purchase"]).agg(F.count(F.lit(1))).select("user_id", *[F.coalesce(c, F.lit(0)).alias(c) for c in ("click", "view", "purchase")])


def _ranks(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    o = table(spark, d, "orders", "o_orderkey", "o_custkey", "o_totalprice")
    return o.select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.lag("o_orderkey").over(w).alias("lg"), F.lead("o_orderkey").over(w).alias("ld"))


_RANKS = "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, lag(o_orderkey) OVER w AS lg, lead(o_orderkey) OVER w AS ld FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)"


def _frames(spark, d):
    w = Window.partitionBy("l_suppkey").orderBy("l_orderkey", "l_linenumber", "l_partkey", "l_quantity")
    r = Window.partitionBy("l_suppkey").orderBy("l_orderkey").rangeBetween(-1000, 0)
    l = table(spark, d, "lineitem", "l_suppkey", "l_orderkey", "l_linenumber", "l_quantity", "l_partkey")
    return l.select("l_orderkey", "l_linenumber", F.sum("l_quantity").over(w.rowsBetween(-2, 0)).alias("q3"), F.sum("l_quantity").over(r).alias("near"))


_FRAMES = "SELECT l_orderkey, l_linenumber, sum(l_quantity) OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_linenumber, l_partkey, l_quantity ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS q3, sum(l_quantity) OVER (PARTITION BY l_suppkey ORDER BY l_orderkey RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS near FROM lineitem"


def _nulls(spark, d):
    """The last large order of a customer up to each of his."""
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    big = F.when(F.col("o_totalprice") > 200000, F.col("o_orderkey"))
    return table(spark, d, "orders", "o_orderkey", "o_custkey", "o_totalprice").select("o_orderkey", F.last(big, ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("last_big"), F.first(big, ignorenulls=True).over(w.rowsBetween(0, Window.unboundedFollowing)).alias("next_big"))


_NULLS = "SELECT o_orderkey, last_value(b IGNORE NULLS) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS last_big, first_value(b IGNORE NULLS) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS next_big FROM (SELECT *, CASE WHEN o_totalprice > 200000 THEN o_orderkey END AS b FROM orders)"


def _topk(spark, d):
    """The ten largest orders of all: the limit is the feature."""
    return table(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(10)


LARGE_RETURNS = "l_returnflag = 'R' AND l_quantity >= 45"


def _sets(kind):
    def run(spark, d):
        """Keys of parts that came back in large lots, one a line, and all keys of parts."""
        a = table(spark, d, "lineitem", F.col("l_partkey").alias("k"), "l_returnflag", "l_quantity").where(LARGE_RETURNS).select("k")
        b = table(spark, d, "part", F.col("p_partkey").alias("k"))
        return {"union": lambda: a.union(b), "intersect": lambda: a.intersect(b), "except": lambda: b.exceptAll(a.distinct()), "distinct": lambda: a.distinct()}[kind]()

    a, b = f"SELECT l_partkey AS k FROM lineitem WHERE {LARGE_RETURNS}", "SELECT p_partkey AS k FROM part"
    return run, {"union": f"{a} UNION ALL {b}", "intersect": f"{a} INTERSECT {b}", "except": f"{b} EXCEPT {a}", "distinct": f"SELECT DISTINCT k FROM ({a})"}[kind]


def _strings(spark, d):
    c = F.col("p_name")
    return table(spark, d, "part", "p_partkey", "p_name", "p_brand").select("p_partkey", F.lower(c).alias("low"), F.length(F.trim(c)).alias("n"), F.substring(c, 1, 3).alias("head"), F.md5(c.cast("binary")).alias("md5"), F.sha2(c.cast("binary"), 256).alias("sha"), F.regexp_replace("p_brand", "[0-9]+", "N").alias("kind"), F.concat_ws("-", "p_brand", c).alias("both"), F.size(F.split("p_brand", "#")).alias("parts"))


_STRINGS = "SELECT p_partkey, lower(p_name) AS low, length(trim(p_name)) AS n, p_name[1:3] AS head, md5(p_name) AS md5, sha256(p_name) AS sha, regexp_replace(p_brand, '[0-9]+', 'N', 'g') AS kind, concat_ws('-', p_brand, p_name) AS both, len(string_split(p_brand, '#')) AS parts FROM part"


def _kmers(spark, d):
    return V.kmers(table(spark, d, "benchmark"), "item_id", "text", 4)


_KMERS = f"SELECT vec_id, name, count(*)::DOUBLE AS weight FROM (SELECT item_id AS vec_id, unnest(CASE WHEN length(t) < 4 THEN [] ELSE list_transform(range(1, length(t) - 2), lambda i: t[i:i + 3]) END) AS name FROM (SELECT item_id, lower(coalesce(text, '')) AS t FROM benchmark)) GROUP BY ALL"


def _terms(name, id_col, role=None):
    def run(spark, d):
        return V.term_counts(table(spark, d, name), id_col, "text", role)

    return run


def _dates(spark, d):
    c = F.col("o_orderdate")
    return table(spark, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.date_format(F.date_trunc("month", c), "yyyy-MM-dd").alias("month"), F.date_format(F.add_months(c, 2), "yyyy-MM-dd").alias("later"), F.datediff(F.lit("2000-01-01").cast("date"), c).alias("days"), F.hour(c).alias("hour"))


_DATES = "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, strftime(o_orderdate::DATE + INTERVAL 2 MONTH, '%Y-%m-%d') AS later, date_diff('day', o_orderdate::DATE, DATE '2000-01-01') AS days, hour(o_orderdate) AS hour FROM orders"


def _math(spark, d):
    c = F.col("l_extendedprice")
    return table(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_extendedprice").select("l_orderkey", "l_linenumber", F.ceil(c).alias("up"), F.floor(c).alias("down"), F.round(F.log(c), 6).alias("ln"), F.round(F.log2(c), 6).alias("lb"), F.round(F.exp(-c / 10000), 6).alias("ex"), F.round(F.pow(c, 0.5), 4).alias("root"), F.greatest(c, F.lit(5000.0)).alias("hi"), F.least(c, F.lit(5000.0)).alias("lo"), F.pmod(F.col("l_orderkey"), F.lit(7)).alias("m"), F.col("l_orderkey").bitwiseAND(F.lit(15)).alias("b"), F.shiftleft(F.col("l_linenumber"), 3).alias("s"))


_MATH = "SELECT l_orderkey, l_linenumber, ceil(l_extendedprice)::BIGINT AS up, floor(l_extendedprice)::BIGINT AS down, round(ln(l_extendedprice), 6) AS ln, round(log2(l_extendedprice), 6) AS lb, round(exp(-l_extendedprice / 10000), 6) AS ex, round(pow(l_extendedprice, 0.5), 4) AS root, greatest(l_extendedprice, 5000.0::DOUBLE) AS hi, least(l_extendedprice, 5000.0::DOUBLE) AS lo, l_orderkey % 7 AS m, l_orderkey & 15 AS b, l_linenumber << 3 AS s FROM lineitem"


def _arrays(spark, d):
    """Sums over packed vectors without exploding them."""
    p = V.pack(V.supplier_brand(spark, d))
    total = F.aggregate("weights", F.lit(0.0), lambda a, x: a + x)
    dot = F.aggregate(F.zip_with("comps", "weights", lambda c, w: c * w), F.lit(0.0), lambda a, x: a + x)
    return p.select("vec_id", F.size("comps").alias("d"), total.alias("l1"), dot.alias("dot"), F.element_at("comps", 1).alias("c0"), F.exists("weights", lambda w: w > 1000).alias("big"), F.size(F.filter("weights", lambda w: w > 500)).alias("n"), F.array_max("weights").alias("top"))


_ARRAYS = _with(V.sql("supplier_brand")) + "SELECT vec_id, count(*) AS d, sum(weight) AS l1, sum(comp * weight) AS dot, min(comp) AS c0, bool_or(weight > 1000) AS big, count(*) FILTER (WHERE weight > 500) AS n, max(weight) AS top FROM v GROUP BY vec_id"


def _maps(spark, d):
    m = V.supplier_brand(spark, d).groupBy("vec_id").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("comp", "weight")))).alias("m"))
    a, b = (m.select(F.col("vec_id").alias(f"id_{x}"), F.col("m").alias(f"m_{x}")) for x in "ab")
    return a.join(b, F.col("id_a") < F.col("id_b")).select("id_a", "id_b", F.round(similarity.map_jaccard(F.col("m_a"), F.col("m_b")), 6).alias("j"))


_MAPS = _with(V.sql("supplier_brand"), similarity.sql_exact()) + "SELECT id_a, id_b, round(j, 6) AS j FROM ex"


def _json(spark, d):
    e = table(spark, d, "events", "event_id", "event_type", "props")
    k = F.from_json("props", "k INT")["k"]
    return e.select("event_id", k.alias("k"), F.get_json_object("props", "$.k").cast("int").alias("k2"), F.to_json(F.struct(k.alias("k"))).alias("back"))


_JSON = "SELECT event_id, (props->>'$.k')::INT AS k, (props->>'$.k')::INT AS k2, '{\"k\":' || (props->>'$.k') || '}' AS back FROM events"


def _sk(spark, d):
    """Suppliers' sketches; the vectors are written once, as the layout, the draws and the sketches each read them."""
    v = materialize(V.supplier_brand(spark, d))
    return redgreen.sketch_batches(V.pack(v), L.of(v), 64, 64, SEED)


#: Vectors of one sketch that stand together, and parts to which pairs of such groups are dealt.
TOGETHER, UDF_PARTS = 256, 48


def _udf(spark, d):
    """Estimates by the registered SQL function and its Arrow twin over the same sketches. Both depend on the sketches alone:
    vectors of one sketch stand in groups, the functions run once for two groups, and then their vectors are paired."""
    from rgsketch.operators.kernel import pandas_agreement

    SQL.register(spark)
    s = materialize(_sk(spark, d).select("vec_id", "sketch"))
    s = s.join(s.groupBy("sketch").agg(F.count("*").alias("n")), "sketch")
    g = s.groupBy("sketch", F.pmod(F.xxhash64("vec_id"), F.ceil(F.col("n") / TOGETHER)).alias("part")).agg(F.min("vec_id").alias("least"), F.collect_list("vec_id").alias("ids"))
    g = materialize(g.drop("part"))
    a, b = (g.select(F.col("least").alias(f"g_{x}"), F.col("ids").alias(f"ids_{x}"), F.col("sketch").alias(f"s_{x}")) for x in "ab")
    j = a.repartition(UDF_PARTS, "g_a").join(b, F.col("g_a") <= F.col("g_b"))
    j = j.select("ids_a", "ids_b", (F.col("g_a") == F.col("g_b")).alias("own"), F.round(F.expr("sketch_similarity(s_a, s_b)"), 6).alias("est"), F.round(pandas_agreement()("s_a", "s_b"), 6).alias("est_arrow"))
    j = j.select(F.explode("ids_a").alias("x"), "ids_b", "own", "est", "est_arrow").select("x", F.explode("ids_b").alias("y"), "own", "est", "est_arrow")
    return j.where("NOT own OR x < y").select(F.least("x", "y").alias("id_a"), F.greatest("x", "y").alias("id_b"), "est", "est_arrow")


_EST64 = (V.sql("supplier_brand"), L.sql(), D.sql(64, 64, SEED), redgreen.sql())
_UDF = _with(*_EST64) + "SELECT a.vec_id AS id_a, b.vec_id AS id_b, round(sum((a.h = b.h)::INT) / 64.0::DOUBLE, 6) AS est, round(sum((a.h = b.h)::INT) / 64.0::DOUBLE, 6) AS est_arrow FROM rg a JOIN rg b ON a.hash_id = b.hash_id AND a.vec_id < b.vec_id GROUP BY ALL"


def _udaf(spark, d):
    """Suppliers' sketches merged by nation with the grouped Arrow function."""
    SQL.register(spark)
    j = _sk(spark, d).join(table(spark, d, "supplier", "s_suppkey", "s_nationkey"), F.col("vec_id") == F.col("s_suppkey"))
    return j.groupBy("s_nationkey").agg(SQL.merge_max("sketch").alias("m")).select("s_nationkey", F.posexplode("m").alias("hash_id", "h"))


_UDAF = _with(*_EST64) + "SELECT s_nationkey, hash_id, min(h) AS h FROM rg JOIN supplier ON s_suppkey = vec_id GROUP BY ALL"


def _udtf(spark, d):
    """The draws on the widths of suppliers' months, by the table function joined to their total."""
    total = L.of(materialize(V.supplier_month(spark, d))).df.agg(F.sum("cap").alias("total"))
    return total.lateralJoin(SQL.RedGreenDraws(F.col("total").outer(), F.lit(8), F.lit(16), F.lit(SEED))).select("hash_id", "step", "r")


_UDTF = _with(V.sql("supplier_month"), L.sql()) + f"SELECT h::INT AS hash_id, t::INT AS step, {rng.sql_uniform(f"'{SEED}'", 'h', 't')} * total AS r FROM range(8) a(h), range(1, 17) b(t), lay_m"


def _sql_surface(spark, d):
    """The sketch of suppliers in SQL text over temporary views."""
    v = V.supplier_brand(spark, d)
    tag = uuid.uuid4().hex[:8]
    v.createOrReplaceTempView(f"rg_v_{tag}")
    D.build(L.of(v), 64, 32, SEED).createOrReplaceTempView(f"rg_d_{tag}")
    return spark.sql(f"SELECT vec_id, hash_id, min(step) AS h FROM rg_v_{tag} JOIN rg_d_{tag} USING (comp) WHERE offset < weight GROUP BY vec_id, hash_id")


def queries() -> dict:
    return {
        "op_scan_csv": _round_trip("csv", header="true"), "op_scan_json": _round_trip("json"), "op_scan_orc": _round_trip("orc"), "op_scan_parquet": _round_trip("parquet"),
        "op_bucketed_join": (_bucketed, "SELECT o_orderkey, sum(l_quantity) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey"),
        "op_join_broadcast": (_join_broadcast, "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey"),
        "op_join_sortmerge": (_join_merge, "SELECT o_custkey, sum(l_quantity) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey"),
        "op_join_range": (_join_range, _RANGE), "op_join_asof": (_join_asof, _RANGE),
        "op_join_interval": (_interval, "SELECT a.event_id AS event_id_a, b.event_id AS event_id_b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = b.event_type AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"),
        "op_join_left": _outer("left"), "op_join_right": _outer("right"), "op_join_outer": _outer("full"),
        "op_join_semi": (_semi, _with(V.sql("doc_terms")) + "SELECT * FROM v WHERE comp IN (SELECT comp FROM v GROUP BY comp HAVING count(*) >= 5)"),
        "op_join_anti": (_anti, "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)"), "op_join_salted": (_salted, _SALTED),
        "op_agg_cube": _grouping("cube"), "op_agg_rollup": _grouping("rollup"), "op_agg_grouping_sets": _grouping("sets"), "op_filters": (_filters, "SELECT p_partkey, p_name, p_brand, p_size FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#13', 'Brand#21', 'Brand#22') AND p_name IS NOT NULL AND p_name NOT LIKE 'zz%'"),
        "op_aggregates": (_aggs, _AGGS), "op_approx_distinct": (_approx, None), "op_percentile": (_percentile, None),
        "op_pivot": (_pivot, "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view, count(*) FILTER (WHERE event_type = 'purchase') AS purchase FROM events GROUP BY user_id"),
        "op_window_rank": (_ranks, _RANKS), "op_window_frames": (_frames, _FRAMES), "op_window_nulls": (_nulls, _NULLS), "op_topk": (_topk, "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10"),
        "op_union": _sets("union"), "op_intersect": _sets("intersect"), "op_except": _sets("except"), "op_distinct": _sets("distinct"),
        "op_strings": (_strings, _STRINGS), "op_kmers": (_kmers, _KMERS), "op_terms_benchmark": (_terms("benchmark", "item_id"), V._NAMED["benchmark_terms"]), "op_terms_conversations": (_terms("conversations", "conv_id", "role"), V._NAMED["conversation_terms"]),
        "op_dates": (_dates, _DATES), "op_math": (_math, _MATH), "op_arrays": (_arrays, _ARRAYS), "op_maps": (_maps, _MAPS), "op_json": (_json, _JSON),
        "op_udf": (_udf, _UDF), "op_udaf": (_udaf, _UDAF), "op_udtf": (_udtf, _UDTF), "op_sql": (_sql_surface, _with(V.sql("supplier_brand"), L.sql(), D.sql(64, 32, SEED), redgreen.sql()) + "SELECT * FROM rg"),
    }
