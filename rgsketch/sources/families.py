"""Vector families over the given tables: long form vec_id BIGINT, comp INT, weight DOUBLE, one row a non-zero."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rgsketch.functions.rng import open_uniform
from rgsketch.sources.tables import table

WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def tokens(text: Column) -> Column:
    """Maximal runs of non-blanks, lower-cased; null gives none."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(WORD), F.lit(0))


def dictionary(names: DataFrame) -> DataFrame:
    """name, comp: a number for every distinct name, without a gap. Names are ranked in 256 slices by the md5's first byte,
    and only the slices' sizes are summed in one place."""
    distinct = names.select("name").distinct().withColumn("slice", F.substring(F.md5(F.col("name").cast("binary")), 1, 2))
    sizes = distinct.groupBy("slice").count()
    before = F.coalesce(F.sum("count").over(Window.orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = sizes.select("slice", before.alias("before"))
    rank = F.row_number().over(Window.partitionBy("slice").orderBy("name"))
    return distinct.join(F.broadcast(starts), "slice").select("name", (F.col("before") + rank - 1).cast("int").alias("comp"))


def encode(named: DataFrame) -> DataFrame:
    """(vec_id, name, weight) with names as component numbers."""
    return named.join(dictionary(named), "name").select("vec_id", "comp", "weight")


def clean(vectors: DataFrame, on_negative: str = "error") -> DataFrame:
    """Finite weights above 0, equal (vec_id, comp) summed. Negative ones raise, are clipped, or go to twin components
    (``split_sign``: component 2c holds the positive part of c, 2c + 1 the negative one); null and NaN always raise."""
    w = F.col("weight")
    bad = w.isNull() | F.isnan(w) | (F.abs(w) == F.lit(float("inf")))
    if on_negative == "error":
        bad = bad | (w < 0)
    v = vectors.select("vec_id", "comp", F.when(bad, F.raise_error(F.lit("weights must be finite and not below 0")).cast("double")).otherwise(w).alias("weight"))
    if on_negative == "split_sign":
        v = v.select("vec_id", (F.col("comp") * 2 + (w < 0).cast("int")).alias("comp"), F.abs(w).alias("weight"))
    return v.where(w > 0).groupBy("vec_id", "comp").agg(F.sum("weight").alias("weight"))


def pack(vectors: DataFrame) -> DataFrame:
    """vec_id, comps, weights: one row a vector, components ascending."""
    got = vectors.groupBy("vec_id").agg(F.sort_array(F.collect_list(F.struct("comp", "weight"))).alias("e"))
    return got.select("vec_id", F.col("e.comp").alias("comps"), F.col("e.weight").alias("weights"))


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("vec_id", F.explode(F.arrays_zip("comps", "weights")).alias("e")).select("vec_id", F.col("e.comps").alias("comp"), F.col("e.weights").alias("weight"))


def term_counts(df: DataFrame, id_col: str, text_col: str, role_col: str | None = None) -> DataFrame:
    """(vec_id, name, weight): tokens of all texts of an id, with their counts."""
    word = F.explode(tokens(F.col(text_col))).alias("t")
    rows = df.select(F.col(id_col).alias("vec_id"), *([F.col(role_col).alias("r")] if role_col else []), word)
    name = F.concat_ws(":", "r", "t") if role_col else F.col("t")
    return rows.groupBy("vec_id", name.alias("name")).agg(F.count("*").cast("double").alias("weight"))


def kmers(df: DataFrame, id_col: str, text_col: str, k: int) -> DataFrame:
    """(vec_id, name, weight): counts of the runs of k characters."""
    text = F.lower(F.coalesce(F.col(text_col), F.lit("")))
    n = F.length(text) - k + 1
    part = F.explode(F.when(n >= 1, F.transform(F.sequence(F.lit(1), n), lambda i: F.substring(text, i, F.lit(k))))).alias("name")
    return df.select(F.col(id_col).alias("vec_id"), part).groupBy("vec_id", "name").agg(F.count("*").cast("double").alias("weight"))


def fold(vectors: DataFrame, buckets: int, seed: int = 0, name_col: str = "comp") -> DataFrame:
    """Components hashed to ``buckets`` and summed; inflates similarity, so candidates need a check."""
    cell = F.pmod(F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col(name_col)).cast("binary")), 1, 13), 16, 10).cast("long"), F.lit(buckets)).cast("int")
    return vectors.groupBy("vec_id", cell.alias("comp")).agg(F.sum("weight").alias("weight"))


def drop_rare(vectors: DataFrame, min_df: int) -> DataFrame:
    """Without components that fewer than ``min_df`` vectors hold."""
    kept = vectors.groupBy("comp").agg(F.count("*").alias("df")).where(F.col("df") >= min_df).select("comp")
    return vectors.join(kept, "comp", "left_semi").select("vec_id", "comp", "weight")


def embeddings(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("i", "e"))
    e = e.select("vec_id", "i", F.col("e").cast("double").alias("e")).where("e <> 0")
    return e.select("vec_id", (F.col("i") * 2 + (F.col("e") < 0).cast("int")).alias("comp"), F.abs("e").alias("weight"))


def _lines(spark, d, *columns):
    return table(spark, d, "lineitem", *columns)


def customer_brand(spark: SparkSession, d: str) -> DataFrame:
    o, p = table(spark, d, "orders", "o_orderkey", "o_custkey"), table(spark, d, "part", "p_partkey", "p_brand")
    rows = _lines(spark, d, "l_orderkey", "l_partkey", "l_quantity").join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(p, F.col("l_partkey") == F.col("p_partkey"))
    return encode(rows.groupBy(F.col("o_custkey").alias("vec_id"), F.col("p_brand").alias("name")).agg(F.sum("l_quantity").alias("weight")))


def supplier_brand(spark: SparkSession, d: str) -> DataFrame:
    rows = _lines(spark, d, "l_suppkey", "l_partkey", "l_quantity").join(table(spark, d, "part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    return encode(rows.groupBy(F.col("l_suppkey").alias("vec_id"), F.col("p_brand").alias("name")).agg(F.sum("l_quantity").alias("weight")))


def supplier_month(spark: SparkSession, d: str) -> DataFrame:
    rows = _lines(spark, d, "l_suppkey", "l_shipdate", "l_extendedprice")
    money = (F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double") / 1000).alias("weight")
    return encode(rows.groupBy(F.col("l_suppkey").alias("vec_id"), F.date_format("l_shipdate", "yyyy-MM").alias("name")).agg(money))


def part_supplier(spark: SparkSession, d: str) -> DataFrame:
    return _lines(spark, d, "l_partkey", "l_suppkey", "l_quantity").groupBy(F.col("l_partkey").alias("vec_id"), F.col("l_suppkey").cast("int").alias("comp")).agg(F.sum("l_quantity").alias("weight"))


def user_hours(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events", "user_id", "event_type", "ts")
    name = F.concat_ws("|", "event_type", F.date_format("ts", "HH"))
    return encode(e.groupBy(F.col("user_id").alias("vec_id"), name.alias("name")).agg(F.count("*").cast("double").alias("weight")))


def doc_terms(spark: SparkSession, d: str) -> DataFrame:
    return encode(term_counts(table(spark, d, "documents", "doc_id", "text"), "doc_id", "text"))


def _letter_shares(batches):
    """Arrow batches (id, text) to (vec_id, comp, weight): one count over a batch's bytes, whose rows are 1 MB or one text."""
    for batch in batches:
        if not batch.num_rows:
            continue
        lo, text = 0, batch.column(1).cast(pa.large_binary()).fill_null(b"")
        edge = np.frombuffer(text.buffers()[1], np.int64)[text.offset : text.offset + len(text) + 1]
        data, sizes = np.frombuffer(text.buffers()[2] or b"", np.uint8), np.diff(edge)
        while lo < batch.num_rows:
            hi = max(lo + 1, int(np.searchsorted(edge, edge[lo] + (1 << 20), side="right")) - 1)
            raw = data[edge[lo] : edge[hi]]
            place = np.where(raw >= 97, raw - 97, raw - 65).astype(np.int64)
            letter = np.flatnonzero(((raw >= 65) & (raw <= 90)) | ((raw >= 97) & (raw <= 122)))
            row = np.repeat(np.arange(hi - lo), sizes[lo:hi])[letter]
            n = np.bincount(row * 26 + place[letter], minlength=26 * (hi - lo)).reshape(-1, 26)
            r, c = np.nonzero(n)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo).take(pa.array(r)), pa.array(c.astype(np.int32)), pa.array(n[r, c] / n.sum(1)[r])], ["vec_id", "comp", "weight"])
            lo = hi


def doc_letters(spark: SparkSession, d: str) -> DataFrame:
    """Shares among the letters a-z of either case. Counted over bytes in Arrow batches: built-ins would read each text once
    a letter and case."""
    rows = table(spark, d, "documents", "doc_id", "text").select(F.col("doc_id").alias("vec_id"), "text")
    return rows.mapInArrow(_letter_shares, "vec_id long, comp int, weight double")


def page_tags(spark: SparkSession, d: str) -> DataFrame:
    tag = F.explode(F.regexp_extract_all(F.coalesce("html", F.lit("")), F.lit("<([A-Za-z][A-Za-z0-9]*)"), F.lit(1))).alias("t")
    rows = table(spark, d, "pages", "page_id", "html").select(F.col("page_id").alias("vec_id"), tag)
    return encode(rows.groupBy("vec_id", F.lower("t").alias("name")).agg(F.count("*").cast("double").alias("weight")))


def conversation_terms(spark: SparkSession, d: str) -> DataFrame:
    return encode(term_counts(table(spark, d, "conversations", "conv_id", "role", "text"), "conv_id", "text", "role"))


def benchmark_terms(spark: SparkSession, d: str) -> DataFrame:
    return encode(term_counts(table(spark, d, "benchmark", "item_id", "text"), "item_id", "text"))


def doc_folded(spark: SparkSession, d: str, buckets: int = 1024) -> DataFrame:
    return fold(term_counts(table(spark, d, "documents", "doc_id", "text"), "doc_id", "text"), buckets, name_col="name")


def synthetic(spark: SparkSession, n: int, d: int, dim: int, power: int = 11, seed: int = 5) -> DataFrame:
    """n made vectors with d non-zeros among dim components (evenly spread from a place of the vector's own), weights
    u ** power of seeded draws: a mean of 1 / (power + 1) of the largest, so the fill is about d / dim / (power + 1)."""
    rows = spark.range(n * d).select(F.floor(F.col("id") / d).alias("vec_id"), F.pmod("id", F.lit(d)).alias("i"))
    comp = F.pmod(F.floor(F.col("i") * dim / d) + F.pmod(F.xxhash64(F.lit(seed), "vec_id"), F.lit(dim)), F.lit(dim)).cast("int")
    return rows.select("vec_id", comp.alias("comp"), F.greatest(F.pow(open_uniform(seed, "w", F.col("vec_id"), F.col("i")), F.lit(power)), F.lit(1e-9)).alias("weight"))


#: Made families for the studies of many non-zeros: vectors, non-zeros, components.
WIDE = {"d1000": (64, 1_000, 1_040), "d10000": (32, 10_000, 50_000), "d100000": (16, 100_000, 145_000)}
BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "embeddings": embeddings, "customer_brand": customer_brand, "supplier_brand": supplier_brand, "supplier_month": supplier_month, "part_supplier": part_supplier, "user_hours": user_hours,
    "doc_terms": doc_terms, "doc_letters": doc_letters, "page_tags": page_tags, "conversation_terms": conversation_terms, "benchmark_terms": benchmark_terms, "doc_folded": doc_folded,
}

_TOKENS = rf"regexp_extract_all(lower(coalesce(text, '')), '{WORD}')"
_NAMED = {
    "customer_brand": "SELECT o_custkey AS vec_id, p_brand AS name, sum(l_quantity) AS weight FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY ALL",
    "supplier_brand": "SELECT l_suppkey AS vec_id, p_brand AS name, sum(l_quantity) AS weight FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL",
    "supplier_month": "SELECT l_suppkey AS vec_id, strftime(l_shipdate, '%Y-%m') AS name, sum(l_extendedprice::DECIMAL(18,2))::DOUBLE / 1000 AS weight FROM lineitem GROUP BY ALL",
    "user_hours": "SELECT user_id AS vec_id, event_type || '|' || strftime(ts, '%H') AS name, count(*)::DOUBLE AS weight FROM events GROUP BY ALL",
    "doc_terms": f"SELECT vec_id, name, count(*)::DOUBLE AS weight FROM (SELECT doc_id AS vec_id, unnest({_TOKENS}) AS name FROM documents) GROUP BY ALL",
    "page_tags": f"SELECT vec_id, lower(name) AS name, count(*)::DOUBLE AS weight FROM (SELECT page_id AS vec_id, unnest(regexp_extract_all(coalesce(html, ''), '<([A-Za-z][A-Za-z0-9]*)', 1)) AS name FROM pages) GROUP BY ALL",
    "conversation_terms": f"SELECT vec_id, concat_ws(':', role, t) AS name, count(*)::DOUBLE AS weight FROM (SELECT conv_id AS vec_id, role, unnest({_TOKENS}) AS t FROM conversations) GROUP BY ALL",
    "benchmark_terms": f"SELECT vec_id, name, count(*)::DOUBLE AS weight FROM (SELECT item_id AS vec_id, unnest({_TOKENS}) AS name FROM benchmark) GROUP BY ALL",
}
_DIRECT = {
    "embeddings": "SELECT vec_id, (2 * (i - 1) + CASE WHEN e < 0 THEN 1 ELSE 0 END)::INT AS comp, abs(e) AS weight FROM (SELECT vec_id, unnest(embedding)::DOUBLE AS e, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE e <> 0",
    "part_supplier": "SELECT l_partkey AS vec_id, l_suppkey::INT AS comp, sum(l_quantity) AS weight FROM lineitem GROUP BY ALL",
    "doc_letters": f"SELECT vec_id, comp, n / sum(n) OVER (PARTITION BY vec_id) AS weight FROM (SELECT doc_id AS vec_id, i::INT AS comp, (length(t) - length(replace(t, chr((97 + i)::INT), '')))::DOUBLE AS n FROM (SELECT doc_id, lower(coalesce(text, '')) AS t FROM documents), range(26) r(i)) WHERE n > 0",
    "doc_folded": f"SELECT vec_id, (('0x' || substr(md5(concat_ws(':', '0', name)), 1, 13))::BIGINT % 1024)::INT AS comp, sum(weight) AS weight FROM ({_NAMED['doc_terms']}) GROUP BY ALL",
}


def sql(family: str, name: str = "v") -> str:
    """A DuckDB common table expression (vec_id, comp, weight) of the family."""
    if family in _DIRECT:
        return f"{name} AS ({_DIRECT[family]})"
    return (
        f"{name}_n AS ({_NAMED[family]}), {name}_d AS (SELECT name, (row_number() OVER (ORDER BY substr(md5(name), 1, 2), name) - 1)::INT AS comp FROM (SELECT DISTINCT name FROM {name}_n)), "
        f"{name} AS (SELECT vec_id, comp, weight FROM {name}_n JOIN {name}_d USING (name))"
    )
