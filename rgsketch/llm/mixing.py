"""Mixing sources to target weights by capped water-filling. Native: DataFrame functions alone.

Every source asks for its weight's share of the total; a source is clamped at ``epochs`` times its size and the excess goes
to the others in proportion to their weights, round by round, until no source is above its clamp. The state of a round is
one number, the level (size per unit of weight): a source is clamped when ``epochs * size <= level * weight``. A source
with ratio target / size repeats each document floor(ratio) times; the fraction left is taken from documents in a seeded
order, cut where the words come nearest to the target. The cut is found over 4096 hash cells of each source, and only the
cell it falls into is ordered row by row, so that a source with any share of the rows is never gathered in one task.

Edge cases: null texts have size 0 and take 0; a null source is a source, last in order; sources without words have target
0; repeated rows count as rows; an empty table gives an empty result; columns other than the named three are not read.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rgsketch.llm.common import materialize, maybe_broadcast

WORD = r"[^\x20\x09-\x0D]+"


def cyclic_weights(sources: DataFrame, weights: tuple[float, ...] = (5, 2, 1)) -> DataFrame:
    """Add ``weight``: the given values in turn, sources by code point, null last. Sources are ranked within ranges of them,
    and only the ranges' counts are summed in one place, as a source may be a host and hosts are many."""
    order = (F.col("source").isNull(), F.col("source"))
    ranged = materialize(sources.repartitionByRange(*order).withColumn("range", F.spark_partition_id()))
    counts = ranged.groupBy("range").agg(F.count("*").alias("n"))
    starts = counts.select("range", F.coalesce(F.sum("n").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    placed = ranged.join(F.broadcast(starts), "range")  # a row a partition
    place = F.col("start") + F.row_number().over(Window.partitionBy("range").orderBy(*order)) - 1
    return placed.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(place, F.lit(len(weights))) + 1).cast("int"))).drop("range", "start")


def water_fill(sources: DataFrame, epochs: float, total: float | None = None) -> DataFrame:
    """Add ``target`` to (source, source_size, weight). ``total`` defaults to the sum of sizes."""
    sources = sources.withColumn("cap", F.col("source_size") * F.lit(float(epochs)))
    first = sources.agg(F.sum("source_size").alias("s"), F.sum("weight").alias("w")).first()
    total = float(first["s"] or 0) if total is None else float(total)
    level = total / first["w"] if first["w"] else 0.0
    while True:
        full = F.col("cap") <= F.lit(level) * F.col("weight")
        r = sources.agg(F.sum(F.when(full, F.col("cap"))).alias("held"), F.sum(F.when(~full, F.col("weight"))).alias("w")).first()
        if not r["w"]:
            level = math.inf
            break
        higher = (total - (r["held"] or 0.0)) / r["w"]
        if higher <= level * (1 + 1e-12):
            break
        level = higher
    target = F.col("cap") if level == math.inf else F.least("cap", F.lit(level) * F.col("weight"))
    return sources.withColumn("target", target).drop("cap")


def _parts(docs: DataFrame, seed: int, id_col: str, text_col: str, source_col: str) -> dict:
    """Of a document: its source's key, its words and its place in the seeded order (60 bits; the cell is the first 12). A
    null id is placed by the text instead, so that rows without ids spread."""
    name = F.coalesce(docs[id_col].cast("string"), F.concat(F.lit("n:"), F.md5(F.coalesce(docs[text_col].cast("string"), F.lit("")).cast("binary"))))
    spot = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), name).cast("binary")), 1, 15), 16, 10).cast("long")
    key = F.when(docs[source_col].isNull(), "n").otherwise(F.concat(F.lit("s"), docs[source_col]))
    return {"doc_id": docs[id_col], "source": docs[source_col], "key": key, "size": F.coalesce(F.regexp_count(docs[text_col], F.lit(WORD)), F.lit(0)).cast("long"), "spot": spot, "cell": F.shiftright(spot, 48)}


def _plan(docs: DataFrame, weigh, epochs: int, seed: int, id_col: str, text_col: str, source_col: str):
    """The documents' parts (written), a row a source (key, source_size, target, whole, rest, cut, before), and their number."""
    base = materialize(docs.select(*[c.alias(n) for n, c in _parts(docs, seed, id_col, text_col, source_col).items()]))
    sources = materialize(weigh(base.groupBy("key", "source").agg(F.sum("size").alias("source_size"))))
    filled = water_fill(sources, epochs).select("key", "source_size", F.round("target", 6).alias("target"))
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    filled = filled.withColumn("whole", F.floor(ratio + 1e-9)).withColumn("rest", F.greatest(F.lit(0.0), F.col("target") - F.col("whole") * F.col("source_size")))
    n = sources.count()
    run = Window.partitionBy("key").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    cells = base.groupBy("key", "cell").agg(F.sum("size").alias("words")).withColumn("before", F.coalesce(F.sum("words").over(run), F.lit(0)))
    cut = cells.join(maybe_broadcast(filled, n), "key").where((F.col("before") < F.col("rest")) & (F.col("rest") <= F.col("before") + F.col("words")))
    return base, materialize(filled.join(cut.select("key", F.col("cell").alias("cut"), "before"), "key", "left")), n


def _at_edge() -> F.Column:
    """Whether a row's cell is the one that its source's rest is cut in, where rows are ordered one by one."""
    return F.coalesce(F.col("cell") == F.col("cut"), F.lit(False))


def _decided() -> F.Column:
    """Copies of a row away from the edge: whole repetitions, and one more before the cut."""
    return F.col("whole") + F.coalesce((F.col("cell") < F.col("cut")).cast("long"), F.lit(0))


def _edge(rows: DataFrame) -> DataFrame:
    """The edge rows with their copies: one more while the words come nearer to the rest."""
    fine = Window.partitionBy("key").orderBy("spot", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    at = F.col("before") + F.coalesce(F.sum("size").over(fine), F.lit(0))
    return rows.where(_at_edge()).withColumn("copies", F.col("whole") + (at + F.col("size") / 2 <= F.col("rest")).cast("long"))


def mix(docs: DataFrame, weigh=cyclic_weights, epochs: int = 3, seed: int = 9, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """Rows doc_id, source, size, source_size, target, copies (whole and fractional repetitions), taken = copies * size."""
    base, plan, n = _plan(docs, weigh, epochs, seed, id_col, text_col, source_col)
    rows = base.join(maybe_broadcast(plan, n), "key")
    both = rows.where(~_at_edge()).withColumn("copies", _decided()).unionByName(_edge(rows))
    return both.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def repeat_rows(docs: DataFrame, weigh=cyclic_weights, epochs: int = 3, seed: int = 9) -> DataFrame:
    """The rows of the mix with docs' columns: each document as often as the mix takes it. Rows are decided by the plan of
    their source where they are read; only those of the cut cells, a 4096th of a source, are looked up, by what ``mix``
    orders them by: rows that agree in it are taken alike, as often as the most of them."""
    base, plan, n = _plan(docs, weigh, epochs, seed, "doc_id", "text", "source")
    own = _parts(docs, seed, "doc_id", "text", "source")
    rows = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("rec"), *[own[c].alias(c) for c in ("doc_id", "key", "size", "spot", "cell")])
    rows = rows.join(maybe_broadcast(plan.select("key", "whole", "cut"), n), "key")
    by = ("key", "spot", "size")
    edge = _edge(base.join(maybe_broadcast(plan, n), "key")).groupBy(*by, "doc_id").agg(F.max("copies").alias("copies")).where("copies > 0")
    looked = rows.where(_at_edge()).drop("cell", "whole", "cut").withColumnRenamed("doc_id", "id").join(edge, list(by)).where(F.col("id").eqNullSafe(F.col("doc_id")))
    plain = rows.where(~_at_edge()).withColumn("copies", _decided()).where("copies > 0")
    both = plain.select("rec", "copies").unionByName(looked.select("rec", "copies"))
    return both.select("rec", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies").cast("long"))).alias("copy")).select("rec.*")


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mix(docs).select("doc_id", "size", "source_size", "target", "taken")


ORACLE = r"""
WITH base AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         ('0x' || substr(md5(concat_ws(':', '9', doc_id::VARCHAR)), 1, 15))::BIGINT AS spot FROM documents),
src AS (SELECT source, sum(size)::BIGINT AS source_size, 3.0::DOUBLE * sum(size) AS cap FROM base GROUP BY source),
w AS (SELECT *, CASE (row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS weight FROM src),
o AS (SELECT *, sum(cap) OVER r - cap AS held, sum(weight) OVER () - (sum(weight) OVER r - weight) AS free_w, (SELECT sum(source_size) FROM src)::DOUBLE AS total
      FROM w WINDOW r AS (ORDER BY cap / weight, source NULLS LAST ROWS UNBOUNDED PRECEDING)),
lv AS (SELECT min_by((total - held) / free_w, cap / weight) AS lam FROM o WHERE (total - held) / free_w < cap / weight),
t AS (SELECT source, source_size, round(least(cap, coalesce(lam, 'inf'::DOUBLE) * weight), 6) AS target FROM w, lv),
f AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size + 1e-9) ELSE 0 END AS whole FROM t),
g AS (SELECT *, greatest(0.0, target - whole * source_size) AS rest FROM f),
r AS (SELECT b.doc_id, b.size, g.source_size, g.target, g.whole, g.rest,
             coalesce(sum(b.size) OVER (PARTITION BY b.source ORDER BY b.spot, b.doc_id, b.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead
      FROM base b JOIN g ON b.source IS NOT DISTINCT FROM g.source)
SELECT doc_id, size, source_size, target, ((whole + CASE WHEN rest > 0 AND ahead + size / 2.0 <= rest THEN 1 ELSE 0 END) * size)::BIGINT AS taken FROM r
"""
