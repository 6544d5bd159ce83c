"""Two-pass external shuffle into shards.

Pass 1 scatters rows uniformly into memory-sized buckets by seeded hashes; pass 2 permutes each bucket by Fisher-Yates. A
row's rank in the concatenated buckets gives its shard (rank modulo shards) and slot, so that the shards' row counts differ
by one at most.

A row's hash is that of all its columns, so that rerunning gives the same order wherever the rows come from. Where rows are
equal, their place in the input is hashed as well: else all copies of a row would share a bucket, however many there are.
These rows and their hashes are written before they are counted and moved, as places must not change between the two; with
equal rows the order is therefore the same for the same input files only.

Edge cases: null ids and texts are values like any other; repeated rows are shuffled apart and each keeps a slot; a row
longer than a bucket makes that bucket longer; an empty table gives an empty result; columns are carried in a struct, so
their names can't clash.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rgsketch.llm.common import materialize

BUCKET_BYTES = 24 << 20
#: Parts of the hashes by which rows are found that may have an equal; a broadcast of so many numbers at most.
SPOTS = 1 << 16
#: Buckets whose counts are summed in one task.
BLOCK = 4096


def _keyed(df: DataFrame, seed: int) -> DataFrame:
    """``rec`` (a struct of df's columns) and ``h``, a seeded hash that differs between equal rows."""
    cols = [df[c] for c in df.columns]
    h = F.xxhash64(F.lit(seed), *cols)
    spot = F.pmod(F.col("h"), F.lit(SPOTS)).alias("spot")
    again = materialize(df.select(h.alias("h")).groupBy("h").count().where("count > 1").select(spot).distinct())
    rows = df.select(F.struct(*cols).alias("rec"), h.alias("h"))
    if again.isEmpty():
        return rows
    placed = rows.select("rec", "h", spot, F.monotonically_increasing_id().alias("at")).join(F.broadcast(again.withColumn("again", F.lit(True))), "spot", "left")
    return materialize(placed.select("rec", F.when(F.col("again"), F.xxhash64(F.lit(seed), "h", "at")).otherwise(F.col("h")).alias("h")))


def _starts(rows: DataFrame) -> DataFrame:
    """bucket, start: rows in the buckets before, summed within blocks of buckets and over the blocks."""
    block = F.floor(F.col("bucket") / BLOCK).alias("block")
    counts = rows.groupBy("bucket").agg(F.count("*").alias("n")).select("bucket", "n", block)
    before = lambda col, w: F.coalesce(F.sum(col).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    blocks = counts.groupBy("block").agg(F.sum("n").alias("n")).select("block", before("n", Window.orderBy("block")).alias("base"))
    own = counts.withColumn("start", before("n", Window.partitionBy("block").orderBy("bucket")))
    return own.join(blocks, "block").select("bucket", (F.col("base") + F.col("start")).alias("start"))


def external_shuffle(df: DataFrame, seed: int = 17, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """``rec`` (a struct of df's columns) and ``rank`` BIGINT, a seeded uniform permutation of 0 .. n - 1."""
    strings = [F.coalesce(F.octet_length(df[c]), F.lit(0)) for c, kind in df.dtypes if kind in ("string", "binary")]
    size = sum(strings, F.lit(16 * len(df.columns))).cast("long")
    total = df.agg(F.sum(size).alias("b")).first()["b"] or 0
    n_buckets = max(1, math.ceil(total / bucket_bytes))
    keyed = _keyed(df, seed)
    keyed = keyed.withColumn("bucket", F.pmod("h", F.lit(n_buckets)).cast("int"))

    def permute(rows: pa.Table, starts: pa.Table) -> pa.Table:
        if not rows.num_rows:
            return pa.table({"rec": rows.column("rec"), "rank": pa.array([], pa.int64())})
        ids = np.argsort(rows.column("h").to_numpy(), kind="stable")  # the order they came in is gone
        order = np.random.default_rng([seed, rows.column("bucket")[0].as_py()]).permutation(len(ids))  # Fisher-Yates
        at = np.empty(len(ids), np.int64)
        at[ids] = order
        return pa.table({"rec": rows.column("rec"), "rank": at + starts.column("start")[0].as_py()})

    kind = T.StructType([keyed.schema["rec"], T.StructField("rank", T.LongType())])
    # a bucket's rows and its one start meet in one exchange; no table of buckets is sent around
    starts = materialize(_starts(keyed.select("bucket")))
    return keyed.groupBy("bucket").cogroup(starts.groupBy("bucket")).applyInArrow(permute, kind)


def shard(df: DataFrame, shards: int, seed: int = 17, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """``rec``, ``shard`` INT and ``slot`` BIGINT (gapless from 0 in each shard)."""
    if shards < 1:
        raise ValueError("shards must be positive")
    out = external_shuffle(df, seed, bucket_bytes)
    return out.select("rec", F.pmod("rank", F.lit(shards)).cast("int").alias("shard"), F.floor(F.col("rank") / shards).cast("long").alias("slot"))


def write_shards(df: DataFrame, path: str, shards: int, seed: int = 17, bucket_bytes: int = BUCKET_BYTES) -> None:
    """Write df's rows in shuffled order, one folder a shard; readers order a shard's rows by ``slot``."""
    out = shard(df, shards, seed, bucket_bytes)
    out.sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    text = F.coalesce(F.col("rec.text"), F.lit(""))
    return shard(docs, 8).select(
        F.col("rec.doc_id").alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"),
        F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
