"""Histograms and sketches of a stream of events, with frozen widths."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rgsketch.operators import redgreen
from rgsketch.sources.tables import materialize, shared_dir


def source(spark: SparkSession, path: str, schema, files_per_batch: int | None = None) -> DataFrame:
    """A stream of the Parquet files at ``path`` (a file, a folder or a pattern)."""
    reader = spark.readStream.schema(schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    df = reader.parquet(path)
    return df.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in df.columns else df  # watermarks need a zone


def drain(stream: DataFrame, mode: str, each: Callable[[DataFrame, int], None], checkpoint: str | None = None) -> str:
    """Run all that is there through ``each`` (a batch and its number) and stop; returns the checkpoint, from which a later
    call goes on."""
    checkpoint = checkpoint or f"{shared_dir(stream.sparkSession)}/rgsketch/stream-{uuid.uuid4().hex}"
    stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(each).start().awaitTermination()
    return checkpoint


def collect_batches(stream: DataFrame, mode: str) -> DataFrame:
    """What the stream yields as a written table: all batches (append, update) or the last one (complete)."""
    spark = stream.sparkSession
    out = f"{shared_dir(spark)}/rgsketch/out-{uuid.uuid4().hex}"
    last = [-1]

    def each(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={i}")
        last[0] = i

    drain(stream, mode, each)
    if last[0] < 0:
        return spark.createDataFrame([], stream.schema)
    read = spark.read.schema(stream.schema)
    return read.parquet(f"{out}/batch={last[0]}") if mode == "complete" else read.option("basePath", out).parquet(out).select(*stream.columns)


def tumbling(events: DataFrame, width: str = "1 day", late: str = "1 day") -> DataFrame:
    w = F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 days", slide: str = "1 day", late: str = "1 day") -> DataFrame:
    w = F.window("ts", width, slide)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    w = F.session_window("ts", gap)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(events: DataFrame, late: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def histogram(events: DataFrame) -> DataFrame:
    """vec_id, name, weight: a user's counts by event type and hour."""
    name = F.concat_ws("|", "event_type", F.date_format("ts", "HH"))
    return events.groupBy(F.col("user_id").alias("vec_id"), name.alias("name")).agg(F.count("*").cast("double").alias("weight"))


class GrowingSketch:
    """Hashes of histograms that only grow: each batch joins the darts between old and new weights alone.

    State is two written tables, a new version of each a batch; widths are frozen, and a weight above its width or a name
    that has no component raises (see ``layout.new_epoch``). A batch that comes again, by its number, is left out. darts
    mustn't be cut to a data set's maxima. Vectors without a hash within the horizon stay out until they grow.
    """

    def __init__(self, layout, darts: DataFrame, components: DataFrame):
        self.layout, self.darts, self.components = layout, darts, components
        self.weights: DataFrame | None = None
        self.hashes: DataFrame | None = None
        self.last = -1

    def add(self, batch: DataFrame, number: int | None = None) -> None:
        number = self.last + 1 if number is None else number
        if number <= self.last:
            return
        unknown = F.raise_error(F.concat(F.lit("no component for "), F.col("name"))).cast("int")
        new = histogram(batch).join(self.components, "name", "left").select("vec_id", F.coalesce("comp", unknown).alias("comp"), "weight")
        old = self.weights if self.weights is not None else new.limit(0)
        all_ = new.unionByName(old.select("vec_id", "comp", F.col("weight"))).groupBy("vec_id", "comp").agg(F.sum("weight").alias("new_weight"))
        grown = all_.join(old.withColumnRenamed("weight", "old_weight"), ["vec_id", "comp"], "left").withColumn("old_weight", F.coalesce("old_weight", F.lit(0.0)))
        cap = self.layout.df.select("comp", "cap")
        over = F.when(F.col("new_weight") > F.col("cap"), F.raise_error(F.lit("weight above its width")).cast("double")).otherwise(F.col("new_weight"))
        grown = materialize(grown.join(cap, "comp").select("vec_id", "comp", "old_weight", over.alias("new_weight")))
        empty = grown.sparkSession.createDataFrame([], redgreen.HASHES)
        self.hashes = materialize(redgreen.update(self.hashes if self.hashes is not None else empty, grown.where("new_weight > old_weight"), self.darts))
        self.weights = grown.select("vec_id", "comp", F.col("new_weight").alias("weight"))
        self.last = number


def stateful_counts(events: DataFrame) -> DataFrame:
    """user_id, n: running counts held in keyed state, one row a user and batch."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def add(key, frames, state):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    return events.groupBy("user_id").applyInPandasWithState(add, "user_id long, n long", "n long", "update", GroupStateTimeout.NoTimeout)
