"""Queries of the streaming side: the events table as a file stream, drained, beside the batch result in SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from rgsketch.operators import redgreen
from rgsketch.plans import darts as D
from rgsketch.plans import layout as L
from rgsketch.queries.sketches import PLAN, SEED, _with
from rgsketch.sources import families as V
from rgsketch.sources.tables import shared_dir, table
from rgsketch.streaming import histograms as H

K, _, STEPS = PLAN["user_hours"]


def _events(spark, d):
    schema = spark.read.parquet(f"{d}/events.parquet").schema
    return H.source(spark, f"{d}/events.parquet*", schema)  # a pattern takes a file as well as a folder


def _complete(build):
    """Times come back without a zone, as the table has them."""

    def run(spark, d):
        out = H.collect_batches(build(_events(spark, d)), "complete")
        return out.select(*[F.col(c).cast("timestamp_ntz").alias(c) if kind == "timestamp" else c for c, kind in out.dtypes])

    return run


def _dedup(spark, d):
    e = _events(spark, d)
    return H.collect_batches(H.deduplicated(e.unionByName(_events(spark, d))), "append").groupBy("event_type").agg(F.count("*").alias("n"))


def _late(spark, d):
    """Append mode: only windows that the watermark has closed come out; rows later than it are dropped."""
    return H.collect_batches(H.tumbling(_events(spark, d), late="1 hour"), "append")


def _sketch(spark, d):
    """A histogram kept by the stream, sketched under the widths of the batch."""
    v = H.collect_batches(H.histogram(_events(spark, d)), "complete")
    names = V.dictionary(v)
    long = v.join(names, "name").select("vec_id", "comp", "weight")
    return redgreen.sketch(long, L.of(long), K, SEED)


def _growth(spark, d):
    """The same hashes, kept by batches of three files: each batch joins only the darts that its growth uncovers."""
    e = table(spark, d, "events")
    path = f"{shared_dir(spark)}/rgsketch/{uuid.uuid4().hex}"
    e.repartition(3).write.parquet(path)
    whole = H.histogram(e)
    names = V.dictionary(whole)
    lay = L.of(whole.join(names, "name").select("vec_id", "comp", "weight"))
    state = H.GrowingSketch(lay, D.prune(D.build(lay, K, STEPS, SEED)), names)
    H.drain(H.source(spark, path, e.schema, 1), "append", state.add)
    return state.hashes


def _state(spark, d):
    """Running counts in keyed state; the last of each user is the count of his events."""
    return H.collect_batches(H.stateful_counts(_events(spark, d)), "update").groupBy("user_id").agg(F.max("n").alias("n"))


_SKETCH = _with(V.sql("user_hours"), L.sql(), D.sql(K, STEPS, SEED, pruned=True), redgreen.sql()) + "SELECT * FROM rg"


def queries() -> dict:
    return {
        "stream_tumbling": (_complete(H.tumbling), "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL"),
        "stream_sliding": (_complete(H.sliding), "SELECT time_bucket(INTERVAL 1 DAY, ts) - INTERVAL 1 DAY * o AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) t(o) GROUP BY ALL"),
        "stream_session": (_complete(H.sessions), "SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS \"end\", count(*) AS n FROM (SELECT *, sum(g) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS g FROM events)) GROUP BY user_id, s"),
        "stream_dedup": (_dedup, "SELECT event_type, count(*) AS n FROM (SELECT DISTINCT event_id, event_type FROM events) GROUP BY event_type"),
        "stream_late": (_late, None), "stream_sketch": (_sketch, _SKETCH), "stream_growth": (_growth, _SKETCH), "stream_state": (_state, "SELECT user_id, count(*) AS n FROM events GROUP BY user_id"),
    }
