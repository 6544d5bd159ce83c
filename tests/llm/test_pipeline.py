import corpus_pipeline
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_stages_take_effect(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert 4 <= len(corpus_pipeline.STAGES) <= 5
    bench = [r["text"] for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    before = {r["doc_id"]: r["text"] for r in docs.collect()}
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.materialize(stage(spark, docs, SF))
        seen[name] = docs
        assert docs.columns[:5] == COLUMNS
    assert {r["doc_id"] for r in seen["language ID"].collect()} == set(before)  # all have letters and a clear language
    one = {r["doc_id"]: r["text"] for r in seen["near-dedup"].collect()}
    assert set(one.values()) == set(one.values()) and len(set(one.values())) == len(one)
    clean = {r["doc_id"]: r["text"] for r in seen["decontamination"].collect()}
    assert not any(b in t for t in clean.values() for b in bench)
    assert all(any(b in one[i] for b in bench) for i in set(one) - set(clean))
    mixed = seen["mixing"].groupBy("doc_id").count()
    assert mixed.agg(F.max("count")).first()[0] <= 3 and {r["doc_id"] for r in mixed.collect()} <= set(clean)
    shards = seen["sharding"]
    assert shards.count() == seen["mixing"].count()
    n = [r["count"] for r in shards.groupBy("shard").count().collect()]
    assert max(n) - min(n) <= 1


def test_runs_on_odd_rows(spark, docs_of):
    rows = [(0, None), (1, ""), (2, "One short text in English words"), (2, "One short text in English words"), (None, "no id at all here"), (3, "12345")] + [(10 + i, f"the words of text number {i} are " + " ".join(f"w{i}x{j}" for j in range(40))) for i in range(30)]
    for df in (docs_of(rows), docs_of([])):
        docs = df
        for _, stage in corpus_pipeline.STAGES:
            docs = corpus_pipeline.materialize(stage(spark, docs, SF))
        assert docs.count() <= 3 * len(rows)
