"""Queries on suppliers' sketches build the vectors once."""

from rgsketch.queries import engine


def test_sketches_read_written_vectors(spark):
    d = "/root/testdata/sf0.001"
    files = engine._sk(spark, d).inputFiles()
    assert files and not any("/lineitem.parquet" in f or "/part.parquet" in f for f in files)
