"""Queries that once made their data up read given tables."""

import pytest

import __spark_entry__


@pytest.mark.parametrize("name", ["est_required_k", "lsh_curve", "op_udtf"])
def test_reads_a_table(spark, name):
    df = __spark_entry__.queries()[name](spark, "/root/testdata/sf0.001")
    assert df.inputFiles() and df.count() > 0
