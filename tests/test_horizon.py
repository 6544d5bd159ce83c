"""Where vectors are thin, rg_part_supplier draws past its SQL's horizon; what it adds are the hashes of a farther one."""

import pytest

import __spark_entry__


def test_part_supplier_is_whole_past_the_horizon(spark, tmp_path):
    duckdb = pytest.importorskip("duckdb")
    rows = [(p, p % 400, float(50 if p % 3 else 1 + p % 5)) for p in range(1200)]  # each part has about 1/400 of the widths or less
    spark.createDataFrame(rows, "l_partkey long, l_suppkey long, l_quantity double").coalesce(1).write.parquet(str(tmp_path / "lineitem.parquet"))
    got = {tuple(r) for r in __spark_entry__.queries()["rg_part_supplier"](spark, str(tmp_path)).collect()}
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    sql = __spark_entry__.oracle_sql()["rg_part_supplier"]
    assert sql.count("range(1, 4097)") == 1
    near = set(con.execute(sql).fetchall())
    far = set(con.execute(sql.replace("range(1, 4097)", "range(1, 1000001)")).fetchall())
    assert len(got) == 1200 * 16 and near < got
    assert min(h for _, _, h in got - near) > 4096
    assert got == far
