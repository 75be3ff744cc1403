"""Relational operators on tables of their own."""

import duckdb

from residua.operators import registry


def test_udtf_reads_the_customers(spark, tmp_path):
    """Vertices come from the given table: before, five made-up ones whatever the table held."""
    keys = [(k,) for k in (7, 3, 3, -4, 1 << 40, None)]
    spark.createDataFrame(keys, "c_custkey long").coalesce(1).write.parquet(f"{tmp_path}/customer.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW customer AS SELECT * FROM '{tmp_path}/customer.parquet/*.parquet'")
    want = con.execute(registry.oracle_sql()["op_udtf"]).fetchall()
    found = registry.queries()["op_udtf"](spark, str(tmp_path))
    key = lambda r: (r[0] is None, r[0] or 0, r[1] or 0)
    assert sorted((tuple(r) for r in found.collect()), key=key) == sorted(want, key=key) and len(want) == 18
    assert [(f.name, f.dataType.simpleString()) for f in found.schema] == [("src", "bigint"), ("dst", "bigint")]
