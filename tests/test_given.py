"""Queries that once made their rows up read a given table, and give what SQL gives."""

from __future__ import annotations

import duckdb
import pytest

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name,table", [("op_recursion", "lineitem"), *((f"src_generated_{k}", "customer") for k in ("cycle", "star", "path", "grid", "uniform", "preferential"))])
def test_rows_come_from_the_table(spark, tmp_path, name, table):
    import __spark_entry__

    for t in ("lineitem", "customer"):
        rows = spark.read.parquet(f"{SF}/{t}.parquet")
        rows.where("c_custkey > 20" if t == "customer" else "l_returnflag <> 'N'").write.parquet(f"{tmp_path}/{t}.parquet")
    c = duckdb.connect()
    got = {}
    for d in (SF, str(tmp_path)):
        for t in ("lineitem", "customer"):
            at = f"{d}/{t}.parquet" + ("" if d == SF else "/*.parquet")
            c.execute(f"CREATE OR REPLACE VIEW {t} AS SELECT * FROM '{at}'")
        from subcount.queries import relational

        query = relational.QUERIES[name] if name != "op_recursion" else None
        if query is None:
            spark.read.parquet(f"{d}/lineitem.parquet").createOrReplaceTempView("lineitem")
            rows = spark.sql(relational.ORACLES[name]).collect()
        else:
            rows = query(spark, d).collect()
        got[d] = sorted(map(tuple, rows))
        assert got[d] == sorted(c.execute(__spark_entry__.oracle_sql()[name]).fetchall())
    assert got[SF] != got[str(tmp_path)]


@pytest.mark.parametrize("name,table,part", [("src_generated_clique", "lineitem", "l_quantity < 20"), ("st_rate_source", "events", "user_id % 3 > 0"), ("pat_catalogue", "region", "r_regionkey < 4")])
def test_patterns_numbers_and_cliques_come_from_the_table(spark, tmp_path, name, table, part):
    import __spark_entry__

    spark.read.parquet(f"{SF}/{table}.parquet").where(part).write.parquet(f"{tmp_path}/{table}.parquet")
    got = []
    for d, files in ((SF, ""), (str(tmp_path), "/*.parquet")):
        c = duckdb.connect()
        c.execute(f"CREATE VIEW {table} AS SELECT * FROM '{d}/{table}.parquet{files}'")
        got.append(sorted(map(tuple, __spark_entry__.queries()[name](spark, d).collect())))
        assert got[-1] == sorted(c.execute(__spark_entry__.oracle_sql()[name]).fetchall())
    assert got[0] != got[1]
