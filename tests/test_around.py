"""Relational operations around a clustering on small tables with known results."""

import duckdb
import pytest

from peakgroups.plans import around

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(around.QUERIES))
def test_same_as_sql(spark, name):
    for table in ("customer", "orders", "lineitem", "documents", "labels", "events", "embeddings"):
        duckdb.sql(f"create or replace view {table} as select * from '{SF}/{table}.parquet'")
    found = around.QUERIES[name](spark, SF)
    columns = sorted(found.columns)
    rows = [tuple(r) for r in found.select(*columns).collect()]
    wanted = duckdb.sql(f"select {', '.join(columns)} from ({around.SQL[name]})").fetchall()
    assert rows and sorted(map(repr, rows)) == sorted(map(repr, wanted))


def test_topk_breaks_ties_by_supplier(spark, tmp_path):
    spark.createDataFrame([(1, 7)], "o_orderkey long, o_custkey long").write.parquet(str(tmp_path / "orders.parquet"))
    spark.createDataFrame([(1, s) for s in (5, 4, 3, 2, 2)], "l_orderkey long, l_suppkey long").write.parquet(str(tmp_path / "lineitem.parquet"))
    rows = around.topk_links(spark, str(tmp_path)).orderBy("place").collect()
    assert [(r.l_suppkey, r.weight) for r in rows] == [(2, 2), (3, 1), (4, 1)]
