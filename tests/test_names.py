"""Clusters named by their members."""

import duckdb
import pytest
from pyspark.sql import functions as F

from peakgroups import catalogue

SF = "/root/testdata/sf0.001"


def test_long_names_are_written_by_tasks_of_their_own(spark, monkeypatch):
    monkeypatch.setattr(catalogue, "_LONG_NAME", 100, raising=False)
    sizes = [40, 50, 60, 41, 3, 2, 1, 70, 80, 90]
    rows = [(c, 1000 * c + i, 1, 1 + c % 2) for c, n in enumerate(sizes) for i in range(n)]
    named = catalogue._signed(spark.createDataFrame(rows, "cluster long, node long, num int, den int"))
    found = named.withColumn("task", F.spark_partition_id()).collect()
    names = {c: ",".join(str(1000 * c + i) for i in range(n)) for c, n in enumerate(sizes)}
    assert sorted((r.members, r.node, r.num, r.den) for r in found) == sorted((names[c], n, a, b) for c, n, a, b in rows)
    by_task = {}
    for r in found:
        by_task.setdefault(r.task, set()).add(r.members)
    assert all(len(x) == 1 for x in by_task.values() if max(map(len, x)) > 100)


def test_no_clusters_no_rows(spark):
    assert catalogue._signed(spark.createDataFrame([], "cluster long, node long, num int, den int")).collect() == []


@pytest.mark.parametrize("sent", [0, 10**6])
def test_named_members_equal_their_sql(spark, monkeypatch, sent):
    monkeypatch.setattr(catalogue, "_SENT_NAMES", sent, raising=False)
    for t in ("customer", "nation"):
        duckdb.sql(f"create or replace view {t} as select * from '{SF}/{t}.parquet'")
    key = "level1_membership_region_tree"
    found = catalogue.queries()[key](spark, SF)
    assert found.dtypes == [("members", "string"), ("node", "bigint"), ("num", "bigint"), ("den", "bigint")]
    assert sorted(map(tuple, found.collect())) == sorted(map(tuple, duckdb.sql(catalogue.oracle_sql()[key]).fetchall()))
