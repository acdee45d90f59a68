"""Hand networks and covers that are made of given tables."""

from collections import defaultdict

import duckdb
import pytest

from peakgroups import catalogue
from peakgroups.plans.hierarchy import solve_levels

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", catalogue.LAID)
def test_hand_network_on_each_run_of_customers(spark, name):
    links, own = catalogue.FIXTURES[name]
    size = 1 + max(x for a, b, _ in links for x in (a, b))
    keys = {r[0] for r in duckdb.sql(f"select c_custkey from '{SF}/customer.parquet'").fetchall()}
    laid, nodes = {}, defaultdict(int)
    for run in range(0, max(keys) + 1, size):
        for a, b, w in links:
            x, y = sorted((run + a, run + b))
            if x in keys and y in keys:
                laid[x, y] = w
                nodes[x] += 0
                nodes[y] += 0
        for n, w in own:
            if run + n in keys:
                nodes[run + n] += w
    net = catalogue.laid_on_customers(spark, SF, name)
    assert {(r.src, r.dst): int(r.weight) for r in net.links.collect()} == laid
    assert {r.node: int(r.self_weight) for r in net.nodes.collect()} == nodes
    wanted = [(lv, c) for lv, rows, _ in solve_levels(laid, nodes) for c in {r[0] for r in rows if not r[4]}]
    found = {(r.level, r.cluster) for r in catalogue.queries()[f"fixture_{name}"](spark, SF).collect()}
    assert found and set(wanted) <= found


def test_cover_of_documents_equals_its_sql(spark):
    duckdb.sql(f"create or replace view documents as select * from '{SF}/documents.parquet'")
    assert [tuple(r) for r in catalogue.queries()["fixture_cover_f14"](spark, SF).collect()] == duckdb.sql(catalogue.oracle_sql()["fixture_cover_f14"]).fetchall()


def test_no_query_without_a_table():
    assert "features_table" not in catalogue.queries()
