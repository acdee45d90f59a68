"""Networks of the tables: plans that keep little on disk, against the SQL they stand for."""

import re

import duckdb
import pytest

from peakgroups.operators.consensus import mutual_candidates, mutual_peaks, preselect
from peakgroups.operators.gains import modularity_gain
from peakgroups.sources import networks


def _documents():
    line = "a b c d e"
    rows = [(i, f"{line} n{i} m{i}") for i in range(20)]  # 20 documents: still linked
    rows += [(100 + i, f"q r s t{i}") for i in range(21)]  # 21: too many
    rows += [(200, "x y z x y z"), (200, "x y z"), (201, "X  y\tz"), (None, "x y z"), (202, "\nx y z "), (203, None), (204, ""), (205, "x y")]
    return rows + [(None, "u v w"), (300, "u v w"), (301, "u v w"), (302, "k l m"), (302, "k l m")]


@pytest.mark.parametrize("least", [1, 2, 3])
@pytest.mark.parametrize("slices", [1, 3])
def test_document_links_equal_their_sql(spark, least, slices):
    docs = spark.createDataFrame(_documents(), "doc_id long, text string")
    found = sorted(map(tuple, networks.doc_links(docs, least, slices).collect()))
    con = duckdb.connect()
    con.execute("create table documents (doc_id bigint, text varchar)")
    con.executemany("insert into documents values (?, ?)", _documents())
    query, shingles = networks.doc_network_sql(least, "duckdb")
    _, ctes = networks.network_sql("doc_shingles", "duckdb")
    wanted = con.execute(f"with {', '.join(ctes)} {query}").fetchall()
    assert wanted and found == sorted(wanted)


def test_one_shuffle_of_shingles_without_their_text(spark):
    docs = spark.createDataFrame(_documents(), "doc_id long, text string")
    plan = networks._slice_pairs(docs, 0, 2)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1


def test_a_slice_holds_a_quarter_of_the_shingles_and_splits_texts_once(spark, monkeypatch):
    docs = spark.createDataFrame(_documents(), "doc_id long, text string")
    seen, pairs = [], networks._slice_pairs
    monkeypatch.setattr(networks, "_slice_pairs", lambda docs, part, slices: (seen.append((part, slices)), pairs(docs, part, slices))[1])
    assert networks.doc_links(docs, 1).count() and seen == [(k, 4) for k in range(4)]
    assert pairs(docs, 0, 4)._jdf.queryExecution().optimizedPlan().toString().count("split(") == 1


@pytest.mark.parametrize("eps", [0.0, 0.3])
def test_peaks_of_both_ends_are_the_mutual_candidates(spark, eps):
    net = networks.from_rows(spark, [(a, b, 1 + (a * b) % 3) for a in range(12) for b in range(a + 1, 12) if (a + b) % 3], [(0, 2)])
    scored = modularity_gain(net)
    old, new = (sorted(map(tuple, x.select("node", "cand", "gkey").collect())) for x in (mutual_candidates(preselect(scored, eps)), mutual_peaks(scored, eps)))
    assert old and old == new


@pytest.mark.parametrize("sent", [7, 1000])
def test_meetings_are_counted_where_they_are_made(spark, sent):
    from peakgroups.operators.meeting import meeting_links

    rows = [(s, u) for s in range(9) for u in range(12) if (s * 7 + u * u) % 5 < 2] + [(3, 5), (3, 5), (None, 1), (2, None)]
    df = spark.createDataFrame(rows, "slot long, user long")
    wanted: dict = {}
    for s, u in rows:
        for t, v in rows:
            if s == t and None not in (s, u, v) and u != v:
                wanted[u, v] = wanted.get((u, v), 0) + 1
    both = meeting_links(df, both=True, sent=sent)
    assert {(r.src, r.dst): r.weight for r in both.collect()} == wanted
    links = meeting_links(df, sent=sent)
    assert {(r.src, r.dst): r.weight for r in links.collect()} == {k: n for k, n in wanted.items() if k[0] < k[1]}
    plan = links._jdf.queryExecution().executedPlan().toString()
    assert "HashAggregate(keys=[src#" in plan and not re.search(r"hashpartitioning\(src#\w+, dst", plan)
