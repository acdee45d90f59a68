"""Hand networks, both execution paths, invariants."""

from fractions import Fraction

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from peakgroups.catalogue import FIXTURES
from peakgroups.operators.contraction import fragment_weights
from peakgroups.operators.formation import SPLITS, admissible_splits
from peakgroups.operators.gains import gain_is_symmetric, modularity, total_weight
from peakgroups.plans import measures, perturb, workloads
from peakgroups.plans.hierarchy import MutualPeakClusterer, middle_level, sample_levels, solve_levels
from peakgroups.schema import Params
from peakgroups.sources import networks

#: Clusters of each level as sets of input items of that level, and modularity after it.
EXPECTED = {
    "f04": ([3], [Fraction(0)]),
    "f05": ([2, 2], [Fraction(1, 6)]),
    "f06": ([4], [Fraction(0)]),
    "f07": ([6], [Fraction(0)]),
    "f09": ([6], [Fraction(0)]),
    "f10": ([7], [Fraction(0)]),
    "f12": ([2, 2], [Fraction(3, 10)]),
}


def levels(name, **params):
    links, own = FIXTURES[name]
    nodes = {x for a, b, _ in links for x in (a, b)}
    o = dict.fromkeys(nodes, 0) | dict(own)
    return list(solve_levels({(min(a, b), max(a, b)): w for a, b, w in links}, o, 0, Params(**params)))


@pytest.mark.parametrize("name", EXPECTED)
def test_small_networks(name):
    found = levels(name)
    sizes, qs = EXPECTED[name]
    assert len(found) == len(qs)
    clusters = {}
    for c, m, _, _, carried in found[0][1]:
        if not carried:
            clusters.setdefault(c, set()).add(m)
    assert sorted(map(len, clusters.values())) == sorted(sizes)
    assert [r["q"] for _, _, r in found] == [pytest.approx(float(q)) for q in qs]


def test_split_of_the_worked_example():
    (_, rows, report), = levels("f01")
    assert sorted((m, Fraction(n, d)) for _, m, n, d, _ in rows) == [(0, 1), (1, 1), (2, Fraction(1, 3)), (2, Fraction(1, 3)), (2, Fraction(1, 3)), (3, 1)]
    assert report["q_before"] == pytest.approx(476 / 1875) and report["q"] == pytest.approx(4 / 15)
    w = workloads.worked_example()
    assert (w["cluster"], w["between_clusters"]) == (15, 10) and fragment_weights(9, 3) == (1, 2)


def test_bowtie_and_path_share_their_middle():
    for name, middle, q in (("f02", 0, 1 / 6), ("f03", 2, 1 / 4)):
        found = levels(name)
        assert len(found) == 2 and found[1][2]["q"] == pytest.approx(q)
        assert sorted((n, d) for _, m, n, d, _ in found[1][1] if m == middle) == [(1, 2), (1, 2)]


def test_two_cliques():
    assert [r["q"] for _, _, r in levels("f08")] == [pytest.approx(59 / 338), pytest.approx(11 / 26)]


def test_late_carried_hub():
    assert levels("f11") == []
    (_, rows, report), = levels("f11", hub_policy="leaf_pull")
    assert len({c for c, *_ in rows}) == 1 and report["q"] == 0 and report["q_dropped"]


def test_admissible_splits_are_all():
    assert set(admissible_splits(200)) == set(SPLITS)


@settings(max_examples=60, deadline=None)
@given(st.dictionaries(st.tuples(st.integers(0, 9), st.integers(0, 9)).filter(lambda p: p[0] < p[1]), st.integers(1, 9), min_size=1), st.integers(0, 5))
def test_shares_and_growth(links, own):
    nodes = {x for p in links for x in p}
    items = nodes
    for _, rows, report in solve_levels(links, dict.fromkeys(nodes, own)):
        shares = {}
        for _, m, n, d, _ in rows:
            shares[m] = shares.get(m, 0) + Fraction(n, d)
        assert set(shares) == items and set(shares.values()) == {1}
        assert report["clusters"] <= report["clustered"]
        items = {c for c, *_ in rows}


@settings(max_examples=40, deadline=None)
@given(st.dictionaries(st.tuples(st.integers(0, 8), st.integers(0, 8)).filter(lambda p: p[0] < p[1]), st.integers(1, 4), min_size=2), st.integers(2, 7))
def test_scaling_weights_changes_nothing(links, by):
    own = {x: 0 for p in links for x in p}
    a, b = list(solve_levels(links, own)), list(solve_levels({k: v * by for k, v in links.items()}, own))
    assert [sorted(r) for _, r, _ in a] == [sorted(r) for _, r, _ in b]


@pytest.mark.parametrize("name", ["f01", "f09"])
def test_dataframe_path_is_the_same(spark, name):
    h = MutualPeakClusterer(Params(tail_links=0)).fit(networks.from_rows(spark, *FIXTURES[name]))
    got = sorted(map(tuple, h.rows.select("level", "cluster", "member", "num", "den", "carried").collect()))
    assert got == sorted((lv, *r) for lv, rows, _ in levels(name) for r in rows)


def test_intake(spark):
    rows = [(1, 2, 2.0), (2, 1, 3.0), (1, 1, 4.0), (None, 1, 1.0), (2, 3, 0.0), (3, 4, None)]
    net = networks.load_network(spark.createDataFrame(rows, "src long, dst long, weight double"))
    assert [tuple(map(int, r)) for r in net.links.collect()] == [(1, 2, 5)]
    assert total_weight(net) == 9
    for bad in (-1.0, float("nan")):
        with pytest.raises(Exception, match="neither negative nor NaN"):
            networks.load_network(spark.createDataFrame([(1, 2, bad)], "src long, dst long, weight double")).links.collect()
    empty = networks.load_network(spark.createDataFrame([], "src long, dst long, weight double"))
    assert MutualPeakClusterer().fit(empty).levels == 0


def test_modularity_forms_agree(spark):
    net = networks.from_rows(spark, *FIXTURES["f02"])
    cover = spark.createDataFrame([(1, 0, 0.5), (1, 1, 1.0), (1, 2, 1.0), (2, 0, 0.5), (2, 3, 1.0), (2, 4, 1.0)], "cluster long, node long, share double")
    assert modularity(net, cover) == pytest.approx(1 / 6)
    assert modularity(net, cover, "similarity") == pytest.approx(1 / 6)
    assert gain_is_symmetric(spark, "modularity") and gain_is_symmetric(spark, "inverse_conductance")


def test_cover_measures(spark):
    make = lambda rows: spark.createDataFrame(rows, "cluster long, node long")
    a, b = make([(1, 1), (1, 2), (1, 3), (2, 4), (2, 5)]), make([(1, 1), (1, 2), (2, 3), (2, 4), (2, 5)])
    assert measures.f1_harmonic(a, b) == pytest.approx(0.8) and measures.f1_average(a, b) == pytest.approx(0.8)
    assert measures.f1_harmonic(a, a) == 1 and measures.nmi(a, a) == pytest.approx(1)
    assert measures.dedupe_cover(make([(1, 1), (1, 2), (7, 2), (7, 1), (3, 1)])).count() == 3


def test_level_choice():
    assert sample_levels(4) == [1, 2, 3, 4] and len(sample_levels(48)) == 10
    assert (sample_levels(48)[0], sample_levels(48)[-1], middle_level(7), middle_level(1)) == (1, 48, 3, 1)


def test_perturbation_is_nested_and_keeps_a_link(spark):
    net = networks.from_rows(spark, [(i, j, 1) for i in range(12) for j in range(i)])
    small, large = perturb.perturb_links(net, 0.1), perturb.perturb_links(net, 0.3)
    assert (small.links.count(), large.links.count()) == (66 - 7, 66 - 20)
    assert large.links.exceptAll(small.links).count() == 0
    assert perturb.perturb_links(net, 1.0).arcs.select("src").distinct().count() == 12


def test_order_does_not_matter(spark):
    workloads.assert_order_free(networks.from_rows(spark, *FIXTURES["f08"]), 2)


def test_weights_are_not_rounded_away(spark):
    rows = spark.createDataFrame([(1, 2, 0.4), (2, 3, 1.4)], "src long, dst long, weight double")
    with pytest.raises(Exception, match="not whole"):
        networks.load_network(rows).links.collect()
    assert {(r.src, r.dst, int(r.weight)) for r in networks.load_network(rows, scale=10).links.collect()} == {(1, 2, 4), (2, 3, 14)}


def test_splitting_can_be_left_out(spark):
    from peakgroups.catalogue import _hierarchy, queries

    whole, without = (sorted(map(tuple, q(spark, "").collect())) for q in (_hierarchy("f02"), queries()["hierarchy_without_split_f02"]))
    assert any(row[3] == 0.5 for row in whole) and all(row[3] == 1.0 for row in without)


def test_work_beyond_the_limit_is_cancelled(spark):
    from peakgroups.plans.workloads import ended_within

    assert ended_within(spark, lambda: spark.range(10).count(), 60)
    slow = spark.range(0, 10**12, 1, 4).selectExpr("sum(hash(id))")
    assert not ended_within(spark, slow.collect, 2)


def test_feeds_of_events_as_a_stream(spark, tmp_path):
    """Windows over a stream of files give what a batch gives, once the watermark has passed."""
    from peakgroups.streaming import feeds

    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    events.repartition(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    run = feeds.window_activity(stream).writeStream.format("memory").queryName("windows").outputMode("append").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "cp")).start()
    run.awaitTermination(120)
    got = {tuple(r) for r in spark.table("windows").collect()}
    want = {tuple(r) for r in feeds.window_activity(events).collect()}
    assert got and got <= want and len(want - got) < 0.2 * len(want)


def test_baselines_find_two_cliques(spark):
    """Baselines on two cliques of four that one link joins."""
    from peakgroups.baselines import labels, moves, structural

    net = networks.from_rows(spark, [(a, b, 1) for q in (0, 4) for a in range(q, q + 4) for b in range(a + 1, q + 4)] + [(3, 4, 1)])
    groups = lambda c: {frozenset(r.node for r in c.where(c.cluster == k).collect()) for k in {r.cluster for r in c.collect()}}
    two = {frozenset(range(4)), frozenset(range(4, 8))}
    assert groups(structural.clique_percolation(net, 3)) == two == groups(structural.clique_percolation(net, 4))
    assert groups(moves.louvain(net)[-1]) == two
    assert groups(structural.structural_clusters(net)) == two
