"""Levels in arrays against those in Python whole numbers, and what follows a split."""

import random
from collections import defaultdict

import numpy as np
import pytest

from peakgroups.operators.components import connected_groups
from peakgroups.plans import hierarchy, workloads
from peakgroups.plans.arrays import ArrayNetwork, array_levels
from peakgroups.plans.hierarchy import MutualPeakClusterer, solve_levels
from peakgroups.schema import Params
from peakgroups.sources import networks


def draw(seed, nodes, most):
    r = random.Random(seed)
    links: dict = defaultdict(int)
    for _ in range(r.randint(1, most)):
        a, b = sorted(r.sample(range(nodes), 2))
        links[a * 7, b * 7] += r.choice((1, 1, 2))
    return dict(links), {n * 7: r.choice((0, 0, 1, 3)) for n in range(nodes)}, r


def in_arrays(links, own, p):
    column = lambda x: np.array(list(x), np.int64)
    net = ArrayNetwork.of(column(a for a, _ in links), column(b for _, b in links), column(links.values()), column(own), column(own.values()))
    steps, found = array_levels(net, 0, p, net.weight), []
    while True:
        try:
            found.append(next(steps))
        except StopIteration as end:
            return found, end.value


def test_levels_in_arrays_are_those_in_whole_numbers():
    stuck = 0
    for seed in range(300):
        links, own, r = draw(seed, 3 + seed % 20, 50)
        p = Params(use_split=r.random() < 0.5, use_narrowing=r.random() < 0.8, hub_policy=r.choice(("veto", "leaf_pull")), include_self=r.random() < 0.2, stop_on_q_drop=r.random() < 0.2)
        found, split = in_arrays(links, own, p)
        wanted = list(solve_levels(links, own, 0, p))
        stuck += bool(split)
        if split:
            wanted = wanted[: len(found)]
        assert [(level, report) for level, _, report in found] == [(level, report) for level, _, report in wanted]
        for (_, rows, _), (_, whole, _) in zip(found, wanted):
            assert sorted(zip(*(x.tolist() for x in rows))) == sorted((c, m, carried) for c, m, _, _, carried in whole)
    assert 0 < stuck < 300


@pytest.mark.parametrize("split", [True, False])
def test_a_large_network_goes_on_after_the_arrays(spark, monkeypatch, split):
    for seed in range(1000):  # a connected network in which the second level splits
        links, own, _ = draw(seed, 16, 40)
        reports = [r for _, _, r in solve_levels(links, own)]
        if len(reports) > 2 and not reports[0]["split"] and reports[1]["split"] and 20 < len(links) < 40 and len({x for ab in links for x in ab}) == 16:
            break
    p = Params(tail_links=14, use_split=split)
    net = networks.from_rows(spark, [(a, b, w) for (a, b), w in links.items()], own.items())
    taken = []
    whole = hierarchy.solve_tail
    monkeypatch.setattr(hierarchy, "solve_tail", lambda *a, **k: taken.append(k.get("whole")) or whole(*a, **k))
    h, one = (MutualPeakClusterer(x).fit(net) for x in (p, Params(use_split=split)))
    assert taken[0] is True and h.report == one.report
    flat = lambda x: sorted(map(tuple, x.flatten_levels(list(range(1, x.levels + 1)), True).collect()))
    assert flat(h) == flat(one)
    assert sorted(map(tuple, h.flatten(2).collect())) == sorted(r[1:] for r in sorted(map(tuple, one.flatten_levels([2]).selectExpr("level", "cluster", "node", "share").collect())))


def test_groups_of_one_task(spark):
    links, _, _ = draw(1, 60, 50)
    pairs = spark.createDataFrame(list(links), "a long, b long")
    assert sorted(hierarchy._held_groups(pairs).collect()) == sorted(connected_groups(pairs).collect())


def test_reorderings_of_a_network_beyond_the_tail_agree(spark, monkeypatch):
    links, own, _ = draw(2, 16, 40)
    links |= {(a, a + 7): 1 for a in range(0, 15 * 7, 7) if (a, a + 7) not in links}  # one connected group
    taken, whole = [], hierarchy.solve_tail
    monkeypatch.setattr(hierarchy, "solve_tail", lambda *a, **k: taken.append(k.get("whole")) or whole(*a, **k))
    monkeypatch.setattr(workloads, "MutualPeakClusterer", lambda: MutualPeakClusterer(Params(tail_links=14, use_split=False)))
    net = networks.from_rows(spark, [(a, b, w) for (a, b), w in links.items()], own.items())
    assert [r.value for r in workloads.run_determinism(net, "mutual_peak", 2).collect()] == [1.0, 1.0]
    assert taken == [True, True]
