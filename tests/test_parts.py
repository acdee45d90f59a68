"""Hierarchies of networks whose connected groups are taken one by one."""

import pytest

from peakgroups.catalogue import FIXTURES
from peakgroups.plans.hierarchy import MutualPeakClusterer
from peakgroups.schema import Params
from peakgroups.sources import networks


@pytest.mark.parametrize("options", [{}, {"use_split": False}])
def test_parts_give_what_the_whole_gives(spark, options):
    links, own, at = [], [], 0
    for name in ("f01", "f02", "f03", "f05", "f08", "f09", "f12", "f03"):
        here, mine = FIXTURES[name]
        links += [(a + at, b + at, w) for a, b, w in here]
        own += [(n + at, w) for n, w in mine]
        at += 1 + max(x for a, b, _ in here for x in (a, b))
    own += [(at, 3)]  # a node without links
    net = networks.from_rows(spark, links, own)
    whole, parts = (MutualPeakClusterer(Params(tail_links=t, **options)).fit(net) for t in (1000, 14))
    assert whole.report == parts.report and whole.levels > 1
    assert parts.rows.select("part").distinct().count() > 1
    rows, flat = ((lambda h: sorted(map(tuple, h.rows.drop("part").collect()))), (lambda h: sorted(map(tuple, h.flatten_levels(list(range(1, h.levels + 1)), True).collect()))))
    assert rows(whole) == rows(parts) and flat(whole) == flat(parts)
