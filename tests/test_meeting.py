"""The best of each user's meetings, counted in arrays, against all of them."""

import random
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from peakgroups.operators.gains import total_weight
from peakgroups.operators.meeting import best_meetings
from peakgroups.plans.hierarchy import MutualPeakClusterer
from peakgroups.schema import Params
from peakgroups.sources.networks import window_network


@pytest.mark.parametrize(("sent", "most", "users"), [(10**6, 10**9, 12), (20, 40, 12), (10**6, 10**9, 400)])
def test_best_meetings(spark, sent, most, users):
    r = random.Random(users)
    slots = {s: set(r.sample(range(users), 2 + s % 5)) for s in range(25)}
    rows = [(s, 10**12 + u, len(us)) for s, us in slots.items() for u in us]
    met = Counter((a, b) for us in slots.values() for a in us for b in us if a != b)
    k = Counter()
    for (a, _), x in met.items():
        k[a] += x
    w = sum(met.values()) // 2
    gains = defaultdict(dict)
    for (a, b), x in met.items():
        gains[a][b] = 2 * w * x - k[a] * k[b]
    wanted = {(a + 10**12, b + 10**12, met[a, b]) for a, gs in gains.items() for b, g in gs.items() if g == max(gs.values()) >= 0}
    got = {tuple(x) for x in best_meetings(spark.createDataFrame(rows, "slot long, user long, n long"), w, sent, most).collect()}
    everything = {(a + 10**12, b + 10**12, x) for (a, b), x in met.items()}
    assert wanted and (got == wanted if sent > 20 else wanted <= got <= everything)


def test_gains_beyond_63_bits_are_left_to_links(spark):
    rows = spark.createDataFrame([(1, 1, 2), (1, 2, 2)], "slot long, user long, n long")
    assert best_meetings(rows, 2**62) is None


def test_candidates_of_a_window_network_are_those_of_all_its_links(spark):
    r = random.Random(3)
    events = [(u, 600 * r.randrange(40)) for u in range(30) for _ in range(8)] + [(None, 0)]
    df = spark.createDataFrame(events, "user_id long, t long").select("user_id", F.timestamp_seconds("t").alias("ts"))
    net = window_network(df)
    w = total_weight(net)
    rows = lambda n, p=Params(): sorted(map(tuple, MutualPeakClusterer(p).candidates(n, w).collect()))
    plain = type(net)(net.links, net.nodes, net.strengths, net.total, net.by_node)
    assert rows(net) == rows(plain) != []
    assert rows(net, Params(approx_eps=0.2)) == rows(plain, Params(approx_eps=0.2))
