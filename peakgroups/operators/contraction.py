"""Contraction of a network by shares."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.schema import WEIGHT, Network

#: Shares are thirds, halves or wholes, so products of two have denominators that divide this.
UNIT = 36


def fragment_weights(own: int, parts: int) -> tuple[Fraction, Fraction]:
    """Own weight of each fragment and the link between two of them."""
    return Fraction(own, parts * parts), Fraction(2 * own, parts * parts)


def fragment_links(net: Network, parts: DataFrame) -> DataFrame:
    """``node, part, other, weight`` (a double): links of split nodes shared equally among
    ``parts(node, k)`` fragments; for looking at, no step needs it (M18)."""
    arcs = net.arcs.join(parts, F.col("src") == F.col("node"))
    return arcs.select("node", F.explode(F.sequence(F.lit(1), F.col("k"))).alias("part"), F.col("dst").alias("other"), (F.col("weight").cast("double") / F.col("k")).alias("weight"))


def contract(net: Network, membership: DataFrame, split: bool) -> tuple[Network, int]:
    """The network between clusters, and by how much its weights are larger.

    ``membership(cluster, node, num, den)``, every node in it; shares ``num / den`` with
    ``den`` at most 3. With membership as a matrix S of shares and A the network, both
    directions of a link and twice the own weight on the diagonal, this is S'AS; it covers
    links between two split nodes as well. ``split`` says whether any share is not 1.
    """
    unit = UNIT if split else 1
    part = F.lit(unit).cast(WEIGHT)
    m = membership.select("cluster", "node", "num", "den")
    a = m.selectExpr("node as src", "cluster as ca", "num as pa", "den as da")
    b = m.selectExpr("node as dst", "cluster as cb", "num as pb", "den as db")
    share = lambda x: (x * part * F.col("pa") * F.col("pb")).cast(WEIGHT) if not split else F.round(x * part * F.col("pa") * F.col("pb") / (F.col("da") * F.col("db"))).cast(WEIGHT)
    between = net.links.join(a, "src").join(b, "dst").select("ca", "cb", share(F.col("weight")).alias("w"))
    own = net.nodes.withColumnRenamed("node", "src").join(a, "src").select("src", "self_weight", "ca", "pa", "da")
    if split:
        both = own.join(b.withColumnRenamed("dst", "src"), "src").where("ca <= cb")
        within = both.select("ca", "cb", (share(F.col("self_weight")) * F.when(F.col("ca") == F.col("cb"), 1).otherwise(2)).cast(WEIGHT).alias("w"))
    else:
        within = own.select("ca", F.col("ca").alias("cb"), F.col("self_weight").cast(WEIGHT).alias("w"))
    folded = between.union(within).groupBy(F.least("ca", "cb").alias("src"), F.greatest("ca", "cb").alias("dst")).agg(F.sum("w").cast(WEIGHT).alias("weight"))
    every = m.select(F.col("cluster").alias("node")).distinct()
    selves = folded.where("src = dst").select(F.col("src").alias("node"), F.col("weight").alias("self_weight"))
    nodes = every.join(selves, "node", "left").select("node", F.coalesce("self_weight", F.lit(0).cast(WEIGHT)).alias("self_weight"))
    return Network(folded.where("src < dst and weight <> 0"), nodes), unit


def common_factor(net: Network) -> int:
    """The largest divisor of ``UNIT`` that divides all weights."""
    divisors = [d for d in range(UNIT, 1, -1) if UNIT % d == 0]
    every = net.links.select("weight").union(net.nodes.select("self_weight"))
    left = every.agg(*[F.max(F.col("weight") % d).alias(f"d{d}") for d in divisors]).first()
    return next((d for d in divisors if left[f"d{d}"] == 0), 1)


def reduced(net: Network) -> Network:
    """The network with weights divided by :func:`common_factor`; gains compare the same."""
    d = common_factor(net)
    if d == 1:
        return net
    cut = lambda c: F.round(F.col(c) / d).cast(WEIGHT)
    return Network(net.links.withColumn("weight", cut("weight")), net.nodes.withColumn("self_weight", cut("self_weight")))


def contract_shares(net: Network, membership: DataFrame) -> tuple[Network, int]:
    """:func:`contract` for any real shares ``(cluster, node, share)``, to nine digits."""
    unit = 10**9
    m = membership.select("cluster", "node", "share")
    a, b = m.selectExpr("node as src", "cluster as ca", "share as pa"), m.selectExpr("node as dst", "cluster as cb", "share as pb")
    share = F.round(F.col("pa") * F.col("pb") * unit).cast(WEIGHT)
    between = net.links.join(a, "src").join(b, "dst").select("ca", "cb", (F.col("weight") * share).cast(WEIGHT).alias("w"))
    own = net.nodes.withColumnRenamed("node", "src").join(a, "src").join(b.withColumnRenamed("dst", "src"), "src").where("ca <= cb")
    within = own.select("ca", "cb", (F.col("self_weight") * share * F.when(F.col("ca") == F.col("cb"), 1).otherwise(2)).cast(WEIGHT).alias("w"))
    folded = between.union(within).groupBy(F.least("ca", "cb").alias("src"), F.greatest("ca", "cb").alias("dst")).agg(F.sum("w").cast(WEIGHT).alias("weight"))
    nodes = m.select(F.col("cluster").alias("node")).distinct().join(folded.where("src = dst").selectExpr("src as node", "weight as self_weight"), "node", "left")
    return Network(folded.where("src < dst"), nodes.select("node", F.coalesce("self_weight", F.lit(0).cast(WEIGHT)).alias("self_weight"))), unit
