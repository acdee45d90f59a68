"""Strengths, gains and modularity (M2-M7)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize
from peakgroups.schema import WEIGHT, Network

#: Nodes of a table that executors hold whole.
SENT_NODES = 1_500_000


def dec(column) -> F.Column:
    return (F.col(column) if isinstance(column, str) else column).cast(WEIGHT)


def node_strengths(net: Network) -> DataFrame:
    """``node, k``: twice the own weight and the weights of all links (M2)."""
    if net.strengths is not None:
        return net.strengths
    own = net.nodes.select("node", (F.col("self_weight") * 2).cast(WEIGHT).alias("k"))
    return own.union(net.arcs.select(F.col("src"), F.col("weight"))).groupBy("node").agg(F.sum("k").cast(WEIGHT).alias("k"))


def total_weight(net: Network) -> int:
    """Own weights and links, each once."""
    if net.total is not None:
        return net.total
    s = net.nodes.agg(F.sum("self_weight")).first()[0] or 0
    return int(s) + int(net.links.agg(F.sum("weight")).first()[0] or 0)


def degrees(net: Network) -> DataFrame:
    """``node, d``: distinct neighbours without itself (P10)."""
    return net.arcs.groupBy(F.col("src").alias("node")).agg(F.count(F.lit(1)).cast("int").alias("d"))


def small(nodes: DataFrame) -> DataFrame:
    """A written table of nodes, sent to all executors if it has :data:`SENT_NODES` or fewer,
    so that joins with it shuffle no links. The results are the same either way."""
    return F.broadcast(nodes) if nodes.limit(SENT_NODES + 1).count() <= SENT_NODES else nodes


def with_strengths(net: Network, strengths: DataFrame | None = None) -> DataFrame:
    """Links with both ends' strengths, ``src, dst, weight, ks, kd``."""
    k = small(materialize(node_strengths(net), "strengths") if strengths is None else strengths)
    a, b = k.select(F.col("node").alias("src"), F.col("k").alias("ks")), k.select(F.col("node").alias("dst"), F.col("k").alias("kd"))
    return net.links.join(a, "src").join(b, "dst").select("src", "dst", "weight", "ks", "kd")


def _modularity_key(w: int):
    return (dec("weight") * F.lit(2 * w).cast(WEIGHT)).cast(WEIGHT) - (dec("ks") * dec("kd")).cast(WEIGHT)


def _conductance_key(w: int):
    """Whole part of 10**9 / conductance of the pair, from 0; no rounding differs between runs."""
    vol = F.col("ks") + F.col("kd")
    cut = vol - 2 * F.col("weight")
    low = F.least(vol, F.lit(2 * w).cast(WEIGHT) - vol)
    return F.when(low <= 0, F.lit(0)).otherwise(F.floor(low * 1_000_000_000 / F.greatest(cut, F.lit(1)))).cast(WEIGHT)


#: Score of a pair, an exact key from ``weight, ks, kd`` and the total weight (M7).
GAINS: dict[str, Callable] = {"modularity": _modularity_key, "inverse_conductance": _conductance_key}


def register_gain(name: str, key: Callable) -> None:
    """Add a score. ``key(w)`` gives a Column over ``weight, ks, kd``; it has to be the same
    for either order of the ends and bounded where it is not negative."""
    GAINS[name] = key


def gain_is_symmetric(spark, name: str, w: int = 100) -> bool:
    """Whether a registered score is the same with its ends changed over, on a small grid."""
    grid = spark.range(1, 8).crossJoin(spark.range(1, 8).withColumnRenamed("id", "o")).crossJoin(spark.range(0, 4).withColumnRenamed("id", "l"))
    there = grid.select(dec("id").alias("ks"), dec("o").alias("kd"), dec("l").alias("weight"))
    both = there.withColumn("x", GAINS[name](w)).selectExpr("kd as ks", "ks as kd", "weight", "x").withColumn("y", GAINS[name](w))
    return both.where("not (x <=> y)").limit(1).count() == 0


def modularity_gain(net: Network, gain: str = "modularity", strengths: DataFrame | None = None, w: int | None = None) -> DataFrame:
    """``src, dst, weight, gkey``: gain of joining the ends of each link, times ``2 w**2``
    and thus a whole number (M6)."""
    w = total_weight(net) if w is None else w
    return with_strengths(net, strengths).select("src", "dst", "weight", GAINS[gain](w).cast(WEIGHT).alias("gkey"))


def modularity(net: Network, membership: DataFrame | None = None, mode: str = "belonging") -> float:
    """Modularity of ``membership(cluster, node, share)``; every node alone if None.

    ``belonging`` (M4): shares enter through the contracted network; equals the plain
    measure (M3) on disjoint covers. ``similarity`` (M5): two nodes count as together by
    the sum of their products of shares; meets every pair of a cluster, for small covers.
    """
    if mode == "similarity":
        return _similarity_modularity(net, membership)
    from peakgroups.operators.contraction import contract_shares

    net = net if membership is None else contract_shares(net, membership)[0]
    w = total_weight(net)
    if not w:
        return 0.0
    inside = int(net.nodes.agg(F.sum("self_weight")).first()[0] or 0)
    squares = int(node_strengths(net).agg(F.sum((F.col("k") * F.col("k")).cast(WEIGHT))).first()[0] or 0)
    return (4 * w * inside - squares) / (4 * w * w)


def _similarity_modularity(net: Network, membership: DataFrame) -> float:
    w = total_weight(net)
    m = membership.select("cluster", "node", "share")
    k = node_strengths(net).join(m, "node").select("cluster", "node", "share", F.col("k").cast("double").alias("k"))
    vol = k.groupBy("cluster").agg(F.sum(F.col("k") * F.col("share")).alias("v")).agg(F.sum(F.col("v") * F.col("v"))).first()[0] or 0.0
    a, b = m.selectExpr("cluster", "node as src", "share as p"), m.selectExpr("cluster as other", "node as dst", "share as q")
    inner = net.links.join(a, "src").join(b, "dst").where("cluster = other").agg(F.sum(F.col("weight").cast("double") * F.col("p") * F.col("q"))).first()[0] or 0.0
    own = net.nodes.join(m, "node").agg(F.sum(F.col("self_weight").cast("double") * F.col("share") * F.col("share"))).first()[0] or 0.0
    return (inner + own) / w - vol / (4 * w * w)
