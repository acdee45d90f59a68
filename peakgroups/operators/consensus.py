"""Mutual-peak consensus (M8-M11): both ends of a link see it as their best."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize
from peakgroups.operators.gains import small


def scored_arcs(scored: DataFrame) -> DataFrame:
    """``node, cand, gkey`` in both directions, without negative gains (M9)."""
    good = scored.where("gkey >= 0")
    return good.selectExpr("src as node", "dst as cand", "gkey").union(good.selectExpr("dst as node", "src as cand", "gkey"))


def peak_gains(scored: DataFrame) -> DataFrame:
    """``node, peak``: the largest non-negative gain of each node that has one (M8)."""
    return scored_arcs(scored).groupBy("node").agg(F.max("gkey").alias("peak"))


def preselect(scored: DataFrame, approx_eps: float = 0.0) -> DataFrame:
    """Neighbours that reach the node's peak, ties kept; with ``approx_eps`` also those
    within that share below it (M32)."""
    reach = F.col("gkey") == F.col("peak") if not approx_eps else F.col("gkey") >= F.col("peak") * F.lit(1 - approx_eps)
    return scored_arcs(scored).join(peak_gains(scored), "node").where(reach).select("node", "cand", "gkey")


def mutual_candidates(pre: DataFrame) -> DataFrame:
    """``node, cand, gkey`` of the links that both ends preselect (M10): an unordered pair
    counted twice, one shuffle."""
    pairs = pre.groupBy(F.least("node", "cand").alias("a"), F.greatest("node", "cand").alias("b")).agg(F.count(F.lit(1)).alias("n"), F.max("gkey").alias("gkey")).where("n = 2")
    return pairs.selectExpr("a as node", "b as cand", "gkey").union(pairs.selectExpr("b as node", "a as cand", "gkey"))


def mutual_peaks(scored: DataFrame, approx_eps: float = 0.0, by_node: DataFrame | None = None) -> DataFrame:
    """What :func:`mutual_candidates` keeps of :func:`preselect`, without a shuffle of links:
    a link is kept if its gain reaches the peaks of both its ends, one row a node.
    ``by_node`` are the scores in both directions, dealt by ``src``, where there are some."""
    best = peak_gains(scored) if by_node is None else by_node.where("gkey >= 0").groupBy(F.col("src").alias("node")).agg(F.max("gkey").alias("peak"))
    peaks = small(materialize(best, "peaks"))
    reach = lambda c: F.col("gkey") == F.col(c) if not approx_eps else F.col("gkey") >= F.col(c) * F.lit(1 - approx_eps)
    good = scored.where("gkey >= 0").select("src", "dst", "gkey")
    ends = good.join(peaks.selectExpr("node as src", "peak as ps"), "src").where(reach("ps")).join(peaks.selectExpr("node as dst", "peak as pd"), "dst").where(reach("pd"))
    return ends.select(F.explode(F.expr("array(struct(src as node, dst as cand, gkey), struct(dst as node, src as cand, gkey))")).alias("x")).select("x.*")


def carried_nodes(nodes: DataFrame, cands: DataFrame) -> DataFrame:
    """Nodes without a mutual candidate."""
    return nodes.select("node").join(cands.select("node"), "node", "left_anti")
