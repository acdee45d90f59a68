"""Re-created baselines on shared neighbours: pruned structural clustering (B6), clique
percolation (B1) and triangle communities (B10). All from published descriptions."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize
from peakgroups.operators.components import connected_groups
from peakgroups.operators.gains import degrees
from peakgroups.schema import Network


def oriented(net: Network) -> DataFrame:
    """``a, b``: links from the end with the lower (degree, id), so that hubs start few."""
    d = degrees(net)
    l = net.links.join(d.selectExpr("node as src", "d as ds"), "src").join(d.selectExpr("node as dst", "d as dd"), "dst")
    up = (F.col("ds") < F.col("dd")) | ((F.col("ds") == F.col("dd")) & (F.col("src") < F.col("dst")))
    return l.select(F.when(up, F.col("src")).otherwise(F.col("dst")).alias("a"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("b"))


def triangles(net: Network) -> DataFrame:
    """``a, b, c``: every triangle once."""
    o = materialize(oriented(net), "oriented")
    wedge = o.join(o.selectExpr("a", "b as c"), "a").where("b <> c")
    return wedge.join(o.selectExpr("a as b", "b as c"), ["b", "c"]).select("a", "b", "c")


def structural_similarity(net: Network, eps: Fraction | None = None) -> DataFrame:
    """``src, dst, common, du, dv``: common closed neighbours and closed degrees of links.

    With ``eps``, links whose degrees alone rule the similarity out are dropped before any
    neighbour is met.
    """
    d = degrees(net).selectExpr("node", "cast(d + 1 as long) as d")
    l = net.links.join(d.selectExpr("node as src", "d as du"), "src").join(d.selectExpr("node as dst", "d as dv"), "dst").select("src", "dst", "du", "dv")
    if eps is not None:
        l = l.where(F.least("du", "dv") * eps.denominator**2 >= F.greatest("du", "dv") * eps.numerator**2)
    a, b = net.arcs.selectExpr("src", "dst as x"), net.arcs.selectExpr("src as dst", "dst as x")
    shared = l.join(a, "src").join(b, ["dst", "x"]).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
    return l.join(shared, ["src", "dst"], "left").select("src", "dst", (F.coalesce("n", F.lit(0)) + 2).alias("common"), "du", "dv")


def structural_clusters(net: Network, eps: Fraction = Fraction(1, 2), mu: int = 3) -> DataFrame:
    """``cluster, node`` (B6): groups of cores with their border nodes, which may overlap.

    Similarity is compared as whole numbers: common**2 / (du * dv) >= eps**2.
    """
    s = structural_similarity(net, eps).where(F.col("common") * F.col("common") * eps.denominator**2 >= F.col("du") * F.col("dv") * eps.numerator**2)
    s = materialize(s.select("src", "dst"), "similar")
    both = s.union(s.selectExpr("dst", "src"))
    cores = materialize(both.groupBy(F.col("src").alias("node")).agg((F.count(F.lit(1)) + 1).alias("n")).where(F.col("n") >= mu).select("node"), "cores")
    core_links = s.join(cores.selectExpr("node as src"), "src").join(cores.selectExpr("node as dst"), "dst").selectExpr("src as a", "dst as b")
    groups = connected_groups(core_links.union(cores.selectExpr("node as a", "node as b")))
    border = both.join(cores.selectExpr("node as src"), "src").join(cores.selectExpr("node as dst"), "dst", "left_anti")
    edge = border.join(groups.selectExpr("node as src", "label"), "src").selectExpr("label as cluster", "dst as node").distinct()
    return groups.selectExpr("label as cluster", "node").union(edge)


def cliques(net: Network, k: int, min_intensity: float | None = None) -> DataFrame:
    """``members``: sorted arrays of every clique of ``k`` nodes, grown a node at a time.

    ``min_intensity`` keeps cliques whose links' geometric mean weight reaches it.
    """
    o = materialize(oriented(net), "oriented")
    found = o.select(F.array("a", "b").alias("m"))
    for _ in range(k - 2):
        grown = found.select("m", F.element_at("m", -1).alias("a")).join(o, "a").select("m", F.col("b").alias("x"))
        links = net.arcs.selectExpr("src as y", "dst as x")
        each = grown.select("m", "x", F.explode(F.expr("slice(m, 1, size(m) - 1)")).alias("y")).join(links, ["x", "y"])
        closed = each.groupBy("m", "x").agg(F.count(F.lit(1)).alias("n")).where("n = size(m) - 1")
        found = materialize(closed.select(F.concat("m", F.array("x")).alias("m")), "cliques")
    out = found.select(F.array_sort("m").alias("members"))
    if min_intensity is None:
        return out
    pairs = out.select("members", F.explode("members").alias("src")).select("members", "src", F.explode("members").alias("dst")).where("src < dst")
    mean = pairs.join(net.links, ["src", "dst"]).groupBy("members").agg(F.exp(F.avg(F.log(F.col("weight").cast("double")))).alias("w"))
    return mean.where(F.col("w") >= min_intensity).select("members")


def clique_percolation(net: Network, k: int = 3, min_intensity: float | None = None) -> DataFrame:
    """``cluster, node`` (B1): unions of ``k``-cliques that share ``k - 1`` nodes."""
    c = materialize(cliques(net, k, min_intensity), "cliques").select("members", F.array_join("members", ",").alias("id"))
    keys = c.select("id", F.explode(F.expr("transform(members, (x, i) -> array_join(array_remove(members, x), ','))")).alias("face"))
    groups = connected_groups(keys.select(F.concat(F.lit("c"), "id").alias("a"), F.concat(F.lit("f"), "face").alias("b")))
    named = groups.where(F.startswith("node", F.lit("c"))).select(F.expr("substring(node, 2)").alias("id"), "label")
    cover = c.join(named, "id").select("label", F.explode("members").alias("node")).distinct()
    return cover.select(F.xxhash64("label").alias("cluster"), "node")


def local_clustering(net: Network) -> DataFrame:
    """``node, t, d``: triangles and degree of each node with neighbours."""
    t = triangles(net).select(F.explode(F.array("a", "b", "c")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("t"))
    return degrees(net).join(t, "node", "left").select("node", F.coalesce("t", F.lit(0)).alias("t"), "d")


def triangle_communities(net: Network, rounds: int = 4) -> DataFrame:
    """``cluster, node`` (B10), disjoint. Each node starts with its neighbour of the highest
    clustering coefficient, then moves to the group with most of its triangles."""
    cc = materialize(local_clustering(net).select("node", F.when(F.col("d") > 1, 2 * F.col("t") / (F.col("d") * (F.col("d") - 1))).otherwise(0.0).alias("cc")), "cc")
    seen = net.arcs.join(cc.selectExpr("node as dst", "cc"), "dst").selectExpr("src as node", "dst as head", "cc").union(cc.selectExpr("node", "node as head", "cc"))
    head = seen.groupBy("node").agg(F.max(F.struct("cc", (-F.col("head")).alias("h"))).alias("x")).selectExpr("node", "-x.h as cluster")
    state = materialize(head, "heads")
    tri = materialize(triangles(net), "triangles")
    corners = tri.selectExpr("a as node", "b as x", "c as y").union(tri.selectExpr("b as node", "a as x", "c as y")).union(tri.selectExpr("c as node", "a as x", "b as y"))
    for step in range(rounds):
        sx, sy = state.selectExpr("node as x", "cluster as cx"), state.selectExpr("node as y", "cluster as cy")
        votes = corners.join(sx, "x").join(sy, "y").where("cx = cy").groupBy("node", F.col("cx").alias("c")).agg(F.count(F.lit(1)).alias("n"))
        pick = votes.groupBy("node").agg(F.max(F.struct("n", (-F.col("c")).alias("c"))).alias("v")).selectExpr("node", "-v.c as better")
        turn = F.pmod(F.xxhash64("node"), F.lit(2)) == step % 2  # half of the nodes at a time
        state = materialize(state.join(pick, "node", "left").select("node", F.when(turn & F.col("better").isNotNull(), F.col("better")).otherwise(F.col("cluster")).alias("cluster")), "heads")
    return state.select("cluster", "node")
