"""From candidates to groups (M12-M16, M19-M20c, M22): decide for all nodes, then merge."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from peakgroups.functions.storage import materialize
from peakgroups.operators.components import connected_groups
from peakgroups.operators.gains import degrees, node_strengths
from peakgroups.schema import WEIGHT, Network, Params

#: (candidates, degree) that may split without adding links: fixed values.
SPLITS = ((2, 2), (2, 3), (3, 3))


def admissible_splits(upto: int) -> list[tuple[int, int]]:
    """All (k, d) with 2 <= k <= d <= upto whose fragments have no more links than before."""
    return [(k, d) for d in range(2, upto + 1) for k in range(2, d + 1) if k * (d - k) + k * (k - 1) // 2 <= d]


def split_allowed(k: F.Column, d: F.Column) -> F.Column:
    """Whether a node with ``k`` candidates and degree ``d`` may split."""
    out = F.lit(False)
    for a, b in SPLITS:
        out = out | ((k == a) & (d == b))
    return out


def tied(cands: DataFrame) -> DataFrame:
    """Candidate rows of nodes with several, with ``k`` and the peak ``g``."""
    several = cands.groupBy("node").agg(F.count(F.lit(1)).cast("int").alias("k"), F.max("gkey").alias("g")).where("k > 1")
    return cands.select("node", "cand").join(several, "node")


def gain_each(cands: DataFrame) -> DataFrame:
    """``node, gain_each``: each of K fragments gains a K-th of the same peak, so the peak."""
    return tied(cands).select("node", F.col("g").alias("gain_each")).distinct()


def gain_all(net: Network, cands: DataFrame, w: int, strengths: DataFrame | None = None) -> DataFrame:
    """``node, k, g, gain_all`` of tied nodes: the key of one group with all candidates.

    Pairs of candidates cost two sums; only links among them are met one by one.
    """
    t = tied(cands)
    k = node_strengths(net) if strengths is None else strengths
    sums = t.join(k.selectExpr("node as cand", "k as kc"), "cand").groupBy("node").agg(
        F.first("k").alias("k"), F.first("g").alias("g"), F.sum("kc").cast(WEIGHT).alias("s1"), F.sum((F.col("kc") * F.col("kc")).cast(WEIGHT)).cast(WEIGHT).alias("s2")
    )
    a, b = t.selectExpr("node", "cand as src"), t.selectExpr("node", "cand as dst")
    inner = net.links.join(a, "src").join(b, ["node", "dst"]).groupBy("node").agg(F.sum("weight").cast(WEIGHT).alias("l"))
    two_w = F.lit(2 * w).cast(WEIGHT)
    apart = F.round(((F.col("s1") * F.col("s1")).cast(WEIGHT) - F.col("s2")) / 2).cast(WEIGHT)
    key = (F.col("g") * F.col("k")).cast(WEIGHT) + (two_w * F.coalesce("l", F.lit(0).cast(WEIGHT))).cast(WEIGHT) - apart
    return sums.join(inner, "node", "left").select("node", "k", "g", key.cast(WEIGHT).alias("gain_all"))


def narrow_candidates(cands: DataFrame, nodes: DataFrame, min_fraction: float = 0.5, include_self: bool = False) -> DataFrame:
    """``node, cand`` of ``nodes``: the candidates that share the most candidates with the
    node, if that is at least ``min_fraction`` of its own (M20)."""
    t = tied(cands).join(nodes.select("node"), "node", "left_semi")
    theirs = cands.selectExpr("node as cand", "cand as common")
    mine = t.selectExpr("node", "cand as common")
    shared = t.join(theirs, "cand").join(mine, ["node", "common"]).groupBy("node", "cand").agg(F.count(F.lit(1)).alias("n"))
    counted = t.join(shared, ["node", "cand"], "left").select("node", "cand", "k", (F.coalesce("n", F.lit(0)) + F.lit(2 if include_self else 0)).alias("n"))
    best = counted.withColumn("most", F.max("n").over(Window.partitionBy("node")))
    return best.where((F.col("n") == F.col("most")) & (F.col("n") > 0) & (F.col("most") >= F.col("k") * F.lit(min_fraction))).select("node", "cand")


def decide_actions(net: Network, cands: DataFrame, w: int, params: Params = Params(), unsplit: DataFrame | None = None, strengths: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """``actions(node, action, k)`` and ``choices(node, cand)``, from one snapshot.

    ``unsplit(node)`` are nodes that may not split (the growth guard's).
    """
    k = node_strengths(net) if strengths is None else strengths
    several = gain_all(net, cands, w, k).join(degrees(net), "node")
    if params.count_split_gain:
        own = several.join(net.nodes, "node").join(k.withColumnRenamed("k", "strength"), "node")
        extra = (F.col("k") - 1) * (F.lit(4 * w).cast(WEIGHT) * F.col("self_weight") - F.col("strength") * F.col("strength"))
        several, pays = own, 2 * F.col("k") * F.col("g") - extra > 2 * F.col("k") * F.col("gain_all")
    else:
        pays = F.col("g") > F.col("gain_all")
    blocked = several.select(F.col("node").alias("b")).where("false") if unsplit is None else unsplit.select(F.col("node").alias("b"))
    several = several.join(blocked, F.col("node") == F.col("b"), "left")
    split = split_allowed(F.col("k"), F.col("d")) & pays & F.col("b").isNull() & F.lit(params.use_split)
    several = materialize(several.select("node", "k", "gain_all", split.alias("split")), "tied")
    rest = several.where("not split")
    narrow = narrow_candidates(cands, rest, params.min_fraction, params.include_self) if params.use_narrowing else cands.select("node", "cand").where("false")
    narrow = materialize(narrow, "narrow")
    named = several.join(narrow.select("node").distinct().withColumn("n", F.lit(1)), "node", "left")
    action = F.when(F.col("split"), "split").when(F.col("n").isNotNull(), "narrow").when(F.col("gain_all") >= 0, "merge_all").otherwise("carried")
    tied_actions = named.select("node", action.alias("action"), "k")
    singles = cands.groupBy("node").agg(F.count(F.lit(1)).cast("int").alias("k")).where("k = 1").select("node", F.lit("single").alias("action"), "k")
    actions = materialize(singles.union(tied_actions), "actions")
    every = actions.where("action in ('single', 'split', 'merge_all')").select("node")
    choices = cands.select("node", "cand").join(every, "node", "left_semi").union(narrow)
    return actions, choices


def union_pairs(actions: DataFrame, choices: DataFrame, hub_policy: str = "veto") -> DataFrame:
    """``a, b`` of virtual nodes to merge: both ends' choices (P17), a split node standing
    as its fragment ``node:partner`` for that partner, late-carried ends left out (P4)."""
    both = choices.select(F.least("node", "cand").alias("x"), F.greatest("node", "cand").alias("y")).distinct()
    ax, ay = actions.selectExpr("node as x", "action as ax"), actions.selectExpr("node as y", "action as ay")
    p = both.join(ax, "x").join(ay, "y")
    if hub_policy == "veto":
        p = p.where("ax <> 'carried' and ay <> 'carried'")
    fragment = lambda n, o, act: F.when(F.col(act) == "split", F.concat_ws(":", F.col(n).cast("string"), F.col(o).cast("string"))).otherwise(F.col(n).cast("string"))
    return p.select(fragment("x", "y", "ax").alias("a"), fragment("y", "x", "ay").alias("b"))


def cluster_id(level: int, label: F.Column) -> F.Column:
    """A cluster's item id: that of a whole member, else a negative hash of the fragment."""
    hashed = -(F.conv(F.substring(F.md5(F.concat(F.lit(f"{level}|"), label)), 1, 15), 16, 10).cast("long") + 1)
    return F.when(F.contains(label, F.lit(":")), hashed).otherwise(F.element_at(F.split(label, ":"), 1).cast("long"))


def memberships(pairs: DataFrame, level: int) -> DataFrame:
    """``cluster, node, num, den`` of the groups; shares of a node add up to 1."""
    groups = connected_groups(pairs)
    parts = groups.select(F.element_at(F.split("node", ":"), 1).cast("long").alias("node"), cluster_id(level, F.col("label")).alias("cluster"))
    den = parts.groupBy("node").agg(F.count(F.lit(1)).cast("int").alias("den"))
    return parts.groupBy("cluster", "node").agg(F.count(F.lit(1)).cast("int").alias("num")).join(den, "node").select("cluster", "node", "num", "den")


def growth_guard(cands: DataFrame, members: DataFrame) -> DataFrame:
    """Nodes of candidate components with more clusters than clustered nodes."""
    comp = connected_groups(cands.selectExpr("node as a", "cand as b"))
    grown = members.join(comp, "node").groupBy("label").agg(F.count_distinct("cluster").alias("c"), F.count_distinct("node").alias("n")).where("c > n")
    return comp.join(grown.select("label"), "label", "left_semi").select("node")


def form_clusters(net: Network, cands: DataFrame, w: int, level: int, params: Params = Params(), strengths: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """``actions`` and ``membership(cluster, node, num, den)`` of one level."""
    actions, choices = decide_actions(net, cands, w, params, strengths=strengths)
    members = materialize(memberships(union_pairs(actions, choices, params.hub_policy), level), "members")
    if params.growth_guard and actions.where("action = 'split'").limit(1).count():
        grown = materialize(growth_guard(cands, members), "grown")
        if grown.limit(1).count():
            actions, choices = decide_actions(net, cands, w, params, grown, strengths)
            members = materialize(memberships(union_pairs(actions, choices, params.hub_policy), level), "members")
    return actions, members
