"""Re-created baselines by modularity moves: Louvain (B2), consensus over it (B3, B13),
randomised greedy (B9) and its core-group ensembles (B7, B8)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize
from peakgroups.operators.components import connected_groups
from peakgroups.operators.contraction import contract
from peakgroups.operators.gains import modularity, node_strengths, total_weight, with_strengths
from peakgroups.schema import WEIGHT, Network


def _sweep(net: Network, w: int, seed: int, max_pass: int) -> DataFrame:
    """``node, group`` after moves of one hash half of the nodes at a time."""
    k = materialize(node_strengths(net), "strengths")
    state = materialize(net.nodes.select("node", F.col("node").alias("group")), "state")
    idle = 0
    for step in range(2 * max_pass):
        vol = state.join(k, "node").groupBy("group").agg(F.sum("k").cast(WEIGHT).alias("vol"))
        to = net.arcs.join(state.selectExpr("node as dst", "group"), "dst").groupBy(F.col("src").alias("node"), "group").agg(F.sum("weight").cast(WEIGHT).alias("l"))
        own = state.selectExpr("node", "group as home", "group").withColumn("l", F.lit(0).cast(WEIGHT))
        reach = to.join(state.selectExpr("node", "group as home"), "node").select("node", "home", "group", "l").union(own.select("node", "home", "group", "l"))
        reach = reach.groupBy("node", "home", "group").agg(F.sum("l").cast(WEIGHT).alias("l")).join(vol, "group").join(k, "node")
        others = F.col("vol") - F.when(F.col("group") == F.col("home"), F.col("k")).otherwise(F.lit(0).cast(WEIGHT))
        gain = (F.lit(2 * w).cast(WEIGHT) * F.col("l")).cast(WEIGHT) - (F.col("k") * others).cast(WEIGHT)
        best = reach.withColumn("g", gain).groupBy("node", "home").agg(F.max(F.struct("g", (F.col("group") == F.col("home")).alias("stay"), (-F.col("group")).alias("c"))).alias("b"))
        turn = F.pmod(F.xxhash64(F.lit(seed), "node"), F.lit(2)) == step % 2
        moved = materialize(best.select("node", F.when(turn, -F.col("b.c")).otherwise(F.col("home")).alias("group"), "home"), "state")
        state = moved.select("node", "group")
        idle = 0 if moved.where("group <> home").limit(1).count() else idle + 1
        if idle == 2:
            break
    return state


def louvain(net: Network, seed: int = 0, max_pass: int = 4, max_levels: int = 10) -> list[DataFrame]:
    """Levels ``cluster, node`` from fine to coarse (B2); disjoint."""
    levels: list[DataFrame] = []
    top, q = None, modularity(net)
    while len(levels) < max_levels:
        w = total_weight(net)
        if not w:
            break
        state = _sweep(net, w, seed + len(levels), max_pass)
        members = state.select(F.col("group").alias("cluster"), "node", F.lit(1).alias("num"), F.lit(1).alias("den"))
        nxt, _ = contract(net, members, False)
        nxt = Network(materialize(nxt.links, "links"), materialize(nxt.nodes, "nodes"))
        better = modularity(nxt)
        if better <= q + 1e-6:
            break
        flat = state.selectExpr("group as cluster", "node")
        top = flat if top is None else top.selectExpr("cluster as c", "node as n").join(flat, F.col("c") == F.col("node")).select("cluster", F.col("n").alias("node"))
        top = materialize(top, "louvain")
        levels.append(top)
        net, q = nxt, better
    return levels or [net.nodes.selectExpr("node as cluster", "node")]


def ensemble_consensus(net: Network, runs: list[DataFrame], tau: float) -> DataFrame:
    """``src, dst, share`` of the links whose ends are together in ``tau`` of the runs."""
    votes = None
    for r in runs:
        a, b = r.selectExpr("node as src", "cluster as ca"), r.selectExpr("node as dst", "cluster as cb")
        v = net.links.join(a, "src").join(b, "dst").where("ca = cb").select("src", "dst")
        votes = v if votes is None else votes.union(v)
    return votes.groupBy("src", "dst").agg((F.count(F.lit(1)) / len(runs)).alias("share")).where(F.col("share") >= tau)


def fast_consensus(net: Network, n_p: int = 5, tau: float = 0.5, seed: int = 0, rounds: int = 3) -> DataFrame:
    """``cluster, node`` (B3): link weights become the share of seeded runs that keep their
    ends together; nodes that lose all links keep their heaviest; until runs agree."""
    at = net
    for r in range(rounds):
        runs = [louvain(at, seed + 101 * r + i)[-1] for i in range(n_p)]
        kept = materialize(ensemble_consensus(at, runs, tau), "consensus")
        lost = net.arcs.join(kept.select(F.explode(F.array("src", "dst")).alias("src")).distinct(), "src", "left_anti")
        best = lost.groupBy("src").agg(F.max(F.struct("weight", (-F.col("dst")).alias("d"))).alias("b")).selectExpr("src", "-b.d as dst")
        back = best.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), F.lit(1.0 / n_p).alias("share"))
        links = kept.union(back).groupBy("src", "dst").agg(F.max("share").alias("share")).select("src", "dst", F.round(F.col("share") * n_p).cast(WEIGHT).alias("weight"))
        at = Network(materialize(links, "links"), net.nodes.select("node", F.lit(0).cast(WEIGHT).alias("self_weight")))
        total, sure = kept.agg(F.count(F.lit(1)), F.count_if(F.col("share") == 1)).first()
        if not total or sure >= 0.98 * total:
            break
    groups = connected_groups(at.links.selectExpr("src as a", "dst as b"))
    return net.nodes.join(groups, "node", "left").select(F.coalesce("label", "node").alias("cluster"), "node")


def randomized_greedy(net: Network, sample: float = 0.5, seed: int = 0, rounds: int = 40) -> DataFrame:
    """``cluster, node`` (B9): in each round a hash sample of groups names its best merge;
    merges that both ends name are made, while modularity grows."""
    flat, q, idle = net.nodes.selectExpr("node as cluster", "node"), modularity(net), 0
    flat = materialize(flat, "greedy")
    for r in range(rounds):
        w = total_weight(net)
        if not w:
            break
        g = with_strengths(net).select("src", "dst", ((F.lit(2 * w).cast(WEIGHT) * F.col("weight")).cast(WEIGHT) - (F.col("ks") * F.col("kd")).cast(WEIGHT)).alias("g")).where("g > 0")
        both = g.union(g.selectExpr("dst", "src", "g")).where(F.pmod(F.xxhash64(F.lit(seed), F.lit(r), "src"), F.lit(1000)) < int(sample * 1000))
        best = both.groupBy("src").agg(F.max(F.struct("g", F.xxhash64(F.lit(seed), F.least("src", "dst"), F.greatest("src", "dst")).alias("h"), "dst")).alias("b")).selectExpr("src", "b.dst as dst")
        best = materialize(best, "best")
        pairs = best.join(best.selectExpr("dst as src", "src as dst"), ["src", "dst"]).where("src < dst")
        one = net.nodes.join(pairs.selectExpr("dst as node", "src as head"), "node", "left").select(F.coalesce("head", "node").alias("cluster"), "node", F.lit(1).alias("num"), F.lit(1).alias("den"))
        one = materialize(one, "merged")
        nxt, _ = contract(net, one, False)
        nxt = Network(materialize(nxt.links, "links"), materialize(nxt.nodes, "nodes"))
        better = modularity(nxt)
        if better > q:
            flat = materialize(flat.selectExpr("cluster as c", "node as n").join(one, F.col("c") == F.col("node")).select("cluster", F.col("n").alias("node")), "greedy")
            net, q, idle = nxt, better, 0
        else:
            idle += 1
            if idle == 3:
                break
    return flat


def core_groups(net: Network, runs: int = 4, seed: int = 0, iterated: bool = False, rounds: int = 3) -> DataFrame:
    """``cluster, node`` (B7; B8 if ``iterated``): nodes that all runs put together are
    contracted, and the rest is left to a final run."""
    flat = materialize(net.nodes.selectExpr("node as cluster", "node"), "cores")
    at, q = net, None
    for r in range(rounds if iterated else 1):
        votes = None
        for i in range(runs):
            one = randomized_greedy(at, seed=seed + 31 * r + i).select("node", F.lit(i).alias("run"), "cluster")
            votes = one if votes is None else votes.union(one)
        key = votes.groupBy("node").agg(F.sort_array(F.collect_list(F.struct("run", "cluster"))).alias("v"))
        cores = key.groupBy("v").agg(F.min("node").alias("cluster")).join(key, "v").select("cluster", "node", F.lit(1).alias("num"), F.lit(1).alias("den"))
        cores = materialize(cores, "cores")
        nxt, _ = contract(at, cores, False)
        nxt = Network(materialize(nxt.links, "links"), materialize(nxt.nodes, "nodes"))
        now = modularity(nxt)
        if q is not None and now <= q:
            break
        flat = materialize(flat.selectExpr("cluster as c", "node as n").join(cores, F.col("c") == F.col("node")).select("cluster", F.col("n").alias("node")), "cores")
        at, q = nxt, now
    last = randomized_greedy(at, seed=seed + 997)
    return flat.selectExpr("cluster as c", "node as n").join(last, F.col("c") == F.col("node")).select("cluster", F.col("n").alias("node"))
