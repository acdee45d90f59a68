"""Perturbed, reordered and planted networks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from peakgroups.functions.storage import materialize
from peakgroups.schema import WEIGHT, Network
from peakgroups.sources.networks import load_network


def perturb_links(net: Network, fraction: float, seed: int = 0, basis: str = "links") -> Network:
    """Without a share of its links, each node keeping one.

    Links go in order of a hash that is the same for every fraction, so a series is nested;
    each node's last link in that order is protected. ``basis="arcs"`` takes the share of
    twice as many (P11). The quota is met by hash order up to protection.
    """
    h = F.xxhash64(F.lit(seed), "src", "dst")
    links = net.links.withColumn("h", h)
    ends = links.select(F.explode(F.array("src", "dst")).alias("node"), "h")
    kept = materialize(ends.groupBy("node").agg(F.max("h").alias("h")).select("h").distinct(), "protected")
    count = net.links.count()
    quota = int(round(fraction * count * (2 if basis == "arcs" else 1)))
    free = materialize(links.join(kept, "h", "left_anti").select("src", "dst", "h"), "free")
    # The quota-th hash: a threshold found by counts in ever smaller ranges, no global sort.
    low, high, need = -(2**63), 2**63 - 1, min(quota, free.count())
    while need and low < high:
        step = max(1, (high - low) // 1024 + 1)
        bucket = F.floor((F.col("h").cast(WEIGHT) - F.lit(low).cast(WEIGHT)) / step).cast("long")
        seen = free.where((F.col("h") >= low) & (F.col("h") <= high)).groupBy(bucket.alias("b")).count().collect()  # 1,024 rows at most
        for r in sorted(seen, key=lambda r: r.b):
            if need <= r["count"]:
                low, high = low + r.b * step, min(high, low + (r.b + 1) * step - 1)
                break
            need -= r["count"]
        if step == 1:
            break
    gone = free.where(F.col("h") <= high).select("src", "dst") if quota else free.where("false").select("src", "dst")
    return Network(net.links.join(gone, ["src", "dst"], "left_anti"), net.nodes)


def shuffle_network(net: Network, seed: int) -> tuple[Network, DataFrame]:
    """The same network under other ids and in another order, with ``node, new_node``."""
    names = net.nodes.select("node").withColumn("h", F.xxhash64(F.lit(seed), "node"))
    ids = materialize(names.select("node", F.col("h").alias("new_node")), "map")
    a, b = ids.selectExpr("node as src", "new_node as a"), ids.selectExpr("node as dst", "new_node as b")
    links = net.links.join(a, "src").join(b, "dst").select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), "weight")
    nodes = net.nodes.join(ids, "node").selectExpr("new_node as node", "self_weight")
    return Network(links.repartition(8, F.xxhash64("src", "dst", F.lit(seed))), nodes.repartition(8, F.xxhash64("node", F.lit(seed)))), ids


def planted_network(spark: SparkSession, n: int, mean_degree: float = 20, max_degree: int = 70, mu: float = 0.275, tau1: float = 2.0, tau2: float = 1.0, min_size: int = 20, max_size: int = 100, overlap_nodes: float = 0.1, overlap_memberships: int = 2, seed: int = 0) -> tuple[Network, DataFrame]:
    """A network with planted overlapping groups, and the groups ``(cluster, node)``.

    Degrees and group sizes follow truncated power laws of hash values; nodes fill group
    slots in hash order; of a node's stubs a share ``1 - mu`` is paired within its groups
    and the rest anywhere. Loops and repeats are dropped. Everything comes from hashes.
    """

    def uniform(*columns):
        return (F.pmod(F.xxhash64(F.lit(seed), *columns), F.lit(2**40)) + 0.5) / float(2**40)

    def power(u, low, high, tau):
        if abs(tau - 1) < 1e-9:
            return F.lit(low) * F.pow(F.lit(high / low), u)
        p = 1 - tau
        return F.pow(F.lit(low**p) + u * F.lit(high**p - low**p), F.lit(1 / p))

    def mean_of(low):
        import math

        return math.log(max_degree / low) / (1 / low - 1 / max_degree) if tau1 == 2 else (low + max_degree) / 2

    low, high = 1.0, float(mean_degree)
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if mean_of(mid) < mean_degree else (low, mid)
    nodes = spark.range(n).withColumnRenamed("id", "node").withColumn("degree", F.round(power(uniform("node", F.lit("d")), low, float(max_degree), tau1)).cast("int"))
    nodes = nodes.withColumn("m", F.when(uniform("node", F.lit("o")) < overlap_nodes, overlap_memberships).otherwise(1))
    nodes = materialize(nodes, "planted-nodes")
    slots = nodes.select("node", F.posexplode(F.sequence(F.lit(1), "m")).alias("slot", "x"), "m", "degree").drop("x")
    total = slots.count()
    import random

    rng, sizes = random.Random(seed), []
    while sum(sizes) < total:
        u = rng.random()
        sizes.append(round(min_size * (max_size / min_size) ** u) if abs(tau2 - 1) < 1e-9 else round((min_size ** (1 - tau2) + u * (max_size ** (1 - tau2) - min_size ** (1 - tau2))) ** (1 / (1 - tau2))))
    starts, at = [], 0
    for i, s in enumerate(sizes):
        starts.append((i, at, at + s))
        at += s
    groups = F.broadcast(spark.createDataFrame(starts, "cluster long, first long, stop long"))
    # Rank of slots by hash: ranges of the hash first, then within a range.
    parts = 64
    h = slots.withColumn("h", F.xxhash64(F.lit(seed), "node", "slot", F.lit("s"))).withColumn("part", F.pmod(F.shiftright("h", 20), F.lit(parts)))
    counts = {r.part: r["count"] for r in h.groupBy("part").count().collect()}
    offsets, at = [], 0
    for p in range(parts):
        offsets.append(at)
        at += counts.get(p, 0)
    base = F.get(F.array(*[F.lit(x) for x in offsets]), F.col("part").cast("int"))
    ranked = h.withColumn("rank", base + F.row_number().over(Window.partitionBy("part").orderBy("h", "node", "slot")) - 1)
    member = materialize(ranked.join(groups, (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("stop"))).select("cluster", "node", "degree", "m").dropDuplicates(["cluster", "node"]), "planted-members")
    inside = member.withColumn("stubs", F.round(F.col("degree") * (1 - mu) / F.col("m")).cast("int")).select("cluster", "node", "stubs")
    outside = nodes.select(F.lit(-1).cast("long").alias("cluster"), "node", F.round(F.col("degree") * mu).cast("int").alias("stubs"))
    outside = outside.withColumn("cluster", -1 - F.pmod(F.xxhash64(F.lit(seed), "node", F.lit("p")), F.lit(max(1, n // 2000))))

    def pair(stubs):
        s = stubs.where("stubs > 0").select("cluster", "node", F.explode(F.sequence(F.lit(1), "stubs")).alias("i"))
        s = s.withColumn("r", F.row_number().over(Window.partitionBy("cluster").orderBy(F.xxhash64(F.lit(seed), "node", "i", F.lit("w")), "node", "i")) - 1)
        a, b = s.where("r % 2 = 0").selectExpr("cluster", "node as src", "r"), s.where("r % 2 = 1").selectExpr("cluster", "node as dst", "r - 1 as r")
        return a.join(b, ["cluster", "r"]).where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()

    links = pair(inside).union(pair(outside)).distinct().withColumn("weight", F.lit(1))
    alone = nodes.select("node", F.lit(0).alias("self_weight"))
    net = load_network(links, node_weights=alone)
    return Network(materialize(net.links, "planted"), materialize(net.nodes, "planted")), member.select("cluster", "node")
