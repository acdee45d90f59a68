"""Re-created baselines: speaker-listener labels (B5), significance groups (B4, simplified),
random control (B11) and the feature table (B14)."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from peakgroups.functions.storage import materialize
from peakgroups.operators.gains import node_strengths, total_weight
from peakgroups.schema import Network


def speaker_listener(net: Network, rounds: int = 20, threshold: float = 0.1, seed: int = 0) -> DataFrame:
    """``cluster, node`` (B5), overlapping: each round a node hears a label from each
    neighbour, drawn from the speaker's memory, and keeps the heaviest."""
    memory = materialize(net.nodes.select("node", F.col("node").alias("label"), F.lit(1).alias("n")), "memory")
    for r in range(rounds):
        run = Window.partitionBy("node").orderBy("label").rowsBetween(Window.unboundedPreceding, 0)
        cum = memory.withColumn("upto", F.sum("n").over(run))
        talk = net.arcs.selectExpr("src as listener", "dst as node", "weight").withColumn("u", F.pmod(F.xxhash64(F.lit(seed), F.lit(r), "listener", "node"), F.lit(r + 1)))
        said = talk.join(cum, "node").where("upto > u and upto - n <= u").groupBy("listener", "label").agg(F.sum("weight").alias("w"))
        heard = said.groupBy("listener").agg(F.max(F.struct("w", F.xxhash64(F.lit(seed + r), "label", "listener").alias("h"), "label")).alias("b")).select(F.col("listener").alias("node"), F.col("b.label").alias("label"), F.lit(1).alias("n"))
        alone = memory.select("node").distinct().join(heard.select("node"), "node", "left_anti").select("node", F.col("node").alias("label"), F.lit(1).alias("n"))
        memory = materialize(memory.union(heard).union(alone).groupBy("node", "label").agg(F.sum("n").cast("int").alias("n")), "memory")
    return memory.where(F.col("n") >= threshold * (rounds + 1)).selectExpr("label as cluster", "node")


def significance_communities(net: Network, p: float = 0.1, seeds: DataFrame | None = None, rounds: int = 4) -> DataFrame:
    """``cluster, node`` (B4), overlapping and simplified: groups grow from nodes with their
    neighbours, and take or drop nodes by the tail of a binomial null of their links inside.

    ``seeds(cluster, node)`` are the starts; each node with its neighbours by default.
    """
    two_w = float(2 * total_weight(net)) or 1.0
    k = materialize(node_strengths(net).select("node", F.col("k").cast("double").alias("k")), "strengths")
    start = net.arcs.selectExpr("src as cluster", "dst as node").union(net.nodes.selectExpr("node as cluster", "node")) if seeds is None else seeds
    state = materialize(start.distinct(), "groups")

    def tail(batches):
        for pdf in batches:
            out = []
            for kin, kk, vol in zip(pdf["kin"], pdf["k"], pdf["vol"]):
                # Chernoff bound of the upper binomial tail: cheap, and monotone as the tail is.
                n, q, x = max(kk, 1.0), min(max(vol / two_w, 1e-12), 1 - 1e-12), kin
                f = min(x / n, 1.0)
                out.append(1.0 if f <= q else math.exp(-n * (f * math.log(f / q) + ((1 - f) * math.log((1 - f) / (1 - q)) if f < 1 else 0.0))))
            pdf["p"] = out
            yield pdf[["cluster", "node", "p"]]

    for _ in range(rounds):
        vol = state.join(k, "node").groupBy("cluster").agg(F.sum("k").alias("vol"))
        inner = net.arcs.join(state.selectExpr("cluster", "node as dst"), "dst").groupBy("cluster", F.col("src").alias("node")).agg(F.sum("weight").cast("double").alias("kin"))
        scored = inner.join(k, "node").join(vol, "cluster").select("cluster", "node", "kin", "k", "vol").mapInPandas(tail, "cluster long, node long, p double")
        kept = materialize(scored.where(F.col("p") < p).select("cluster", "node"), "groups")
        same = kept.exceptAll(state).limit(1).count() == 0 and state.exceptAll(kept).limit(1).count() == 0
        state = kept
        if same:
            break
    from peakgroups.plans.measures import dedupe_cover

    return dedupe_cover(state)


def random_communities(net: Network, truth: DataFrame, seed: int = 0) -> DataFrame:
    """``cluster, node`` (B11): groups of the truth's sizes, filled in hash order along links."""
    near = net.arcs.groupBy(F.col("src").alias("node")).agg(F.min(F.xxhash64(F.lit(seed), "dst")).alias("h"))
    order = net.nodes.join(near, "node", "left").withColumn("part", F.pmod(F.xxhash64(F.lit(seed), F.coalesce("h", "node")), F.lit(64)))
    counts = {r.part: r["count"] for r in order.groupBy("part").count().collect()}  # 64 rows at most
    offsets, at = [], 0
    for i in range(64):
        offsets.append(at)
        at += counts.get(i, 0)
    rank = F.get(F.array(*[F.lit(x) for x in offsets]), F.col("part").cast("int")) + F.row_number().over(Window.partitionBy("part").orderBy("h", "node")) - 1
    sizes = truth.groupBy("cluster").agg(F.count_distinct("node").alias("size"))
    total = Window.orderBy("cluster").rowsBetween(Window.unboundedPreceding, 0)
    slots = sizes.withColumn("stop", F.sum("size").over(total)).select("cluster", (F.col("stop") - F.col("size")).alias("first"), "stop")
    return order.withColumn("r", rank).join(slots, (F.col("r") >= F.col("first")) & (F.col("r") < F.col("stop"))).select("cluster", "node")


#: hierarchical, multi_scale, deterministic, overlapping, weighted, parameter_free, consensus
#: of each algorithm; "*" in part, "o" in theory, "!" with override: fixed values.
FEATURES = {
    "mutual_peak": "+ + + + + +! +",
    "clique_percolation": "- + + + + - -",
    "louvain": "+ + - - + + -",
    "fast_consensus": "- - - - o * +",
    "significance": "+ + - + + * +",
    "speaker_listener": "- + - + + * -",
    "structural": "- - + + - - -",
    "core_groups": "- - - - - * +",
    "core_groups_iterated": "- - - - - * +",
    "triangle": "- - - - - * -",
    "random": "- - - - + + -",
}
FEATURE_NAMES = ("hierarchical", "multi_scale", "deterministic", "overlapping", "weighted", "parameter_free", "consensus")


def algorithm_features(spark: SparkSession) -> DataFrame:
    """The feature table."""
    return spark.createDataFrame([(a, *f.split()) for a, f in FEATURES.items()], ["algo", *FEATURE_NAMES])
