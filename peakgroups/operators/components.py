"""Connected groups of a pair list (M22), by least label with pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize, release


def connected_groups(pairs: DataFrame, max_rounds: int = 200) -> DataFrame:
    """``pairs(a, b)`` -> ``(node, label)`` with the least node of each connected group.

    A round takes the least label among a node's neighbours and then follows the label's
    own label, so chains shorten geometrically. Labels are a written table after each
    step: joins on a label that a large group shares exchange both sides, and AQE splits
    them. Null ends are ignored. An empty pair list gives an empty table.
    """
    kept = pairs.select("a", "b").where("a is not null and b is not null")
    arcs = materialize(kept.union(kept.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "arcs")
    labels = materialize(arcs.groupBy(F.col("a").alias("node")).agg(F.least(F.col("node"), F.min("b")).alias("label")), "labels")
    for _ in range(max_rounds):
        near = arcs.join(labels, arcs.b == labels.node).select(F.col("a").alias("node"), "label")
        pulled = labels.union(near).groupBy("node").agg(F.min("label").alias("label"))
        hooked = materialize(pulled, "hooked")
        up = hooked.select(F.col("node").alias("label"), F.col("label").alias("top"))
        jumped = materialize(hooked.join(up, "label").select("node", F.col("top").alias("label")), "labels")
        moved = jumped.join(labels.withColumnRenamed("label", "before"), "node").where("label <> before").limit(1).count()
        release(labels)
        release(hooked)
        labels = jumped
        if not moved:
            release(arcs)
            return labels
    raise RuntimeError(f"no fixed point after {max_rounds} rounds")
