"""Accuracy, stability and cost measures."""

from __future__ import annotations

import resource
import time
from collections.abc import Callable

import psutil
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from peakgroups.functions.storage import materialize

METRICS = "run string, algo string, dataset string, step int, level int, metric string, value double"


def pair_f1(a: DataFrame, b: DataFrame) -> DataFrame:
    """``ca, cb, common, f1`` of clusters of two covers ``(cluster, node)`` that meet (A1).

    Counts of a pair are summed before they are shuffled, so large clusters cost no more
    than the nodes that they share.
    """
    x, y = a.select(F.col("cluster").alias("ca"), "node").distinct(), b.select(F.col("cluster").alias("cb"), "node").distinct()
    na, nb = x.groupBy("ca").agg(F.count(F.lit(1)).alias("na")), y.groupBy("cb").agg(F.count(F.lit(1)).alias("nb"))
    met = x.join(y, "node").groupBy("ca", "cb").agg(F.count(F.lit(1)).alias("common"))
    return met.join(na, "ca").join(nb, "cb").select("ca", "cb", "common", (2 * F.col("common") / (F.col("na") + F.col("nb"))).alias("f1"))


def _directed(a: DataFrame, b: DataFrame) -> tuple[float, float]:
    f1 = pair_f1(a, b)
    out = []
    for cover, key in ((a, "ca"), (b, "cb")):
        n = cover.select("cluster").distinct().count()
        best = f1.groupBy(key).agg(F.max("f1").alias("f1")).agg(F.sum("f1")).first()[0] or 0.0
        out.append(best / n if n else 0.0)
    return out[0], out[1]


def f1_average(a: DataFrame, b: DataFrame) -> float:
    """Mean of the two averages of best matches (A2)."""
    x, y = _directed(a, b)
    return (x + y) / 2


def f1_harmonic(a: DataFrame, b: DataFrame) -> float:
    """Harmonic mean of the two averages of best matches (A3)."""
    x, y = _directed(a, b)
    return 2 * x * y / (x + y) if x + y else 0.0


def nmi(a: DataFrame, b: DataFrame) -> float:
    """Normalised mutual information (by the larger entropy) of two disjoint covers (A4)."""
    x, y = a.select(F.col("cluster").alias("ca"), "node"), b.select(F.col("cluster").alias("cb"), "node")
    joint = x.join(y, "node").groupBy("ca", "cb").agg(F.count(F.lit(1)).alias("n"))
    n = joint.agg(F.sum("n")).first()[0]
    if not n:
        return 0.0
    h = lambda d: d.agg(-F.sum(F.col("n") / n * F.log2(F.col("n") / n))).first()[0]
    ha, hb = (h(joint.groupBy(c).agg(F.sum("n").alias("n"))) for c in ("ca", "cb"))
    most = max(ha, hb)
    return (ha + hb - h(joint)) / most if most else 1.0


def dedupe_cover(cover: DataFrame) -> DataFrame:
    """``cover(cluster, node)`` without clusters of exactly the same nodes (W5): the least
    cluster of each stays. A cluster's signature is two sums of hashes and a size, so none
    is gathered in one place."""
    c = cover.select("cluster", "node").distinct()
    sums = [F.sum(F.xxhash64("node", F.lit(s)).cast("decimal(38,0)")).alias(f"h{s}") for s in (1, 2)]
    sig = c.groupBy("cluster").agg(F.count(F.lit(1)).alias("n"), *sums)
    keep = sig.groupBy("n", "h1", "h2").agg(F.min("cluster").alias("cluster")).select("cluster")
    return c.join(keep, "cluster")


def best_level_score(hierarchy, truth: DataFrame, most: int = 10) -> tuple[int, float]:
    """The best F1h over up to ten evenly spaced levels, with its level."""
    from peakgroups.plans.hierarchy import sample_levels

    picked = sample_levels(hierarchy.levels, most)
    flat = materialize(hierarchy.flatten_levels(picked), "flat")
    scores = [(f1_harmonic(flat.where(F.col("level") == at), truth), -at) for at in picked]
    score, at = max(scores, default=(0.0, 0))
    return -at, score


def delta_f1h(metrics: DataFrame) -> DataFrame:
    """``f1h`` rows of a series with ``delta``, by how much they fell since the step before
    (A7); positive means that the method senses the change."""
    w = Window.partitionBy("run", "algo", "dataset").orderBy("step")
    return metrics.where("metric = 'f1h'").withColumn("delta", F.lag("value").over(w) - F.col("value"))


def surges(metrics: DataFrame, tolerance: float = 0.05) -> DataFrame:
    """:func:`delta_f1h` with ``surge``: a rise beyond the tolerance, or a jump."""
    d = delta_f1h(metrics)
    return d.withColumn("surge", F.coalesce((F.col("delta") < -tolerance) | (F.col("delta") > 4 * tolerance), F.lit(False)))


def stability_verdict(metrics: DataFrame, tolerance: float = 0.05) -> DataFrame:
    """``algo, dataset, deterministic, robust, sensitive`` (W1d). Deterministic: the runs of a
    step agree; robust: no surge; sensitive: F1h never rises from step to step."""
    spread = metrics.where("metric = 'f1h'").groupBy("algo", "dataset", "step").agg((F.max("value") - F.min("value")).alias("s"))
    same = spread.groupBy("algo", "dataset").agg((F.max("s") < 1e-12).alias("deterministic"))
    s = surges(metrics, tolerance).groupBy("algo", "dataset").agg(F.bool_and(~F.col("surge")).alias("robust"), F.bool_and(F.coalesce(F.col("delta") >= 0, F.lit(True))).alias("sensitive"))
    return same.join(s, ["algo", "dataset"])


def relative_improvement(metrics: DataFrame, algo: str, metric: str = "f1h") -> DataFrame:
    """Mean over data sets of ``algo``'s value over each other algorithm's."""
    m = metrics.where(F.col("metric") == metric).groupBy("algo", "dataset").agg(F.avg("value").alias("value"))
    own = m.where(F.col("algo") == algo).selectExpr("dataset", "value as own")
    return m.where(F.col("algo") != algo).join(own, "dataset").groupBy("algo").agg(F.avg(F.col("own") / F.col("value")).alias("ratio"))


def shuffle_deviation(metrics: DataFrame) -> DataFrame:
    """Mean and deviation over runs (A5)."""
    return metrics.groupBy("algo", "dataset", "step", "level", "metric").agg(F.avg("value").alias("mean"), F.stddev_pop("value").alias("deviation"))


def level_counts(hierarchy) -> int:
    """Levels of a hierarchy."""
    return hierarchy.levels


def work_counters(hierarchy) -> dict[str, int]:
    """Links and items met over all levels."""
    return {"levels": hierarchy.levels, "links": sum(r["links"] for r in hierarchy.report), "items": sum(r["items"] for r in hierarchy.report)}


def measured_run(fn: Callable, *args) -> tuple[object, float, float]:
    """``(result, seconds, peak MB)`` of a call: resident memory of this Python and the JVM
    under it (A9, A10); the peaks are the processes' own, so run each in a fresh session."""
    began = time.perf_counter()
    out = fn(*args)
    seconds = time.perf_counter() - began
    mb = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024
    for p in psutil.Process().children(recursive=True):
        try:
            with open(f"/proc/{p.pid}/status") as f:
                mb += next((int(x.split()[1]) / 1024 for x in f if x.startswith("VmHWM")), 0)
        except OSError:
            continue
    return out, seconds, mb


def metrics_frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """Rows of :data:`METRICS`."""
    return spark.createDataFrame(rows, METRICS)
