"""The experiments (W1-W11) as runnable functions; results are rows of ``METRICS``."""

from __future__ import annotations

import threading
import uuid
from collections.abc import Callable, Iterable
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from peakgroups.baselines import labels, moves, structural
from peakgroups.functions.storage import materialize
from peakgroups.operators.contraction import fragment_weights
from peakgroups.plans.hierarchy import MutualPeakClusterer, middle_level, sample_levels
from peakgroups.plans.measures import dedupe_cover, f1_harmonic, measured_run, metrics_frame
from peakgroups.plans.perturb import perturb_links, planted_network, shuffle_network
from peakgroups.schema import Network
from peakgroups.sources import networks

#: Shares of links taken away, step by step, and reorderings: fixed values.
FRACTIONS, SHUFFLES = (0.01, 0.03, 0.05, 0.07, 0.09, 0.11, 0.13, 0.15), 4


def _mutual_peak(net: Network) -> list[DataFrame]:
    h = MutualPeakClusterer().fit(net)
    picked = sample_levels(h.levels)
    flat = materialize(h.flatten_levels(picked), "flat")
    return [flat.where(F.col("level") == at).select("cluster", "node", "share") for at in picked]


#: Name -> levels of a network, or covers over the parameter's range for flat methods.
ALGORITHMS: dict[str, Callable[[Network], list[DataFrame]]] = {
    "mutual_peak": _mutual_peak,
    "clique_percolation": lambda net: [structural.clique_percolation(net, k) for k in range(3, 8)],
    "louvain": lambda net: moves.louvain(net),
    "fast_consensus": lambda net: [moves.fast_consensus(net, 5, tau) for tau in (0.5,)],
    "significance": lambda net: [labels.significance_communities(net, p) for p in (0.1, 0.01)],
    "speaker_listener": lambda net: [labels.speaker_listener(net, threshold=r) for r in (0.1, 0.4)],
    "structural": lambda net: [structural.structural_clusters(net, Fraction(e, 10)) for e in (2, 3, 4, 5, 6)],
    "core_groups": lambda net: [moves.core_groups(net)],
    "core_groups_iterated": lambda net: [moves.core_groups(net, iterated=True)],
    "triangle": lambda net: [structural.triangle_communities(net)],
}
DETERMINISTIC = ("mutual_peak", "clique_percolation", "structural")
STABILITY_SET = ("mutual_peak", "clique_percolation", "fast_consensus", "significance", "structural", "core_groups", "core_groups_iterated")


def middle_cover(net: Network, algo: str) -> DataFrame:
    """The cover at the middle of the hierarchy or of the parameter's range."""
    if algo == "mutual_peak":
        h = MutualPeakClusterer().fit(net)
        return h.flatten(middle_level(h.levels)).select("cluster", "node")
    found = ALGORITHMS[algo](net)
    return found[(len(found) - 1) // 2].select("cluster", "node")


def run_robustness(net: Network, algo: str, fractions: Iterable[float] = FRACTIONS, shuffles: int = SHUFFLES, dataset: str = "net") -> DataFrame:
    """F1h of each step's middle cover against the step before, per reordering."""
    rows = []
    for run in range(shuffles):
        before = None
        for step, fraction in enumerate((0.0, *fractions)):
            cut = perturb_links(net, fraction)
            shuffled, ids = shuffle_network(cut, run + 1)
            back = ids.selectExpr("new_node as node", "node as old")
            cover = middle_cover(shuffled, algo).join(back, "node").selectExpr("cluster", "old as node")
            cover = materialize(cover, "cover")
            if before is not None:
                rows.append((f"shuffle{run}", algo, dataset, step, 0, "f1h", f1_harmonic(cover, before)))
            before = cover
    return metrics_frame(net.links.sparkSession, rows)


def run_accuracy(nets: dict[str, tuple[Network, DataFrame]], algos: Iterable[str], shuffles: int = 1) -> DataFrame:
    """Best F1h over levels against the deduplicated truth."""
    rows = []
    for name, (net, truth) in nets.items():
        truth = materialize(dedupe_cover(truth), "truth")
        for run in range(shuffles):
            at, back = net, None
            if shuffles > 1:
                at, ids = shuffle_network(net, run + 1)
                back = ids.selectExpr("new_node as node", "node as old")
            for algo in algos:
                if algo == "random":
                    covers = [labels.random_communities(at, truth if back is None else truth.join(back.selectExpr("old as node", "node as n"), "node").selectExpr("cluster", "n as node"), run)]
                else:
                    covers = ALGORITHMS[algo](at)
                if back is not None:
                    covers = [c.join(back, "node").selectExpr("cluster", "old as node") for c in covers]
                best = max((f1_harmonic(c, truth) for c in covers), default=0.0)
                rows.append((f"shuffle{run}", algo, name, 0, 0, "f1h", best))
    return metrics_frame(next(iter(nets.values()))[0].links.sparkSession, rows)


def run_determinism(net: Network, algo: str, shuffles: int = SHUFFLES, dataset: str = "net") -> DataFrame:
    """F1h of each reordering's middle cover against the first's: 1 throughout if the
    algorithm does not depend on order (W2)."""
    rows, first = [], None
    for run in range(shuffles):
        shuffled, ids = shuffle_network(net, run + 1)
        back = ids.selectExpr("new_node as node", "node as old")
        cover = materialize(middle_cover(shuffled, algo).join(back, "node").selectExpr("cluster", "old as node"), "cover")
        first = cover if first is None else first
        rows.append((f"shuffle{run}", algo, dataset, 0, 0, "f1h", f1_harmonic(cover, first)))
    return metrics_frame(net.links.sparkSession, rows)


def assert_order_free(net: Network, shuffles: int = SHUFFLES) -> None:
    """Raise if the hierarchy changes when nodes and links are reordered."""
    if run_determinism(net, "mutual_peak", shuffles).where("value < 1").limit(1).count():
        raise AssertionError("the cover depends on the order of nodes or links")


def run_resources(nets: dict[str, Network], algos: Iterable[str], limit_seconds: float = 72 * 3600) -> DataFrame:
    """Seconds, peak megabytes and whether it ended within the limit, of one run each (W6, A9,
    A10, A14). The peak is that of all processes since they began: one algorithm a session."""
    spark = next(iter(nets.values())).links.sparkSession
    rows = []
    for name, net in nets.items():
        for algo in algos:
            whole = lambda net=net, algo=algo: [c.write.format("noop").mode("overwrite").save() for c in ALGORITHMS[algo](net)]
            (finished, seconds, mb) = measured_run(lambda: ended_within(spark, whole, limit_seconds))
            rows += [("run", algo, name, 0, 0, "seconds", seconds), ("run", algo, name, 0, 0, "peak_mb", mb), ("run", algo, name, 0, 0, "finished", float(finished))]
    return metrics_frame(spark, rows)


def ended_within(spark: SparkSession, work: Callable, limit_seconds: float) -> bool:
    """Whether ``work()`` ends before its Spark jobs are cancelled at the limit."""
    late = threading.Event()
    over = threading.Event()

    def cancel() -> None:
        late.set()
        while not over.wait(0.2):  # jobs that start after the limit go as well
            spark.sparkContext.cancelJobsWithTag(tag)

    tag = f"limited-{uuid.uuid4().hex}"
    timer = threading.Timer(limit_seconds, cancel)
    spark.sparkContext.addJobTag(tag)
    timer.start()
    try:
        work()
    except Exception:
        if not late.is_set():
            raise
        return False
    finally:
        over.set()
        timer.cancel()
        spark.sparkContext.removeJobTag(tag)
    return not late.is_set()


def run_granularity(net: Network, dataset: str = "net") -> DataFrame:
    """Levels and clusters of the hierarchical methods, and clusters by order statistics."""
    h = MutualPeakClusterer().fit(net)
    lv = moves.louvain(net)
    rows = [("run", "mutual_peak", dataset, 0, r["level"], "clusters", float(r["clusters"])) for r in h.report]
    rows += [("run", "louvain", dataset, 0, i + 1, "clusters", float(c.select("cluster").distinct().count())) for i, c in enumerate(lv)]
    rows.append(("run", "significance", dataset, 0, 0, "clusters", float(labels.significance_communities(net).select("cluster").distinct().count())))
    rows += [("run", "mutual_peak", dataset, 0, 0, "levels", float(h.levels)), ("run", "louvain", dataset, 0, 0, "levels", float(len(lv)))]
    return metrics_frame(net.links.sparkSession, rows)


def run_clique_sweep(net: Network, first: int = 3, last: int = 7, dataset: str = "net") -> DataFrame:
    """Clusters found and seconds taken by clique percolation for each clique size."""
    rows = []
    for k in range(first, last + 1):
        n, seconds, _ = measured_run(lambda k=k: structural.clique_percolation(net, k).select("cluster").distinct().count())
        rows += [("run", "clique_percolation", dataset, k, 0, "clusters", float(n)), ("run", "clique_percolation", dataset, k, 0, "seconds", seconds)]
    return metrics_frame(net.links.sparkSession, rows)


def run_scaling(nets: dict[str, Network]) -> DataFrame:
    """Work counters of growing networks."""
    rows = []
    for name, net in nets.items():
        h = MutualPeakClusterer().fit(net)
        rows += [("run", "mutual_peak", name, 0, r["level"], "links", float(r["links"])) for r in h.report]
        rows.append(("run", "mutual_peak", name, 0, 0, "levels", float(h.levels)))
    return metrics_frame(next(iter(nets.values())).links.sparkSession, rows)


def planted_grid(spark: SparkSession, sizes: Iterable[int] = (1000, 5000, 20000, 50000), degrees: Iterable[int] = (5, 25, 75)) -> dict[str, tuple[Network, DataFrame]]:
    """The grid of planted networks (W3); the largest degree grows from 70 to 800."""
    sizes = list(sizes)
    out = {}
    for n in sizes:
        top = round(70 + 730 * (n - 1000) / 49000) if n > 1000 else 70
        for d in degrees:
            out[f"planted-{n}-{d}"] = planted_network(spark, n, d, max(top, 3 * d), seed=n + d)
    return out


def document_truths(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """Covers of documents by language, by equal text, and, overlapping, by the benchmark
    items of which they hold a run of eight words, for N8 and N9 (W4)."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    lang = docs.select(F.xxhash64("lang").alias("cluster"), F.col("doc_id").alias("node"))
    text = docs.select(F.xxhash64("text").alias("cluster"), F.col("doc_id").alias("node"))
    several = text.groupBy("cluster").count().where("count > 1").select("cluster")
    runs = "transform(sequence(0, size(w) - 8), i -> array_join(slice(w, i + 1, 8), ' '))"
    words = F.split(F.trim(F.lower("text")), r"\s+").alias("w")
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select(F.col("item_id").alias("cluster"), words).where("size(w) >= 8").select("cluster", F.explode(F.expr(runs)).alias("run")).distinct()
    held = docs.select(F.col("doc_id").alias("node"), words).where("size(w) >= 8").select("node", F.explode(F.expr(runs)).alias("run"))
    passages = held.join(items, "run").select("cluster", "node").distinct()
    return {"language": lang, "copies": text.join(several, "cluster"), "passages": passages}


def worked_example() -> dict[str, Fraction]:
    """The split of a node of weight 9 with three links of 12 to neighbours of 10."""
    own, link = fragment_weights(9, 3)
    to_own, to_other = Fraction(12, 3), Fraction(12, 3) + link
    return {"fragment": own, "between_fragments": link, "to_candidate": to_own, "to_other_fragment": to_other, "cluster": 10 + own + to_own, "between_clusters": 2 * to_other - link}
