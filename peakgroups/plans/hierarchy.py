"""The level loop (M23-M26, M30, M33): cluster, contract, repeat until nothing forms."""

from __future__ import annotations

import hashlib
import json
from collections import defaultdict
from dataclasses import asdict, dataclass, field, replace
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from peakgroups.functions.storage import materialize
from peakgroups.operators.components import connected_groups
from peakgroups.operators.consensus import mutual_peaks, scored_arcs
from peakgroups.operators.contraction import UNIT, contract, reduced
from peakgroups.operators.formation import SPLITS, form_clusters
from peakgroups.operators.gains import modularity, modularity_gain, node_strengths, total_weight
from peakgroups.operators.meeting import best_meetings
from peakgroups.plans.arrays import ArrayNetwork, array_levels, can_hold, least_of_groups
from peakgroups.schema import WEIGHT, Network, Params

_ROWS = "level int, cluster long, member long, num int, den int, carried boolean, report string, part int"
#: Arrays hold a network of so many times ``tail_links`` in the memory of the tail's dicts.
ARRAY_TIMES = 10
#: Rows of a batch that a task hands to Spark, and of levels that a task writes out.
_BATCH, _OUT_ROWS = 100_000, 4_000_000


@dataclass
class Hierarchy:
    """Levels from 1, the finest. ``rows(level, cluster, member, num, den, carried)``: what
    each item of a level is made of, in items of the level below."""

    rows: DataFrame
    report: list[dict] = field(default_factory=list)
    tail_from: int = 0

    @property
    def levels(self) -> int:
        return len(self.report)

    def members(self, level: int) -> DataFrame:
        """Clusters of a level in items of the level below, with shares."""
        r = self.rows.where((F.col("level") == level) & ~F.col("carried"))
        return r.select("cluster", "member", (F.col("num") / F.col("den")).alias("share"))

    def flatten(self, level: int, include_carried: bool = False) -> DataFrame:
        """``cluster, node, share`` of a level in nodes of the input."""
        return self.flatten_levels([level], include_carried).select("cluster", "node", "share")

    def flatten_levels(self, levels: list[int], include_carried: bool = False) -> DataFrame:
        """:meth:`flatten` of several levels at once, with ``level``.

        Large levels are joined one by one; what :func:`solve_tail` made in one task is
        followed down in one task, too.
        """
        flat, parts = None, []
        for at in range(1, min(self.tail_from, max(levels, default=0)) + 1):
            r = self.rows.where(F.col("level") == at).select("cluster", "member", (F.col("num") / F.col("den")).alias("p"), "carried")
            flat = materialize(r.selectExpr("cluster", "member as node", "p as share", "carried") if flat is None else _above(r, flat), "flat")
            if at in levels:
                parts.append(flat.select(F.lit(at).alias("level"), "cluster", "node", "share", "carried"))
        later = [x for x in levels if x > self.tail_from]
        if later:
            if any(r["split"] for r in self.report[self.tail_from : max(later)]):
                tail = materialize(_follow_tail(self.rows, self.tail_from, later), "flat-tail")
            else:
                tail = _follow_runs(self.rows, self.tail_from, later, self.report[self.tail_from]["items"])
            parts.append(tail if flat is None else _above(tail.selectExpr("level", "cluster", "node as member", "share as p", "carried"), flat, ["level"]))
        out = self.rows.select("level", "cluster", F.col("member").alias("node"), F.lit(1.0).alias("share"), "carried").where("false")
        for x in parts:
            out = out.unionByName(x)
        return (out if include_carried else out.where("not carried")).select("level", "cluster", "node", "share")

    def report_frame(self, spark: SparkSession) -> DataFrame:
        """``level_report`` of the engine: counts and modularity of each level."""
        shape = "level int, items long, links long, clusters long, pairs long, clustered long, carried long, split long, q_before double, q double, q_dropped boolean"
        return spark.createDataFrame([[r[c.split()[0]] for c in shape.split(", ")] for r in self.report], shape)

    def write(self, path: str) -> None:
        """Rows as Parquet by level."""
        self.rows.write.partitionBy("level").parquet(path)


def _above(upper: DataFrame, flat: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Members of a level's clusters in input nodes, from those of the level below."""
    keys = keys or []
    up = flat.selectExpr("cluster as member", "node", "share", "carried as below")
    joined = upper.join(up, "member").select(*keys, "cluster", "node", (F.col("p") * F.col("share")).alias("share"), (F.col("carried") & F.col("below")).alias("carried"))
    return joined.groupBy(*keys, "cluster", "node").agg(F.round(F.sum("share"), 12).alias("share"), F.bool_and("carried").alias("carried"))


def _follow_tail(rows: DataFrame, start: int, levels: list[int]) -> DataFrame:
    """``level, cluster, node, share, carried`` in items of level ``start``; parts of the
    network that :func:`solve_parts` took one by one are followed one by one."""
    wanted = set(levels)

    def follow(pdf):
        import pandas as pd

        out, below = [], None
        for level, part in pdf.sort_values("level").groupby("level"):
            now: dict = defaultdict(lambda: defaultdict(Fraction))
            carried: dict = {}
            for c, m, num, den, alone in zip(part["cluster"], part["member"], part["num"], part["den"], part["carried"]):
                for node, share in (below[0][m] if below else {m: Fraction(1)}).items():
                    now[c][node] += share * Fraction(int(num), int(den))
                carried[c] = bool(alone) and (below is None or below[1][m])
            below = now, carried
            if level in wanted:
                out += [(level, c, node, round(float(share), 12), carried[c]) for c, nodes in now.items() for node, share in nodes.items()]
        return pd.DataFrame(out, columns=["level", "cluster", "node", "share", "carried"]).astype({"level": "int32"})

    tail = rows.where((F.col("level") > start) & (F.col("level") <= max(levels)))
    return tail.groupBy("part").applyInPandas(follow, "level int, cluster long, node long, share double, carried boolean")


def _follow_runs(rows: DataFrame, start: int, levels: list[int], items: int) -> DataFrame:
    """:func:`_follow_tail` where no item is split: a node is in one cluster at a time, so one
    task finds from which level to which, and others write the levels out."""
    wanted = sorted(set(levels))
    shape = "node long, lo int, hi int, cluster long, carried boolean"
    schema = to_arrow_schema(StructType.fromDDL(shape))

    def follow(batches):
        import numpy as np
        import pyarrow as pa

        found = [b for b in batches if b.num_rows]
        if not found:
            return
        table = pa.Table.from_batches(found)
        part, level, cluster, member, carried = (table[c].to_numpy() for c in ("part", "level", "cluster", "member", "carried"))
        by_level = np.lexsort((level, part))
        for rows_at in np.split(by_level, np.flatnonzero(np.diff(part[by_level])) + 1):
            for x in _runs(level[rows_at], cluster[rows_at], member[rows_at], carried[rows_at], start + 1, wanted):
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in x], schema=schema)

    # A level that leaves an item as it is has nothing to say about it.
    tail = rows.where((F.col("level") > start) & (F.col("level") <= wanted[-1]) & (~F.col("carried") | (F.col("level") == start + 1)))
    tail = tail.select("part", "level", "cluster", "member", "carried")
    one = rows.where("part > 0").limit(1).count() == 0
    runs = (tail.repartition(1) if one else tail.repartition("part")).mapInArrow(follow, shape)
    tasks = min(1000, items * len(wanted) // _OUT_ROWS)
    runs = materialize(runs.repartition(tasks, "node") if tasks > 1 else runs, "runs")
    at = F.element_at(F.lit(wanted) if len(wanted) > 1 else F.array(F.lit(wanted[0])), F.col("at") + 1).cast("int")
    return runs.select("node", "cluster", "carried", F.explode(F.sequence("lo", "hi")).alias("at")).select(at.alias("level"), "cluster", "node", F.lit(1.0).alias("share"), "carried")


def _runs(level, cluster, member, carried, first, wanted):
    """``node, lo, hi, cluster, carried`` in batches, by node: ``lo`` to ``hi`` are positions in
    ``wanted``. Rows are in order of level; those of ``first`` name every node."""
    import numpy as np

    starts = np.flatnonzero(np.append(True, np.diff(level) != 0))
    ids = np.sort(member[level == first])
    n = len(ids)
    now, alone = np.arange(n), np.ones(n, bool)
    moves = [(np.arange(n), np.full(n, first), now, alone)]
    for lo, hi in zip(starts, np.append(starts[1:], len(level))):
        inside = ~carried[lo:hi]
        to, hit = np.arange(n), np.zeros(n, bool)
        m = np.searchsorted(ids, member[lo:hi][inside])
        to[m], hit[m] = np.searchsorted(ids, cluster[lo:hi][inside]), True
        after = to[now]
        moved = np.flatnonzero((after != now) | (alone & hit[now]))
        now, alone = after, alone & ~hit[now]
        moves.append((moved, np.full(len(moved), level[lo]), now[moved], alone[moved]))
    node, at, to, still = (np.concatenate(x) for x in zip(*moves))
    order = np.argsort(node, kind="stable")
    node, at, to, still = node[order], at[order], to[order], still[order]
    until = np.append(np.where(node[1:] == node[:-1], at[1:], wanted[-1] + 1), wanted[-1] + 1)
    lo, hi = np.searchsorted(wanted, at), np.searchsorted(wanted, until) - 1
    some = lo <= hi
    out = ids[node[some]], lo[some].astype("int32"), hi[some].astype("int32"), ids[to[some]], still[some]
    for i in range(0, len(out[0]), _BATCH):
        yield [x[i : i + _BATCH] for x in out]


def sample_levels(levels: int, most: int = 10) -> list[int]:
    """Evenly spaced levels, the first and the last among them."""
    if levels <= most:
        return list(range(1, levels + 1))
    return sorted({1 + round(i * (levels - 1) / (most - 1)) for i in range(most)})


def middle_level(levels: int) -> int:
    """The level at half the height."""
    return max(1, levels // 2)


class MutualPeakClusterer:
    """Parameter-free stable clustering; ``params`` may force what the method decides."""

    def __init__(self, params: Params = Params()):
        self.params = params

    def candidates(self, net: Network, w: int, strengths: DataFrame | None = None) -> DataFrame:
        """Clustering candidates of a level."""
        if net.slots is not None and self.params.gain == "modularity" and self.params.use_consensus and not self.params.approx_eps:
            best = best_meetings(net.slots, w)
            if best is not None:
                best = materialize(best.withColumn("weight", F.col("weight").cast(WEIGHT)), "best")
                net = replace(net, links=best.where("src < dst"), by_node=best)
        scored = modularity_gain(net, self.params.gain, strengths, w)
        if not self.params.use_consensus:
            return scored_arcs(scored)
        by_node = None if net.by_node is None else modularity_gain(replace(net, links=net.by_node), self.params.gain, strengths, w)
        return mutual_peaks(scored, self.params.approx_eps, by_node)

    def fit(self, net: Network) -> Hierarchy:
        """All levels. Large levels are DataFrame jobs; once a network has ``tail_links``
        links or fewer, one task finishes it by the same exact rules, and one of up to
        :data:`ARRAY_TIMES` as many for as long as no node splits."""
        p, parts, report, joined = self.params, [], [], 0
        net = Network(materialize(net.links, "links"), materialize(net.nodes, "nodes"))
        level, q, stuck = 0, None, False
        in_tasks = p.gain == "modularity" and p.tail_links
        while level < p.max_levels:
            (m, between), (n, inside) = (x.agg(F.count(F.lit(1)), F.sum(c)).first() for x, c in ((net.links, "weight"), (net.nodes, "self_weight")))
            w = int(between or 0) + int(inside or 0)
            small = max(m, n) <= p.tail_links
            held = max(m, n) <= ARRAY_TIMES * p.tail_links
            if level == 0 and w and not small and in_tasks and not p.stop_on_q_drop and not stuck:
                found = solve_parts(net, w, p, held)
                if found is not None:
                    parts.append(found[0])
                    report = found[1]
                    break
            if in_tasks and (small or held and can_hold(p, w) and not stuck):
                tail = materialize(solve_tail(net, level, p, w, whole=not small), "tail")
                ends = [json.loads(r.report) for r in tail.where("report is not null").select("report").orderBy("level").collect()]
                levels = [{k: v for k, v in r.items() if k not in ("q_exact", "last")} for r in ends if "stuck" not in r]
                report += levels
                parts.append(tail.where("report is null"))
                stuck = len(levels) < len(ends)
                if not stuck:
                    break
                if levels:
                    every = _follow_runs(parts[-1], level, [level + len(levels)], n).selectExpr("cluster", "node", "1 as num", "1 as den")
                    level += len(levels)
                    net, _ = contract(net, every, False)
                    net = Network(materialize(net.links, "links"), materialize(net.nodes, "nodes"))
                    q, joined = report[-1]["q"], level
                continue
            stuck = False
            if not w or net.links.limit(1).count() == 0:
                break
            level += 1
            strengths = materialize(node_strengths(net), "strengths")
            cands = materialize(self.candidates(net, w, strengths), "cands")
            actions, members = form_clusters(net, cands, w, level, p, strengths)
            counts = members.agg(F.count_distinct("cluster"), F.count_distinct("node"), F.count_if(F.col("den") > 1)).first()
            if not counts[0]:
                break
            alone = net.nodes.select("node").join(members.select("node"), "node", "left_anti")
            every = materialize(members.withColumn("carried", F.lit(False)).unionByName(alone.selectExpr("node as cluster", "node", "1 as num", "1 as den", "true as carried")), "level")
            before = modularity(net) if q is None else q
            split = counts[2] > 0
            nxt, _ = contract(net, every, split)
            nxt = Network(materialize(nxt.links, "links"), materialize(nxt.nodes, "nodes"))
            nxt = reduced(nxt) if split else nxt
            q = modularity(nxt)
            sizes = members.groupBy("cluster").count().where("count = 2").count()
            items = net.nodes.count()
            report.append({"level": level, "items": items, "links": net.links.count(), "clusters": counts[0], "pairs": sizes, "clustered": counts[1], "carried": items - counts[1], "split": members.where("den > 1").select("node").distinct().count(), "q_before": before, "q": q, "q_dropped": q < before})
            parts.append(every.select(F.lit(level).alias("level"), "cluster", F.col("node").alias("member"), "num", "den", "carried", F.lit(None).cast("string").alias("report"), F.lit(0).alias("part")))
            joined = level
            if p.stop_on_q_drop and q < before:
                break
            net = nxt
        spark = net.links.sparkSession
        rows = spark.createDataFrame([], _ROWS)
        for x in parts:
            rows = rows.union(x)
        return Hierarchy(rows.drop("report"), report, joined)


def solve_tail(net: Network, level: int, params: Params, total: int, part: DataFrame | None = None, whole: bool = False) -> DataFrame:
    """The remaining levels of a network of bounded size, in one task; with ``part(node,
    part)``, those of each part in a task of its own, in a network of weight ``total``. With
    ``whole`` only those before one with a split, and a report of that."""
    options, known = asdict(params), None if part is None else total
    # Weights that arrays cannot hold go as text.
    kind = "long" if can_hold(params, total) else "string"
    one = net.links.selectExpr("src as a", "dst as b", f"cast(weight as {kind}) as w").union(net.nodes.selectExpr("node as a", "cast(null as long) as b", f"cast(self_weight as {kind}) as w"))
    schema = to_arrow_schema(StructType.fromDDL(_ROWS))

    def solve(batches):
        import numpy as np
        import pyarrow as pa

        found = [b for b in batches if b.num_rows]
        if not found:
            return
        table = pa.Table.from_batches(found)
        del found
        parts = table["part"].to_numpy()
        order = np.argsort(parts, kind="stable")
        for at in np.split(order, np.flatnonzero(np.diff(parts[order])) + 1):
            rows = table.take(pa.array(at)) if len(at) < len(order) else table
            no = int(parts[at[0]])
            for lvl, cluster, member, num, den, carried, report in _tail_blocks(rows, level, Params(**options), known, whole):
                n = len(cluster)
                for i in range(0, n, _BATCH):
                    size = min(_BATCH, n - i)
                    cut = [x[i : i + size] if hasattr(x, "__len__") else np.full(size, x) for x in (cluster, member, num, den, carried)]
                    columns = [np.full(size, lvl), *cut, [report] * size, np.full(size, no)]
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema)], schema=schema)

    if part is None:
        dealt = one.selectExpr("0 as part", "a", "b", "w").repartition(1)
    else:
        tasks = 1 + (part.agg(F.max("part")).first()[0] or 0)
        dealt = one.join(part.selectExpr("node as a", "part"), "a").selectExpr("part", "a", "b", "w").repartitionById(tasks, "part")
    return dealt.mapInArrow(solve, _ROWS)


def solve_parts(net: Network, w: int, params: Params, held: bool = False) -> tuple[DataFrame, list[dict]] | None:
    """``rows, report`` of all levels if every connected group has ``tail_links`` links or
    fewer, else None.

    Groups never meet at any level and know of each other only the total weight, so tasks
    take whole groups, some together, and carry on alone. A part in which nothing forms any
    more has its items carried through the levels that others still have. With ``held``
    one task finds the groups.
    """
    pairs = net.links.selectExpr("src as a", "dst as b")
    label = (materialize(_held_groups(pairs), "groups") if held else connected_groups(pairs)).withColumnRenamed("label", "root")
    size = net.links.join(label.withColumnRenamed("node", "src"), "src").groupBy("root").count().agg(F.max("count"), F.sum("count")).first()
    if (size[0] or 0) > params.tail_links:
        return None
    parts = max(1, -(-4 * size[1] // params.tail_links))
    part = net.nodes.select("node").join(label, "node", "left").select("node", F.pmod(F.xxhash64(F.coalesce("root", "node")), F.lit(parts)).cast("int").alias("part"))
    tail = materialize(solve_tail(net, 0, params, w, materialize(part, "parts")), "tail")
    ends = [(r.part, json.loads(r.report)) for r in tail.where("report is not null").select("part", "report").collect()]
    last = {at: r for at, r in ends if r["last"]}
    most = max((r["level"] for r in last.values()), default=0)
    done = {(at, r["level"]): r for at, r in ends if not r["last"]}
    report, q = [], sum((Fraction(r["q0"]) for r in last.values()), Fraction(0))
    for level in range(1, most + 1):
        at = [done.get((x, level)) or r for x, r in last.items()]
        row = {k: sum(r[k] for r in at) for k in ("items", "links", "clusters", "pairs", "clustered", "carried", "split")}
        before, q = q, sum((Fraction(r["q_exact"]) for r in at), Fraction(0))
        report.append({"level": level, **row, "q_before": float(before), "q": float(q), "q_dropped": q < before})
    plain = tail.where("report is null")
    idle = plain.where("num = 0").withColumn("level", F.explode(F.expr(f"case when level <= {most} then sequence(level, {most}) else array() end"))).withColumn("num", F.lit(1))
    return plain.where("num > 0").unionByName(idle.select(plain.columns)), report


def _held_groups(pairs: DataFrame) -> DataFrame:
    """:func:`connected_groups` of pairs that one task holds."""

    def label(batches):
        import numpy as np
        import pyarrow as pa

        found = [b for b in batches if b.num_rows]
        if found:
            a, b = (pa.Table.from_batches(found)[c].to_numpy() for c in "ab")
            ids = np.unique(np.concatenate([a, b]))
            least = ids[least_of_groups(len(ids), np.searchsorted(ids, a), np.searchsorted(ids, b))]
            for i in range(0, len(ids), _BATCH):
                yield pa.RecordBatch.from_arrays([pa.array(x[i : i + _BATCH]) for x in (ids, least)], names=["node", "label"])

    return pairs.repartition(1).mapInArrow(label, "node long, label long")


def _tail_blocks(table, level, p, total, whole):
    """``level, cluster, member, num, den, carried, report`` in arrays, or lists, of rows."""
    import pyarrow as pa
    import pyarrow.compute as pc

    is_node = pc.is_null(table["b"])
    nodes, ends = table.filter(is_node), table.filter(pc.invert(is_node))
    if pa.types.is_string(table["w"].type):
        own = {a: int(w) for a, w in zip(nodes["a"].to_pylist(), nodes["w"].to_pylist())}
        links = {(a, b): int(w) for a, b, w in zip(ends["a"].to_pylist(), ends["b"].to_pylist(), ends["w"].to_pylist())}
        start = exact = None if total is None else _modularity(links, own, total)
        stuck = True
    else:
        net = ArrayNetwork.of(*(ends[c].to_numpy() for c in ("a", "b", "w")), *(nodes[c].to_numpy() for c in ("a", "w")))
        w = net.weight if total is None else total
        start = exact = net.modularity(w)
        steps = array_levels(net, level, p, w)
        while True:
            try:
                level, (cluster, member, carried), report = next(steps)
            except StopIteration as end:
                stuck = end.value
                break
            exact = report.pop("q_exact")
            yield level, cluster, member, 1, 1, carried, None
            yield _report(level, report, exact)
        if stuck and whole:
            yield level + 1, [0], [0], 1, 1, False, json.dumps({"stuck": True})
            return
        if not stuck and total is None:
            return
        links, own = net.dicts()
    items, left = list(own), len(links)
    if stuck:
        for level, rows, report in solve_levels(links, own, level, p, total):
            yield level, *(list(x) for x in zip(*rows)), None
            exact, left = report.pop("q_exact"), report.pop("left")
            items = list({r[0] for r in rows})
            yield _report(level, report | {"left": left}, exact)
    if total is None:
        return
    # A part's end: its items, with a num of 0, from the level after its last one on.
    yield level + 1, items, items, 0, 1, True, None
    final = {"level": level, "items": len(items), "links": left, "clusters": 0, "pairs": 0, "clustered": 0, "carried": len(items), "split": 0}
    yield level + 1, [0], [0], 1, 1, False, json.dumps(final | {"q0": str(start), "q_exact": str(exact), "last": True})


def _report(level, report, exact):
    shown = {k: v for k, v in report.items() if k != "left"}
    return level, [0], [0], 1, 1, False, json.dumps(shown | {"q_exact": str(exact), "last": False})


def _modularity(links, own, w) -> Fraction:
    k = {n: 2 * s for n, s in own.items()}
    for (a, b), x in links.items():
        k[a] += x
        k[b] += x
    return Fraction(4 * w * sum(own.values()) - sum(x * x for x in k.values()), 4 * w * w)


def solve_levels(links: dict, own: dict, level: int = 0, p: Params = Params(), total: int | None = None):
    """Levels of a network in Python whole numbers: ``(level, rows, report)`` each.

    ``links[a, b]`` with ``a < b``; ``own[node]`` for every node. The same rules as the
    DataFrame steps, which the tests hold against each other. ``total`` is the weight of the
    whole network, where these are connected groups of it.
    """
    links, own = dict(links), dict(own)
    w = sum(own.values()) + sum(links.values()) if total is None else total
    while level < p.max_levels:
        if not w or not links:
            return
        level += 1
        near: dict = defaultdict(dict)
        k = {n: 2 * s for n, s in own.items()}
        for (a, b), x in links.items():
            near[a][b] = near[b][a] = x
            k[a] += x
            k[b] += x
        gain = {n: {c: 2 * w * x - k[n] * k[c] for c, x in cs.items()} for n, cs in near.items()}
        pre = {}
        for n, gs in gain.items():
            top = max(gs.values())
            floor = top * (1 - p.approx_eps) if p.approx_eps else top
            pre[n] = {c for c, g in gs.items() if g >= 0 and (g >= floor or not p.use_consensus)} if top >= 0 else set()
        cands = {n: {c for c in cs if n in pre[c]} for n, cs in pre.items()}
        cands = {n: cs for n, cs in cands.items() if cs}
        blocked: set = set()
        while True:
            action, choice = _decide(cands, gain, near, own, k, w, blocked, p)
            groups, den = _merge(action, choice, p)
            grown = _grown(cands, groups) if p.growth_guard and any(a == "split" for a in action.values()) else set()
            if not grown or grown <= blocked:
                break
            blocked |= grown
        if not groups:
            return
        rows, share = [], defaultdict(dict)
        for label, parts in groups.items():
            cid = _cluster_id(level, label)
            for node, num in parts.items():
                rows.append((cid, node, num, den[node], False))
                share[node][cid] = Fraction(num, den[node])
        carried = [n for n in own if n not in share]
        for n in carried:
            rows.append((n, n, 1, 1, True))
            share[n][n] = Fraction(1)
        before = _modularity(links, own, w)
        items, m = len(own), len(links)
        split = sum(1 for s in share.values() if any(x != 1 for x in s.values()))
        inside = sum(own.values()) + sum(links.values())
        links, own = _contract(links, own, share, UNIT if split else 1, w)
        w = w * (sum(own.values()) + sum(links.values())) // inside
        q = _modularity(links, own, w)
        report = {"level": level, "items": items, "links": m, "clusters": len(groups), "pairs": sum(len(g) == 2 for g in groups.values()), "clustered": items - len(carried), "carried": len(carried), "split": split, "q_before": float(before), "q": float(q), "q_dropped": q < before, "q_exact": q, "left": len(links)}
        yield level, rows, report
        if p.stop_on_q_drop and q < before:
            return


def _decide(cands, gain, near, own, k, w, blocked, p):
    action, choice = {}, {}
    for n, cs in cands.items():
        size = len(cs)
        if size == 1:
            action[n], choice[n] = "single", set(cs)
            continue
        peak = max(gain[n][c] for c in cs)
        s1 = sum(k[c] for c in cs)
        # Links among the candidates, each met from both ends.
        inner = sum(x for c in cs for o, x in (near[c].items() if len(near[c]) < size else ((o, near[c][o]) for o in cs if o in near[c])) if o in cs) // 2
        whole = size * peak + 2 * w * inner - (s1 * s1 - sum(k[c] * k[c] for c in cs)) // 2
        pays = peak > whole if not p.count_split_gain else 2 * size * peak - (size - 1) * (4 * w * own[n] - k[n] * k[n]) > 2 * size * whole
        if p.use_split and (size, len(near[n])) in SPLITS and n not in blocked and pays:
            action[n], choice[n] = "split", set(cs)
            continue
        shared = {c: len(cs & cands[c]) + (2 if p.include_self else 0) for c in cs} if p.use_narrowing else {0: 0}
        most = max(shared.values())
        if most > 0 and most >= size * p.min_fraction:
            action[n], choice[n] = "narrow", {c for c, x in shared.items() if x == most}
        elif whole >= 0:
            action[n], choice[n] = "merge_all", set(cs)
        else:
            action[n], choice[n] = "carried", set()
    return action, choice


def _merge(action, choice, p):
    parent: dict = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for n, cs in choice.items():
        for c in cs:
            if p.hub_policy == "veto" and "carried" in (action[n], action[c]):
                continue
            a = f"{n}:{c}" if action[n] == "split" else str(n)
            b = f"{c}:{n}" if action[c] == "split" else str(c)
            a, b = sorted((find(a), find(b)))
            parent[b] = a
    groups, den = defaultdict(lambda: defaultdict(int)), defaultdict(int)
    least: dict = {}
    for v in parent:
        r = find(v)
        least[r] = min(least.get(r, v), v)
    for v in parent:
        node = int(v.split(":")[0])
        groups[least[find(v)]][node] += 1
        den[node] += 1
    return groups, den


def _grown(cands, groups) -> set:
    comp: dict = {}
    for start in cands:
        if start not in comp:
            comp[start], todo = start, [start]
            while todo:
                for c in cands[todo.pop()]:
                    if c not in comp:
                        comp[c] = start
                        todo.append(c)
    clusters, nodes = defaultdict(int), defaultdict(set)
    for parts in groups.values():
        at = comp[next(iter(parts))]
        clusters[at] += 1
        nodes[at] |= set(parts)
    bad = {c for c, n in clusters.items() if n > len(nodes[c])}
    return {n for n, c in comp.items() if c in bad}


def _cluster_id(level: int, label: str) -> int:
    return -(int(hashlib.md5(f"{level}|{label}".encode()).hexdigest()[:15], 16) + 1) if ":" in label else int(label)


def _contract(links, own, share, unit, whole):
    out: dict = defaultdict(int)
    for (a, b), x in links.items():
        for ca, pa in share[a].items():
            for cb, pb in share[b].items():
                out[min(ca, cb), max(ca, cb)] += x * unit * pa * pb
    for n, s in own.items():
        at = sorted(share[n].items())
        for i, (ca, pa) in enumerate(at):
            for cb, pb in at[i:]:
                out[ca, cb] += s * unit * pa * pb * (1 if ca == cb else 2)
    if unit > 1:
        every = [int(x) for x in out.values()]
        d = next((d for d in range(UNIT, 0, -1) if UNIT % d == 0 and whole * unit % d == 0 and all(x % d == 0 for x in every)), 1)
        out = {key: int(x) // d for key, x in out.items()}
    selves = {a: int(x) for (a, b), x in out.items() if a == b}
    return {key: int(x) for key, x in out.items() if key[0] != key[1] and x}, {c: selves.get(c, 0) for s in share.values() for c in s}
