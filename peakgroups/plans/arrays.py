"""Levels of a network held in arrays, for as long as no node has to split."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from fractions import Fraction

import numpy as np

from peakgroups.operators.formation import SPLITS
from peakgroups.schema import Params

#: Weights below this keep all keys, and what is added up of them, in 63 bits.
MOST_WEIGHT = 2**30
#: Rows that a step lays side by side at a time.
_AT_ONCE = 4_000_000


@dataclass
class ArrayNetwork:
    """Items in the order of their ids' text, so that of a group's labels the least index is
    the least text; links ``a, b, x`` once, between indices ``a < b`` and in their order;
    ``k`` are the strengths."""

    ids: np.ndarray
    own: np.ndarray
    a: np.ndarray
    b: np.ndarray
    x: np.ndarray
    k: np.ndarray

    @classmethod
    def of(cls, src, dst, weight, node, own) -> ArrayNetwork:
        """From links and nodes by id."""
        by_id = np.argsort(node, kind="stable")
        text = np.argsort(node[by_id].astype("S20"), kind="stable")
        rank = np.empty(len(node), np.int64)
        rank[text] = np.arange(len(node))
        a, b = (rank[np.searchsorted(node[by_id], end)] for end in (src, dst))
        a, b = np.minimum(a, b), np.maximum(a, b)
        order = np.argsort(a * len(node) + b)
        a, b, x, own = a[order], b[order], weight[order], own[by_id][text]
        k = 2 * own
        np.add.at(k, a, x)
        np.add.at(k, b, x)
        return cls(node[by_id][text], own, a, b, x, k)

    @property
    def weight(self) -> int:
        return sum(self.own.tolist()) + sum(self.x.tolist())

    def modularity(self, w: int) -> Fraction:
        return Fraction(4 * w * int(self.own.sum()) - int((self.k * self.k).sum()), 4 * w * w) if w else Fraction(0)

    def dicts(self) -> tuple[dict, dict]:
        """``links, own`` as :func:`~peakgroups.plans.hierarchy.solve_levels` takes them."""
        ends = (x.tolist() for x in (np.minimum(self.ids[self.a], self.ids[self.b]), np.maximum(self.ids[self.a], self.ids[self.b])))
        return dict(zip(zip(*ends), self.x.tolist())), dict(zip(self.ids.tolist(), self.own.tolist()))


def can_hold(p: Params, w: int) -> bool:
    """Whether :func:`array_levels` knows what ``p`` asks for and a total weight of ``w``."""
    return p.use_consensus and not p.approx_eps and w < MOST_WEIGHT


def array_levels(net: ArrayNetwork, level: int, p: Params, w: int) -> Iterator[tuple[int, tuple, dict]]:
    """``level, (cluster, member, carried), report`` of each level by the rules of
    :func:`~peakgroups.plans.hierarchy.solve_levels`, which the tests hold against it.

    ``net`` becomes the network between the clusters. Ends before a level at which a node
    splits; returns whether it does.
    """
    before = net.modularity(w)
    while level < p.max_levels and w and len(net.a):
        n, m = len(net.ids), len(net.a)
        src, dst, sel = _choices(net, p, w)
        if sel is None:
            return True
        label = least_of_groups(n, src[sel], dst[sel])
        joined = np.zeros(n, bool)
        joined[src[sel]] = joined[dst[sel]] = True
        clustered = int(joined.sum())
        if not clustered:
            return False
        level += 1
        sizes = np.bincount(label[joined], minlength=n)
        rows = net.ids[label], net.ids, ~joined
        _contract(net, label)
        q = net.modularity(w)
        counts = {"items": n, "links": m, "clusters": int((sizes > 0).sum()), "pairs": int((sizes == 2).sum()), "clustered": clustered, "carried": n - clustered, "split": 0}
        yield level, rows, {"level": level, **counts, "q_before": float(before), "q": float(q), "q_dropped": q < before, "q_exact": q, "left": len(net.a)}
        if p.stop_on_q_drop and q < before:
            return False
        before = q
    return False


def _sums(at: np.ndarray, x: np.ndarray, n: int) -> np.ndarray:
    """Sums of ``x`` by ``at``; below :data:`MOST_WEIGHT` doubles hold them exactly."""
    return np.bincount(at, x, n).astype(np.int64)


def _choices(net: ArrayNetwork, p: Params, w: int):
    """``node, cand, chosen`` of all candidates; None for ``chosen`` if a node splits."""
    n, a, b, k = len(net.ids), net.a, net.b, net.k
    g = 2 * w * net.x - k[a] * k[b]
    peak = np.full(n, -1)
    good = g >= 0
    np.maximum.at(peak, a[good], g[good])
    np.maximum.at(peak, b[good], g[good])
    m = good & (g == peak[a]) & (g == peak[b])
    ca, cb = a[m], b[m]
    src, dst = np.concatenate([ca, cb]), np.concatenate([cb, ca])
    order = np.argsort(src * n + dst)
    src, dst = src[order], dst[order]
    size = np.bincount(src, minlength=n)
    tied = size > 1
    if not tied.any():
        return src, dst, np.ones(len(src), bool)
    t, c = src[tied[src]], dst[tied[src]]
    s1, s2, inner = (np.zeros(n, np.int64) for _ in range(3))
    np.add.at(s1, t, k[c])
    np.add.at(s2, t, k[c] * k[c])
    degree = np.bincount(a, minlength=n) + np.bincount(b, minlength=n)
    near = np.zeros(n, bool)
    near[c] = True
    near = near[a] & near[b]
    u, v, x, first = _oriented(n, a[near], b[near], net.x[near], degree)
    for i, j in _side_by_side(first[c], first[c + 1] - first[c]):
        found, _ = _find(t[i] * n + v[j], t * n + c)
        np.add.at(inner, t[i][found], x[j][found])
    whole = size * peak + 2 * w * inner - (s1 * s1 - s2) // 2
    if p.use_split:
        may = np.flatnonzero(tied & np.logical_or.reduce([(size == s) & (degree == d) for s, d in SPLITS]))
        for s, peak_, whole_, own, k_ in zip(*(y[may].tolist() for y in (size, peak, whole, net.own, k))):
            if peak_ > whole_ if not p.count_split_gain else 2 * s * peak_ - (s - 1) * (4 * w * own - k_ * k_) > 2 * s * whole_:
                return src, dst, None
    most = np.zeros(n, np.int64)
    shared = np.zeros(len(src), np.int64)
    if p.use_narrowing:
        shared = _shared(n, ca, cb, size, src, dst) + (2 if p.include_self else 0)
        np.maximum.at(most, t, shared[tied[src]])
    narrow = tied & (most > 0) & (most >= size * p.min_fraction)
    late = tied & ~narrow & (whole < 0)
    sel = np.where(narrow[src], shared == most[src], ~late[src])
    if p.hub_policy == "veto":
        sel &= ~late[src] & ~late[dst]
    return src, dst, sel


def _oriented(n, a, b, x, degree):
    """Links from the end of fewer to that of more, by first end, and where each node's begin:
    no node has more than the root of twice all links."""
    up = (degree[a] < degree[b]) | ((degree[a] == degree[b]) & (a < b))
    u, v = np.where(up, a, b), np.where(up, b, a)
    order = np.argsort(u * n + v)
    u, v = u[order], v[order]
    return u, v, x[order], np.searchsorted(u, np.arange(n + 1))


def _side_by_side(start: np.ndarray, count: np.ndarray):
    """``i, j``: every ``i`` with ``start[i]`` and the ``count[i] - 1`` numbers after it."""
    ends = np.cumsum(count)
    lo = 0
    while lo < len(count):
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + _AT_ONCE, "right")))
        part = count[lo:hi]
        i = np.repeat(np.arange(lo, hi), part)
        yield i, np.arange(len(i)) - np.repeat(np.cumsum(part) - part, part) + start[i]
        lo = hi


def _find(wanted: np.ndarray, keys: np.ndarray):
    """Which of ``wanted`` are among the sorted ``keys``, and where."""
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    found = keys[at] == wanted
    return found, at[found]


def _shared(n, ca, cb, size, src, dst) -> np.ndarray:
    """How many candidates the two ends of each candidate row have in common: triangles."""
    out = np.zeros(len(src), np.int64)
    both = (size[ca] > 1) & (size[cb] > 1)
    if not both.any():
        return out
    u, v, _, first = _oriented(n, ca[both], cb[both], ca[both], size)
    keys, count = u * n + v, np.zeros(len(u), np.int64)
    for i, j in _side_by_side(first[v], first[v + 1] - first[v]):
        found, third = _find(u[i] * n + v[j], keys)
        for x in (i[found], j[found], third):
            np.add.at(count, x, 1)
    rows = src * n + dst
    for ends in (u * n + v, v * n + u):
        out[np.searchsorted(rows, ends)] = count
    return out


def least_of_groups(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least index of each node's connected group."""
    label = np.arange(n)
    while True:
        la, lb = label[a], label[b]
        apart = la != lb
        if not apart.any():
            return label
        a, b, la, lb = a[apart], b[apart], la[apart], lb[apart]
        np.minimum.at(label, np.maximum(la, lb), np.minimum(la, lb))
        while (label[label] != label).any():
            label = label[label]


def _contract(net: ArrayNetwork, label: np.ndarray) -> None:
    n = len(label)
    root = label == np.arange(n)
    new = (np.cumsum(root) - 1)[label]
    n = int(root.sum())
    own = _sums(new, net.own, n)
    a, b, x = new[net.a], new[net.b], net.x
    within = a == b
    own += _sums(a[within], x[within], n)
    # Links between roots stay in order, so that few are sorted where few items are clustered.
    moved = ~within & ~(root[net.a] & root[net.b])
    kept = ~within & ~moved
    key = np.minimum(a[moved], b[moved]) * n + np.maximum(a[moved], b[moved])
    order = np.argsort(key)
    key, x = np.concatenate([a[kept] * n + b[kept], key[order]]), np.concatenate([x[kept], x[moved][order]])
    order = np.argsort(key, kind="stable")
    key, x = key[order], x[order]
    first = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, np.int64)
    x = np.add.reduceat(x, first) if len(key) else x
    key = key[first]
    net.ids, net.own, net.a, net.b, net.x, net.k = net.ids[root], own, key // max(n, 1), key % max(n, 1), x, _sums(new, net.k, n)
