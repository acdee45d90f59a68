"""Relations of the engine and checks at its edge."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

#: Exact integer weights and comparison keys.
WEIGHT = "decimal(38,0)"
LINKS = f"src long, dst long, weight {WEIGHT}"
NODES = f"node long, self_weight {WEIGHT}"


@dataclass(frozen=True)
class Network:
    """Undirected links once (``src < dst``) and every node with its own weight.

    A network whose links are best made anew for each use, as there may be nearly one for any
    two nodes, has besides what is known without them: ``strengths(node, k)``, the ``total``
    weight, and ``by_node(src, dst, weight)``, both directions dealt by ``src``. Where a
    weight is the number of meetings, ``slots(slot, user, n)`` are those of each node, with
    how many the slot has.
    """

    links: DataFrame
    nodes: DataFrame
    strengths: DataFrame | None = None
    total: int | None = None
    by_node: DataFrame | None = None
    slots: DataFrame | None = None

    @property
    def arcs(self) -> DataFrame:
        """Both directions of every link."""
        return self.links.select("src", "dst", "weight").union(self.links.selectExpr("dst as src", "src as dst", "weight"))


@dataclass(frozen=True)
class Params:
    """Overrides; the method needs none."""

    gain: str = "modularity"
    use_consensus: bool = True
    use_split: bool = True
    use_narrowing: bool = True
    min_fraction: float = 0.5
    hub_policy: str = "veto"  # or "leaf_pull" (P4)
    growth_guard: bool = True  # P5
    count_split_gain: bool = False  # P6
    include_self: bool = False  # P8
    approx_eps: float = 0.0  # M32
    stop_on_q_drop: bool = False  # P12
    max_levels: int = 1000
    tail_links: int = 200_000
