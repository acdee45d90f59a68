"""Everything under SQL names: views and a table function."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from peakgroups.plans.hierarchy import Hierarchy
from peakgroups.schema import Network


def register_views(spark: SparkSession, net: Network, hierarchy: Hierarchy) -> None:
    """Views ``links``, ``nodes`` and ``hierarchy``, and ``expand_members(list)``."""
    net.links.createOrReplaceTempView("links")
    net.nodes.createOrReplaceTempView("nodes")
    hierarchy.rows.createOrReplaceTempView("hierarchy")

    @udtf(returnType="cluster: bigint, member: bigint")
    class ExpandMembers:
        """One row for each member of a cluster's comma-joined list."""

        def eval(self, cluster: int, members: str):
            for m in (members or "").split(","):
                if m:
                    yield cluster, int(m)

    spark.udtf.register("expand_members", ExpandMembers)


def write_cover_csv(cover, path: str) -> None:
    """A line of space-separated nodes for each cluster. A cluster is one line of text, so it
    is gathered in one row; write ``(cluster, node)`` as Parquet where clusters are large."""
    from pyspark.sql import functions as F

    cover.groupBy("cluster").agg(F.array_join(F.sort_array(F.collect_list("node")).cast("array<string>"), " ").alias("value")).select("value").write.text(path)
