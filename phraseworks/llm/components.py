"""Connected components of a distributed edge list, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import settle


def _both(edges: DataFrame) -> DataFrame:
    return edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))


def _large_star(edges: DataFrame) -> DataFrame:
    """Each larger neighbour of a node is linked to the least of the node and its neighbours."""
    sides = _both(edges)
    # written, so that the join below has a plain shuffle on either side and may cut a hub's rows into several tasks
    least = settle(sides.groupBy("u").agg(F.min("v").alias("low")).select(F.col("u").alias("w"), F.least("u", "low").alias("low")), "least")
    return sides.where("v > u").join(least, F.col("u") == F.col("w")).select(F.col("v").alias("u"), F.col("low").alias("v"))


def _small_star(edges: DataFrame) -> DataFrame:
    """Each smaller neighbour of a node, and the node, are linked to the least of them."""
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("low")).withColumnRenamed("u", "w")
    moved = down.join(least, F.col("u") == F.col("w")).select(F.col("v").alias("u"), F.col("low").alias("v"))
    return moved.union(least.select(F.col("w").alias("u"), F.col("low").alias("v"))).where("u <> v")


def _is_done(edges: DataFrame) -> bool:
    """Whether the edges are stars: no node has two roots, and no root a root of its own."""
    ends = edges.select(F.col("u").alias("node"), F.lit(1).alias("child"), F.lit(0).alias("root")).union(edges.select("v", F.lit(0), F.lit(1)))
    return ends.groupBy("node").agg(F.sum("child").alias("child"), F.max("root").alias("root")).where("child + root > 1").isEmpty()


def components(edges: DataFrame, label: str = "components") -> DataFrame:
    """edges (u, v) in any order and direction -> (node, component), the component being its least node. Nodes without an
    edge to another node are not listed. Every round is written to the shared folder; the driver sees one answer a round."""
    now = settle(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), label)
    while not _is_done(now):
        now = settle(_small_star(_large_star(now)).distinct(), label)
    return now.select(F.col("u").alias("node"), F.col("v").alias("component"))
