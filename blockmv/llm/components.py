"""Connected components of an edge table by alternating star contractions; all state stays distributed."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def _lowest(edges: DataFrame) -> DataFrame:
    """Per node u, the smallest neighbour. Pre-aggregated before the shuffle, so hubs cost one row for each task."""
    return edges.groupBy("u").agg(F.min("v").alias("m"))


def _large_star(edges: DataFrame) -> DataFrame:
    """Hang every larger neighbour of u onto the smallest of u and its neighbours. edges: u > v."""
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = _lowest(both).select("u", F.least("u", "m").alias("m"))
    return both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Hang u and its smaller neighbours onto the smallest of them. edges: u > v."""
    low = _lowest(edges)
    moved = edges.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(low.select("u", F.col("m").alias("v"))).filter("u <> v").distinct()


def _only_stars(edges: DataFrame) -> bool:
    """Whether each child has one root, and no root is a child: then each star is a component. One row per node at most
    leaves a task for each of its roles."""
    roles = edges.select(F.col("u").alias("n"), F.lit(1).alias("child"), F.lit(0).alias("root")).union(edges.select("v", F.lit(0), F.lit(1)))
    both = roles.groupBy("n").agg(F.sum("child").alias("child"), F.max("root").alias("root"))
    return both.filter("child > 1 or (child = 1 and root = 1)").isEmpty()


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """edges (u, v) of one ordered type, in any direction -> node, root: the smallest node of its component.

    Nodes without an edge do not appear. Each round is written to the shared folder, so lineage stays short and a lost
    executor repeats one round at most. Self-loops and repeated edges are ignored; an empty table gives no rows.
    """
    now = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).filter("u <> v").distinct()
    now = common.materialise(now, "edges")
    for _ in range(max_rounds):
        if _only_stars(now):
            return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select("v", "v").distinct())
        after = common.materialise(_small_star(_large_star(now)), "edges")
        common.discard(now)
        now = after
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
