"""Which points of a graph can be found: relational measures over (src, dst) edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from navgraph.session import written


def unreachable_degree(nodes: DataFrame, edges: DataFrame, entry: int | None = None) -> DataFrame:
    """Live points without an in-edge in any layer; the entry point is exempt. nodes: label."""
    found = nodes.join(edges.select(F.col("dst").alias("label")).distinct(), "label", "left_anti")
    return found if entry is None else found.filter(F.col("label") != entry)


def found_bfs(edges: DataFrame, entry: int, most_rounds: int = 10_000) -> DataFrame:
    """Labels that can be walked to from `entry`. One join per hop; every few hops the visited set is written out."""
    spark = edges.sparkSession
    hops = written(edges.select("src", "dst").distinct(), "bfs-edges")
    seen = frontier = spark.createDataFrame([(entry,)], "label long")
    for i in range(most_rounds):
        new = frontier.join(hops, frontier["label"] == hops["src"]).select(F.col("dst").alias("label")).distinct().join(seen, "label", "left_anti")
        frontier = written(new, "bfs-frontier")
        if frontier.isEmpty():
            return seen
        seen = seen.unionByName(frontier)
        if i % 4 == 3:
            seen = written(seen, "bfs-seen")
    raise RuntimeError(f"no end after {most_rounds} rounds")


def unreachable_bfs(nodes: DataFrame, edges: DataFrame, entry: int) -> DataFrame:
    return nodes.join(found_bfs(edges, entry), "label", "left_anti")
