"""Connected components of a table of links, without gathering any of it on the driver."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from navgraph.session import ship, written

#: Links that one task unites at most (16 bytes each, and about eight times that while it works); more go by joins.
ONE_TASK = 4_000_000


def united(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of the links, ascending, and the least node that each is linked with, directly or not."""
    nodes, place = np.unique(np.concatenate((a, b)), return_inverse=True)
    x, y = place[: len(a)], place[len(a) :]
    up = np.arange(len(nodes))
    while len(x):
        x, y = up[x], up[y]
        apart = x != y
        x, y = np.minimum(x[apart], y[apart]), np.maximum(x[apart], y[apart])
        np.minimum.at(up, y, x)
        while (up[up] != up).any():
            up = up[up]
    return nodes, nodes[up]


def _joined(star: DataFrame, most_rounds: int) -> DataFrame:
    """Every node sends its larger neighbours to its least one, then its smaller ones too, until nothing changes. Trees become
    stars within about log2(nodes) rounds. Each round is written out, so lineage stays short."""

    def least(edges: DataFrame) -> DataFrame:
        return edges.groupBy("a").agg(F.min("b").alias("m"))

    before = None
    for _ in range(most_rounds):
        both = star.unionByName(star.select(F.col("b").alias("a"), F.col("a").alias("b")))
        small = least(both.unionByName(both.select("a", F.col("a").alias("b"))))
        large = both.filter("b > a").join(small, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = least(large).select(F.col("a"), F.col("m"))
        next_ = large.join(low, "a").filter("b != m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select("a", F.col("m").alias("b"))).distinct()
        star = written(next_, "links")
        state = tuple(star.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
        if state == before:
            return star.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(star.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
        before = state
    raise RuntimeError(f"no end after {most_rounds} rounds")


def components(links: DataFrame, most_rounds: int = 60, one_task: int = ONE_TASK) -> DataFrame:
    """One row (node, component) for every node of links (a, b) but self-links, component being the least node it is linked
    with, directly or not. Nodes are whole numbers; a link with a null end counts for nothing, repeated links do no harm.

    Tables of at most `one_task` links, counted once written, go through one task; larger ones through rounds of joins.
    """
    ship(links.sparkSession)
    star = written(links.filter("a != b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")), "links")
    if star.count() > one_task:
        return _joined(written(star.distinct(), "links"), most_rounds)

    def pack(batches):
        a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for batch in batches:
            a.append(batch.column(0).to_numpy())
            b.append(batch.column(1).to_numpy())
        a, b = np.concatenate(a), np.concatenate(b)
        nodes, least = united(a, b)
        own = nodes != least
        yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([nodes[own].tobytes()], pa.binary()), pa.array([least[own].tobytes()], pa.binary())], names=["all", "a", "b"])

    def unite(key, table):
        a, b = (np.frombuffer(b"".join(table.column(c).to_pylist()), np.int64) for c in ("a", "b"))
        nodes, least = united(a, b)
        return pa.table({"node": nodes, "component": least})

    # What a task has united already goes on as one row.
    return star.mapInArrow(pack, "all int, a binary, b binary").groupBy("all").applyInArrow(unite, "node long, component long")
