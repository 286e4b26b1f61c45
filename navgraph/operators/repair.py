"""Repair of a graph around reused slots, a batch at a time.

All reads see the lists from before the batch and a slot in the batch stands for its new occupant, so the result depends on no
order, a retried task repeats it, and one batch of one slot equals the kernel's repair. The five strategies are three choices.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from navgraph.functions.vectors import l2, rng_prune


@dataclass(frozen=True)
class Strategy:
    """targets: "out", "mutual" or "mutual+twohop"; pool: "twohop" or "local"; alpha of the pruning."""

    targets: str
    pool: str
    alpha: float


STRATEGIES = {
    "native": Strategy("out", "twohop", 1.0),
    "mutual_alpha": Strategy("mutual", "twohop", 1.0),
    "mutual_beta": Strategy("mutual", "local", 1.0),
    "mutual_gamma": Strategy("mutual", "local", 1.1),
    "mutual_twohop": Strategy("mutual+twohop", "local", 1.1),
}


def two_hop(edges: DataFrame, batch: DataFrame) -> DataFrame:
    """(d, node): out-neighbours of each slot of the batch, and theirs."""
    one = edges.join(F.broadcast(batch.select(F.col("slot").alias("src"))), "src").select(F.col("src").alias("d"), F.col("dst").alias("node"))
    two = one.join(edges.select(F.col("src").alias("node"), "dst"), "node").select("d", F.col("dst").alias("node"))
    return one.unionByName(two).distinct()


def targets(edges: DataFrame, batch: DataFrame, kind: str, keep_batch: bool = False, two: DataFrame | None = None) -> DataFrame:
    """(d, u): which lists are rewritten for which slot. Those in the batch are left out; placement writes their lists. two: what
    two_hop() gives, if it is there already."""
    e = edges.select("src", "dst")
    slots = batch.select("slot")
    back = e.join(F.broadcast(slots), F.col("dst") == F.col("slot")).select(F.col("dst").alias("d"), F.col("src").alias("u"))
    one = e.join(F.broadcast(slots), F.col("src") == F.col("slot")).select(F.col("src").alias("d"), F.col("dst").alias("u"))
    found = one.distinct()
    if kind != "out":
        found = found.join(back, ["d", "u"], "left_semi")
    if kind == "mutual+twohop":
        far = (two_hop(e, batch) if two is None else two).withColumnRenamed("node", "u").filter("d != u").join(back, ["d", "u"], "left_semi")
        found = found.unionByName(far).distinct()
    return found if keep_batch else found.join(F.broadcast(slots), found["u"] == F.col("slot"), "left_anti")


def pools(edges: DataFrame, batch: DataFrame, strategy: Strategy, two: DataFrame | None = None) -> DataFrame:
    """(u, cand): candidates of every target, over all slots it is a target of; without itself."""
    e, t = edges.select("src", "dst"), targets(edges, batch, strategy.targets, two=two)
    if strategy.pool == "twohop":
        near = t.join(two_hop(e, batch) if two is None else two, "d").select("u", F.col("node").alias("cand"))
    else:
        own = t.select("u").distinct().join(e, F.col("u") == F.col("src")).select("u", F.col("dst").alias("cand"))
        near = own.unionByName(t.join(e, F.col("d") == F.col("src")).select("u", F.col("dst").alias("cand")))
    return near.unionByName(t.select("u", F.col("d").alias("cand"))).distinct().filter("u != cand")


def occupants(vectors: DataFrame, batch: DataFrame, incoming: DataFrame) -> DataFrame:
    """(slot, vec) with the new points in the slots of the batch. vectors: label, vec; batch: slot, label; incoming: label, vec."""
    b = batch.select(F.col("slot").alias("s"), F.col("label").alias("n"))
    new = b.join(incoming.select(F.col("label").alias("n"), "vec"), "n").select(F.col("s").alias("slot"), "vec")
    old = vectors.join(F.broadcast(b), vectors["label"] == F.col("s"), "left_anti").select(F.col("label").alias("slot"), "vec")
    return old.unionByName(new)


def pruned(pool: DataFrame, vectors: DataFrame, cap: int, alpha: float) -> DataFrame:
    """(u, nbrs): the relaxed-neighbourhood selection from (u, cand). vectors: slot, vec."""
    v = vectors.select("slot", F.col("vec").cast("array<double>").alias("v"))
    c = pool.join(v.select(F.col("slot").alias("cand"), F.col("v").alias("cv")), "cand").join(v.select(F.col("slot").alias("u"), F.col("v").alias("uv")), "u")
    c = c.groupBy("u").agg(F.collect_list(F.struct(l2(F.col("uv"), F.col("cv")).alias("dist"), F.col("cand").alias("id"), F.col("cv").alias("vec"))).alias("c"))
    return c.select("u", rng_prune(F.col("c"), cap, alpha).alias("nbrs"))


def repair_batch(lists: DataFrame, vectors: DataFrame, batch: DataFrame, incoming: DataFrame, strategy: Strategy, cap: int) -> DataFrame:
    """(u, nbrs): new lists of the targets. lists: src, nbrs."""
    e = lists.select("src", F.explode("nbrs").alias("dst"))
    return pruned(pools(e, batch, strategy), occupants(vectors, batch, incoming), cap, strategy.alpha)


def replaced(lists: DataFrame, new: DataFrame) -> DataFrame:
    """lists with those of `new` (u, nbrs) instead of the old ones."""
    n = new.select(F.col("u").alias("src"), F.col("nbrs").alias("new"))
    return lists.join(n, "src", "left").select("src", F.coalesce("new", "nbrs").alias("nbrs"))


def stale_in_edges(edges: DataFrame, batch: DataFrame, kind: str) -> DataFrame:
    """(src, dst): edges into reused slots from nodes that no repair looked at, and that aren't reused themselves."""
    slots = F.broadcast(batch.select("slot"))
    into = edges.select("src", "dst").join(slots, F.col("dst") == F.col("slot"), "left_semi").join(slots, F.col("src") == F.col("slot"), "left_anti")
    return into.join(targets(edges, batch, kind).select(F.col("d").alias("dst"), F.col("u").alias("src")), ["src", "dst"], "left_anti")
