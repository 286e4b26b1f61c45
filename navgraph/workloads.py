"""Churn scenarios as tables of (iter, op, label), drawn by md5 so that every engine reproduces them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from navgraph.functions.vectors import draw
from navgraph.session import written


def numbered(df: DataFrame, *columns: str, name: str = "i") -> tuple[DataFrame, int]:
    """Adds each row's place (from 0) in the order of `columns`, and gives the number of rows.

    Rows are dealt into ranges and numbered within them; only the ranges' sizes, one row a partition, come together.
    """
    ranges = written(df.repartitionByRange(*columns).withColumn("_range", F.spark_partition_id()), "ranges")
    sizes = {r["_range"]: r["n"] for r in ranges.groupBy("_range").agg(F.count(F.lit(1)).alias("n")).collect()}
    before, total = {}, 0
    for k in sorted(sizes):
        before[k], total = total, total + sizes[k]
    first = F.element_at(F.map_from_arrays(F.array(*map(F.lit, before)), F.array(*map(F.lit, before.values()))), F.col("_range")) if before else F.lit(0)
    place = F.row_number().over(Window.partitionBy("_range").orderBy(*columns)) - 1 + first
    return ranges.withColumn(name, place.cast("long")).drop("_range"), total


def full_coverage(points: DataFrame, parts: int = 100) -> DataFrame:
    """(iter, label): equal parts by label (the first ones one larger, if need be), one per iteration; each is deleted and put back."""
    placed, n = numbered(points.select("label"), "label")
    small, larger = divmod(n, parts)
    i = F.col("i")
    part = F.when(i < larger * (small + 1), F.floor(i / (small + 1))).otherwise(larger + F.floor((i - larger * (small + 1)) / max(small, 1)))
    return placed.select(part.cast("int").alias("iter"), "label")


def random_churn(points: DataFrame, iters: int, batch: int, seed: int = 42) -> DataFrame:
    """(iter, label): in every iteration the `batch` labels with the least draw."""
    turns = points.select("label", F.explode(F.sequence(F.lit(0), F.lit(iters - 1))).alias("iter"))
    rank = F.row_number().over(Window.partitionBy("iter").orderBy(draw(F.col("label"), seed, F.col("iter")), "label"))
    return turns.withColumn("_n", rank).filter(F.col("_n") <= batch).select("iter", "label")


def new_data(points: DataFrame, iters: int = 10) -> DataFrame:
    """(iter, op, label): the first half is loaded; each iteration swaps a share of it for one of the second half."""
    placed, n = numbered(points.select("label"), "label")
    half = n // 2
    place = F.when(F.col("i") < half, F.col("i")).otherwise(F.col("i") - half)
    size = F.when(F.col("i") < half, F.lit(max(half, 1))).otherwise(F.lit(max(n - half, 1)))
    return placed.select(F.floor(place * iters / size).cast("int").alias("iter"), F.when(F.col("i") < half, "delete").otherwise("insert").alias("op"), "label")


def slot_pairs(deleted: DataFrame, inserted: DataFrame, order: str = "fifo") -> DataFrame:
    """(slot, label): the slot marked first goes to the first insertion (fifo) or to the last (reverse). deleted: slot, seq;
    inserted: label, seq."""
    d, _ = numbered(deleted.select("slot", "seq"), "seq", "slot", name="n")
    i, total = numbered(inserted.select("label", "seq"), "seq", "label", name="n")
    if order != "fifo":
        i = i.withColumn("n", F.lit(total - 1) - F.col("n"))
    return d.select("slot", "n").join(i.select("label", "n"), "n").select("slot", "label")
