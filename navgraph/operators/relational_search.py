"""Search of a one-layer graph for many queries at once, by joins: all queries go one hop further per round."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from navgraph.functions.vectors import l2
from navgraph.session import written


def beam_search(lists: DataFrame, vectors: DataFrame, queries: DataFrame, entry: int, k: int, ef: int, most_rounds: int = 1000) -> DataFrame:
    """query_id, rank, slot, dist. lists: src, nbrs; vectors: slot, vec; queries: query_id, vec.

    Every round opens all unopened slots of each query's beam of ef; what was seen is kept, so nothing is opened twice. With
    ef of at least the number of slots, everything that can be walked to is found. Rounds are written out, their end is a
    single count.
    """
    hops = written(lists.select("src", F.explode("nbrs").alias("slot")), "hops")
    v = vectors.select("slot", F.col("vec").cast("array<double>").alias("v"))
    q = queries.select("query_id", F.col("vec").cast("array<double>").alias("q"))

    def measured(pairs: DataFrame) -> DataFrame:
        return pairs.join(v, "slot").join(q, "query_id").select("query_id", "slot", l2(F.col("v"), F.col("q")).alias("dist"), F.lit(False).alias("opened"))

    best = F.row_number().over(Window.partitionBy("query_id").orderBy("dist", "slot"))
    seen = written(measured(q.select("query_id", F.lit(entry).cast("long").alias("slot"))), "beam")
    for _ in range(most_rounds):
        beam = seen.withColumn("n", best)
        todo = beam.filter((F.col("n") <= ef) & ~F.col("opened")).select("query_id", F.col("slot").alias("src"))
        if todo.isEmpty():
            return seen.withColumn("rank", best).filter(F.col("rank") <= k).select("query_id", "rank", "slot", "dist")
        new = todo.join(hops, "src").select("query_id", "slot").distinct().join(seen.select("query_id", "slot"), ["query_id", "slot"], "left_anti")
        old = beam.select("query_id", "slot", "dist", (F.col("opened") | (F.col("n") <= ef)).alias("opened"))
        seen = written(old.unionByName(measured(new)), "beam")
    raise RuntimeError(f"no end after {most_rounds} rounds")
