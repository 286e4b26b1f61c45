"""Vector sets of the given tables (label, vec, version)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navgraph.session import ship

#: Words whose hashes a task remembers at most.
WORDS = 1_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("label"), F.col("embedding").alias("vec"), F.lit(0).cast("long").alias("version"))


def hashed_documents(spark: SparkSession, sf_dir: str, dim: int = 64) -> DataFrame:
    """Signed word hashes: bucket by eight hex digits of the word's md5, sign by the ninth, summed, unit length."""
    ship(spark)

    def hashed(batches):
        import hashlib

        import numpy as np
        import pyarrow as pa

        known: dict[str, int] = {}  # word: twice its bucket, and one more for a minus
        for b in batches:
            out = np.zeros((b.num_rows, dim), np.int64)
            for row, text in zip(out, b.column("text").to_pylist(), strict=True):
                words = (text or "").split(" ")
                for w in words:
                    if w not in known:
                        h = hashlib.md5(w.encode()).hexdigest()
                        known[w] = 2 * (int(h[:8], 16) % dim) + int(h[8], 16) % 2
                n = np.bincount(np.fromiter(map(known.__getitem__, words), np.int64, len(words)), minlength=2 * dim)
                row += n[::2] - n[1::2]
                if len(known) > WORDS:
                    known.clear()
            yield pa.RecordBatch.from_arrays([b.column("label"), pa.ListArray.from_arrays(np.arange(0, out.size + 1, dim, dtype=np.int32), out.ravel())], ["label", "n"])

    texts = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("label"), "text")
    kind = texts.schema["label"].dataType.simpleString()
    # Columns a component: unlike functions of arrays these are compiled. The squares are whole numbers, so the order of their sum counts for nothing.
    c = [f"n{i}" for i in range(dim)]
    sums = texts.mapInArrow(hashed, f"label {kind}, n array<long>").groupBy("label").agg(*(F.sum(F.col("n")[i]).cast("double").alias(x) for i, x in enumerate(c)))
    sums = sums.withColumn("length", F.sqrt(reduce(lambda x, y: x + y, (F.col(x) * F.col(x) for x in c))))
    unit = F.array(*(F.when(F.col("length") > 0, F.col(x) / F.col("length")).otherwise(F.col(x)) for x in c))
    return sums.select("label", unit.cast("array<float>").alias("vec"), F.lit(0).cast("long").alias("version"))


def part_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per part: means of quantity, price, discount, tax; shares of return flags, line status and ship quarters."""
    flag, status, quarter = F.col("l_returnflag"), F.col("l_linestatus"), F.quarter("l_shipdate")
    share = lambda c: F.avg(c.cast("double"))
    return table(spark, sf_dir, "lineitem").groupBy("l_partkey").agg(
        F.avg("l_quantity").alias("quantity"), F.avg("l_extendedprice").alias("price"), F.avg("l_discount").alias("discount"), F.avg("l_tax").alias("tax"),
        *(share((flag == x).cast("int")).alias(f"flag_{x.lower()}") for x in "ANR"), *(share((status == x).cast("int")).alias(f"status_{x.lower()}") for x in "FO"),
        *(share((quarter == q).cast("int")).alias(f"quarter_{q}") for q in range(1, 5)),
    )


def part_profiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = part_features(spark, sf_dir)
    columns = f.columns[1:]
    spread = f.agg(*(x for c in columns for x in (F.avg(c).alias(f"m_{c}"), F.stddev_pop(c).alias(f"s_{c}"))))
    scored = F.array(*(F.coalesce((F.col(c) - F.col(f"m_{c}")) / F.nullif(F.col(f"s_{c}"), F.lit(0.0)), F.lit(0.0)) for c in columns))
    return f.crossJoin(F.broadcast(spread)).select(F.col("l_partkey").alias("label"), scored.cast("array<float>").alias("vec"), F.lit(0).cast("long").alias("version"))


VECTOR_SETS = {"embeddings": embeddings, "documents": hashed_documents, "parts": part_profiles}
