"""The update log as a stream: ingest, windows, and the maintained index behind foreachBatch."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navgraph.operators import index as ix
from navgraph.operators.index import GraphParams, MaintainedIndex, RebuildPolicy
from navgraph.session import scratch_path, written
from navgraph.sources import vectors as sources

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def as_log(events: DataFrame, vectors: DataFrame, n: int) -> DataFrame:
    """signup inserts, error deletes, purchase upserts; the vector comes from the static side."""
    op = F.when(F.col("event_type") == "signup", "upsert").when(F.col("event_type") == "error", "delete").when(F.col("event_type") == "purchase", "upsert")
    log = events.select(F.col("event_id").alias("seq"), op.alias("op"), (F.col("event_id") % n).alias("label"), ((F.col("event_id") * 7 + 3) % n).alias("source")).filter("op IS NOT NULL")
    return log.join(vectors.select(F.col("label").alias("source"), "vec"), "source").select("seq", "op", "label", "vec")


def windowed_rates(events: DataFrame, width: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Operations by type and window; later ones than `late` are dropped here."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def deduplicated(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def served_then_deleted(queries: DataFrame, deletes: DataFrame, within: str = "2 hours") -> DataFrame:
    """Interval join of two streams: a label that was asked for and deleted within `within`. Both: label, ts."""
    q = queries.select(F.col("label").alias("asked"), F.col("ts").alias("asked_at")).withWatermark("asked_at", "10 minutes")
    d = deletes.select("label", F.col("ts").alias("deleted_at")).withWatermark("deleted_at", "10 minutes")
    return q.join(d, F.expr(f"asked = label AND deleted_at BETWEEN asked_at AND asked_at + INTERVAL {within}"))


def maintain(log: DataFrame, index: MaintainedIndex, checkpoint: str):
    """Applies each micro-batch to the index. A batch that is run again has the number of an epoch that exists, and is left out."""

    def step(batch: DataFrame, number: int) -> None:
        index.apply(ix.normalized_log(batch), number)

    return log.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def replay(spark: SparkSession, sf_dir: str, params: GraphParams, files: int = 8) -> DataFrame:
    """The index of the embeddings after all events, streamed in `files` files, one after the other."""
    path = scratch_path(spark, "events")
    src = sources.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    first, last = src.agg(F.min("event_id"), F.max("event_id")).first()
    step = max(1, -(-(last - first + 1) // files))
    for start in range(first, last + 1, step):  # a file stream takes files by their age
        src.filter(F.col("event_id").between(start, start + step - 1)).coalesce(1).write.mode("append").parquet(path)
    p = written(sources.embeddings(spark, sf_dir), "points")
    index = MaintainedIndex(written(ix.build(p, params, 4, compiled=True), "index"), params, policy=RebuildPolicy(200))
    maintain(as_log(events(spark, path), p, p.count()), index, scratch_path(spark, "stream")).awaitTermination()
    return ix.live(index.index)


def late_aside(events: DataFrame, path: str, late: str, checkpoint: str):
    """Events more than `late` behind the newest one of earlier batches go to `path`/late, the others to `path`/on_time, so that
    nothing that a watermark drops is lost. A batch that runs again writes the same folders."""
    spark = events.sparkSession

    def step(batch: DataFrame, number: int) -> None:
        before = spark.read.schema("number long, newest timestamp").parquet(f"{path}/newest").filter(F.col("number") < number).agg(F.max("newest")).first()[0] if number else None
        is_late = F.lit(False) if before is None else F.col("ts") < F.lit(before) - F.expr(f"INTERVAL {late}")
        for name, wanted in (("late", is_late), ("on_time", ~is_late)):
            batch.filter(wanted).write.mode("overwrite").parquet(f"{path}/{name}/batch={number}")
        batch.agg(F.lit(number).cast("long").alias("number"), F.max("ts").alias("newest")).write.mode("overwrite").parquet(f"{path}/newest/batch={number}")

    return events.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def search_stream(queries: DataFrame, index: MaintainedIndex, k: int, ef: int, path: str, checkpoint: str):
    """Stream of queries (query_id, vec) against the index as it is when a batch comes; hits go to `path`, a folder a batch."""

    def step(batch: DataFrame, number: int) -> None:
        index.search(batch, k, ef).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return queries.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def mixed(log: DataFrame, index: MaintainedIndex, k: int, ef: int, path: str, checkpoint: str):
    """One stream of updates and queries (op "query"): each batch's updates are applied, then its queries answered below `path`."""

    def step(batch: DataFrame, number: int) -> None:
        own = written(batch, "mixed")
        index.apply(ix.normalized_log(own.filter("op != 'query'")), number)
        index.search(own.filter("op = 'query'").select(F.col("seq").alias("query_id"), "vec"), k, ef).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return log.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def stateful(log: DataFrame, params: GraphParams, strategy: str = "mutual_gamma", shards: int = 4) -> DataFrame:
    """(shard, live, reuses, unreachable) after each batch: every shard's graph is the state of its key, changed in order of seq."""
    import pandas as pd
    import pyarrow as pa
    from pyspark.sql.streaming.state import GroupStateTimeout

    from navgraph.operators.kernel import GraphKernel
    from navgraph.session import ship

    ship(log.sparkSession)

    def change(key, batches, state):
        table = None
        if state.exists:
            with pa.ipc.open_stream(state.get[0]) as reader:
                table = reader.read_all()
        g = GraphKernel.from_table(table) if table is not None else None
        for r in sorted((r for frame in batches for r in frame.to_dict("records")), key=lambda r: r["seq"]):
            g = g or (GraphKernel(len(r["vec"]), params.m, params.m0, params.ef_construction, params.metric) if r["vec"] is not None else None)
            if g is not None:
                g.mark_deleted(r["label"])
                if r["op"] != "delete":
                    g.replace_update(r["label"], r["vec"], strategy, r["seq"] + 1)
        if g is None or not g.label:
            return
        out, table = pa.BufferOutputStream(), g.table("main", key[0], shards)
        with pa.ipc.new_stream(out, table.schema) as writer:
            writer.write_table(table)
        state.update((out.getvalue().to_pybytes(),))
        yield pd.DataFrame({"shard": [key[0]], "live": [len(g.live())], "reuses": [g.reuses], "unreachable": [len(g.unreachable_degree())]})

    dealt = log.select("seq", "op", "label", "vec", ix.shard_of(F.col("label"), shards).alias("shard"))
    return dealt.groupBy("shard").applyInPandasWithState(change, "shard int, live long, reuses long, unreachable long", "graph binary", "update", GroupStateTimeout.NoTimeout)
