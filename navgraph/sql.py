"""The index from SQL: table functions, a data source, and vector functions."""

from __future__ import annotations

import pyarrow.dataset as ds
from pyarrow import fs
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from navgraph.functions import vectors
from navgraph.operators.kernel import GraphKernel
from navgraph.schema import INDEX, arrow_schema
from navgraph.session import ship


def _filesystem(path: str):
    """The file system of a path as Arrow sees it; without a scheme, that of this machine (file:, hdfs:, s3: and others by URI)."""
    return fs.FileSystem.from_uri(path) if "://" in path else fs.FileSystem.from_uri(f"file://{path.removeprefix('file:')}")


def _dataset(path: str, epoch: int):
    system, root = _filesystem(path)
    return ds.dataset(f"{root.rstrip('/')}/epoch={epoch}", filesystem=system, partitioning="hive", format="parquet")


def _read(path: str, epoch: int, shard: int, slot: int | None = None):
    """The rows of one shard, or of one slot of it."""
    names = list(arrow_schema(INDEX).names)
    wanted = ds.field("shard") == shard
    return _dataset(path, epoch).to_table(columns=names, filter=wanted if slot is None else wanted & (ds.field("slot") == slot))


class AnnSearch:
    """ann_search(TABLE(queries with query_id, vec and shard) PARTITION BY (shard), path, epoch, k, ef): the k nearest of each query
    in the shard of its row. A partition of the table has one shard, which is opened once; rank over all shards is the caller's
    (see ann_search_all)."""

    def __init__(self):
        self.open: tuple | None = None
        self.graph: GraphKernel | None = None

    def eval(self, row, path: str, epoch: int, k: int, ef: int):
        at = (path, epoch, row["shard"])
        if self.open != at:
            rows = _read(*at)
            self.open, self.graph = at, GraphKernel.from_table(rows) if len(rows) else None
        for d, s in self.graph.knn(row["vec"], k, ef) if self.graph else ():
            yield row["query_id"], row["shard"], self.graph.label[s], float(d)


def ann_search_all(spark: SparkSession, queries: str, path: str, epoch: int, k: int, ef: int):
    """query_id, rank, label, dist of the k nearest over all shards saved below `path`, for the table or view `queries`
    (query_id, vec). Every shard is a partition of its own."""
    shards = f"SELECT DISTINCT shard FROM parquet.`{path.rstrip('/')}/epoch={epoch}`"
    asked = f"SELECT q.query_id, q.vec, s.shard FROM {queries} q CROSS JOIN ({shards}) s"
    hits = f"SELECT * FROM ann_search(TABLE({asked}) PARTITION BY (shard), '{path}', {epoch}, {k}, {ef})"
    return spark.sql(f"SELECT query_id, rank, label, dist FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, label) AS rank FROM ({hits})) WHERE rank <= {k}")


class GraphNeighbors:
    """graph_neighbors(path, epoch, shard, slot, layer): the out-list of a slot. Only the slot's row group is read."""

    def eval(self, path: str, epoch: int, shard: int, slot: int, layer: int):
        for own in _read(path, epoch, shard, slot).column("nbrs").to_pylist():
            if layer < len(own):
                yield from enumerate(own[layer])


class _Shard(InputPartition):
    def __init__(self, files: list[str]):
        self.files = files


class IndexReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.epoch = options["path"], int(options["epoch"])

    def partitions(self):
        return [_Shard([f]) for f in _dataset(self.path, self.epoch).files]

    def read(self, partition):
        system = _filesystem(self.path)[0]
        schema = arrow_schema(INDEX)
        for f in partition.files:
            for batch in ds.dataset([f], filesystem=system, partitioning=ds.partitioning(flavor="hive"), format="parquet").to_batches(columns=schema.names):
                for r in batch.to_pylist():
                    yield tuple(dict(r[n]) if n == "stats" and r[n] is not None else r[n] for n in schema.names)


class IndexSource(DataSource):
    """spark.read.format("navgraph").option("epoch", n).load(path)"""

    @classmethod
    def name(cls) -> str:
        return "navgraph"

    def schema(self) -> str:
        return INDEX

    def reader(self, schema):
        return IndexReader(self.options)


def register(spark: SparkSession) -> None:
    """ann_search, graph_neighbors, format navgraph, and vec_dot, vec_l2, vec_cosine."""
    ship(spark)
    spark.udtf.register("ann_search", F.udtf(AnnSearch, returnType="query_id: bigint, shard: int, label: bigint, dist: double"))
    spark.udtf.register("graph_neighbors", F.udtf(GraphNeighbors, returnType="place: int, slot: bigint"))
    spark.dataSource.register(IndexSource)
    vectors.register(spark)
