"""Exact nearest neighbours: ground truth, the deterministic k-NN graph, radius search."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from navgraph.functions.vectors import METRICS, l2
from navgraph.session import ship

#: Numbers of all queries' vectors together that are sent to every task at most (8 bytes each); more are dealt out in blocks.
SENT = 8 << 20
#: Rows of points that meet the queries at once, and queries that they meet at once.
ROWS, ASKED = 4096, 1024


def pairs(points: DataFrame, queries: DataFrame, most: int = 50_000) -> DataFrame:
    """Every query with every point. More than `most` queries go to blocks; points are read once per block and each block is dealt out
    over as many keys as there are blocks, so that no key holds all points."""
    n = queries.limit(most + 1).count()
    if n <= most:
        return points.crossJoin(F.broadcast(queries))
    blocks = -(-queries.count() // most)
    salts = 16
    q = queries.withColumn("_block", F.pmod(F.xxhash64("query_id"), F.lit(blocks))).withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    p = points.withColumn("_block", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))).withColumn("_salt", F.pmod(F.xxhash64("label"), F.lit(salts)).cast("int"))
    return p.join(q, ["_block", "_salt"]).drop("_block", "_salt")


def apart(x: np.ndarray, q: np.ndarray, metric: str) -> np.ndarray:
    """Distances of pairs of rows, as the Column forms define them (NaN where a cosine has none)."""
    if metric == "l2":
        return np.sqrt(((x - q) ** 2).sum(-1))
    product = (x * q).sum(-1)
    if metric == "ip":
        return -product
    lengths = np.sqrt((x * x).sum(-1)) * np.sqrt((q * q).sum(-1))
    return np.where(lengths > 0, 1 - product / np.where(lengths > 0, lengths, 1), np.nan)


def _products(points: DataFrame, ids: np.ndarray, vectors: np.ndarray, k: int, metric: str, exclude_self: bool) -> DataFrame:
    """The k nearest of each query in every run of points: matrix products choose a few more than k, whose distances are then
    taken exactly."""
    ship(points.sparkSession)
    sent = points.sparkSession.sparkContext.broadcast((ids, vectors))

    def search(batches):
        own, q = sent.value
        lengths = (q * q).sum(1)
        for batch in batches:
            for at in range(0, batch.num_rows, ROWS):
                part = batch.slice(at, ROWS)
                labels = part.column(0).to_numpy()
                x = part.column(1).flatten().to_numpy().reshape(len(labels), -1)
                norm = (x * x).sum(1)
                for b in range(0, len(own), ASKED):
                    some = slice(b, b + ASKED)
                    score = q[some] @ x.T
                    if metric == "l2":
                        score = norm - 2 * score
                    elif metric == "ip":
                        score = -score
                    else:
                        score = -score / np.maximum(np.sqrt(norm) * np.sqrt(lengths[some])[:, None], 1e-300)
                    if exclude_self:
                        score[own[some][:, None] == labels] = np.inf
                    few = min(k + 4, len(labels))
                    near = np.argpartition(score, few - 1, axis=1)[:, :few]
                    # Those as near as the last one within rounding stay too.
                    last = np.take_along_axis(score, near, 1).max(1, keepdims=True)
                    r, c = np.nonzero(score <= last + 1e-9 * (np.abs(last) + 1)) if np.isfinite(last).all() else (np.repeat(np.arange(len(near)), few), near.ravel())
                    d = apart(x[c], q[some][r], metric)
                    good = ~np.isnan(d) & ((own[some][r] != labels[c]) | (not exclude_self))
                    r, c, d = r[good], c[good], d[good]
                    order = np.lexsort((labels[c], d, r))
                    r, c, d = r[order], c[order], d[order]
                    keep = np.arange(len(r)) - np.searchsorted(r, r) < k
                    yield pa.RecordBatch.from_arrays([pa.array(own[some][r[keep]]), pa.array(labels[c[keep]]), pa.array(d[keep])], names=["query_id", "label", "dist"])

    return points.select(F.col("label").cast("long").alias("label"), "pv").mapInArrow(search, "query_id long, label long, dist double")


def ranked(found: DataFrame, k: int) -> DataFrame:
    """The k nearest labels of each query (ties: smaller label); partial limits run before the exchange."""
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("dist", "label"))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k)


def knn(points: DataFrame, queries: DataFrame, k: int, metric: str = "l2", exclude_self: bool = False, where: Column | None = None, sent: int = SENT) -> DataFrame:
    """query_id, rank, label, dist. points: label, vec; queries: query_id, vec. `where` filters points before the search.

    Queries of at most `sent` numbers in all, all of one length, meet the points in matrix products; others by expressions, in
    blocks. Both give the same.
    """
    p = (points if where is None else points.filter(where)).select("label", F.col("vec").cast("array<double>").alias("pv"))
    q = queries.select(F.col("query_id").cast("long").alias("query_id"), F.col("vec").cast("array<double>").alias("qv"))
    n, total, least, most = q.agg(F.count(F.lit(1)), F.sum(F.size("qv")), F.min(F.size("qv")), F.max(F.size("qv"))).first()
    if n and total <= sent and least == most > 0:
        table = q.toArrow()
        vectors = table.column("qv").combine_chunks().flatten().to_numpy().reshape(n, -1)
        return ranked(_products(p.filter(F.size("pv") == most), table.column("query_id").to_numpy(), vectors, k, metric, exclude_self), k).select("query_id", "rank", "label", "dist")
    found = pairs(p, q)
    if exclude_self:
        found = found.filter("label != query_id")
    found = found.select("query_id", "label", METRICS[metric](F.col("pv"), F.col("qv")).alias("dist")).filter("dist IS NOT NULL")
    return ranked(found, k).select("query_id", "rank", "label", "dist")


def knn_graph(points: DataFrame, k: int) -> DataFrame:
    """src, nbrs (nearest first): the deterministic one-layer graph G0."""
    found = knn(points, points.select(F.col("label").alias("query_id"), "vec"), k, exclude_self=True)
    return found.groupBy(F.col("query_id").alias("src")).agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", "label"))), lambda x: x["label"]).alias("nbrs"))


def edges(lists: DataFrame) -> DataFrame:
    return lists.select("src", F.posexplode("nbrs").alias("place", "dst"))


def radius(points: DataFrame, r: float, rows: int = ROWS) -> DataFrame:
    """a < b with distance of at most r.

    Points are dealt by hash into blocks of about `rows`, and every two blocks meet in one task's matrix product, which leaves pairs
    near enough but for rounding; their distances are then taken exactly. Null vectors, and pairs of different lengths, have no distance.
    """
    ship(points.sparkSession)
    p = points.select(F.col("label").cast("long").alias("label"), F.col("vec").cast("array<double>").alias("vec")).filter("label IS NOT NULL AND vec IS NOT NULL")
    n = p.count()
    blocks = max(1, -(-n // rows))
    p = p.withColumn("block", F.pmod(F.xxhash64("label"), F.lit(blocks)).cast("int"))
    # Block i meets block j where i <= j; a row goes to all pairs of which its block is one.
    pair = lambda i, j: F.struct(F.least(i, j).alias("i"), F.greatest(i, j).alias("j"))
    dealt = p.withColumn("pair", F.explode(F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda j: pair(F.col("block"), j)))).select("pair.i", "pair.j", "block", "label", "vec")

    def meet(key, table):
        i, j = (k.as_py() for k in key)
        block, size = table.column("block").to_numpy(), table.column("vec").combine_chunks().value_lengths().to_numpy()
        found = []
        for length in np.unique(size):
            own = table.filter(pa.array(size == length))
            labels, x, at = own.column("label").to_numpy(), own.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(own), -1), block[size == length]
            one, two = np.flatnonzero(at == i), np.flatnonzero(at == j)
            norm = (x * x).sum(1)
            for k in range(0, len(one), ASKED):
                few = one[k : k + ASKED]
                with np.errstate(all="ignore"):
                    apart2 = norm[few][:, None] + norm[two] - 2 * (x[few] @ x[two].T)
                    slack = 1e-9 * (norm[few][:, None] + norm[two] + r * r)
                # Not above it, so that what has no number is looked at again.
                u, v = np.nonzero(~(apart2 > r * r + slack))
                u, v = few[u], two[v]
                low, high = np.where(labels[u] < labels[v], u, v), np.where(labels[u] < labels[v], v, u)
                good = (labels[low] < labels[high]) & ((u < v) if i == j else True)
                low, high = low[good], high[good]
                for c in range(0, len(low), 1 << 16):
                    l, h = low[c : c + (1 << 16)], high[c : c + (1 << 16)]  # noqa: E741
                    with np.errstate(all="ignore"):
                        d = apart(x[l], x[h], "l2")
                    near = d <= r
                    found.append((labels[l][near], labels[h][near], d[near]))
        parts = [np.concatenate(c) if found else np.zeros(0) for c in (zip(*found, strict=True) if found else [()] * 3)]
        return pa.table({"a": pa.array(parts[0], pa.int64(), from_pandas=False), "b": pa.array(parts[1], pa.int64()), "dist": pa.array(parts[2], pa.float64())})

    return dealt.groupBy("i", "j").applyInArrow(meet, "a long, b long, dist double")


__all__ = ["edges", "knn", "knn_graph", "l2", "pairs", "radius", "ranked"]
