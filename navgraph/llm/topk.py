"""Exact top-k inner products by dual-tree search over cover trees.

Queries and candidates are dealt to blocks by their nearest pivot, so that blocks are small in space; each block's cover tree
is built once. A pair of blocks, or of tree nodes, is left out if no point of the one can score with any query of the other
what the worst of those queries has as its kth score: q.p <= cq.cp + Rq |cp| + Rp |cq| + Rq Rp, for centres c and covering radii
R. Every query block first meets the candidate block that lies best for it; the kth scores found there rule out whole pairs of
blocks before any of their vectors move, and go along with those that stay. Leaves are large and scored by one matrix product,
so that vectors that no bound can tell apart cost no more than the plain product.
"""

from __future__ import annotations

import io

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from navgraph.functions.vectors import dot, norm
from navgraph.llm.arrow import named
from navgraph.session import ship, written

#: Rows of a block of candidates and of queries; of a leaf of candidates and of queries; children of a node.
CANDIDATES, QUERIES, LEAF, ASKED, CHILDREN = 8192, 1024, 512, 64, 16
#: Most pivots, which every task gets. They are picked by hash and decide about speed alone.
PIVOTS = 256
NONE = np.iinfo(np.int64).min + 1


class CoverTree:
    """Nodes as arrays over points in an order that keeps a node's points together. Children's centres are picked farthest
    first, so they keep apart; every point goes to its nearest."""

    PARTS = ("x", "ids", "low", "high", "centre", "radius", "child", "children")

    def __init__(self, **parts: np.ndarray):
        for k in self.PARTS:
            setattr(self, k, parts[k])

    @classmethod
    def of(cls, x: np.ndarray, ids: np.ndarray, leaf: int) -> CoverTree:
        order, low, high, centre, radius, child, children = np.arange(len(x)), [0], [len(x)], [0], [], [0], [0]
        far = lambda points, c: np.sqrt(((x[points] - x[c]) ** 2).sum(1))
        if len(x):
            centre = [int(far(order, np.argmin(far(order, 0))).argmin())]
        todo = 0
        while todo < len(low):
            a, b, c = low[todo], high[todo], centre[todo]
            points = order[a:b]
            least = far(points, c)
            radius.append(float(least.max(initial=0.0)))
            if b - a > leaf and radius[-1] > 0:
                owner, picked = np.zeros(len(points), np.int64), [c]
                while len(picked) < 2 or (len(picked) < CHILDREN and least.max() > radius[-1] / 2):
                    picked.append(int(points[least.argmax()]))
                    new = far(points, picked[-1])
                    nearer = new < least
                    owner[nearer], least = len(picked) - 1, np.minimum(least, new)
                order[a:b] = points[np.argsort(owner, kind="stable")]
                ends = a + np.cumsum(np.bincount(owner, minlength=len(picked)))
                child[todo], children[todo] = len(low), len(picked)
                low += [a, *ends[:-1].tolist()]
                high += ends.tolist()
                centre += picked
                child += [0] * len(picked)
                children += [0] * len(picked)
            todo += 1
        place = np.empty(len(x), np.int64)
        place[order] = np.arange(len(x))
        whole = lambda v: np.array(v, np.int64)
        return cls(x=x[order], ids=ids[order], low=whole(low), high=whole(high), centre=place[whole(centre)] if len(x) else whole(centre), radius=np.array(radius), child=whole(child), children=whole(children))

    def dumped(self) -> bytes:
        out, small = io.BytesIO(), not len(self.x) or np.abs(self.x).max() < 1 << 15
        np.savez(out, **{k: getattr(self, k) for k in self.PARTS if k != "x"}, x=self.x.astype(np.int16) if small else self.x)
        return out.getvalue()

    @classmethod
    def loaded(cls, data: bytes) -> CoverTree:
        with np.load(io.BytesIO(data)) as parts:
            return cls(**{k: parts[k].astype(np.float64) if k == "x" else parts[k] for k in cls.PARTS})


class Best:
    """The k best (score, then smaller id) of each query so far; scores below `floor` aren't asked for."""

    def __init__(self, n: int, k: int, floor: np.ndarray | None = None):
        self.k, self.score, self.id = k, np.full((n, k), NONE), np.full((n, k), np.iinfo(np.int64).max)
        self.floor = np.full(n, NONE) if floor is None else floor.copy()

    def offer(self, rows: slice, scores: np.ndarray, ids: np.ndarray) -> None:
        least, n = self.floor[rows], scores.shape[1]
        if n > self.k:
            least = np.maximum(least, np.partition(scores, n - self.k, axis=1)[:, n - self.k])
        r, c = np.nonzero((scores >= least[:, None]) & (scores > NONE))
        if not len(r):
            return
        which, place = np.unique(r, return_inverse=True)
        own = which + rows.start
        row = np.concatenate((np.repeat(np.arange(len(which)), self.k), place))
        s, i = np.concatenate((self.score[own].ravel(), scores[r, c])), np.concatenate((self.id[own].ravel(), ids[c]))
        order = np.lexsort((i, -s, row))
        row = row[order]
        first = np.flatnonzero(np.concatenate(([True], row[1:] != row[:-1])))
        order = order[(first[:, None] + np.arange(self.k)).ravel()]
        self.score[own], self.id[own] = s[order].reshape(-1, self.k), i[order].reshape(-1, self.k)
        self.floor[own] = np.maximum(self.floor[own], self.score[own, -1])


def products(a: np.ndarray, b: np.ndarray, largest: float) -> np.ndarray:
    """Exact inner products of whole numbers. largest: at least the product of the largest lengths, which bounds every sum."""
    if largest < 1 << 24:
        return np.rint(a.astype(np.float32) @ b.astype(np.float32).T).astype(np.int64)
    if largest < 1 << 53:
        return np.rint(a @ b.T).astype(np.int64)
    if largest >= 1 << 62 and (np.abs(a @ b.T).max(initial=0) >= 0.999 * (1 << 63) or max(np.abs(a).max(initial=0), np.abs(b).max(initial=0)) >= 1 << 63):
        raise OverflowError("scores don't fit 64-bit whole numbers")
    return a.astype(np.int64) @ b.astype(np.int64).T


def dual_search(q: CoverTree, p: CoverTree, k: int, floor: np.ndarray | None = None) -> tuple[Best, int]:
    """The best of every query among points with another id, and the number of scores that were computed."""
    best, work = Best(len(q.x), k, floor), 0
    if not len(q.x) or not len(p.x):
        return best, work
    cq, cp = q.x[q.centre], p.x[p.centre]
    nq, np_ = np.sqrt((cq * cq).sum(1)), np.sqrt((cp * cp).sum(1))
    most = cq @ cp.T + q.radius[:, None] * np_ + p.radius * nq[:, None] + np.outer(q.radius, p.radius)
    most += 1e-9 * np.abs(most) + 1e-6
    largest = float(np.sqrt((q.x * q.x).sum(1).max() * (p.x * p.x).sum(1).max())) * (1 + 1e-9) + 1
    stack = [(0, 0)]
    while stack:
        a, b = stack.pop()
        rows = slice(int(q.low[a]), int(q.high[a]))
        if rows.stop == rows.start or most[a, b] < best.floor[rows].min():
            continue
        if not p.children[b] and not q.children[a]:
            for at in range(int(p.low[b]), int(p.high[b]), 4 * LEAF):
                own = slice(at, min(at + 4 * LEAF, int(p.high[b])))
                scores = products(q.x[rows], p.x[own], largest)
                work += scores.size
                scores[q.ids[rows][:, None] == p.ids[own]] = NONE
                best.offer(rows, scores, p.ids[own])
        elif q.children[a] and (not p.children[b] or q.radius[a] >= p.radius[b]):
            found = np.arange(q.child[a], q.child[a] + q.children[a])
            stack += [(int(c), b) for c in found[np.argsort(most[found, b])]]
        else:
            found = np.arange(p.child[b], p.child[b] + p.children[b])
            stack += [(a, int(c)) for c in found[np.argsort(most[a, found])]]
    return best, work


BLOCK = "side string, block string, dim int, n long, centre array<double>, radius double, tree binary"


def blocks(placed: DataFrame, side: str, size: int, leaf: int) -> DataFrame:
    """One row per block: its centre, covering radius and tree. placed: dim, pivot, id, v. Rows of a pivot beyond `size` are
    dealt to further blocks by hash."""

    def plant(key, table):
        dim = table.column("dim")[0].as_py()
        tree = CoverTree.of(table.column("v").combine_chunks().flatten().to_numpy().reshape(-1, dim).astype(np.float64), table.column("id").to_numpy(), leaf)
        return pa.table({"side": [side], "block": [key[0].as_py()], "dim": pa.array([dim], pa.int32()), "n": [len(tree.x)], "centre": [tree.x[tree.centre[0]].tolist()], "radius": [float(tree.radius[0])], "tree": pa.array([tree.dumped()], pa.binary())})

    sizes = placed.groupBy("dim", "pivot").agg(F.ceil(F.count(F.lit(1)) / size).alias("parts"))
    dealt = placed.join(sizes, ["dim", "pivot"]).withColumn("block", F.concat_ws("-", "dim", "pivot", F.pmod(F.xxhash64("id"), F.col("parts")).cast("string")))
    return dealt.select("block", "dim", "id", "v").groupBy("block").applyInArrow(plant, BLOCK)


def top_k(vectors: DataFrame, is_query, k: int = 5, id_column: str = "vec_id", vector_column: str = "embedding", scale: float = 256.0) -> DataFrame:
    """query_id, rank (from 1), vec_id, score: for each row where `is_query` holds, the k best other rows.

    Components are floor(scale * x), scores exact whole numbers; ties go to the smaller id; fewer candidates give fewer rows.
    Vectors that are null, empty, or hold a null or non-finite component take no part; nor do rows with a null id. Only
    vectors of one length are compared. Of rows that share an id, the one with the greatest vector counts. Scores beyond 64
    bits raise an OverflowError. An empty table gives an empty result; other columns are not read.
    """
    spark = vectors.sparkSession
    ship(spark)
    x = named(vector_column)
    fine = x.isNotNull() & (F.size(x) > 0) & F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf")).cast("double")))
    quantised = F.transform(x, lambda v: F.floor(v.cast("double") * F.lit(scale)).cast("double")) if scale < 1e300 else x
    rows = vectors.filter(F.coalesce(fine, F.lit(False)) & named(id_column).isNotNull()).select(named(id_column).cast("long").alias("id"), quantised.alias("v"), F.coalesce(is_query, F.lit(False)).alias("q"))
    rows = written(rows.groupBy("id").agg(F.max(F.struct("v", "q")).alias("own")).select("id", "own.v", "own.q", F.size("own.v").alias("dim")), "vectors")
    n, asked = rows.agg(F.count(F.lit(1)), F.count(F.when(F.col("q"), 1))).first()
    wanted = [min(PIVOTS, -(-2 * n // CANDIDATES)), min(PIVOTS, -(-asked // QUERIES))]
    picked = [(r["dim"], r["v"]) for r in rows.orderBy(F.xxhash64("id", F.lit(7)), "id").limit(max(wanted)).select("dim", "v").collect()]

    def placed(rows: DataFrame, n: int) -> DataFrame:
        """Adds the nearest of the first n pivots of the vector's length; -1 if there is none."""
        own = [(k, dim, np.array(v)) for k, (dim, v) in enumerate(picked[:n])]

        def place(batches):
            for batch in batches:
                dims, v = batch.column(2).to_numpy(), batch.column(1)
                nearest = np.full(len(dims), -1, np.int32)
                for dim in {d for _, d, _ in own}:
                    some = np.flatnonzero(dims == dim)
                    if len(some):
                        x = v.take(pa.array(some)).flatten().to_numpy().reshape(-1, dim)
                        c = np.stack([p for _, d, p in own if d == dim])
                        nearest[some] = np.array([i for i, d, _ in own if d == dim], np.int32)[((c * c).sum(1) - 2 * (x @ c.T)).argmin(1)]
                yield pa.RecordBatch.from_arrays([batch.column(0), v, batch.column(2), pa.array(nearest)], names=["id", "v", "dim", "pivot"])

        return rows.select("id", "v", "dim").mapInArrow(place, "id long, v array<double>, dim int, pivot int")

    every = written(blocks(placed(rows, wanted[0]), "candidates", CANDIDATES, LEAF).unionByName(blocks(placed(rows.filter("q"), wanted[1]), "queries", QUERIES, ASKED)), "vector-blocks")
    c = every.filter("side = 'candidates'").select("dim", F.col("block").alias("block"), F.col("centre").alias("cc"), F.col("radius").alias("cr"))
    q = every.filter("side = 'queries'").select("dim", F.col("block").alias("asks"), F.col("centre").alias("qc"), F.col("radius").alias("qr"))
    near = dot(F.col("qc"), F.col("cc"))
    most = near + F.col("qr") * norm(F.col("cc")) + F.col("cr") * norm(F.col("qc")) + F.col("qr") * F.col("cr")
    # Only centres and radii meet here, one row a block.
    pairs = q.join(c, "dim").select("asks", "block", near.alias("near"), (most + F.lit(1e-9) * F.abs(most) + F.lit(1e-6)).alias("most"))

    def met(pairs: DataFrame) -> DataFrame:
        """query_id, vec_id, score, of every pair of blocks; a row without query_id holds the least floor. pairs: asks, block, floors."""
        trees = every.select("side", F.col("block").alias("of"), "tree")
        sent = [pairs.join(trees.filter(F.col("side") == side), F.col(key) == F.col("of")).select("asks", "block", "side", "tree", floors.alias("floors")) for side, key, floors in (("candidates", "block", F.lit(None).cast("binary")), ("queries", "asks", F.col("floors")))]

        def search(key, table):
            side = table.column("side").to_pylist()
            tree = {s: CoverTree.loaded(t.as_py()) for s, t in zip(side, table.column("tree"), strict=True)}
            floors = table.column("floors")[side.index("queries")].as_py()
            best, _ = dual_search(tree["queries"], tree["candidates"], k, None if floors is None else np.frombuffer(floors, np.int64))
            good, none = best.score > NONE, pa.nulls(1, pa.int64())
            found = pa.table({"query_id": np.repeat(tree["queries"].ids, k)[good.ravel()], "vec_id": best.id[good], "score": best.score[good]})
            own = pa.table({"query_id": none, "vec_id": none, "score": pa.array([int(best.floor.min(initial=np.iinfo(np.int64).max))]), "asks": [key[0].as_py()], "floors": pa.array([best.floor.tobytes()], pa.binary())})
            return pa.concat_tables([found.append_column("asks", pa.nulls(len(found), pa.string())).append_column("floors", pa.nulls(len(found), pa.binary())), own])

        return sent[0].unionByName(sent[1]).groupBy("asks", "block").applyInArrow(search, "query_id long, vec_id long, score long, asks string, floors binary")

    start = pairs.groupBy("asks").agg(F.max_by("block", F.struct("near", "block")).alias("block")).withColumn("floors", F.lit(None).cast("binary"))
    first = written(met(start), "first-hits")
    known = first.filter("query_id IS NULL").select("asks", F.col("score").alias("least"), "floors")
    rest = pairs.join(start.select("asks", "block"), ["asks", "block"], "left_anti").join(known, "asks").filter(F.col("most") >= F.col("least"))
    found = first.unionByName(met(rest.select("asks", "block", "floors"))).filter("query_id IS NOT NULL").select("query_id", "vec_id", "score")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op4_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    return top_k(vectors, F.col("vec_id") % 50 == 0)


SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
)
SELECT query_id, rank::INT AS rank, vec_id, score FROM (
  SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.e, c.e)::BIGINT AS score,
         row_number() OVER (PARTITION BY q.vec_id ORDER BY list_inner_product(q.e, c.e) DESC, c.vec_id) AS rank
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0
) WHERE rank <= 5
"""
