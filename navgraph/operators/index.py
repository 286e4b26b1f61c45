"""Sharded indexes as DataFrames: build, log application, search on main and backup, backup rebuild, maintenance facade.

A shard is one graph of bounded size; its operations are applied in order by one task, shards run side by side. Grouped tasks
are pure functions of shard state and ordered log, so a retried task gives the same rows. Slots are reused within a shard.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from navgraph import jvm
from navgraph.functions.vectors import centroid, is_valid, l2_sq
from navgraph.operators.kernel import GraphKernel
from navgraph.operators.repair import STRATEGIES
from navgraph.schema import HITS, INDEX, arrow_schema
from navgraph.session import scratch_path, ship, written

#: Memory of one shard's graph, as Python and numpy hold it; the number of shards follows from it.
SHARD_BYTES = 256 << 20
#: What the JVM's tasks read: rows of an index, points (with turn) and operations (with seq and op).
GIVEN = "shard int, slot long, label long, vec array<float>, version long, level int, deleted_seq long, entry boolean, nbrs array<array<long>>, stats map<string,double>, role string, seq long, op string, turn string"
#: Queries that one task asks a shard; more go to further tasks, each with a copy of the shard.
QUERY_BLOCK = 20_000
#: Shards whose centres are sent to all tasks at most, when queries are routed.
ROUTED = 100_000


@dataclass(frozen=True)
class GraphParams:
    m: int = 16
    m0: int | None = None
    ef_construction: int = 200
    metric: str = "l2"


def shard_of(label, shards: int) -> Column:
    return F.pmod(F.xxhash64(label), F.lit(shards)).cast("int")


def point_bytes(dim: int, params: GraphParams) -> int:
    """A vector in doubles, and about 40 bytes a neighbour in a list of a layer; upper layers add little."""
    return 8 * dim + 40 * (params.m0 or 2 * params.m) + 200


def shards_for(points: DataFrame, params: GraphParams = GraphParams(), most: int = SHARD_BYTES) -> int:
    n, dim = points.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    return max(1, -(-n * point_bytes(dim or 0, params) // most))


def validated(points: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows fit for an index, and rejected ones: bad vectors and null labels."""
    dim = points.filter(is_valid(F.col("vec"))).agg(F.mode(F.size("vec"), True)).first()[0]
    good = is_valid(F.col("vec"), dim or 0) & F.col("label").isNotNull()
    return points.filter(good), points.filter(~good)


def by_space(points: DataFrame, pivots: DataFrame) -> DataFrame:
    """Adds shard: the nearest of the pivots (shard, vec), of which there is one a shard."""
    p = F.broadcast(pivots.agg(F.collect_list(F.struct(F.col("vec").cast("array<double>").alias("v"), "shard")).alias("_pivots")))
    near = F.array_min(F.transform("_pivots", lambda x: F.struct(l2_sq(F.col("vec"), x["v"]).alias("d"), x["shard"].alias("shard"))))
    return points.crossJoin(p).withColumn("shard", near["shard"].cast("int")).drop("_pivots")


def pivots_of(points: DataFrame, shards: int) -> DataFrame:
    """(shard, vec) of as many points, picked by the md5 of their labels."""
    some = points.orderBy(F.md5(F.col("label").cast("string")), "label").limit(shards).select("label", "vec")
    return written(some.select((F.row_number().over(Window.orderBy("label")) - 1).cast("int").alias("shard"), "vec"), "pivots")


def _table(rows: list[dict], ddl: str) -> pa.Table:
    return pa.Table.from_pylist(rows, arrow_schema(ddl))


def _matrix(column: pa.ChunkedArray) -> np.ndarray:
    column = column.combine_chunks()
    return column.flatten().to_numpy().astype(np.float64).reshape(len(column), -1)


def _in_jvm(rows: DataFrame, shards: int, task: str, ddl: str, params: GraphParams = GraphParams(), role: str = "main", strategy: str = "mutual_gamma", marks_first: bool = False, k: int = 0, ef: int = 0) -> DataFrame:
    """A task of navgraph/jvm/Shard.java on every shard; columns of GIVEN that `rows` lacks are null."""
    columns = [c.split() for c in GIVEN.split(", ")]
    own = rows.select(*((F.col(c) if c in rows.columns else F.lit(None)).cast(kind).alias(c) for c, kind in columns))
    s = STRATEGIES[strategy]
    given = [task, role, shards, params.m, params.m0 or 2 * params.m, params.ef_construction, ("out", "mutual", "mutual+twohop").index(s.targets), s.pool == "twohop", float(s.alpha), marks_first, k, ef, rows.sparkSession.sparkContext.defaultParallelism]
    return jvm.each_partition(own.repartitionById(shards, "shard"), "Shard", given, ddl)


def has_floats(df: DataFrame) -> bool:
    return df.schema["vec"].dataType.simpleString() == "array<float>"


def build(points: DataFrame, params: GraphParams = GraphParams(), shards: int | None = None, role: str = "main", check: bool = False, compiled: bool = False) -> DataFrame:
    """Inserts every point (label, vec, version) into its shard's graph, by label hash order.

    shards: as many as the size asks for, if not given. Points with a column `shard` keep it (then give shards). check: points that
    aren't fit (see validated) are left out; without it they fail the build. compiled: by l2 and over floats the tasks go in the executor's
    JVM, with equal rows.
    """
    ship(points.sparkSession)
    points = validated(points)[0] if check else points
    shards = shards or shards_for(points, params)
    shard = F.col("shard") if "shard" in points.columns else shard_of(F.col("label"), shards)
    placed = points.select("label", "vec", "version", shard.alias("shard"), F.md5(F.col("label").cast("string")).alias("turn"))
    if compiled and params.metric == "l2" and has_floats(points):
        return _in_jvm(placed, shards, "build", INDEX, params, role)

    def make(key, table):
        table = table.sort_by([("turn", "ascending"), ("label", "ascending"), ("version", "ascending")])
        x = _matrix(table.column("vec"))
        g = GraphKernel(x.shape[1], params.m, params.m0, params.ef_construction, params.metric)
        for label, version, v in zip(table.column("label").to_pylist(), table.column("version").to_pylist(), x, strict=True):
            if label not in g.slot_of:
                g.insert(label, v, version)
        return g.table(role, key[0].as_py(), shards)

    return placed.groupBy("shard").applyInArrow(make, INDEX)


def rebuild(index: DataFrame, params: GraphParams, shards: int | None = None) -> DataFrame:
    """A fresh index over the live points: the costly remedy that the backup avoids."""
    return build(live(index), params, shards)


def live(index: DataFrame) -> DataFrame:
    return index.filter("deleted_seq IS NULL").select("label", "vec", "version")


def edges(index: DataFrame) -> DataFrame:
    """(shard, layer, src, dst) by slot."""
    e = index.select("shard", F.col("slot").alias("src"), F.posexplode("nbrs").alias("layer", "own"))
    return e.select("shard", "layer", "src", F.explode("own").alias("dst"))


def meta(index: DataFrame) -> DataFrame:
    stat = lambda k: F.max(F.when(F.col("entry"), F.try_element_at("stats", F.lit(k)))).cast("long")
    return index.groupBy("role", "shard").agg(
        F.max(F.when(F.col("entry"), F.col("slot"))).alias("entry_slot"), F.max("level").alias("max_layer"), F.count(F.lit(1)).alias("n_slots"), F.count(F.when(F.col("deleted_seq").isNull(), 1)).alias("n_live"),
        stat("reuses").alias("reuse_count"), F.max(F.size("vec")).alias("dim"), stat("shards").alias("shards"),
    )


def shards_in(index: DataFrame) -> int:
    """The number of shards that an index was built with."""
    return int(index.filter("entry").agg(F.max(F.try_element_at("stats", F.lit("shards")))).first()[0] or 1)


def normalized_log(log: DataFrame) -> DataFrame:
    """The last operation per label (by seq); an upsert stays one operation."""
    return log.groupBy("label").agg(F.max_by(F.struct(*(c for c in log.columns if c != "label")), "seq").alias("last")).select(*(("label" if c == "label" else F.col(f"last.{c}").alias(c)) for c in log.columns))


def routed(index: DataFrame, log: DataFrame, shards: int, pivots: DataFrame | None = None) -> DataFrame:
    """The log with a shard: by hash of the label; with pivots, deletions go to where the label is live and insertions to the
    nearest pivot, so an upsert that moves is both."""
    if pivots is None:
        return log.select("seq", "op", "label", "vec", shard_of(F.col("label"), shards).alias("shard"))
    home = index.filter("deleted_seq IS NULL").select(F.col("label").alias("of"), F.col("shard").alias("home"))
    leaves = log.filter("op IN ('delete', 'upsert', 'insert')").join(home, F.col("label") == F.col("of")).select("seq", F.lit("delete").alias("op"), "label", F.lit(None).cast("array<float>").alias("vec"), F.col("home").alias("shard"))
    comes = by_space(log.filter("op IN ('insert', 'upsert')"), pivots).select("seq", F.lit("insert").alias("op"), "label", "vec", "shard")
    return leaves.unionByName(comes)


def apply_log(index: DataFrame, log: DataFrame, strategy: str = "mutual_gamma", shards: int | None = None, marks_first: bool = False, order: str | None = None, params: GraphParams = GraphParams(), pivots: DataFrame | None = None, compiled: bool = False) -> DataFrame:
    """The index after operations (seq, op, label, vec), in order of seq within a shard. op: delete, unmark, insert, upsert.

    insert reuses the slot that was marked first (with order "lifo": last), or grows the graph where none is marked, repairing
    around it; a label that is live already is deleted first. A point's version is its operation's seq + 1 (0: from the
    build), so that what a backup kept of an earlier one can be told apart. marks_first: all deletions of the log go before its insertions. shards
    and params count only where a shard is new. Shards that the log doesn't touch pass by without being opened.
    compiled: over floats the tasks go in the executor's JVM, with equal rows; for graphs by l2 that reuse first marked slots first, and logs that touch
    every shard given.
    """
    ship(index.sparkSession)
    shards = shards or shards_in(index)
    ops = routed(index, log, shards, pivots)
    if compiled and order != "lifo" and has_floats(ops):
        return _in_jvm(index.unionByName(ops, allowMissingColumns=True), shards, "change", INDEX, params, "main", strategy, marks_first)

    def change(key, old, new):
        if not len(new):
            return old.select([c.split()[0] for c in INDEX.split(", ")])
        todo = sorted(new.select(["seq", "op", "label"]).to_pylist(), key=lambda r: (marks_first and r["op"] != "delete", r["seq"], r["op"] != "delete"))
        some = new.filter(new.column("vec").is_valid())
        vectors = dict(zip(zip(some.column("seq").to_pylist(), some.column("label").to_pylist(), strict=True), _matrix(some.column("vec")) if len(some) else [], strict=True))
        if len(old):
            g, role = GraphKernel.from_table(old), old.column("role")[0].as_py()
        elif not vectors:
            return old.select([c.split()[0] for c in INDEX.split(", ")])
        else:
            g, role = GraphKernel(len(next(iter(vectors.values()))), params.m, params.m0, params.ef_construction, params.metric), "main"
        g.order = order or g.order
        for r in todo:
            if r["op"] == "delete":
                g.mark_deleted(r["label"])
            elif r["op"] == "unmark":
                g.unmark(r["label"])
            else:
                g.mark_deleted(r["label"])
                g.replace_update(r["label"], vectors[r["seq"], r["label"]], strategy, r["seq"] + 1)
        return g.table(role, key[0].as_py(), shards)

    return index.groupBy("shard").cogroup(ops.groupBy("shard")).applyInArrow(change, INDEX)


def compact(index: DataFrame, strategy: str = "mutual_gamma") -> DataFrame:
    """Marked slots dropped, lists repaired around them and slots numbered anew."""

    def change(key, table):
        g, shards = GraphKernel.from_table(table), next(int(dict(x.as_py())["shards"]) for x in table.column("stats") if x.is_valid)
        g.compact(strategy)
        return g.table(table.column("role")[0].as_py(), key[0].as_py(), shards)

    ship(index.sparkSession)
    return index.groupBy("shard").applyInArrow(change, INDEX)


def probed(index: DataFrame, queries: DataFrame, n_probe: int | None) -> DataFrame:
    """queries with the shards to ask (column at): all, or the n_probe whose centres are nearest; turn: the shard's place among these."""
    if n_probe is None:
        return queries.select("query_id", "vec").crossJoin(F.broadcast(index.select(F.col("shard").alias("at")).distinct())).withColumn("turn", F.lit(1))
    centres = written(index.filter("deleted_seq IS NULL").groupBy("shard").agg(centroid("vec", shards_dim(index)).alias("c")), "centres")
    if (n := centres.count()) > ROUTED:
        raise ValueError(f"{n} shards are too many to route by one table of centres (at most {ROUTED})")
    near = queries.select("query_id", "vec").crossJoin(F.broadcast(centres)).withColumn("d", l2_sq(F.col("vec"), F.col("c")))
    turn = F.row_number().over(Window.partitionBy("query_id").orderBy("d", "shard"))
    return near.withColumn("turn", turn).filter(F.col("turn") <= n_probe).select("query_id", "vec", F.col("shard").alias("at"), "turn")


def shards_dim(index: DataFrame) -> int:
    return int(index.agg(F.max(F.size("vec"))).first()[0] or 0)


def search_hits(index: DataFrame, queries: DataFrame, k: int, ef: int, source: str = "main", n_probe: int | None = None, turns: bool = False, compiled: bool = False) -> DataFrame:
    """The k nearest in every shard that is asked, for every query, not yet merged. turns: with the shard's place among those asked.
    compiled: see apply_log; a shard's queries are dealt out over the threads of one JVM."""
    ship(index.sparkSession)
    asked = probed(index, queries, n_probe)
    if compiled and not turns and has_floats(asked):
        rows = asked.select(F.col("at").alias("shard"), F.lit("ask").alias("op"), F.col("query_id").alias("label"), F.col("query_id").alias("seq"), "vec")
        return _in_jvm(index.unionByName(rows, allowMissingColumns=True), shards_in(index), "search", HITS, role=source, k=k, ef=ef)
    blocks = max(1, -(-queries.count() // QUERY_BLOCK))
    asked = asked.withColumn("part", F.pmod(F.xxhash64("query_id"), F.lit(blocks)).cast("int"))
    state = index.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))) if blocks > 1 else index.withColumn("part", F.lit(0))

    def find(key, state, batch):
        out: dict[str, list] = {c: [] for c in ("query_id", "rank", "label", "version", "dist")}
        turn = []
        if len(state) and len(batch):
            g = GraphKernel.from_table(state)
            g.walks = []
            for query, place, v in zip(batch.column("query_id").to_pylist(), batch.column("turn").to_pylist(), _matrix(batch.column("vec")), strict=True):
                found = g.knn(v, k, ef)
                turn += [place] * len(found)
                out["query_id"] += [query] * len(found)
                out["rank"] += range(1, len(found) + 1)
                out["label"] += [g.label[s] for _, s in found]
                out["version"] += [g.version[s] for _, s in found]
                out["dist"] += [d for d, _ in found]
        schema = arrow_schema(given)
        own = [*(pa.array(out[c], schema.field(c).type) for c in out), pa.array([source] * len(out["rank"]), pa.string()), pa.array(turn, pa.int32())]
        return pa.table(own[: len(schema)], schema=schema)

    given = f"{HITS}, turn int" if turns else HITS
    return state.groupBy("shard", "part").cogroup(asked.groupBy("at", "part")).applyInArrow(find, given)


def merged(hits: DataFrame, k: int) -> DataFrame:
    """One hit per label (the nearer), then the k nearest of each query."""
    once = hits.groupBy("query_id", "label").agg(F.min(F.struct("dist", "source", "version")).alias("near")).select("query_id", "label", "near.*")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("dist", "label"))
    return once.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "label", "version", "dist", "source")


def knn(index: DataFrame, queries: DataFrame, k: int, ef: int, n_probe: int | None = None) -> DataFrame:
    """query_id, rank, label, version, dist, source. n_probe: only the shards whose centres are nearest are asked."""
    return merged(search_hits(index, queries, k, ef, "main", n_probe), k)


def knn_by_probes(index: DataFrame, queries: DataFrame, k: int, ef: int, probes: tuple[int, ...]) -> dict[int, DataFrame]:
    """knn() for several numbers of shards asked: one search of the most, of whose hits each number takes those of its shards."""
    hits = written(search_hits(index, queries, k, ef, "main", max(probes), True), "hits")
    return {n: merged(hits.filter(F.col("turn") <= n), k) for n in probes}


def dual(main: DataFrame, backup: DataFrame, queries: DataFrame, k: int, ef: int, hits: DataFrame | None = None, compiled: bool = False) -> DataFrame:
    """Both indexes are searched in one job; backup hits that the main index has deleted or changed since are left out. hits: the main
    index's search_hits, if they are known. compiled: see search_hits."""
    now = main.filter("deleted_seq IS NULL").select("label", "version")
    extra = search_hits(backup, queries, k, ef, "backup", compiled=compiled).join(now, ["label", "version"], "left_semi").select(*[c.split()[0] for c in HITS.split(", ")])
    hits = search_hits(main, queries, k, ef, compiled=compiled) if hits is None else hits
    return merged(hits.unionByName(extra), k)


def found_slots(index: DataFrame, compiled: bool = False) -> DataFrame:
    """(shard, label) of live points that an exhaustive search returns. compiled: see apply_log."""
    ship(index.sparkSession)
    if compiled:
        return _in_jvm(index, shards_in(index), "found", "shard int, label long")

    def find(key, table):
        g = GraphKernel.from_table(table)
        return _table([{"shard": key[0].as_py(), "label": g.label[s]} for s in sorted(g.enumerate_found())], "shard int, label long")

    return index.groupBy("shard").applyInArrow(find, "shard int, label long")


def unfound(index: DataFrame, compiled: bool = False) -> DataFrame:
    return live(index).join(found_slots(index, compiled).select("label"), "label", "left_anti")


def build_backup(index: DataFrame, params: GraphParams = GraphParams(), shards: int | None = None, compiled: bool = False) -> DataFrame:
    """A small index over the live points that the main one doesn't find."""
    return build(unfound(index, compiled), params, shards, "backup", compiled=compiled)


def measures(index: DataFrame) -> DataFrame:
    """shard, metric, value: unreachable points by the three definitions, health violations, work counters."""
    ship(index.sparkSession)

    def measure(key, table):
        g = GraphKernel.from_table(table)
        out = {"live": len(g.live()), "unreachable_degree": len(g.unreachable_degree()), "unreachable_bfs": len(g.unreachable_bfs()), "unreachable_search": len(g.unreachable_search()), **{f"bad_{k}": v for k, v in g.health().items()}, **{f"work_{k}": v for k, v in g.count.items()}}
        return _table([{"shard": key[0].as_py(), "metric": k, "value": float(v)} for k, v in out.items()], "shard int, metric string, value double")

    return index.groupBy("shard").applyInArrow(measure, "shard int, metric string, value double")


@dataclass
class RebuildPolicy:
    """Due when the reuses since the last rebuild reach tau."""

    tau: int = 40_000

    def due(self, reuses: int) -> bool:
        return reuses >= self.tau


@dataclass
class MaintainedIndex:
    """Main index and backup behind one face. Every change writes the shards it touches and keeps the others where they are; the
    epoch's number makes retries harmless."""

    index: DataFrame
    params: GraphParams = field(default_factory=GraphParams)
    strategy: str = "mutual_gamma"
    policy: RebuildPolicy = field(default_factory=RebuildPolicy)
    shards: int | None = None
    backup: DataFrame | None = None
    epoch: int = -1
    reuses_at_rebuild: int = 0
    paths: dict[int, str] = field(default_factory=dict)
    #: Whether all graphs are such as go in the JVM: see apply_log.
    compiled: bool = False

    def _put(self, changed: DataFrame) -> None:
        """Writes shards; self.paths has the place of each, one entry a shard."""
        path = scratch_path(changed.sparkSession, "epoch")
        changed.withColumn("part", F.col("shard")).write.partitionBy("part").parquet(path)
        spark = changed.sparkSession
        new = spark.read.schema(f"{INDEX}, part int").parquet(path).select("part").distinct().collect()
        self.paths |= {r["part"]: f"{path}/part={r['part']}" for r in new}
        if self.paths:
            self.index = spark.read.schema(INDEX).parquet(*self.paths.values())

    def apply(self, log: DataFrame, epoch: int | None = None) -> MaintainedIndex:
        if epoch is not None and epoch <= self.epoch:
            return self
        if not self.paths:
            self.shards = self.shards or shards_in(self.index)
            stat = lambda k: F.max(F.coalesce(F.try_element_at("stats", F.lit(k)), F.lit(0.0)))
            other = self.index.filter("entry").agg(stat("metric"), stat("lifo")).first()
            self.compiled = self.params.metric == "l2" and not any(other)
            self._put(self.index)
        ops = written(log, "log")
        touched = {r["shard"] for r in ops.select(shard_of(F.col("label"), self.shards).alias("shard")).distinct().collect()}
        if touched:
            old = self.index.filter(F.col("shard").isin(sorted(touched)))
            self._put(apply_log(old, ops, self.strategy, self.shards, params=self.params, compiled=self.compiled))
        self.epoch = self.epoch + 1 if epoch is None else epoch
        total = meta(self.index).agg(F.sum("reuse_count")).first()[0] or 0
        if self.policy.due(total - self.reuses_at_rebuild):
            self.rebuild_backup()
            self.reuses_at_rebuild = total
        return self

    def rebuild_backup(self) -> None:
        self.backup = written(build_backup(self.index, self.params, compiled=self.compiled), "backup")

    def search(self, queries: DataFrame, k: int, ef: int) -> DataFrame:
        return knn(self.index, queries, k, ef) if self.backup is None else dual(self.index, self.backup, queries, k, ef)


# ---- storage


def save(index: DataFrame, path: str, epoch: int) -> str:
    """One folder per epoch, partitioned by role and shard; the pointer to the current epoch is written last."""
    target = f"{path.rstrip('/')}/epoch={epoch}"
    index.write.mode("overwrite").partitionBy("role", "shard").parquet(target)
    spark = index.sparkSession
    spark.createDataFrame([(epoch,)], "epoch long").coalesce(1).write.mode("append").json(f"{path.rstrip('/')}/current")
    return target


def load(spark: SparkSession, path: str, epoch: int | None = None) -> DataFrame:
    if epoch is None:
        epoch = spark.read.schema("epoch long").json(f"{path.rstrip('/')}/current").agg(F.max("epoch")).first()[0]
    names = [c.split()[0] for c in INDEX.split(", ")]
    return spark.read.schema(INDEX).parquet(f"{path.rstrip('/')}/epoch={epoch}").select(*names)


def register_views(index: DataFrame) -> None:
    """ng_nodes, ng_lists, ng_edges and ng_meta."""
    index.select("role", "shard", "slot", "label", "vec", "level", F.col("deleted_seq").isNotNull().alias("deleted"), "deleted_seq", "version").createOrReplaceTempView("ng_nodes")
    index.select("role", "shard", "slot", F.posexplode("nbrs").alias("layer", "nbrs")).createOrReplaceTempView("ng_lists")
    edges(index).createOrReplaceTempView("ng_edges")
    meta(index).createOrReplaceTempView("ng_meta")


