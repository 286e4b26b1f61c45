"""The paper's comparison of repair strategies, as traces (scenario, dataset, strategy, iter, metric, value).

Each strategy's run is one task per shard, so all strategies run side by side. run_churn says what a run is; over vectors in floats, as
those of the given tables are, the same run goes in the JVM (navgraph/jvm). Counts of distances and candidates stand
for cost without regard to the machine; seconds are taken inside the kernel, and those of searches side by side added up.
"""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from navgraph import jvm
from navgraph.operators.index import _matrix, _table
from navgraph.operators.kernel import GraphKernel
from navgraph.operators.repair import STRATEGIES, Strategy
from navgraph.schema import TRACE
from navgraph.session import ship, written


def batches(scenario: str, labels: list[int], iters: int, size: int, seed: int, guard=None) -> list[tuple[list[int], list[int]]]:
    """(deleted, inserted) labels of each iteration, as the tables of navgraph.workloads have them."""
    import hashlib

    labels = sorted(labels)
    n = len(labels)
    if scenario == "full_coverage":
        cut = [round(i * n / iters) for i in range(iters + 1)]
        return [(labels[a:b], labels[a:b]) for a, b in zip(cut, cut[1:], strict=False)]
    if scenario == "new_data":
        half = n // 2
        cut = [i * half // iters for i in range(iters + 1)]
        far = [half + i * (n - half) // iters for i in range(iters + 1)]
        return [(labels[cut[i] : cut[i + 1]], labels[far[i] : far[i + 1]]) for i in range(iters)]
    return [(b, b) for i in range(iters) for b in [sorted(labels, key=lambda x: (hashlib.md5(f"{seed}:{i}:{x}".encode()).hexdigest(), x))[:size]]]


def recall_of(g: GraphKernel, asked: list[int], k: int, ef: int, truth: dict[int, set[int]]) -> float:
    """Share of the true k nearest live slots that are found, over the slots `asked` (whose vectors are the queries)."""
    hits = [len(truth[s] & {n for _, n in g.knn(g.vec[s], k, ef)}) / max(1, len(truth[s])) for s in asked]
    return float(np.mean(hits)) if hits else 0.0


def truth_of(g: GraphKernel, asked: list[int], k: int) -> dict[int, set[int]]:
    live = np.array(g.live())
    x = g.vec[live]
    return {s: set(live[np.lexsort((live, ((x - g.vec[s]) ** 2).sum(1)))[:k]].tolist()) for s in asked}


def run_churn(x: dict[int, np.ndarray], scenario: str, strategy: str | Strategy, iters: int, size: int, m: int, m0: int, ef: int, seed: int = 42, tau: int | None = None, guarded: bool = False, ask_ef: tuple[int, ...] = (), recall_ef: tuple[int, ...] = (), rebuilt: bool = False, dataset: str = "", name: str = "") -> list[dict]:
    """One strategy (a name, or any targets, pool and alpha) through one scenario. A batch's marks come first; its points return in
    reverse order, so that a label rarely gets its own slot back. guarded: points that nothing points at aren't deleted. tau:
    backup rebuilt after so many reuses; what neither main nor backup finds is counted by searching both. recall_ef: recall of the 10 nearest
    by beam, of about 100 live points, after the build and every tenth iteration. ask_ef: at the end, share of all points that find themselves,
    by beam. Points that a search for all misses are counted in about 20 of the iterations, the first and the last among them, those without an
    in-edge in all. rebuilt: at the end, seconds and both recalls of a graph built anew over the live points."""
    labels, name = sorted(x), name or (strategy if isinstance(strategy, str) else str(strategy.alpha))
    strategy = STRATEGIES[strategy] if isinstance(strategy, str) else strategy
    start = labels[: len(labels) // 2] if scenario == "new_data" else labels
    g = GraphKernel(len(x[labels[0]]), m, m0, ef)
    for label in start:
        g.insert(label, x[label])
    backup: GraphKernel | None = None
    out: list[dict] = []

    def note(i: int, **values: float) -> None:
        out.extend({"scenario": scenario, "dataset": dataset, "strategy": name, "iter": i, "metric": k, "value": float(v)} for k, v in values.items())

    every = max(1, iters // 20)

    def measure(i: int) -> None:
        if (i + 1) % every and i != iters - 1:
            note(i, unreachable_degree=len(g.unreachable_degree()), live=len(g.live()))
            return
        found = g.enumerate_found()
        lost = set(g.live()) - found - {g.entry}
        note(i, unreachable_degree=len(g.unreachable_degree()), unreachable_search=len(lost), live=len(g.live()))
        if tau is not None:
            # A backup's hit counts if the main index still holds that version of the point.
            extra = {(backup.label[s], backup.version[s]) for s in backup.enumerate_found()} if backup is not None else set()
            note(i, unreachable_with_backup=sum((g.label[s], g.version[s]) not in extra for s in lost), backup_size=len(backup.label) if backup is not None else 0)
        if recall_ef and i % 10 in (9, -1 % 10):
            live = g.live()
            asked = live[:: max(1, len(live) // 100)]
            truth = truth_of(g, asked, 10)
            note(i, **{f"recall_at_{e}": recall_of(g, asked, 10, e, truth) for e in recall_ef})

    measure(-1)
    rebuilt_at = 0
    for i, (gone, back) in enumerate(batches(scenario, labels, iters, size, seed)):
        if guarded:
            bad = {g.label[s] for s in g.unreachable_degree()}
            gone = back = [v for v in gone if v not in bad]
        before, began = dict(g.count), time.perf_counter()
        versions = {v: g.version[g.slot_of[v]] + 1 for v in gone if v in g.slot_of}
        for v in gone:
            g.mark_deleted(v)
        for v in reversed(back):
            g.replace_update(v, x[v], strategy, versions.get(v, 0))
        took = time.perf_counter() - began
        note(i, update_seconds=took, updates=len(back), **{f"work_{k}": v - before.get(k, 0) for k, v in g.count.items()})
        if tau is not None and g.reuses - rebuilt_at >= tau:
            rebuilt_at, began = g.reuses, time.perf_counter()
            backup = GraphKernel(g.dim, m, m0, ef)
            for s in sorted(set(g.live()) - g.enumerate_found()):
                backup.insert(g.label[s], g.vec[s], g.version[s])
            note(i, rebuild_seconds=time.perf_counter() - began)
        measure(i)

    def self_recall(h: GraphKernel, e: int) -> float:
        live = h.live()
        return sum(bool(found) and (found[0][1] == s or found[0][0] < 1e-9) for s in live for found in [h.knn(h.vec[s], 1, e)]) / max(len(live), 1)

    for e in ask_ef:
        began = time.perf_counter()
        note(e, self_recall=self_recall(g, e), search_seconds=time.perf_counter() - began)
    if rebuilt:
        began, fresh = time.perf_counter(), GraphKernel(g.dim, m, m0, ef)
        for s in g.live():
            fresh.insert(g.label[s], g.vec[s], g.version[s])
        note(0, reconstruction_seconds=time.perf_counter() - began, reconstruction_distances=sum(fresh.count[k] for k in ("search", "connect", "prune")), reconstruction_unreachable=len(fresh.unreachable_search()))
        for e in ask_ef:
            note(e, reconstruction_self_recall=self_recall(fresh, e))
    return out


def churn(points: DataFrame, scenario: str, iters: int, size: int = 0, m: int = 8, m0: int | None = None, ef: int = 40, strategies=tuple(STRATEGIES), dataset: str = "", shards: int = 1, **options) -> DataFrame:
    """Trace of every strategy (names, or a dictionary of names and strategies). points: label, vec; all of them take part. With several
    shards each runs the scenario on its own points."""
    spark = points.sparkSession
    own = strategies if isinstance(strategies, dict) else {s: STRATEGIES[s] for s in strategies}
    if points.schema["vec"].dataType.elementType.typeName() == "float":
        found = _compiled(points, scenario, iters, size, m, m0 or 2 * m, ef, own, dataset, shards, **options)
    else:
        found = _plain(points, scenario, iters, size, m, m0 or 2 * m, ef, own, dataset, shards, **options)
    return found if shards == 1 else found.groupBy("scenario", "dataset", "strategy", "iter", "metric").agg(F.sum("value").alias("value"))


def _plain(points: DataFrame, scenario: str, iters: int, size: int, m: int, m0: int, ef: int, own: dict[str, Strategy], dataset: str, shards: int, **options) -> DataFrame:
    """run_churn in Python, for vectors in doubles."""
    spark = points.sparkSession
    ship(spark)
    names = spark.createDataFrame([(s,) for s in own], "strategy string")
    p = points.select("label", "vec", F.pmod(F.xxhash64("label"), F.lit(shards)).alias("shard")).crossJoin(F.broadcast(names))

    def run(key, table):
        x = dict(zip(table.column("label").to_pylist(), _matrix(table.column("vec")), strict=True))
        return _table(run_churn(x, scenario, own[key[0].as_py()], iters, size or max(1, len(x) // 100), m, m0, ef, dataset=dataset, name=key[0].as_py(), **options), TRACE)

    return p.groupBy("strategy", "shard").applyInArrow(run, TRACE)


def _compiled(points: DataFrame, scenario: str, iters: int, size: int, m: int, m0: int, ef: int, own: dict[str, Strategy], dataset: str, shards: int, seed: int = 42, tau: int | None = None, guarded: bool = False, ask_ef: tuple[int, ...] = (), recall_ef: tuple[int, ...] = (), rebuilt: bool = False) -> DataFrame:
    """run_churn in the JVM, with equal figures; a partition a strategy and shard, however small."""
    spark = points.sparkSession
    ship(spark)

    def pack(batches):
        import pyarrow as pa

        for b in batches:
            labels, shard = b.column("label").to_numpy(zero_copy_only=False), b.column("shard").to_numpy(zero_copy_only=False)
            x = b.column("vec").flatten().to_numpy(zero_copy_only=False).reshape(len(labels), -1)
            parts = [(int(s), labels[shard == s].astype("<i8").tobytes(), x[shard == s].astype("<f4").tobytes()) for s in np.unique(shard)]
            yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in parts], pa.int32()), pa.array([p[1] for p in parts], pa.binary()), pa.array([p[2] for p in parts], pa.binary())], ["shard", "labels", "vecs"])

    packed = points.select(F.col("label").cast("long").alias("label"), "vec", F.pmod(F.xxhash64("label"), F.lit(shards)).cast("int").alias("shard")).mapInArrow(pack, "shard int, labels binary, vecs binary")
    turns = F.explode(F.sequence(F.lit(0), F.lit(len(own) - 1)))
    placed = packed.withColumn("turn", turns).select((F.col("turn") * shards + F.col("shard")).cast("int").alias("place"), "labels", "vecs").repartitionById(len(own) * shards, "place")
    a = lambda kind, values: jvm.array(spark, kind, list(values))
    aims = ("out", "mutual", "mutual+twohop")
    given = [scenario, dataset, a(str, own), a(int, (aims.index(s.targets) for s in own.values())), a(bool, (s.pool == "twohop" for s in own.values())), a(float, (s.alpha for s in own.values())), shards, iters, size, m, m0, ef]
    return jvm.each_partition(placed, "Churn", [*given, jvm.long(spark, seed), jvm.long(spark, -1 if tau is None else tau), guarded, rebuilt, a(int, ask_ef), a(int, recall_ef), spark.sparkContext.defaultParallelism], TRACE)


def update_time(trace: DataFrame) -> DataFrame:
    """Seconds and distance counts per strategy, and how many times faster than the conventional update."""
    work = F.col("metric").isin("work_search", "work_prune", "work_connect")
    sums = trace.filter("iter >= 0").groupBy("scenario", "dataset", "strategy").agg(F.sum(F.when(F.col("metric") == "update_seconds", F.col("value"))).alias("seconds"), F.sum(F.when(work, F.col("value"))).alias("distances"), F.sum(F.when(F.col("metric") == "work_candidates", F.col("value"))).alias("candidates"))
    base = sums.filter("strategy = 'native'").select("scenario", "dataset", F.col("seconds").alias("s0"), F.col("distances").alias("d0"))
    return sums.join(F.broadcast(base), ["scenario", "dataset"]).select("scenario", "dataset", "strategy", "seconds", "distances", "candidates", (F.col("s0") / F.col("seconds")).alias("speed_up"), (F.col("d0") / F.col("distances")).alias("distance_ratio"))


def growth(trace: DataFrame, metric: str = "unreachable_search") -> DataFrame:
    """Unreachable points after each iteration less those after the build."""
    t = trace.filter(F.col("metric") == metric)
    first = t.filter("iter = -1").select("scenario", "dataset", "strategy", F.col("value").alias("built"))
    return t.join(F.broadcast(first), ["scenario", "dataset", "strategy"]).select("scenario", "dataset", "strategy", "iter", "value", (F.col("value") - F.col("built")).alias("growth"))


def query_versus_update(points: DataFrame, m: int = 8, ef: int = 40, least: float = 0.9, dataset: str = "") -> DataFrame:
    """The smallest beam that finds at least `least` of the points themselves (else the widest tried), and seconds per query and per conventional update."""
    t = written(churn(points, "random", 3, m=m, ef=ef, strategies=("native",), dataset=dataset, ask_ef=(5, 10, 20, 40, 80, 160, 320)), "trace")
    value = lambda metric: t.filter(F.col("metric") == metric).select(F.col("iter").alias("ef"), F.col("value").alias(metric))
    asked = value("self_recall").join(value("search_seconds"), "ef").withColumn("short", F.col("self_recall") < least)
    fine = asked.orderBy("short", F.when(F.col("short"), -F.col("ef")).otherwise(F.col("ef"))).limit(1)
    n = t.filter("metric = 'live' AND iter = -1").agg(F.max("value").alias("n"))
    up = t.filter("metric IN ('update_seconds', 'updates') AND iter >= 0").groupBy().pivot("metric", ["update_seconds", "updates"]).agg(F.sum("value"))
    found = fine.crossJoin(F.broadcast(n)).crossJoin(F.broadcast(up))
    return found.select(F.lit(dataset).alias("dataset"), "ef", F.col("self_recall").alias("recall"), (F.col("search_seconds") / F.col("n")).alias("query_seconds"), (F.col("update_seconds") / F.col("updates")).alias("update_seconds")).withColumn("ratio", F.col("update_seconds") / F.col("query_seconds"))
