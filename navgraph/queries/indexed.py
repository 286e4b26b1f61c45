"""Queries on the layered index itself. What SQL can state (exhaustive search, invariants, live sets) has its SQL."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from functools import partial, reduce

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from navgraph import experiments, planner
from navgraph.operators import index as ix
from navgraph.operators.index import GraphParams
from navgraph.operators.repair import STRATEGIES, Strategy
from navgraph.queries.methods import E, asks, knn_sql
from navgraph.session import written
from navgraph.sources import vectors as sources
from navgraph.streaming import updates
from navgraph.workloads import random_churn

QUERIES: dict = {}
SQL: dict[str, str] = {}
SMALL = GraphParams(8, 16, 40)


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def churned(spark, sf, strategy="mutual_gamma", iters=3, shards=4) -> DataFrame:
    """An index after `iters` random batches of deletion and return."""
    p = sources.embeddings(spark, sf)
    index = written(ix.build(p, SMALL, shards), "index")
    batches = written(random_churn(p, iters, max(1, p.count() // 100)), "batches")
    log = batches.select(F.col("iter").cast("long").alias("iter"), "label", F.explode(F.array(F.lit("delete"), F.lit("insert"))).alias("op"))
    log = log.join(p.select("label", "vec"), "label").select((F.col("iter") * 1_000_000_000 + F.when(F.col("op") == "insert", 500_000_000 - F.col("label")).otherwise(F.col("label"))).alias("seq"), "op", "label", "vec")
    return written(ix.apply_log(index, log, strategy, shards), "index")


@query("dual_search_exhaustive", knn_sql("list_distance(p.v, q.v)"))
def dual_search_exhaustive(spark, sf):
    """With a beam as wide as the graph, main and backup together give the exact answer over all live points."""
    main = churned(spark, sf)
    backup = written(ix.build_backup(main, SMALL, 4), "backup")
    q = asks(sources.embeddings(spark, sf))
    return ix.dual(main, backup, q, 10, 100_000).select("query_id", "rank", "label", F.round("dist", 4).alias("dist"))


@query("main_only_exhaustive")
def main_only_exhaustive(spark, sf):
    """Without the backup: the exact answer over the points that are found."""
    return ix.knn(churned(spark, sf), asks(sources.embeddings(spark, sf)), 10, 100_000).select("query_id", "rank", "label", F.round("dist", 4).alias("dist"))


@query("recall_main_vs_dual")
def recall_main_vs_dual(spark, sf):
    """Recall of the ten nearest of the hashed documents after churn, with the widest beam: of the main index alone, and with its backup."""
    from navgraph.operators import exact

    p = written(sources.hashed_documents(spark, sf), "points")
    q, small = asks(p), GraphParams(4, 8, 40)
    index = written(ix.build(p, small, 2, compiled=True), "index")
    log = random_churn(p, 3, max(1, p.count() // 20)).select(F.col("iter").cast("long").alias("iter"), "label").join(p.select("label", "vec"), "label")
    index = written(ix.apply_log(index, log.select((F.col("iter") * 1_000_000_000 + F.col("label")).alias("seq"), F.lit("upsert").alias("op"), "label", "vec"), "native", compiled=True), "index")
    backup = written(ix.build_backup(index, small, 2, compiled=True), "backup")
    truth = written(exact.knn(p, q, 10).groupBy("query_id").agg(F.max("dist").alias("reach"), F.count(F.lit(1)).alias("n")), "truth")
    hits = written(ix.search_hits(index, q, 10, 100_000, compiled=True), "hits")
    parts = []
    for name, found in (("main", ix.merged(hits, 10)), ("dual", ix.dual(index, backup, q, 10, 100_000, hits, compiled=True))):
        # Equal vectors are as good as each other: a hit is one as near as the tenth.
        near = found.join(truth, "query_id").groupBy("query_id", "n").agg(F.count(F.when(F.col("dist") <= F.col("reach") + 1e-6, 1)).alias("hits"))
        parts.append(truth.select("query_id", "n").join(near.select("query_id", "hits"), "query_id", "left").agg(F.round(F.avg(F.coalesce("hits", F.lit(0)) / F.col("n")), 4).alias("recall")).select(F.lit(name).alias("index"), "recall"))
    return parts[0].unionByName(parts[1])


@query("routed_search_recall")
def routed_search_recall(spark, sf):
    """Shards by space and queries sent to the nearest of them: recall of the ten nearest by number of shards asked."""
    from navgraph.operators import exact

    p = written(sources.part_profiles(spark, sf), "points")
    q = asks(p)
    index = written(ix.build(ix.by_space(p, ix.pivots_of(p, 8)), SMALL, 8), "index")
    truth = written(exact.knn(p, q, 10).groupBy("query_id").agg(F.collect_set("label").alias("g")), "truth")
    out = None
    for n, hits in ix.knn_by_probes(index, q, 10, 80, (1, 2, 4, 8)).items():
        found = hits.groupBy("query_id").agg(F.collect_set("label").alias("l"))
        r = truth.join(found, "query_id").agg(F.round(F.avg(F.size(F.array_intersect("g", "l")) / F.size("g")), 4).alias("recall")).select(F.lit(n).alias("shards_asked"), "recall")
        out = r if out is None else out.unionByName(r)
    return out


@query("sharded_search_exhaustive", knn_sql("list_distance(p.v, q.v)"))
def sharded_search_exhaustive(spark, sf):
    """Three shards, each with its backup: the same exact answer."""
    main = churned(spark, sf, shards=3)
    backup = written(ix.build_backup(main, SMALL, 3), "backup")
    return ix.dual(main, backup, asks(sources.embeddings(spark, sf)), 10, 100_000).select("query_id", "rank", "label", F.round("dist", 4).alias("dist"))


@query("live_set_after_churn", "SELECT vec_id AS label FROM embeddings")
def live_set_after_churn(spark, sf):
    return ix.live(churned(spark, sf)).select("label")


def _health(spark, sf, strategy):
    return ix.measures(churned(spark, sf, strategy)).filter("metric LIKE 'bad_%'").agg(F.sum("value").cast("long").alias("violations"))


for _s in STRATEGIES:
    query(f"graph_health_{_s}", "SELECT 0::BIGINT AS violations")(partial(_health, strategy=_s))


@query("level_kept_on_reuse", "SELECT 0::BIGINT AS changed")
def level_kept_on_reuse(spark, sf):
    p = sources.embeddings(spark, sf)
    before = ix.build(p, SMALL, 4).select("shard", "slot", F.col("level").alias("was"))
    return churned(spark, sf).join(before, ["shard", "slot"]).filter("level <> was").agg(F.count(F.lit(1)).alias("changed"))


@query("hnsw_search_recall")
def hnsw_search_recall(spark, sf):
    """recall@10 against the exact answer, by beam width."""
    from navgraph.operators import exact

    p = sources.embeddings(spark, sf)
    q, index = asks(p), written(ix.build(p, SMALL), "index")
    truth = written(exact.knn(p, q, 10).groupBy("query_id").agg(F.collect_set("label").alias("g")), "truth")
    out = None
    for ef in (10, 20, 40, 80, 160):
        found = ix.knn(index, q, 10, ef).groupBy("query_id").agg(F.collect_set("label").alias("l"))
        r = truth.join(found, "query_id").agg(F.avg(F.size(F.array_intersect("g", "l")) / F.size("g")).alias("recall")).select(F.lit(ef).alias("ef"), "recall")
        out = r if out is None else out.unionByName(r)
    return out


_kept: dict = {}


def _trace(spark, sf, scenario="random", dataset="embeddings", share=None, iters=None, **more) -> DataFrame:
    """The trace of a scenario over a whole vector set, at the published numbers of iterations; run once a session."""
    key = (spark.sparkContext.applicationId, sf, scenario, dataset, share, iters, str(more))
    if key not in _kept:
        p = written(sources.VECTOR_SETS[dataset](spark, sf), "points")
        size = max(1, int(p.count() * share)) if share else 0
        m = 4 if dataset == "documents" else 8
        options = {"m": m, "m0": 2 * m, "ef": 40} | more
        _kept[key] = written(experiments.churn(p, scenario, iters or {"full_coverage": 100, "random": 200, "new_data": 10}[scenario], size, dataset=dataset, **options), "trace")
    return _kept[key]


for _scenario in ("full_coverage", "random", "new_data"):
    for _set in ("embeddings", "documents", "parts"):
        _name = _scenario if _set == "embeddings" else f"{_scenario}_{_set}"
        query(f"update_time_{_name}")(lambda spark, sf, s=_scenario, d=_set: experiments.update_time(_trace(spark, sf, s, d)))
        query(f"unreachable_growth_{_name}")(lambda spark, sf, s=_scenario, d=_set: experiments.growth(_trace(spark, sf, s, d)))


@query("update_trace")
def update_trace(spark, sf):
    return _trace(spark, sf, "new_data", "embeddings")


for _scenario in ("full_coverage", "random"):
    for _set in ("documents", "parts"):

        @query(f"self_recall_by_ef_{_scenario}_{_set}")
        def self_recall_by_ef(spark, sf, s=_scenario, d=_set):
            """The whole base as queries, after churn, by beam."""
            t = _trace(spark, sf, s, d, 0.05 if s == "random" else None, 20 if s == "random" else None, ask_ef=(10, 20, 40, 80, 160))
            return t.filter("metric IN ('self_recall', 'search_seconds')")


@query("guarded_churn_trace")
def guarded_churn_trace(spark, sf):
    """5 % of the points per round, none that is unreachable already: unreachable points, and recall by beam every tenth round."""
    return _trace(spark, sf, "random", "documents", 0.05, 40, strategies=("native", "mutual_gamma"), guarded=True, recall_ef=(20, 80, 320))


@query("backup_versus_native")
def backup_versus_native(spark, sf):
    """Full coverage with a backup rebuilt every four iterations, beside the conventional update without one: points that neither
    the main index nor the backup finds."""
    n = sources.hashed_documents(spark, sf).count()
    t = _trace(spark, sf, "full_coverage", "documents", strategies=("native", "mutual_gamma"), tau=max(1, 4 * n // 100))
    return t.filter("metric IN ('unreachable_search', 'unreachable_with_backup', 'backup_size', 'rebuild_seconds')")


@query("reconstruction_versus_backup")
def reconstruction_versus_backup(spark, sf):
    """What a graph built anew costs and finds, beside a backup's rebuild."""
    n = sources.hashed_documents(spark, sf).count()
    t = _trace(spark, sf, "random", "documents", 0.05, 20, strategies=("native", "mutual_gamma"), tau=max(1, 20 * n // 100), ask_ef=(20, 80), rebuilt=True)
    return t.filter("metric LIKE 'reconstruction%' OR metric IN ('self_recall', 'rebuild_seconds') OR (metric LIKE 'unreachable%' AND iter = 19)")


@query("query_versus_update")
def query_versus_update(spark, sf):
    with ThreadPoolExecutor(len(sources.VECTOR_SETS)) as side_by_side:
        found = side_by_side.map(inheritable_thread_target(spark)(lambda name: experiments.query_versus_update(sources.VECTOR_SETS[name](spark, sf), dataset=name)), sources.VECTOR_SETS)
        return reduce(DataFrame.unionByName, found)


@query("alpha_sweep")
def alpha_sweep(spark, sf):
    """Mutual targets and local pools with alpha 1.0, 1.05, 1.1 and 1.2: work, and unreachable points after the last round."""
    sweep = {f"alpha {a}": Strategy("mutual", "local", a) for a in (1.0, 1.05, 1.1, 1.2)}
    t = _trace(spark, sf, "random", "documents", 0.05, 20, strategies=sweep)
    last = F.max_by("value", "iter")
    total = lambda metric: F.sum(F.when(F.col("metric") == metric, F.col("value")))
    lost = t.filter("metric = 'unreachable_search'").groupBy("strategy").agg(last.alias("unreachable"))
    return t.groupBy("strategy").agg(total("work_candidates").alias("candidates"), total("work_prune").alias("distances")).join(F.broadcast(lost), "strategy")


@query("experiment_report")
def experiment_report(spark, sf):
    """Figures as a table: strategies in columns, scenarios in rows; distances that native needs over those of each."""
    scenarios = ("full_coverage", "random", "new_data")
    with ThreadPoolExecutor(len(scenarios)) as side_by_side:
        traces = side_by_side.map(inheritable_thread_target(spark)(lambda s: experiments.update_time(_trace(spark, sf, s, "embeddings"))), scenarios)
        out = reduce(DataFrame.unionByName, traces)
    return out.groupBy("scenario").pivot("strategy", list(STRATEGIES)).agg(F.first("distance_ratio"))


@query("planner_choices", """SELECT 'search' AS decision, l_returnflag AS part, count(*) AS size, CASE WHEN count(*) <= 100000 THEN 'exact' ELSE 'graph' END AS choice FROM lineitem GROUP BY l_returnflag
UNION ALL SELECT 'repair', l_linenumber::VARCHAR, count(*), CASE WHEN count(*) <= 10000 THEN 'kernel' ELSE 'relational' END FROM lineitem GROUP BY l_linenumber""")
def planner_choices(spark, sf):
    """What to do with the lines of the order table as they are: search those of a flag, replace those of a line number."""
    lines = sources.table(spark, sf, "lineitem")
    sizes = lambda decision, part: lines.groupBy(F.col(part).cast("string").alias("part")).agg(F.count(F.lit(1)).alias("size")).select(F.lit(decision).alias("decision"), "part", "size")
    choose = {"search": lambda n: planner.choose_search(n, 1.0, 10), "repair": lambda n: planner.choose_repair(n, 1)}
    found = sizes("search", "l_returnflag").unionByName(sizes("repair", "l_linenumber")).collect()  # a few flags and line numbers
    return spark.createDataFrame([(*r, choose[r.decision](r["size"]).choice) for r in found], "decision string, part string, size long, choice string")


@query("streamed_index_live_set", f"""WITH {E}, n AS (SELECT count(*) AS n FROM e), l AS (
  SELECT event_id % (SELECT n FROM n) AS label, arg_max(event_type, event_id) AS last FROM events WHERE event_type IN ('signup', 'error', 'purchase') GROUP BY 1)
SELECT label FROM e WHERE label NOT IN (SELECT label FROM l WHERE last = 'error')""")
def streamed_index_live_set(spark, sf):
    """The live set after the update log has gone through the stream, batch by batch."""
    return updates.replay(spark, sf, SMALL).select("label")
