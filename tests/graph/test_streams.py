"""Streams against the same operations in one batch, and plans that need no exchange."""

import datetime as dt

import numpy as np
import pytest

from navgraph.operators import exact, index
from navgraph.operators.index import GraphParams, MaintainedIndex
from navgraph.streaming import updates

PARAMS = GraphParams(4, 8, 40)
LOG = "seq long, op string, label long, vec array<float>"


@pytest.fixture(scope="module")
def points(spark):
    x = np.random.default_rng(5).standard_normal((90, 6)).astype(np.float32)
    return spark.createDataFrame([(i, v.tolist(), 0) for i, v in enumerate(x)], "label long, vec array<float>, version long").cache()


def files(spark, path, rows, schema, n=3):
    for part in np.array_split(np.arange(len(rows)), n):
        spark.createDataFrame([rows[i] for i in part], schema).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def log(rng, n=60):
    return [(i, "delete" if i % 4 == 3 else "upsert", int(rng.integers(0, 60)), None if i % 4 == 3 else rng.standard_normal(6).astype(np.float32).tolist()) for i in range(n)]


def test_maintained_by_a_stream(spark, points, tmp_path):
    rows = log(np.random.default_rng(1))
    m = MaintainedIndex(index.build(points, PARAMS, 3), PARAMS)
    updates.maintain(files(spark, f"{tmp_path}/log", rows, LOG), m, f"{tmp_path}/c").awaitTermination()
    last = {r[2]: r for r in rows}
    live = {k for k in range(90) if last.get(k, (0, "", 0))[1] != "delete"}
    assert {r.label for r in index.live(m.index).collect()} == live and m.epoch == 2
    moved = {r.label: list(r.vec) for r in index.live(m.index).collect()}
    assert all(moved[k] == pytest.approx(r[3]) for k, r in last.items() if r[1] == "upsert")


def test_untouched_shards_stay_where_they_are(spark, points):
    m = MaintainedIndex(index.build(points, PARAMS, 4), PARAMS)
    m.apply(spark.createDataFrame([(0, "delete", 1, None)], LOG))
    before = dict(m.paths)
    m.apply(spark.createDataFrame([(1, "delete", 2, None)], LOG))
    assert sum(before[k] != m.paths[k] for k in before) == 1 and m.index.count() == 90 and index.live(m.index).count() == 88


def test_state_by_shard(spark, tmp_path):
    rows = [(i, "upsert" if op == "upsert" else op, label, vec) for i, op, label, vec in log(np.random.default_rng(2))]
    s = updates.stateful(files(spark, f"{tmp_path}/log", rows, LOG), PARAMS, shards=2)
    s.writeStream.outputMode("update").format("memory").queryName("ng_shards").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start().awaitTermination()
    found = {}
    for r in spark.table("ng_shards").collect():
        found[r.shard] = max(found.get(r.shard, (0, 0)), (r.reuses, r.live))
    last = {r[2]: r for r in rows}
    assert spark.table("ng_shards").count() >= 4 and len(found) == 2
    final = {}
    for r in spark.table("ng_shards").collect():
        final[r.shard] = r.live
    assert sum(final.values()) == sum(r[1] != "delete" for r in last.values())


def test_queries_within_the_stream_and_against_it(spark, points, tmp_path):
    x = {r.label: list(r.vec) for r in points.collect()}
    rows = [(0, "upsert", 200, [9.0] * 6), (1, "query", 0, [9.0] * 6), (2, "delete", 200, None), (3, "query", 0, x[5])]
    m = MaintainedIndex(index.build(points, PARAMS, 2), PARAMS)
    updates.mixed(files(spark, f"{tmp_path}/log", rows, LOG, 2), m, 1, 60, f"{tmp_path}/hits", f"{tmp_path}/c").awaitTermination()
    assert {(r.query_id, r.label) for r in spark.read.parquet(f"{tmp_path}/hits").collect()} == {(1, 200), (3, 5)}
    asked = [(k, x[k]) for k in range(6)]
    updates.search_stream(files(spark, f"{tmp_path}/q", asked, "query_id long, vec array<float>", 2), m, 1, 60, f"{tmp_path}/found", f"{tmp_path}/d").awaitTermination()
    assert sum(r.query_id == r.label for r in spark.read.parquet(f"{tmp_path}/found").collect()) >= 5


EVENTS = "event_id long, ts timestamp, label long"


def at(minutes):
    return dt.datetime(2024, 1, 1) + dt.timedelta(minutes=minutes)


def test_late_events_are_kept_aside(spark, tmp_path):
    rows = [(0, at(0), 1), (1, at(60), 1), (2, at(30), 2), (3, at(55), 2), (4, at(70), 3), (5, at(20), 3)]
    updates.late_aside(files(spark, f"{tmp_path}/e", rows, EVENTS), f"{tmp_path}/out", "10 minutes", f"{tmp_path}/c").awaitTermination()
    late, on_time = ({r.event_id for r in spark.read.schema(EVENTS).parquet(f"{tmp_path}/out/{k}").collect()} for k in ("late", "on_time"))
    assert late == {2, 5} and on_time == {0, 1, 3, 4}


def test_served_then_deleted_and_duplicates(spark, tmp_path):
    asked, gone = [(1, at(0), 7), (2, at(5), 8)], [(3, at(30), 7), (4, at(300), 8)]
    q, d = (files(spark, f"{tmp_path}/{n}", r, EVENTS, 1) for n, r in (("q", asked), ("d", gone)))
    updates.served_then_deleted(q, d).writeStream.outputMode("append").format("memory").queryName("ng_served").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start().awaitTermination()
    assert [r.asked for r in spark.table("ng_served").collect()] == [7]
    twice = files(spark, f"{tmp_path}/t", [(1, at(0), 7), (1, at(0), 7), (2, at(1), 7)], EVENTS, 1)
    updates.deduplicated(twice).writeStream.outputMode("append").format("memory").queryName("ng_once").option("checkpointLocation", f"{tmp_path}/x").trigger(availableNow=True).start().awaitTermination()
    assert spark.table("ng_once").count() == 2


def test_windowed_rates_in_two_output_modes(spark, tmp_path):
    schema = "event_id long, ts timestamp, event_type string"
    rows = [(i, at(10 * i), "view") for i in range(20)]
    for mode in ("append", "complete"):
        s = updates.windowed_rates(files(spark, f"{tmp_path}/{mode}", rows, schema, 2))
        s.writeStream.outputMode(mode).format("memory").queryName(f"ng_{mode}").option("checkpointLocation", f"{tmp_path}/c{mode}").trigger(availableNow=True).start().awaitTermination()
    assert sum(r.n for r in spark.table("ng_complete").collect()) == 20 and 0 < sum(r.n for r in spark.table("ng_append").collect()) <= 20


def test_bucketed_join_needs_no_exchange(spark):
    from navgraph.queries.relational import bucketed

    a, b = (bucketed(spark.range(1000).selectExpr("id AS k", f"id % {n} AS v"), "k", f"t{n}") for n in (3, 7))
    plan = a.join(b.hint("merge"), "k")._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Exchange" not in plan


def test_both_ways_of_exact_search(points):
    q = points.filter("label % 7 = 0").selectExpr("label AS query_id", "vec")
    for metric in ("l2", "ip", "cosine"):
        fast, slow = ([(r.query_id, r["rank"], r.label, round(r.dist, 9)) for r in exact.knn(points, q, 6, metric, True, sent=n).orderBy("query_id", "rank").collect()] for n in (10**6, 0))
        assert fast == slow and len(fast) == 13 * 6


def test_routing_finds_all_when_all_are_asked(points):
    i = index.build(index.by_space(points, index.pivots_of(points, 3)), PARAMS, 3)
    q = points.filter("label < 10").selectExpr("label AS query_id", "vec")
    key = lambda n: sorted((r.query_id, r["rank"], r.label) for r in index.knn(i, q, 3, 60, n).collect())
    assert key(None) == key(3) and len(key(1)) == 30


def test_moving_between_shards_by_space(spark, points):
    pivots = index.pivots_of(points, 3)
    i = index.build(index.by_space(points, pivots), PARAMS, 3)
    x = {r.label: (list(r.vec), r.shard) for r in i.collect()}
    other = next(k for k in x if x[k][1] != x[0][1])
    changed = index.apply_log(i, spark.createDataFrame([(0, "upsert", 0, x[other][0])], LOG), pivots=pivots)
    live = {r.label: r.shard for r in changed.filter("deleted_seq IS NULL").collect()}
    assert len(live) == 90 and live[0] == x[other][1]


def test_one_search_for_several_numbers_of_shards(points):
    i = index.build(index.by_space(points, index.pivots_of(points, 4)), PARAMS, 4)
    q = points.filter("label < 20").selectExpr("label AS query_id", "vec")
    rows = lambda f: sorted((r.query_id, r["rank"], r.label, r.dist) for r in f.collect())
    found = index.knn_by_probes(i, q, 5, 60, (1, 2, 4))
    assert all(rows(found[n]) == rows(index.knn(i, q, 5, 60, n)) for n in found) and len({str(rows(f)) for f in found.values()}) > 1
