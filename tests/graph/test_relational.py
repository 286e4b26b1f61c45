"""Set-at-a-time repair against the kernel, for one slot and every strategy."""

import numpy as np
import pytest

from navgraph.operators import exact, index, repair
from navgraph.operators.index import GraphParams, MaintainedIndex, RebuildPolicy
from navgraph.operators.kernel import GraphKernel
from navgraph.operators.repair import STRATEGIES


@pytest.fixture(scope="module")
def points(spark):
    x = np.random.default_rng(5).standard_normal((80, 6)).astype(np.float32)
    return spark.createDataFrame([(i, v.tolist(), 0) for i, v in enumerate(x)], "label long, vec array<float>, version long").cache()


@pytest.mark.parametrize("strategy", STRATEGIES)
def test_one_slot(spark, points, strategy):
    old, new = points.filter("label < 79"), points.filter("label = 79")
    lists = exact.knn_graph(old, 6)
    rows, vectors = {r.src: r.nbrs for r in lists.collect()}, {r.label: r.vec for r in points.collect()}
    g = GraphKernel(6, 6, 6, 40)
    g.vec = np.array([vectors[i] for i in range(79)], float)
    g.label, g.version, g.level = list(range(79)), [0] * 79, [0] * 79
    g.nbrs, g.slot_of, g.entry = [[list(rows[i])] for i in range(79)], {i: i for i in range(79)}, 0
    expected = g.repair_slot(11, vectors[79], STRATEGIES[strategy], place=False)[0]
    batch = spark.createDataFrame([(11, 79)], "slot long, label long")
    got = {r.u: r.nbrs for r in repair.repair_batch(lists, old, batch, new, STRATEGIES[strategy], 6).collect()}
    assert got == expected


def test_partitions_do_not_matter(points):
    a, b = (index.build(points.repartition(n), GraphParams(4, 8, 40), 3).orderBy("shard", "slot").select("shard", "slot", "label", "nbrs").collect() for n in (1, 7))
    assert a == b


def test_stale_backup_and_tau(spark, points):
    m = MaintainedIndex(index.build(points, GraphParams(4, 8, 40)), GraphParams(4, 8, 40), policy=RebuildPolicy(5))
    log = [(2 * i + k, op, i, [float(i)] * 6 if op == "insert" else None) for i in range(5) for k, op in enumerate(("delete", "insert"))]
    m.apply(spark.createDataFrame(log, "seq long, op string, label long, vec array<float>"), 0)
    assert m.backup is not None and m.epoch == 0
    assert m.apply(spark.createDataFrame([(1, "delete", 50, None)], "seq long, op string, label long, vec array<float>"), 0).epoch == 0
    stale = index.build(points.filter("label < 5"), GraphParams(4, 8, 40), 1, "backup")
    q = points.filter("label = 2").selectExpr("label AS query_id", "vec")
    assert {r.label: round(r.dist, 3) for r in index.dual(m.index, stale, q, 80, 100).collect()}[2] > 0
    found = m.search(q, 3, 100).collect()
    assert [r["rank"] for r in found] == [1, 2, 3]


def test_bad_vectors_are_reported(spark):
    rows = [(1, [1.0, 2.0]), (2, None), (3, [float("nan"), 1.0]), (4, [1.0]), (None, [1.0, 2.0]), (5, [0.5, 0.5])]
    good, bad = index.validated(spark.createDataFrame(rows, "label long, vec array<float>"))
    assert {r.label for r in good.collect()} == {1, 5} and bad.count() == 4


def test_store(spark, points, tmp_path):
    i = index.build(points, GraphParams(4, 8, 40), 2)
    index.save(i, str(tmp_path), 3)
    assert index.load(spark, str(tmp_path)).count() == 80
    index.register_views(index.load(spark, str(tmp_path)))
    assert spark.sql("SELECT sum(n_live) FROM ng_meta").first()[0] == 80


def test_search_by_joins(points):
    from navgraph.operators.relational_search import beam_search

    lists = exact.knn_graph(points, 6)
    got = beam_search(lists, points.selectExpr("label AS slot", "vec"), points.filter("label < 3").selectExpr("label AS query_id", "vec"), 0, 5, 100).collect()
    rows, x = {r.src: r.nbrs for r in lists.collect()}, {r.label: np.array(r.vec, float) for r in points.collect()}
    seen, todo = {0}, [0]
    while todo:
        for n in rows[todo.pop()]:
            if n not in seen:
                seen.add(n)
                todo.append(n)
    for q in range(3):
        best = sorted((float(np.linalg.norm(x[q] - x[s])), s) for s in seen)[:5]
        assert [(r.slot, round(r.dist, 6)) for r in sorted(got, key=lambda r: r["rank"]) if r.query_id == q] == [(s, round(d, 6)) for d, s in best]
