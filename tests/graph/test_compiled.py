import numpy as np
import pytest

from navgraph import experiments
from navgraph.operators.repair import STRATEGIES, Strategy

OPTIONS = [
    ("full_coverage", 7, 0, {"tau": 20, "recall_ef": (5, 20)}),
    ("random", 10, 9, {"guarded": True, "ask_ef": (3, 12), "recall_ef": (15,)}),
    ("new_data", 4, 0, {"ask_ef": (10, 500), "rebuilt": True, "tau": 5}),
]


def points(n, dim, seed=3):
    """Vectors on a coarse grid, with equal ones among them, and labels that aren't their places."""
    x = np.random.default_rng(seed).integers(-3, 4, (n, dim)).astype(np.float32) / np.float32(3)
    x[n // 2 : n // 2 + 5] = x[0]
    return {7 * i - 50: v for i, v in enumerate(x)}


@pytest.mark.parametrize(("scenario", "iters", "size", "options"), OPTIONS)
def test_runs_in_the_jvm_equal_those_of_the_kernel(spark, scenario, iters, size, options):
    x, own = points(150, 11), STRATEGIES | {"wide": Strategy("mutual+twohop", "twohop", 1.05)}
    p = spark.createDataFrame([(k, v.tolist()) for k, v in x.items()], "label long, vec array<float>").repartition(3)
    trace = experiments.churn(p, scenario, iters, size, m=3, m0=5, ef=12, strategies=own, dataset="d", **options)
    assert trace.rdd.getNumPartitions() == len(own)  # side by side
    assert "ArrowPython" not in (plan := trace._jdf.queryExecution().executedPlan().toString()) and "FlatMapGroupsInArrow" not in plan
    got = {(r.scenario, r.dataset, r.strategy, r.iter, r.metric): r.value for r in trace.collect() if "seconds" not in r.metric}
    plain = [r for name, s in own.items() for r in experiments.run_churn({k: v.astype(float) for k, v in x.items()}, scenario, s, iters, size or 1, 3, 5, 12, dataset="d", name=name, **options)]
    wanted = {(r["scenario"], r["dataset"], r["strategy"], r["iter"], r["metric"]): r["value"] for r in plain if "seconds" not in r["metric"]}
    assert got == pytest.approx(wanted, abs=1e-12) and len(got) > 100


@pytest.mark.parametrize("scale", [1e-24, 1.0, 3e19])
def test_distances_that_floats_cannot_tell(spark, scale):
    """Distances apart by less than a float's rounding, whose squares run over or under in floats: decided as the kernel decides them."""
    from pathlib import Path

    from navgraph import jvm

    loader = jvm._classes(spark)
    assert loader.loadClass("navgraph.Near")
    plain = spark._jvm.org.codehaus.janino.SimpleCompiler()  # what stands in for it compiles as well
    plain.cook((Path(jvm.__file__).parent / "NearPlain.java").read_text())
    rng = np.random.default_rng(8)
    v = (1 + rng.integers(-3, 4, (120, 21)) * 2.0**-22) * np.where(rng.random((120, 21)) < 0.5, 1, -1) * rng.choice([1, 2], (120, 1)) * scale
    v[100:] = v[:20]
    x = dict(enumerate(v.astype(np.float32)))
    p = spark.createDataFrame([(k, w.tolist()) for k, w in x.items()], "label long, vec array<float>")
    own = {s: STRATEGIES[s] for s in ("native", "mutual_gamma")}
    options = {"ask_ef": (4, 30), "recall_ef": (10,), "tau": 30}
    got = {(r.strategy, r.iter, r.metric): r.value for r in experiments.churn(p, "random", 10, 12, m=3, m0=5, ef=12, strategies=own, **options).collect() if "seconds" not in r.metric}
    wanted = {(r["strategy"], r["iter"], r["metric"]): r["value"] for s in own for r in experiments.run_churn({k: w.astype(float) for k, w in x.items()}, "random", s, 10, 12, 3, 5, 12, **options) if "seconds" not in r["metric"]}
    assert got == pytest.approx(wanted, abs=1e-12) and len(got) > 100


def test_shards_and_doubles_and_no_points(spark):
    x = points(90, 4)
    rows = [(k, [float(c) for c in v]) for k, v in x.items()]
    floats, doubles = spark.createDataFrame(rows, "label long, vec array<float>"), spark.createDataFrame(rows, "label long, vec array<double>")
    of = lambda p: {(r.strategy, r.iter, r.metric): r.value for r in experiments.churn(p, "full_coverage", 3, m=3, ef=8, shards=2).collect() if "seconds" not in r.metric}
    assert of(floats) == pytest.approx(of(doubles)) and of(floats)["native", 2, "live"] == 90
    assert not experiments.churn(floats.filter("label IS NULL"), "random", 3, m=3, ef=8).collect()


def test_hashed_documents_by_plain_arithmetic(spark, tmp_path):
    """Repeated and null ids, null and empty texts, words of several bytes; no word is a row of its own."""
    import hashlib

    from navgraph.sources import vectors as sources

    rows = [(1, "a b"), (1, "b c b"), (None, "x"), (2, None), (3, ""), (4, "  é ü\n x  "), (None, "y z"), (5, "w w w")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    wanted = {}
    for label, text in rows:
        for w in (text or "").split(" "):
            h = hashlib.md5(w.encode()).hexdigest()
            wanted.setdefault(label, np.zeros(16))[int(h[:8], 16) % 16] += -1 if int(h[8], 16) % 2 else 1
    found = sources.hashed_documents(spark, str(tmp_path), 16)
    assert "Generate" not in found._jdf.queryExecution().executedPlan().toString()
    got = {r.label: np.float32(r.vec) for r in found.collect()}
    assert got.keys() == wanted.keys()
    for label, v in wanted.items():
        assert (got[label] == np.float32(v / np.sqrt((v * v).sum()) if v.any() else v)).all()


def test_shards_in_the_jvm_have_the_rows_of_the_kernel(spark):
    """Build, logs that delete, unmark, insert, upsert and bring new labels, and what is found: row by row."""
    from navgraph.operators import index as ix

    x, params, rng = points(160, 9), ix.GraphParams(3, 5, 12), np.random.default_rng(6)
    p = spark.createDataFrame([(k, v.tolist(), 0) for k, v in x.items()] + [(-50, x[6].tolist(), 1)], "label long, vec array<float>, version long").repartition(5)
    rows = lambda df: sorted(repr(tuple(sorted(c.items()) if isinstance(c, dict) else c for c in r)) for r in df.collect())
    plain, made = ix.build(p, params, 3).cache(), ix.build(p, params, 3, compiled=True)
    assert "ArrowPython" not in (plan := made._jdf.queryExecution().executedPlan().toString()) and "InArrow" not in plan
    made = made.cache()
    assert rows(plain) == rows(made) and len(rows(made)) == 160
    labels, seq = [*x, 5000, 5001], 10
    for strategy in ("native", "mutual_gamma", *STRATEGIES):
        log = []
        for label in rng.choice(labels, 70, replace=False).tolist():
            for op in rng.choice(["delete", "unmark", "insert", "upsert"], rng.integers(1, 4)).tolist():
                log.append((seq := seq + 1, op, label, None if op in ("delete", "unmark") else (rng.integers(-3, 4, 9) / 3).tolist()))
        log = spark.createDataFrame(log, "seq long, op string, label long, vec array<float>").repartition(4)
        for first in (False, True):
            a, b = (ix.apply_log(i, log, strategy, 3, marks_first=first, params=params, compiled=c) for i, c in ((plain, False), (made, True)))
            assert rows(a) == rows(b), (strategy, first)
        plain, made = a.cache(), b.cache()
        assert rows(ix.found_slots(plain)) == rows(ix.found_slots(made, True))
    assert rows(ix.build_backup(plain, params, 3)) == rows(ix.build_backup(made, params, 3, True))


def test_maintained_index_goes_in_the_jvm_where_it_can(spark):
    from navgraph.operators import index as ix

    p = spark.createDataFrame([(k, v.tolist(), 0) for k, v in points(40, 4).items()], "label long, vec array<float>, version long")
    log = spark.createDataFrame([(1, "delete", -50, None), (2, "upsert", -43, [1.0] * 4), (3, "upsert", 999, [0.5] * 4)], "seq long, op string, label long, vec array<float>")
    for metric in ("l2", "ip"):
        params = ix.GraphParams(3, 6, 10, metric)
        m = ix.MaintainedIndex(ix.build(p, params, 2), params, policy=ix.RebuildPolicy(1)).apply(log)
        assert m.compiled == (metric == "l2") and m.backup is not None
        assert {r.label for r in ix.live(m.index).collect()} == {*points(40, 4), 999} - {-50}


def test_wide_searches_in_the_jvm_have_the_hits_of_the_kernel(spark):
    """Beams narrower and wider than the shards, many equal vectors, marked points, a backup, and no floats."""
    from navgraph.operators import index as ix

    params, rng = ix.GraphParams(3, 5, 12), np.random.default_rng(1)
    x = (rng.integers(-3, 4, (3000, 9)) / 3).astype(np.float32)
    x[1500:1560], x[2000:2900, :6] = x[0], x[5, :6]
    p = spark.createDataFrame([(7 * i - 50, v.tolist(), 0) for i, v in enumerate(x)], "label long, vec array<float>, version long")
    q = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x[::60])], "query_id long, vec array<float>")
    log = spark.createDataFrame([(i, "delete", 7 * i - 50, None) for i in range(0, 900, 2)], "seq long, op string, label long, vec array<float>")
    built = ix.build(p, params, 2, compiled=True).cache()
    marked = ix.apply_log(built, log, compiled=True).cache()
    backup = ix.build_backup(marked, params, 2, compiled=True).cache()
    of = lambda df: sorted(map(tuple, df.collect()))
    for index in (built, marked):
        for k, ef in ((10, 10), (10, 1200), (10, 100_000), (300, 1100)):
            found = ix.search_hits(index, q, k, ef, compiled=True)
            assert "InArrow" not in found._jdf.queryExecution().executedPlan().toString()
            assert of(found) == of(ix.search_hits(index, q, k, ef)), (k, ef)
    hits = ix.search_hits(marked, q, 10, 1200, compiled=True).cache()
    assert of(ix.dual(marked, backup, q, 10, 1200, hits, compiled=True)) == of(ix.dual(marked, backup, q, 10, 1200))
    assert of(ix.search_hits(marked, q.withColumn("vec", q["vec"].cast("array<double>")), 10, 50, compiled=True)) == of(ix.search_hits(marked, q, 10, 50, compiled=True))


def test_searches_of_all_points_go_side_by_side(spark):
    """Seconds are the threads' together, the pieces are each done once."""
    from pathlib import Path

    from navgraph import jvm

    assert "Side" in jvm.SOURCES and "new Selves(" in (Path(jvm.__file__).parent / "Churn.java").read_text()
    x = points(5000, 6)
    p = spark.createDataFrame([(k, v.tolist()) for k, v in x.items()], "label long, vec array<float>")
    t = {(r.iter, r.metric): r.value for r in experiments.churn(p, "random", 1, m=4, ef=10, strategies=("native",), ask_ef=(5, 5000)).collect()}
    assert 0 < t[5, "self_recall"] <= t[5000, "self_recall"] <= 1 and t[5000, "search_seconds"] > t[5, "search_seconds"] > 0
