"""Dual-tree search against all products."""

import numpy as np
import pyspark.sql.functions as F
import pytest

from navgraph.llm import topk


def exact(q, qi, x, ids, k):
    out = {}
    for v, i in zip(q, qi, strict=True):
        s = (x.astype(object) @ v.astype(object)).tolist()
        out[int(i)] = sorted(((-int(a), int(b)) for a, b in zip(s, ids, strict=True) if b != i))[:k]
    return out


@pytest.mark.parametrize(("kind", "most"), [("clusters", 0.4), ("even", 1.0)])
def test_dual_search(kind, most):
    """The share of pairs that are scored: few where vectors lie in clusters, all where nothing tells them apart."""
    rng = np.random.default_rng(4)
    spread = rng.normal(0, 8, (40, 16)) if kind == "clusters" else np.zeros((1, 16))
    x = np.floor(256 * (spread[rng.integers(0, len(spread), 6000)] + rng.normal(0, 0.3, (6000, 16))))
    x[100:110] = x[100]
    ids, asked = np.arange(6000) * 3, np.arange(0, 6000, 25)
    best, work = topk.dual_search(topk.CoverTree.of(x[asked], ids[asked], 16), topk.CoverTree.of(x, ids, 128), 5)
    assert work <= most * len(asked) * 6000
    tree = topk.CoverTree.of(x[asked], ids[asked], 16)
    found = {int(i): [(-int(s), int(j)) for s, j in zip(best.score[n], best.id[n], strict=True)] for n, i in enumerate(tree.ids)}
    assert found == exact(x[asked], ids[asked], x, ids, 5)
    print(f"{kind}: {work / len(asked) / 6000:.3f} of the pairs scored")


def test_tree_covers_and_travels():
    rng = np.random.default_rng(5)
    x = np.floor(rng.normal(0, 50, (700, 6)))
    x[:300] = x[0]
    tree = topk.CoverTree.loaded(topk.CoverTree.of(x, np.arange(700), 20).dumped())
    assert (tree.x == x[tree.ids]).all()
    for n in range(len(tree.low)):
        own = tree.x[tree.low[n] : tree.high[n]]
        assert np.sqrt(((own - tree.x[tree.centre[n]]) ** 2).sum(1)).max(initial=0) <= tree.radius[n] + 1e-9


def test_large_numbers(spark):
    rows = [(i, [float(v), float(w)]) for i, (v, w) in enumerate([(3e6, 1.0), (3e6, 2.0), (-3e6, 5.0), (1.0, 1.0)])]
    found = {(r.query_id, r["rank"]): (r.vec_id, r.score) for r in topk.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") < 2, 2).collect()}
    v = [[int(256 * a) for a in x] for _, x in rows]
    assert found[0, 1] == (1, v[0][0] * v[1][0] + v[0][1] * v[1][1]) and found[1, 2] == (3, v[1][0] * v[3][0] + v[1][1] * v[3][1])
    with pytest.raises(Exception, match="64-bit"):
        topk.top_k(spark.createDataFrame([(0, [3e38]), (1, [3e38])], "vec_id long, embedding array<double>"), F.col("vec_id") == 0).collect()


def test_several_blocks(spark, monkeypatch):
    """Many blocks, pairs of which are left out, give what all products give."""
    rng = np.random.default_rng(6)
    spread = rng.normal(0, 8, (12, 8))
    x = spread[rng.integers(0, 12, 1500)] + rng.normal(0, 0.3, (1500, 8))
    for name, value in (("CANDIDATES", 200), ("QUERIES", 20)):
        monkeypatch.setattr(topk, name, value)
    frame = spark.createDataFrame([(i, [float(a) for a in v], "clash") for i, v in enumerate(x)], "vec_id long, embedding array<double>, q string").repartition(4)
    got = {}
    for r in topk.top_k(frame, F.col("vec_id") % 25 == 0).collect():
        got.setdefault(r.query_id, []).append((r["rank"], -r.score, r.vec_id))
    asked = np.arange(0, 1500, 25)
    y = np.floor(256 * x)
    assert {k: [t[1:] for t in sorted(v)] for k, v in got.items()} == exact(y[asked], asked, y, np.arange(1500), 5)
