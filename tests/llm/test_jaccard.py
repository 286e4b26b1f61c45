"""The Jaccard join against all pairs."""

import numpy as np
import pytest

from navgraph.llm import components, jaccard


def family(rng, groups, most):
    sets = []
    for _ in range(groups):
        base = rng.choice(10**12, rng.integers(1, 90), replace=False).astype(np.uint64) << np.uint64(20)
        for _ in range(rng.integers(1, most)):
            keep = base[rng.random(len(base)) < rng.choice([0.8, 0.95, 1.0])]
            sets.append(np.unique(keep if len(keep) else base))
    return sets


def linked(x, y, percent=75):
    common = len(np.intersect1d(x, y))
    return 100 * common >= percent * (len(x) + len(y) - common)


def groups(links, n):
    up = list(range(n))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i, j in links:
        a, b = sorted((root(i), root(j)))
        up[b] = a
    return [root(i) for i in range(n)]


def test_tree_join_against_all_pairs():
    rng = np.random.default_rng(3)
    sets = family(rng, 60, 9)
    n, copies = len(sets), rng.integers(1, 5, len(sets))
    everything = [(i, j) for i in range(n) for j in range(i) if linked(sets[i], sets[j])]
    partners = np.zeros(n, int)
    for i, j in everything:
        partners[i] += copies[j]
        partners[j] += copies[i]
    links, found, compared = jaccard.tree_join(sets, list(range(n)), list(range(n)), 75, copies)
    assert groups(links, n) == groups(everything, n) and found.tolist() == partners.tolist() and set(links) <= {(i, j) for i, j in everything} | {(j, i) for i, j in everything}
    assert compared < 0.8 * n * (n + 1) / 2
    left, right = list(range(0, n, 2)), list(range(1, n, 2))
    parts = [jaccard.tree_join(sets, a, b, 75, copies) for a, b in ((left, right), (left, left), (right, right))]
    assert groups([x for p in parts for x in p[0]], n) == groups(everything, n) and sum(p[1] for p in parts).tolist() == partners.tolist()


def brute(rows):
    sets = {}
    for k, (_, t) in enumerate(rows):
        w = (t or "").encode().lower().split()
        sets[k] = {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()
    pairs = [(i, j) for i in sets for j in sets if j < i and sets[i] and sets[j] and 100 * len(x := sets[i] & sets[j]) >= 75 * (len(sets[i]) + len(sets[j]) - len(x))]
    least = groups(pairs, len(rows))
    return {rows[k][0]: (len(sets[k]), min(rows[m][0] for m in range(len(rows)) if least[m] == least[k]), sum(k in p for p in pairs)) for k in sets}


@pytest.fixture(scope="module")
def rows():
    """One block of near copies of several pieces, exact copies, small groups, a line that all share, and texts alone."""
    rng = np.random.default_rng(11)
    word = lambda: "".join(rng.choice(list("abcdefgh"), 6))
    base, line = [word() for _ in range(60)], "this line of eleven words stands in each of the texts"
    texts = []
    for _ in range(150):
        own = list(base)
        for k in rng.choice(60, rng.integers(0, 3), replace=False):
            own[k] = word()
        texts.append(" ".join(own))
    texts += [" ".join(base)] * 40
    for _ in range(60):
        own = [word() for _ in range(rng.integers(0, 40))]
        texts += [" ".join([*own, line])] + [" ".join([*own, word(), line])] * int(rng.integers(0, 2))
    texts += [None, "", "Word", "word", "a b c", "A B  C", "d e f g h", "d e f g h"]
    ids = rng.permutation(3 * len(texts))[: len(texts)]
    return [(int(i), t) for i, t in zip(ids, texts, strict=True)]


def test_against_brute_force(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    found = {r.doc_id: (r.n_shingles, r.component_id, r.n_links) for r in jaccard.near_groups(docs).collect()}
    assert found == brute(rows)
    kept = {r.doc_id for r in jaccard.keep_one(docs.selectExpr("*", "1 AS later_copy", "2 AS node", "3 AS `a.b`", "4 AS chunk", "5 AS id")).collect()}
    assert kept == {k for k, v in found.items() if v[1] == k}


def test_components_by_joins_and_in_one_task(spark):
    rng = np.random.default_rng(0)
    a, b = rng.integers(0, 300, 250), rng.integers(0, 300, 250)
    path = np.arange(500, 620)
    a, b = np.concatenate((a, path[:-1])), np.concatenate((b, path[1:]))
    links = spark.createDataFrame([(int(x), int(y)) for x, y in zip(a, b, strict=True)] + [(None, 3)], "a long, b long").repartition(5)
    one, joined = (sorted(tuple(r) for r in components.components(links, one_task=n).collect()) for n in (10**6, 10))
    nodes, least = components.united(a[a != b], b[a != b])
    assert one == joined == list(zip(nodes.tolist(), least.tolist(), strict=True))
    assert components.components(links.filter("a = b")).count() == 0
