import numpy as np
import pytest

from navgraph.experiments import run_churn
from navgraph.operators.kernel import GraphKernel, level_of
from navgraph.operators.repair import STRATEGIES

POINTS = {"u": (-1, 0.2), "v": (1, 0), "t": (0.2, 0), "w": (-2, 0), "d": (0, 0), "e": (-3, 0)}
NAMES = list(POINTS)


def hand_made(lists):
    g = GraphKernel(2, 2, 2, 10)
    g.vec = np.array([POINTS[n] for n in NAMES], float)
    g.label, g.version, g.level = list(range(6)), [0] * 6, [0] * 6
    g.nbrs = [[[NAMES.index(c) for c in lists[n]]] for n in NAMES]
    g.slot_of, g.entry = {i: i for i in range(6)}, NAMES.index("w")
    return g


STRANDED = {"u": "wt", "v": "tp", "t": "up", "w": "eu", "d": "t", "e": "w"}
KEPT = {"u": "wv", "v": "tp", "t": "u", "w": "eu", "d": "v", "e": "w"}


@pytest.mark.parametrize(("strategy", "expected", "work", "lost"), [("native", STRANDED, 8, "v"), ("mutual_alpha", STRANDED | {"v": "t"}, 4, "v"), ("mutual_beta", KEPT, 3, ""), ("mutual_gamma", KEPT, 3, ""), ("mutual_twohop", KEPT, 3, "")])
def test_a_point_stranded_by_two_hop_candidates(strategy, expected, work, lost):
    g = hand_made({"d": "uv", "u": "dw", "v": "t", "t": "u", "w": "eu", "e": "w"})
    assert not g.unreachable_degree()
    g.mark_deleted(NAMES.index("d"))
    g.replace_update(99, (5, 5), strategy)
    name = [n if n != "d" else "p" for n in NAMES]
    assert {n: "".join(name[x] for x in g.nbrs[i][0]) for i, n in enumerate(NAMES)} == expected
    assert g.count["candidates"] == work
    assert {name[s] for s in g.unreachable_degree()} == set(lost) == {name[s] for s in g.unreachable_search()}


@pytest.mark.parametrize(("strategy", "lists"), [("native", {"u": "wt", "v": "tp"}), ("mutual_alpha", {"u": "wt"}), ("mutual_gamma", {"u": "wv"}), ("mutual_twohop", {"u": "wv", "t": "vu"})])
def test_who_is_repaired(strategy, lists):
    g = hand_made({"d": "uv", "u": "dw", "v": "t", "t": "ud", "w": "eu", "e": "w"})
    g.mark_deleted(NAMES.index("d"))
    name = [n if n != "d" else "p" for n in NAMES]
    new = g.repair_slot(NAMES.index("d"), (5, 5), STRATEGIES[strategy])[0]
    assert {NAMES[u]: "".join(name[x] for x in own) for u, own in new.items()} == lists


def graph(n=300, dim=16, m=6, seed=0):
    x = np.random.default_rng(seed).standard_normal((n, dim))
    g = GraphKernel(dim, m, 2 * m, 40)
    for i in range(n):
        g.insert(i, x[i])
    return g, x


@pytest.mark.parametrize("strategy", STRATEGIES)
def test_churn_keeps_the_graph_sound(strategy):
    g, x = graph()
    levels = list(g.level)
    for batch in range(4):
        gone = list(range(batch * 20, batch * 20 + 20))
        for i in gone:
            assert g.mark_deleted(i)
        assert not {g.label[s] for _, s in g.knn(x[gone[0]], 10, 300)} & set(gone)
        for i in reversed(gone):
            g.replace_update(i, x[i], strategy)
        assert not any(g.health().values()) and g.level == levels and set(g.slot_of) == set(range(300))
        assert g.unreachable_degree() <= g.unreachable_bfs() <= g.unreachable_search()


def test_exhaustive_search_is_exact_over_what_is_found():
    g, x = graph()
    found = sorted(g.enumerate_found() | {g.entry})
    for q in np.random.default_rng(1).standard_normal((10, 16)):
        d = np.sqrt(((x[found] - q) ** 2).sum(1))
        assert [s for _, s in g.knn(q, 10, 300)] == [found[i] for i in np.lexsort((found, d))[:10]]


def test_small_cases():
    g = GraphKernel(2, 4)
    assert g.knn((0, 0), 3, 10) == [] and g.enumerate_found() == set()
    g.replace_update(7, (1, 1), "native")
    assert [s for _, s in g.knn((0, 0), 5, 10)] == [0]
    g.mark_deleted(7)
    assert g.knn((0, 0), 5, 10) == [] and not g.mark_deleted(7) and g.unmark(7)
    for i in range(10):
        g.insert(100 + i, (3, 3))
    assert not any(g.health().values()) and len(g.knn((3, 3), 3, 20)) == 3
    g.mark_deleted(g.label[g.entry])
    entry = g.entry
    g.replace_update(500, (9, 9), "mutual_gamma")
    assert g.entry == entry and entry not in g.nbrs[entry][0]
    version = g.version[g.slot_of[103]]
    g.upsert(103, (4, 4), "mutual_gamma")
    assert g.version[g.slot_of[103]] == version + 1
    assert level_of(5, 4) == level_of(5, 4) >= 0


def test_rows_round_trip_and_compaction():
    g, x = graph(120)
    for i in range(10):
        g.mark_deleted(i)
    h = GraphKernel.from_table(g.table("main", 0))
    assert h.nbrs == g.nbrs and h.marked == g.marked and h.entry == g.entry and h.slot_of == g.slot_of
    gone = h.compact()
    assert len(h.label) == 120 - gone and not any(h.health().values()) and set(h.slot_of) == set(range(10, 120))
    assert all(h.label[s] == label and (h.vec[s] == np.float32(x[label])).all() for label, s in h.slot_of.items())


def test_which_slot_is_reused():
    for order, slots in (("fifo", [3, 5, 4]), ("lifo", [4, 5, 3])):
        g, x = graph(40)
        g.order = order
        for i in (3, 5, 4):
            g.mark_deleted(i)
        assert [g.replace_update(100 + i, x[i], "mutual_gamma") for i in range(3)] == slots and g.next_free() is None


def one_by_one(g, centre, candidates, cap, alpha):
    d = {c: float(((g.vec[c] - centre) ** 2).sum()) for c in candidates}
    kept, asked = [], len(candidates)
    for c in sorted(candidates, key=lambda c: (d[c], c)):
        if len(kept) == cap:
            break
        asked += len(kept)
        if not any(alpha * alpha * float(((g.vec[c] - g.vec[a]) ** 2).sum()) < d[c] for a in kept):
            kept.append(c)
    return kept, asked


def test_pruning_against_a_reading_one_by_one():
    g, x = graph(200)
    g.vec[50:60] = g.vec[50]
    rng = np.random.default_rng(8)
    for alpha in (1.0, 1.1, 1.2):
        for _ in range(60):
            own = rng.choice(200, rng.integers(1, 60), replace=False).tolist()
            centre, before = x[int(rng.integers(0, 200))], g.count["prune"]
            assert (g.prune(centre, own, 8, alpha), g.count["prune"] - before) == one_by_one(g, centre, own, 8, alpha)
    g.fill = True
    assert len(g.prune(x[0], list(range(1, 40)), 12)) == 12


def test_options_of_selection():
    g, x = graph(150)
    h = GraphKernel(16, 6, 12, 40, extend=True, fill=True)
    for i in range(150):
        h.insert(i, x[i])
    assert not any(h.health().values()) and len(h.unreachable_search()) <= len(g.unreachable_search()) + 2
    h.drop_marked = True
    for i in range(30):
        h.mark_deleted(i)
    new = h.repair_slot(0, x[0], STRATEGIES["mutual_gamma"])
    assert not any(n in h.marked and n != 0 for layer in new.values() for own in layer.values() for n in own)


def test_shape_of_the_claims():
    """Small pools save work; alpha above 1 with a local pool strands no more points than the conventional update; the backup
    leaves nothing unfound right after its rebuild."""
    rng = np.random.default_rng(3)
    centres = rng.standard_normal((30, 12))
    x = {i: centres[i % 30] + 0.2 * rng.standard_normal(12) for i in range(400)}
    total = {}
    for s in STRATEGIES:
        t = run_churn(x, "random", s, 12, 20, 4, 8, 40)
        total[s] = (sum(r["value"] for r in t if r["metric"] == "work_candidates"), [r["value"] for r in t if r["metric"] == "unreachable_search"][-1])
    work = {s: v[0] for s, v in total.items()}
    assert work["native"] > work["mutual_alpha"] > work["mutual_beta"] and work["mutual_twohop"] < work["native"]
    assert total["mutual_gamma"][1] <= total["native"][1] + 4
    t = run_churn(x, "full_coverage", "mutual_gamma", 8, 0, 4, 8, 40, tau=200)
    assert [r["value"] for r in t if r["metric"] == "unreachable_with_backup" and r["iter"] in (3, 7)] == [0.0, 0.0]


def test_a_beam_as_wide_as_the_graph_is_a_walk():
    rng = np.random.default_rng(11)
    x = np.round(rng.standard_normal((300, 4)), 1)
    g = GraphKernel(4, 3, 4, 12)
    for i, v in enumerate(x):
        g.insert(i, v)
    for i in range(0, 300, 9):
        g.mark_deleted(i)
    for i in range(0, 300, 27):
        g.replace_update(1000 + i, x[i] + 0.1, "native")
    for kept in (None, []):
        g.walks = kept
        for q in rng.standard_normal((40, 4)):
            start = g.descend(q, 0)
            seen = g.reached(start[0])
            wanted = sorted((float(d), s) for d, s in zip(np.sqrt(((g.vec[sorted(seen)] - q) ** 2).sum(1)), sorted(seen), strict=True) if s not in g.marked)[:7]
            before = g.count["search"]
            got = g.knn(q, 7, 100_000)
            assert [s for _, s in got] == [s for _, s in wanted] and g.count["search"] - before >= len(seen)
    assert len(g.walks) < 40


def test_exhaustive_searches_share_their_walk():
    rng, calls = np.random.default_rng(12), []
    g = GraphKernel(4, 4, 8, 40)
    for i, v in enumerate(rng.standard_normal((400, 4))):
        g.insert(i, v)
    g.walks = []
    for q in rng.standard_normal((50, 4)):
        g.knn(q, 5, 1000)
        calls.append(len(g.walks))
    assert calls[-1] <= 3
