"""Nearest examples against plain Python and dense arrays, and on documents that weren't learned from."""

import re
import zlib
from collections import Counter

import numpy as np
import pytest

from navgraph.llm import toxicity


def test_block_max_search_is_exact(monkeypatch):
    monkeypatch.setattr(toxicity, "BLOCK", 32)
    rng = np.random.default_rng(2)
    doc, term, _ = toxicity.counted(rng.integers(0, 500, 4000), rng.integers(0, 300, 4000))
    weight = rng.random(len(doc))
    dense = np.zeros((500, 300))
    dense[doc, term] = weight
    index, scored = toxicity.BlockMaxIndex(doc, term, weight, 500, 300), 0
    for _ in range(10):
        asked = [np.unique(rng.integers(0, 300, rng.integers(1, 6))) for _ in range(6)]
        q, leave = [rng.random(len(t)) for t in asked], rng.integers(0, 500, 6)
        row = np.repeat(np.arange(6), [len(t) for t in asked])
        r, ids, scores, blocks = index.search(row, np.concatenate(asked), np.concatenate(q), 6, 3, leave)
        scored += blocks
        for i in range(6):
            s = dense[:, asked[i]] @ q[i]
            s[leave[i]] = 0
            best = [j for j in np.lexsort((np.arange(500), -s))[:3] if s[j] > 0]
            assert ids[r == i].tolist() == best and scores[r == i] == pytest.approx(s[best], rel=1e-5)
    assert scored < 60 * index.n_blocks


def test_beginnings_are_whole_characters():
    import pyarrow as pa

    from navgraph.llm.textscan import words

    found = [len(toxicity.terms(w)[0]) for w in words(pa.array(["réeuxment", "日本語日本", "abcd", "abcdefg x"]), toxicity.LETTERS, toxicity.LOWER)]
    assert found == [3 + 2 + 1 + 3 + 1]
    a, b = (next(iter(words(pa.array([t]), toxicity.LETTERS, toxicity.LOWER))) for t in ("réeuxment", "RéEu"))
    assert toxicity.terms(a)[1][1] != toxicity.terms(b)[1][0] and toxicity.terms(a)[1][1] == toxicity.terms(next(iter(words(pa.array(["réeuz"]), toxicity.LETTERS, toxicity.LOWER))))[1][1]


def plain_terms(text):
    out = Counter()
    for w in re.findall(r"[a-z\x80-\U0010ffff]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")):
        out[w] += 1
        for n in toxicity.STEMS:
            if len(w) > n:
                out[n, w[:n]] += 1
    return out


def test_query_against_dense_vectors(spark):
    sf = "/root/testdata/sf0.001"
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect() if zlib.crc32(str(r.doc_id).encode()) % 4 != 2}
    found = {r.doc_id: (r.score, [e.doc_id for e in r.evidence]) for r in toxicity.op1_toxicity(spark, sf).collect()}
    counts = {k: plain_terms(t) for k, t in docs.items()}
    seen, examples = set(), []
    for k in sorted(labels):
        if (docs[k] or "") not in seen:
            seen.add(docs[k] or "")
            examples.append(k)
    df, own = Counter(t for c in counts.values() for t in c), Counter(t for k in examples for t in counts[k])
    vocabulary = [t for t in own if own[t] >= toxicity.FEWEST and df[t] <= max(toxicity.MOST_SHARE * len(docs), toxicity.MOST_ANYWAY)]
    number = {t: i for i, t in enumerate(vocabulary)}
    idf = np.array([np.log((1 + len(docs)) / df[t]) for t in vocabulary])

    def vector(c):
        v = np.zeros(len(vocabulary))
        for t, n in c.items():
            if t in number:
                v[number[t]] = n * idf[number[t]]
        return v / (np.sqrt(v @ v) or 1)

    x, toxic = np.array([vector(counts[k]) for k in examples]), np.array([float(labels[k] == 1) for k in examples])
    prior = (toxic.sum() + 0.5) / (len(toxic) + 5)

    def vote(v, leave=-1):
        s = x @ v
        if leave >= 0:
            s[leave] = 0
        best = [i for i in np.lexsort((np.arange(len(s)), -s))[: toxicity.NEIGHBOURS] if s[i] > 0]
        return (s[best] @ toxic[best] + toxicity.SHRINK * prior) / (s[best].sum() + toxicity.SHRINK), [examples[i] for i in best]

    some = [i for i in range(len(examples)) if x[i].any()]
    a, b = toxicity.fitted(np.array([vote(x[i], i)[0] for i in some]), toxic[some])
    alone = 0
    for k, c in counts.items():
        v = vector(c)
        if not v.any():
            alone += 1
            assert found[k][0] == pytest.approx(prior) and not found[k][1]
            continue
        p, near = vote(v)
        p = min(max(p, 1e-4), 1 - 1e-4)
        assert found[k][0] == pytest.approx(1 / (1 + np.exp(-(a * np.log(p / (1 - p)) + b))), abs=1e-5)
        assert found[k][1][0] == near[0] or docs[found[k][1][0]] == docs[near[0]]
    print(f"{alone} of {len(docs)} documents without a neighbour")


@pytest.mark.parametrize(("sf", "least"), [("sf0.01", 0.75), ("sf0.1", 0.93)])
def test_average_precision_on_held_out_documents(spark, sf, least):
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"/root/testdata/{sf}/labels.parquet").collect()}
    rows = toxicity.op1_toxicity(spark, f"/root/testdata/{sf}").filter("held_out").select("doc_id", "score", "predicted", "evidence").collect()
    alone = np.mean([not r.evidence for r in rows])
    rows = [r for r in rows if labels.get(r.doc_id) is not None]
    y = np.array([labels[r.doc_id] for r in sorted(rows, key=lambda r: -r.score)], float)
    p = float((np.cumsum(y) / np.arange(1, len(y) + 1) * y).sum() / y.sum())
    hit, clean = (np.mean([r.predicted for r in rows if labels[r.doc_id] == k]) for k in (1, 0))
    print(f"{sf}: {len(y)} held-out labels, {int(y.sum())} toxic: average precision {p:.3f}; predicted: {hit:.3f} of the toxic, {clean:.3f} of the others; {alone:.4f} of held-out documents without a neighbour")
    assert p >= least
