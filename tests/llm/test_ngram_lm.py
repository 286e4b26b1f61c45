"""Scores against exact counts, and documents that the corpus holds twice."""

import math
from collections import Counter

import numpy as np
import pyspark.sql.functions as F
import pytest

from navgraph.llm import ngram_lm


def test_scores_against_exact_counts(spark):
    """The filter's levels are those of the exact counts but for its few false ones, which can only raise a level."""
    rng = np.random.default_rng(3)
    vocabulary = [f"w{i}" for i in range(400)]
    weight = 1 / np.arange(1, 401)
    texts = [" ".join(rng.choice(vocabulary, rng.integers(0, 80), p=weight / weight.sum())) for _ in range(300)] + [None, ""]
    rows = [(i, t, i % 10 != 0, "x", "y") for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, train boolean, one string, `a.b` string").repartition(5)
    found = {r.doc_id: r for r in ngram_lm.score(docs).collect()}
    own = {i: [*(t or "").split(), None] for i, t, *_ in rows}
    uni, pairs, documents = Counter(), Counter(), 0
    for i, _, train, *_ in rows:
        if train:
            documents += 1
            uni.update(own[i])
            pairs.update(zip(["begin", *own[i]], own[i], strict=False))
    model = ngram_lm.Model(sum(uni.values()), len(uni), documents)
    of = lambda c: int(ngram_lm.level(np.array([c]))[0]) if c else 0

    def cells(i):
        out, before = [], ngram_lm.ENDS
        for v, w in zip(["begin", *own[i]], own[i], strict=False):
            here = ngram_lm.ENDS if w is None else of(uni[w])
            out.append(before << 16 | here << 8 | of(pairs[v, w]))
            before = here
        return np.array(out)

    numbers = Counter(c for i, _, train, *_ in rows if train for c in cells(i).tolist())
    model.fit(np.array(list(numbers)), np.array(list(numbers.values())))
    once, twice = (sum(c == k for c in pairs.values()) for k in (1, 2))
    assert model.discount == pytest.approx(min(once / (once + 2 * twice), ngram_lm.MOST_DISCOUNT))
    raised = []
    for i, r in found.items():
        raised.append(r.score - float(model.log10(cells(i)).sum()))
        assert r.one == "x" and r["a.b"] == "y"
        assert r.n_known == sum(uni[w] > 0 for w in own[i]) and r.train_tokens == model.total
        assert r.base_score == pytest.approx(sum(math.log10((uni[w] + 0.1) / (model.total + 0.1 * (len(uni) + 1))) for w in own[i]), abs=1e-6)
    # A false level raises a pair's share by half or so; a pair never seen that seems to be costs more, once in thousands.
    assert min(raised) > -0.5 and np.mean(raised) < 0.6 and np.quantile(raised, 0.95) < 2


def test_documents_that_occur_twice(spark):
    """Over what the base says, texts that have an exact copy score higher per token than those that have no near copy."""
    from navgraph.llm import jaccard

    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    n = Counter(r.text for r in docs.collect())
    near = {r.doc_id: r.n_links for r in jaccard.near_groups(docs).collect()}
    texts = {r.doc_id: r.text for r in docs.collect()}
    rows = ngram_lm.op5_lm_scoring(spark, sf).filter("n_tokens > 30").select("doc_id", "held_out", ((F.col("score") - F.col("base_score")) / F.col("n_tokens")).alias("more")).collect()
    for held in (True, False):
        twice, once = (np.array([r.more for r in rows if r.held_out == held and k(r.doc_id)]) for k in (lambda i: n[texts[i]] > 1, lambda i: near[i] == 0))
        above = np.mean(twice[:, None] > once[None, :])
        print(f"held out {held}: {len(twice)} copied, {len(once)} single documents: a copied one scores higher in {above:.3f} of the pairs; above the single ones' 0.9 quantile are {np.mean(twice > np.quantile(once, 0.9)):.3f} of the copied")
        assert above > (0.9 if held else 0.65)
