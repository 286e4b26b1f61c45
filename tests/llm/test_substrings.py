"""Repeated passages against a plain reading in order of doc_id."""

import numpy as np
import pyarrow as pa
import pytest

from navgraph.llm import deal, substrings
from navgraph.llm.textscan import GRAPHIC, words


def plain(rows, size=20):
    """doc_id: kept words. Rows with one doc_id are judged against what came with smaller ids, and against earlier starts of all
    rows of that id."""
    first, out = {}, {}
    for k, t in rows:
        w = (t or "").split()
        for i in range(len(w) - size + 1):
            key = tuple(w[i : i + size])
            first[key] = min(first.get(key, (k, i)), (k, i))
    for k, t in rows:
        w, gone = (t or "").split(), set()
        for i in range(len(w) - size + 1):
            if first[tuple(w[i : i + size])] != (k, i):
                gone |= set(range(i, i + size))
        out.setdefault(k, []).append(" ".join(x for i, x in enumerate(w) if i not in gone))
    return {k: sorted(v) for k, v in out.items()}


def rows():
    rng = np.random.default_rng(5)
    texts = [" ".join(rng.choice(["a", "b"], rng.integers(0, 120), p=[0.9, 0.1])) for _ in range(40)]
    word = lambda n: [f"w{x}" for x in rng.integers(0, 10_000, n)]
    passage = [word(n) for n in (25, 40, 19, 20)]
    for _ in range(120):
        t = word(rng.integers(0, 60))
        for p in passage:
            if rng.random() < 0.4:
                cut = int(rng.integers(0, 6))
                t += p[cut:] + word(rng.integers(0, 9))
        texts.append(" ".join(t))
    texts += [texts[60]] * 5 + [None, "", "short text"]
    return [(int(i), t) for i, t in zip(rng.permutation(4 * len(texts))[: len(texts)], texts, strict=True)] + [(5000, texts[70]), (5000, texts[71])]


@pytest.mark.parametrize("hot", [substrings.HOT, 3])
def test_against_a_plain_reading(spark, monkeypatch, hot):
    monkeypatch.setattr(deal, "CHUNK_BYTES", 4000)
    monkeypatch.setattr(deal, "LEAST_BITS", 3)
    monkeypatch.setattr(substrings, "HOT", hot)
    docs = spark.createDataFrame(rows(), "doc_id long, text string").repartition(5).selectExpr("*", "1 AS id", "2 AS chunk", "3 AS body", "4 AS row", "5 AS `a.b`", "6 AS starts")
    found = {}
    for r in substrings.dedup(docs).collect():
        assert r.n_words == len((r.text or "").split()) and r.n_removed == r.n_words - len(r.kept.split()) and r.starts == 6
        found.setdefault(r.doc_id, []).append(r.kept)
    assert {k: sorted(v) for k, v in found.items()} == plain(rows())


def test_more_words_than_characters_there_are():
    """1.2 million distinct words in recurring passages of one chunk."""
    n = 1_200_000
    text = " ".join(f"{i:x}" for i in range(n))
    texts = pa.array([text, "x " + text, "an other text that shares nothing at all"])
    made = substrings.Passages(np.array([1, 2, 3]), texts, lambda values: np.ones(len(values), np.uint8), deal.mask(8, substrings.WIDTH))
    _, blobs = made.sent(8)
    codes = np.frombuffer(b"".join(substrings.judged([b])[0] for b in blobs), np.uint8)
    gone = [g[w.offsets[i] : w.offsets[i + 1]].sum() for w, g in made.removed(codes, 8) for i in range(len(w.offsets) - 1)]
    assert gone == [0, n, 0]


def test_phrases_of_words_of_several_digits(monkeypatch):
    rng = np.random.default_rng(1)
    line = rng.integers(0, 50, 3000)
    texts = pa.array([" ".join(f"w{x}" for x in line[:2000]), "w1", " ".join(f"w{x}" for x in line[2000:])])
    (w,) = words(texts, GRAPHIC)
    phrases = np.unique(w.hashes[rng.integers(0, 1900, 40)[:, None] + np.arange(3)], axis=0)
    one = substrings.Phrases(phrases)
    monkeypatch.setattr(substrings, "BASE", 4)
    three = substrings.Phrases(phrases)
    expected = [i for i in range(len(w.hashes) - 2) if (phrases == w.hashes[i : i + 3]).all(1).any() and len(set(w.owner()[i : i + 3])) == 1]
    assert one.digits == 1 and three.digits == 3 and three.find(w).tolist() == expected
    monkeypatch.undo()
    assert one.find(w).tolist() == expected
