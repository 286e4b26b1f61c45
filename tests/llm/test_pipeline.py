"""The pipeline on the smallest documents against plain Python."""

import re

import corpus_pipeline
from navgraph.llm import secrets

SF = "/root/testdata/sf0.001"


def near_groups(texts):
    sets = {}
    for k, t in texts.items():
        w = (t or "").encode().lower().split()
        sets[k] = {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()
    up = {k: k for k in sets}

    def root(k):
        while up[k] != k:
            k = up[k]
        return k

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b] and 100 * len(x := sets[a] & sets[b]) >= 75 * (len(sets[a]) + len(sets[b]) - len(x)):
                i, j = sorted((root(a), root(b)))
                up[j] = i
    return {k: root(k) for k in sets}


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    lang = {k for k, t in texts.items() if re.search(r"[^\W\d_]", t or "")}
    group = near_groups({k: texts[k] for k in lang})
    kept = {k for k in lang if group[k] == k}
    split = lambda t: re.findall(rb"[0-9a-z\x80-\xff]+", (t or "").encode().lower())
    windows = {}
    for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect():
        w = split(r.text)
        n = min(10, len(w))
        windows.setdefault(n, set()).update(tuple(w[i : i + n]) for i in range(len(w) - n + 1) if n)
    clean = {k for k in kept if not any(tuple(w[i : i + n]) in s for w in [split(texts[k])] for n, s in windows.items() if n for i in range(len(w) - n + 1))}
    found = corpus_pipeline.run(spark, SF).collect()
    assert {r.doc_id for r in found} <= clean
    import re as _re

    allowed = _re.compile("|".join(f"(?:{x})" for x in secrets.ALLOWED))
    sizes = {}
    for r in found:
        spans = secrets.find(texts[r.doc_id].encode(), allowed)[1]
        assert r.text == secrets.without(texts[r.doc_id], spans) and 0 < r.taken <= 2 * r.size
        sizes.setdefault(r.source, [0, r.target])[0] += r.taken
    for taken, target in sizes.values():
        assert abs(taken - target) < 2
