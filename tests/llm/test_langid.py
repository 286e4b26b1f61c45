"""The recurrent network: gradients by differences, padding, letters, and accuracy on documents it didn't learn from."""

import numpy as np
import pytest

from navgraph.llm import langid


def test_gradients():
    net, rng = langid.Network(["a", "b"], hidden=5, embed=3), np.random.default_rng(0)
    x, y = rng.integers(0, 256, (6, 3)).astype(np.int16), np.array([0, 1, 0])
    x[4:, 1] = langid.NONE
    m = x < langid.NONE
    loss = lambda: -sum(net.log_probabilities(x)[t, y[b], b] for t in range(6) for b in range(3) if m[t, b]) / m.sum()
    for k in net.PARTS:
        setattr(net, k, getattr(net, k).astype(np.float64))
    for k, g in zip(net.PARTS, net._gradients(x, y), strict=True):
        p = getattr(net, k)
        for i in (np.unravel_index(j, g.shape) for j in np.argsort(-np.abs(g), axis=None)[:3]):
            old = p[i]
            p[i] = old + 1e-2
            up = loss()
            p[i] = old - 1e-2
            down = loss()
            p[i] = old
            assert g[i] == pytest.approx((up - down) / 2e-2, rel=0.02, abs=1e-4), k


def test_padding_changes_nothing():
    net, rng = langid.Network(["a", "b", "c"]), np.random.default_rng(1)
    long, short = rng.integers(0, 256, 40).astype(np.int16), rng.integers(0, 256, 17).astype(np.int16)
    both = np.full((40, 2), langid.NONE, np.int16)
    both[:, 0], both[:17, 1] = long, short
    together, alone = net.pooled(both), net.pooled(short[:, None])
    assert together[0][:, 1] == pytest.approx(alone[0][:, 0], abs=1e-3) and (together[1][:, 1] == alone[1][:, 0]).all()
    again = langid.Network.loaded(net.dumped())
    assert again.labels == net.labels and (again.pooled(both)[0] == together[0]).all()


def test_a_label_rests_on_other_words():
    net = langid.Network(["a", "b"])
    one, two = (np.frombuffer(t, np.uint8).astype(np.int16)[:, None] for t in (b"xx word yy", b"qq word zz"))
    assert (net.log_probabilities(one)[3:7] != net.log_probabilities(two)[3:7]).all()


def test_letters():
    assert not any(langid.has_letter(t.encode()) for t in ("", "² ½ ①", "Ⅷ 12 _ !", "\n\t", "٣"))
    assert all(langid.has_letter(t.encode()) for t in ("a", "1 é", "日", "ª"))


def test_accuracy_on_held_out_documents(spark):
    import pyspark.sql.functions as F

    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    found = langid.op3_language_id(spark, "/root/testdata/sf0.01").join(docs.select("doc_id", "lang", "text"), "doc_id")
    rows = found.filter(F.col("held_out") & F.col("lang").isNotNull() & (F.col("lang_pred") != langid.UNKNOWN)).select("lang", "lang_pred", F.length("text").alias("n")).collect()
    right = np.mean([r.lang == r.lang_pred for r in rows])
    print(f"{len(rows)} held-out documents, accuracy {right:.4f}")
    assert len(rows) > 300 and right >= 0.99


def test_inference_in_place_gives_what_training_sees():
    net, rng = langid.Network(["a", "b", "c"]), np.random.default_rng(3)
    x = rng.integers(0, 256, (50, 9)).astype(np.int16)
    x[31:, 2], x[:, 5], x[7:, 8] = langid.NONE, langid.NONE, langid.NONE
    mask = x < langid.NONE
    logits = net._logits(net._states(x, mask.astype(np.float32)))
    wanted = logits - np.log(np.exp(logits).sum(1, keepdims=True))
    assert np.abs((net.log_probabilities(x) - wanted) * mask[:, None]).max() < 1e-5


def test_inference_holds_no_states():
    import tracemalloc

    net, x = langid.Network(["a", "b", "c", "d"]), np.zeros((langid.RUN, langid.TOGETHER), np.int16)
    tracemalloc.start()
    net.log_probabilities(x)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    states = 4 * (langid.RUN + 1) * 2 * (net.n + net.e + 1) * langid.TOGETHER
    assert most < 0.5 * states


def test_inference_by_exponentials(monkeypatch):
    """No tanh, which some processors take slowly; exponents far too large for a float give the same as tanh."""
    net, rng = langid.Network(["a", "b", "c"]), np.random.default_rng(4)
    net.gates[:, ::2, -1], net.gates[:, 1::4, -1], net.given[:, ::2, -1] = -100, 100, -100
    x = rng.integers(0, 256, (30, 6)).astype(np.int16)
    logits = net._logits(net._states(x, None))
    wanted = logits - np.log(np.exp(logits).sum(1, keepdims=True))
    monkeypatch.setattr(np, "tanh", None)
    with np.errstate(all="raise", under="ignore"):
        assert np.abs(net.log_probabilities(x) - wanted).max() < 1e-4
