import pytest
from pyspark.sql import Row

from navgraph.llm import mixing


def shared_by_rounds(sizes, weights=(3, 1, 2), share=1.5, most=2.0):
    """Shares by weight, and what is above a limit is shared anew among the others, until none is."""
    names = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: weights[i % 3] for i, s in enumerate(names)}
    target, left, open_ = dict.fromkeys(names, 0.0), share * sum(sizes.values()), set(names)
    while left > 1e-9 and open_:
        total = sum(weight[s] for s in open_)
        extra = {s: left * weight[s] / total for s in open_}
        left = 0.0
        for s, x in extra.items():
            target[s] += x
            if target[s] >= most * sizes[s]:
                left += target[s] - most * sizes[s]
                target[s] = most * sizes[s]
                open_.discard(s)
    return target


def documents(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, source string, n_chars long, size string, taken string")


@pytest.mark.parametrize("lengths", [{"a": 500, "b": 20, "c": 300, None: 40}, {"a": 1, "b": 1000, "c": 0}])
def test_targets_and_totals(spark, lengths):
    rows, k = [], 0
    for source, n in lengths.items():
        for i in range(n // 10):
            rows.append((k, " ".join(["w"] * 10), source, None, "old", "old"))
            k += 1
        rows.append((k, "x " * (n % 10), source, None, None, None))
        k += 1
    found = mixing.mix(documents(spark, rows)).collect()
    sizes, taken, target = dict.fromkeys(lengths, 0), dict.fromkeys(lengths, 0), {}
    for r in found:
        assert 0 <= r.taken <= 2 * r["size"] and r.n_chars is None
        sizes[r.source] += r["size"]
        taken[r.source] += r.taken
        target[r.source] = r.target
    assert len(found) == len(rows) and sizes == lengths
    expected = shared_by_rounds(sizes)
    for s in lengths:
        assert target[s] == pytest.approx(expected[s])
        assert abs(taken[s] - target[s]) < 2


def test_repeated_rows_nulls_and_long_texts(spark):
    rows = [(7, "a b c", "s", 1, None, None)] * 40 + [(None, None, None, 1, None, None), (8, "", "s", 1, None, None), (9, "y " * 50_000, "t", 1, None, None)]
    found = mixing.mix(documents(spark, rows)).collect()
    assert len(found) == len(rows)
    assert len({r.taken for r in found if r.doc_id == 7}) == 1
    assert mixing.mix(documents(spark, [])).count() == 0


def test_columns_with_the_names_used_inside(spark):
    rows = [(k, "a b c d", "s" if k % 3 else "t") for k in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    names = ["place", "of", "copies", "edge", "part", "left", "bucket", "prefix", "n", "weight", "Place", "a.b", "size", "words"]
    more = docs.selectExpr("*", *(f"'x' AS `{n}`" for n in names if n != "Place"))
    plain, clash = ({r.doc_id: r.taken for r in mixing.mix(d).collect()} for d in (docs, more))
    assert plain == clash and set(mixing.mix(more).columns) == {"doc_id", "text", "source", *names, "source_size", "target", "taken"} - {"Place"}


def test_a_table_of_sources_beyond_the_bound_is_shuffled(spark, monkeypatch):
    docs = documents(spark, [(k, "a b c d", f"s{k % 7}", None, None, None) for k in range(60)])
    sent = {r.doc_id: r.taken for r in mixing.mix(docs).collect()}
    monkeypatch.setattr(mixing, "SENT", 3)
    assert sent == {r.doc_id: r.taken for r in mixing.mix(docs).collect()}
