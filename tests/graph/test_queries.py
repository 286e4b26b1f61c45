"""Relational queries on small tables made for what sizes and layouts bring about, against their SQL in DuckDB."""

import duckdb
import pytest

import __spark_entry__ as entry


def against_sql(spark, name, path, *tables):
    """Rows of the query and of its SQL, sorted, as text, so that 0.0 and -0.0 differ."""
    con = duckdb.connect()
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path}/{t}.parquet/*.parquet'")
    got = sorted(repr(tuple(r)) for r in entry.queries()[name](spark, str(path)).collect())
    return got, sorted(map(repr, con.execute(entry.oracle_sql()[name]).fetchall()))


def test_zero_keeps_its_sign(spark, tmp_path):
    rows = [(i, [x] * 64, 1) for i, x in enumerate((0.25, -0.2501, 0.0))]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    for name in ("op_centroid", "op_centroid_aggregate"):
        got, wanted = against_sql(spark, name, tmp_path, "embeddings")
        assert got == wanted and "-0.0" in got[0], name


def test_lateral_join_ranks_within_customers(spark, tmp_path):
    spark.createDataFrame([(1,), (1,), (2,), (3,)], "c_custkey long").write.parquet(f"{tmp_path}/customer.parquet")
    orders = [(10 + i, 1, float(i % 5)) for i in range(40)] + [(90, 2, None), (91, 2, 5.0), (92, 2, 5.0), (93, 4, 1.0)]
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long, o_totalprice double").write.parquet(f"{tmp_path}/orders.parquet")
    got, wanted = against_sql(spark, "op_join_lateral", tmp_path, "orders", "customer")
    assert got == wanted and len(got) == 4
    # No sort over all customers' orders may stand before the exchange that deals them out.
    plan = entry.queries()["op_join_lateral"](spark, str(tmp_path))._jdf.queryExecution().executedPlan().toString()
    assert "rangepartitioning" not in plan


def test_layers_and_choices_follow_the_tables(spark, tmp_path):
    for n, path in ((5, tmp_path / "few"), (300, tmp_path / "many")):
        spark.createDataFrame([(i, [1.0] if i % 3 else None) for i in range(n)], "vec_id long, embedding array<float>").write.parquet(f"{path}/embeddings.parquet")
        spark.range(n * 40).selectExpr("'R' AS l_returnflag", "CAST(id % 2 AS INT) AS l_linenumber").write.parquet(f"{path}/lineitem.parquet")
        for name, table in (("op_recursive_layers", "embeddings"), ("planner_choices", "lineitem")):
            got, wanted = against_sql(spark, name, path, table)
            assert got == wanted and len(got) == {5: {"op_recursive_layers": 1, "planner_choices": 3}, 300: {"op_recursive_layers": 4, "planner_choices": 3}}[n][name], got


def test_interval_join_meets_spans_only(spark, tmp_path):
    minutes = [0, 1, 119, 120, 121, 239, 240, 241, 360, 1439, 1440, 1559, 1560]
    rows = [(10 * i + k, m, ("view", "error")[k > 4]) for i, m in enumerate(minutes) for k in (3, 4, 5, 9)] + [(1000 + 10 * i + 3, m, "error") for i, m in enumerate(minutes)]
    events = spark.createDataFrame(rows, "event_id long, m int, event_type string")
    for kind in ("timestamp", "timestamp_ntz"):
        path = tmp_path / kind
        events.selectExpr("event_id", f"CAST(TIMESTAMP '2024-01-01 00:00:00' + make_interval(0, 0, 0, 0, 0, m) AS {kind}) AS ts", "event_type").write.parquet(f"{path}/events.parquet")
        got, wanted = against_sql(spark, "op_join_interval", path, "events")
        assert got == wanted and len(got) > len(minutes)
        plan = entry.queries()["op_join_interval"](spark, str(path))._jdf.queryExecution().optimizedPlan().toString()
        assert "s#" in plan.split("Join Inner")[1].split("\n")[0]


def test_radius_by_blocks(spark):
    import numpy as np

    from navgraph.operators import exact

    rng = np.random.default_rng(4)
    x = np.round(rng.standard_normal((120, 3)), 1)
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(500, x[0].tolist()), (501, None), (502, [float("nan"), 0.0, 0.0]), (503, [0.5, 0.5])]
    points = spark.createDataFrame(rows, "label long, vec array<double>")
    wanted = sorted((i, j, round(float(np.sqrt(((x[i % 500] - x[j % 500]) ** 2).sum())), 9)) for i in [*range(120), 500] for j in [*range(120), 500] if i < j and np.sqrt(((x[i % 500] - x[j % 500]) ** 2).sum()) <= 0.5)
    for rows in (4096, 17):
        got = exact.radius(points, 0.5, rows)
        assert sorted((p.a, p.b, round(p.dist, 9)) for p in got.collect()) == wanted and (0, 500) in {(a, b) for a, b, _ in wanted}
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoopJoin" not in plan and "CartesianProduct" not in plan
