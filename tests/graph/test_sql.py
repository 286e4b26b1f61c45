import numpy as np

from navgraph import sql
from navgraph.operators import index


def test_functions_and_source(spark, tmp_path):
    x = np.random.default_rng(5).standard_normal((60, 4)).astype(np.float32)
    points = spark.createDataFrame([(i, v.tolist(), 0) for i, v in enumerate(x)], "label long, vec array<float>, version long")
    index.save(index.build(points, index.GraphParams(4, 8, 40), 2), str(tmp_path), 1)
    sql.register(spark)
    points.selectExpr("label AS query_id", "vec").createOrReplaceTempView("asked")
    got = sql.ann_search_all(spark, "asked", str(tmp_path), 1, 3, 60).collect()
    assert len(got) == 180 and sum(r.query_id == r.label and r.dist < 1e-5 and r["rank"] == 1 for r in got) >= 55
    i = spark.read.format("navgraph").option("epoch", 1).load(str(tmp_path))
    saved = index.load(spark, str(tmp_path), 1)
    assert sorted((r.shard, r.slot, r.label, r.nbrs) for r in i.collect()) == sorted((r.shard, r.slot, r.label, r.nbrs) for r in saved.collect())
    first = saved.filter("shard = 0 AND slot = 0").first()
    assert [r.slot for r in spark.sql(f"SELECT * FROM graph_neighbors('{tmp_path}', 1, 0, 0, 0)").collect()] == first.nbrs[0]
    assert round(spark.sql("SELECT vec_l2(array(0D, 3D), array(4D, 0D)) AS d").first().d, 6) == 5
