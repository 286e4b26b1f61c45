"""Queries of the methods, measures and workloads, each with the same thing in SQL."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from navgraph import workloads
from navgraph.functions import vectors as V
from navgraph.operators import exact, reach, repair
from navgraph.operators.repair import STRATEGIES
from navgraph.session import written
from navgraph.sources import vectors as sources

QUERIES: dict = {}
SQL: dict[str, str] = {}

E = "e AS (SELECT vec_id AS label, embedding::DOUBLE[] AS v, label AS tag FROM embeddings)"
CAP, SEED = 8, 42
#: The base is the first nine tenths of the points by label; a twenty-fifth of all points is replaced by the first of the rest.
BASE = "label IN (SELECT label FROM e ORDER BY label LIMIT (SELECT count(*) * 9 // 10 FROM e))"


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def asks(p: DataFrame) -> DataFrame:
    return p.filter("label % 50 = 0").select(F.col("label").alias("query_id"), "vec")


# ---- exact search
_distance = {"l2": "list_distance(p.v, q.v)", "ip": "-list_inner_product(p.v, q.v)", "cosine": "list_cosine_distance(p.v, q.v)"}


def _knn(spark, sf, metric="l2"):
    p = sources.embeddings(spark, sf)
    return exact.knn(p, asks(p), 10, metric).select("query_id", "rank", "label", F.round("dist", 4).alias("dist"))


def knn_sql(distance: str, where: str = "TRUE", k: int = 10, ask: str = "q.label % 50 = 0") -> str:
    return f"WITH {E} SELECT query_id, rank::INT AS rank, label, round(d, 4) AS dist FROM (SELECT q.label AS query_id, p.label, {distance} AS d, row_number() OVER (PARTITION BY q.label ORDER BY {distance}, p.label) AS rank FROM e q, e p WHERE {ask} AND {where}) WHERE rank <= {k}"


for _m in _distance:
    query(f"exact_knn_{_m}", knn_sql(_distance[_m]))(partial(_knn, metric=_m))


@query("exact_knn_filtered", knn_sql(_distance["l2"], "p.tag = 3"))
def exact_knn_filtered(spark, sf):
    tags = sources.table(spark, sf, "embeddings").select(F.col("vec_id").alias("label"), F.col("embedding").alias("vec"), F.col("label").alias("tag"))
    return exact.knn(tags, asks(tags), 10, where=F.col("tag") == 3).select("query_id", "rank", "label", F.round("dist", 4).alias("dist"))


@query("exact_knn_join", knn_sql(_distance["l2"], "p.tag = 1", 3, "q.tag = 0"))
def exact_knn_join(spark, sf):
    tags = sources.table(spark, sf, "embeddings").select(F.col("vec_id").alias("label"), F.col("embedding").alias("vec"), F.col("label").alias("tag"))
    found = exact.knn(tags.filter("tag = 1"), tags.filter("tag = 0").select(F.col("label").alias("query_id"), "vec"), 3)
    return found.select("query_id", "rank", "label", F.round("dist", 4).alias("dist"))


@query("radius_search", f"WITH {E} SELECT a.label AS a, b.label AS b, round(list_distance(a.v, b.v), 4) AS dist FROM e a JOIN e b ON a.label < b.label WHERE list_distance(a.v, b.v) <= 1.05")
def radius_search(spark, sf):
    return exact.radius(sources.embeddings(spark, sf), 1.05).select("a", "b", F.round("dist", 4).alias("dist"))


# ---- the deterministic graph G0
def g0_sql(k: int, where: str = "TRUE") -> str:
    return f"{E}, b0 AS (SELECT * FROM e WHERE {where}), g AS (SELECT src, dst, r FROM (SELECT a.label AS src, b.label AS dst, row_number() OVER (PARTITION BY a.label ORDER BY list_distance(a.v, b.v), b.label) AS r FROM b0 a JOIN b0 b ON a.label <> b.label) WHERE r <= {k})"


@query("knn_graph_g0", f"WITH {g0_sql(4)} SELECT src, list_sort(list(dst)) AS nbrs FROM g GROUP BY src")
def knn_graph_g0(spark, sf):
    return exact.knn_graph(sources.embeddings(spark, sf), 4).select("src", F.array_sort("nbrs").alias("nbrs"))


DEGREES = (2, 3, 4, 5, 8, 10)


@query("g0_unreachable_degree", f"WITH {g0_sql(10)} SELECT k, count(*) AS unreachable FROM (SELECT k, label FROM e, (SELECT unnest([2, 3, 4, 5, 8]) AS k) ks WHERE NOT EXISTS (SELECT 1 FROM g WHERE g.dst = e.label AND g.r <= ks.k)) GROUP BY k")
def g0_unreachable_degree(spark, sf):
    p = sources.embeddings(spark, sf)
    e = exact.edges(written(exact.knn_graph(p, 10), "g0"))
    found = [reach.unreachable_degree(p, e.filter(F.col("place") < k)).agg(F.count(F.lit(1)).alias("unreachable")).select(F.lit(k).alias("k"), "unreachable") for k in DEGREES[:-1]]
    return found[0].unionByName(found[1]).unionByName(found[2]).unionByName(found[3]).unionByName(found[4]).filter("unreachable > 0")


def _found_sql(k: int) -> str:
    return f"WITH RECURSIVE {g0_sql(k)}, f AS (SELECT 0::BIGINT AS label UNION SELECT g.dst FROM f JOIN g ON g.src = f.label)"


@query("g0_unreachable_bfs", _found_sql(4) + " SELECT label FROM e WHERE label NOT IN (SELECT label FROM f)")
def g0_unreachable_bfs(spark, sf):
    p = sources.embeddings(spark, sf)
    return reach.unreachable_bfs(p.select("label"), exact.edges(exact.knn_graph(p, 4)), 0)


@query("backup_members_g0", _found_sql(4) + " SELECT 'backup' AS role, label, len(v)::INT AS dim FROM e EXCEPT SELECT 'backup', label, len(v)::INT FROM e JOIN f USING (label)")
def backup_members_g0(spark, sf):
    """What a backup has to hold: all points less those that are found, with their vectors' length."""
    p = sources.embeddings(spark, sf)
    found = reach.found_bfs(exact.edges(exact.knn_graph(p, 4)), 0)
    return p.select(F.lit("backup").alias("role"), "label", F.size("vec").alias("dim")).join(found, "label", "left_anti")


@query("unreachable_share", _found_sql(4) + " SELECT round(count(*) FILTER (WHERE label NOT IN (SELECT label FROM f)) / count(*)::DOUBLE, 6) AS share FROM e")
def unreachable_share(spark, sf):
    p = sources.embeddings(spark, sf)
    lost = g0_unreachable_bfs(spark, sf).withColumn("lost", F.lit(1))
    return p.join(lost, "label", "left").agg(F.round(F.count("lost") / F.count(F.lit(1)), 6).alias("share"))


@query("g0_mutual_ratio", f"WITH {g0_sql(4)} SELECT g.src, count(h.src)::BIGINT AS mutual, count(*)::BIGINT AS degree FROM g LEFT JOIN g h ON g.src = h.dst AND g.dst = h.src GROUP BY g.src")
def g0_mutual_ratio(spark, sf):
    e = exact.edges(exact.knn_graph(sources.embeddings(spark, sf), 4)).select("src", "dst")
    back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("one"))
    return e.join(back, ["src", "dst"], "left").groupBy("src").agg(F.count("one").alias("mutual"), F.count(F.lit(1)).alias("degree"))


@query("degree_statistics", f"WITH {g0_sql(4)}, d AS (SELECT label, (SELECT count(*) FROM g WHERE g.dst = e.label) AS n FROM e) SELECT n::BIGINT AS in_degree, count(*)::BIGINT AS nodes FROM d GROUP BY n")
def degree_statistics(spark, sf):
    p = sources.embeddings(spark, sf)
    into = exact.edges(exact.knn_graph(p, 4)).groupBy(F.col("dst").alias("label")).agg(F.count(F.lit(1)).alias("n"))
    return p.join(into, "label", "left").groupBy(F.coalesce("n", F.lit(0)).cast("long").alias("in_degree")).agg(F.count(F.lit(1)).alias("nodes"))


@query("level_histogram", "WITH u AS (SELECT (('0x' || substr(md5('lvl:' || vec_id), 1, 8))::BIGINT + 1) / 4294967297.0::DOUBLE AS u FROM embeddings) SELECT m, floor(-ln(u) / ln(m))::INT AS level, count(*)::BIGINT AS n FROM u, (SELECT unnest([4, 8, 16]) AS m) GROUP BY ALL")
def level_histogram(spark, sf):
    p = sources.embeddings(spark, sf)
    per = F.explode(F.array(*(F.struct(F.lit(m).alias("m"), V.level(F.col("label"), m).alias("level")) for m in (4, 8, 16))))
    return p.select(per.alias("x")).select("x.*").groupBy("m", "level").agg(F.count(F.lit(1)).alias("n"))


# ---- pruning
def prune_sql(alpha: float, cap: int) -> str:
    """CTEs from c(u, cand, d, v) to pruned(u, nbrs): candidates one by one, with the kept ones in a list."""
    return f"""
o AS (SELECT u, cand, d, v, row_number() OVER (PARTITION BY u ORDER BY d, cand) AS n FROM c),
st AS (
  SELECT u, 0::BIGINT AS n, []::BIGINT[] AS kept, []::DOUBLE[][] AS vs FROM (SELECT DISTINCT u FROM o)
  UNION ALL
  SELECT st.u, o.n,
    CASE WHEN len(kept) < {cap} AND len(list_filter(vs, lambda a: {alpha}::DOUBLE * list_distance(a, o.v) < o.d)) = 0 THEN list_append(kept, o.cand) ELSE kept END,
    CASE WHEN len(kept) < {cap} AND len(list_filter(vs, lambda a: {alpha}::DOUBLE * list_distance(a, o.v) < o.d)) = 0 THEN list_append(vs, o.v) ELSE vs END
  FROM st JOIN o ON o.u = st.u AND o.n = st.n + 1
),
pruned AS (SELECT u, arg_max(kept, n) AS nbrs FROM st GROUP BY u)"""


_PRUNE_C = "c AS (SELECT u, cand, d, v FROM (SELECT a.label AS u, b.label AS cand, list_distance(a.v, b.v) AS d, b.v, row_number() OVER (PARTITION BY a.label ORDER BY list_distance(a.v, b.v), b.label) AS r FROM e a JOIN e b ON a.label <> b.label ) WHERE r <= 20)"


def _prune(spark, sf, alpha=1.0, simple=False):
    p = sources.embeddings(spark, sf)
    found = exact.knn(p, p.select(F.col("label").alias("query_id"), "vec"), 20, exclude_self=True)
    c = found.join(p.select("label", F.col("vec").cast("array<double>").alias("v")), "label").groupBy(F.col("query_id").alias("u")).agg(F.collect_list(F.struct("dist", F.col("label").alias("id"), F.col("v").alias("vec"))).alias("c"))
    return c.select("u", (V.nearest(F.col("c"), 6) if simple else V.rng_prune(F.col("c"), 6, alpha)).alias("nbrs"))


for _a in (1.0, 1.05, 1.1, 1.2):
    query(f"rng_prune_a{round(_a * 100) if _a in (1.05,) else round(_a * 10)}", f"WITH RECURSIVE {E}, {_PRUNE_C}, {prune_sql(_a, 6)} SELECT u, nbrs FROM pruned")(partial(_prune, alpha=_a))
query("nearest_prune", f"WITH {E}, {_PRUNE_C} SELECT u, list(cand ORDER BY d, cand)[1:6] AS nbrs FROM c GROUP BY u")(partial(_prune, simple=True))

# ---- workloads
EMB = "SELECT vec_id AS label FROM embeddings"
N100 = "(SELECT greatest(1, count(*) // 100) FROM embeddings)"


@query("full_coverage_parts", f"SELECT (ntile(100) OVER (ORDER BY label) - 1)::INT AS iter, label FROM ({EMB})")
def full_coverage_parts(spark, sf):
    return workloads.full_coverage(sources.embeddings(spark, sf), 100)


RANDOM_SQL = f"SELECT iter, label FROM (SELECT iter, label, row_number() OVER (PARTITION BY iter ORDER BY md5('42:' || iter || ':' || label), label) AS n FROM ({EMB}), (SELECT unnest(range(200))::INT AS iter)) WHERE n <= {N100}"


@query("random_batches", RANDOM_SQL)
def random_batches(spark, sf):
    p = sources.embeddings(spark, sf)
    return workloads.random_churn(p, 200, max(1, p.count() // 100))


_ND = f"n AS (SELECT label, row_number() OVER (ORDER BY label) - 1 AS i, count(*) OVER () AS n FROM ({EMB})), w AS (SELECT CASE WHEN i < n // 2 THEN floor(i * 10 / greatest(n // 2, 1)) ELSE floor((i - n // 2) * 10 / greatest(n - n // 2, 1)) END::INT AS iter, CASE WHEN i < n // 2 THEN 'delete' ELSE 'insert' END AS op, label FROM n)"


@query("new_data_batches", f"WITH {_ND} SELECT * FROM w")
def new_data_batches(spark, sf):
    return workloads.new_data(sources.embeddings(spark, sf))


@query("new_data_end_state", f"SELECT label FROM (SELECT label, row_number() OVER (ORDER BY label) - 1 AS i, count(*) OVER () AS n FROM ({EMB})) WHERE i >= n // 2")
def new_data_end_state(spark, sf):
    """The live set after all swaps, from the log: loaded labels less the deleted, and the inserted."""
    log = written(workloads.new_data(sources.embeddings(spark, sf)), "new-data")
    first = log.filter("op = 'delete'").select("label", F.lit(-1).alias("iter"), F.lit("insert").alias("op"))
    last = F.max_by("op", F.struct("iter", "op"))
    return first.unionByName(log.select("label", "iter", "op")).groupBy("label").agg(last.alias("op")).filter("op = 'insert'").select("label")


@query("live_set_after_marks", f"WITH b AS ({RANDOM_SQL}) SELECT label FROM ({EMB}) WHERE label NOT IN (SELECT label FROM b WHERE iter = 0)")
def live_set_after_marks(spark, sf):
    p = sources.embeddings(spark, sf)
    return p.select("label").join(random_batches(spark, sf).filter("iter = 0"), "label", "left_anti")


_BATCH = f"dl AS (SELECT label AS slot, row_number() OVER (ORDER BY md5('{SEED}:0:' || label), label) AS n FROM b0), bt AS (SELECT dl.slot, i.label FROM dl JOIN (SELECT label, row_number() OVER (ORDER BY label) AS n FROM e WHERE label NOT IN (SELECT label FROM b0)) i ON dl.n = i.n WHERE dl.n <= (SELECT greatest(1, count(*) // 25) FROM e))"


@query("slot_reuse_pairs", f"WITH {E}, b0 AS (SELECT * FROM e WHERE {BASE}), {_BATCH} SELECT slot, label FROM bt")
def slot_reuse_pairs(spark, sf):
    return split(sources.embeddings(spark, sf))[2]


def split(p: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The base, the points to come, and which of them takes whose slot."""
    placed, n = workloads.numbered(p, "label")
    old, incoming = placed.filter(F.col("i") < n * 9 // 10).drop("i"), placed.filter(F.col("i") >= n * 9 // 10).drop("i")
    drawn, _ = workloads.numbered(old.select(F.col("label").alias("slot"), V.draw(F.col("label"), SEED, 0).alias("draw")), "draw", "slot", name="seq")
    pairs = workloads.slot_pairs(drawn.filter(F.col("seq") < max(1, n // 25)), incoming.select("label", F.col("label").alias("seq")))
    return old, incoming, pairs


# ---- repair on G0
def setting(spark: SparkSession, sf: str, k: int = 8):
    old, incoming, pairs = split(sources.embeddings(spark, sf))
    return old, incoming, written(exact.knn_graph(old, k), "g0"), written(pairs, "batch")


def targets_sql(strategy: str) -> str:
    kind = STRATEGIES[strategy].targets
    two = ", two AS (SELECT src AS d, dst AS node FROM g WHERE src IN (SELECT slot FROM bt) UNION SELECT g.src, h.dst FROM g JOIN g h ON g.dst = h.src WHERE g.src IN (SELECT slot FROM bt))"
    one = "SELECT src AS d, dst AS u FROM g WHERE src IN (SELECT slot FROM bt)"
    back = " AND EXISTS (SELECT 1 FROM g b WHERE b.src = {u} AND b.dst = {d})"
    if kind != "out":
        one += back.format(u="g.dst", d="g.src")
    if kind == "mutual+twohop":
        one += " UNION SELECT d, node FROM two WHERE node <> d" + back.format(u="two.node", d="two.d")
    return f"{two}, t AS (SELECT DISTINCT d, u FROM ({one}) WHERE u NOT IN (SELECT slot FROM bt))"


def pools_sql(strategy: str) -> str:
    if STRATEGIES[strategy].pool == "twohop":
        near = "SELECT u, node AS cand FROM t JOIN two USING (d)"
    else:
        near = "SELECT u, dst AS cand FROM t JOIN g ON g.src = t.u UNION SELECT u, dst FROM t JOIN g ON g.src = t.d"
    return f"{targets_sql(strategy)}, pool AS (SELECT DISTINCT u, cand FROM ({near} UNION SELECT u, d FROM t) WHERE u <> cand)"


def repaired_sql(strategy: str) -> str:
    occupants = "oc AS (SELECT b0.label AS slot, v FROM b0 WHERE label NOT IN (SELECT slot FROM bt) UNION ALL SELECT bt.slot, e.v FROM bt JOIN e USING (label))"
    c = "c AS (SELECT u, cand, list_distance(x.v, y.v) AS d, y.v FROM pool JOIN oc x ON x.slot = u JOIN oc y ON y.slot = cand)"
    return f"WITH RECURSIVE {g0_sql(8, BASE)}, {_BATCH}{pools_sql(strategy)}, {occupants}, {c}, {prune_sql(STRATEGIES[strategy].alpha, CAP)}"


G8 = f"WITH {g0_sql(8, BASE)}, {_BATCH}"


def _targets(spark, sf, strategy):
    _, _, g, b = setting(spark, sf)
    return repair.targets(exact.edges(g), b, STRATEGIES[strategy].targets)


def _pool(spark, sf, strategy):
    _, _, g, b = setting(spark, sf)
    return repair.pools(exact.edges(g), b, STRATEGIES[strategy]).groupBy("u").agg(F.array_sort(F.collect_list("cand")).alias("pool"))


def _lists(spark, sf, strategy):
    old, incoming, g, b = setting(spark, sf)
    return repair.repair_batch(g, old, b, incoming, STRATEGIES[strategy], CAP)


for _s in STRATEGIES:
    query(f"repair_targets_{_s}", f"{G8}{targets_sql(_s)} SELECT d, u FROM t")(partial(_targets, strategy=_s))
    query(f"repair_pool_{_s}", f"{G8}{pools_sql(_s)} SELECT u, list_sort(list(cand)) AS pool FROM pool GROUP BY u")(partial(_pool, strategy=_s))
    query(f"repair_lists_{_s}", f"{repaired_sql(_s)} SELECT u, nbrs FROM pruned")(partial(_lists, strategy=_s))


def _unions(parts):
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _all_sql(one: str, head, tail: str) -> str:
    return " UNION ALL ".join(f"SELECT '{s}' AS strategy, x.* FROM ({head(s)} {tail}) x" for s in STRATEGIES)


@query("repair_work_by_strategy", _all_sql("", lambda s: G8 + pools_sql(s), "SELECT count(DISTINCT u)::BIGINT AS targets, count(*)::BIGINT AS candidates, round(count(*) / count(DISTINCT u)::DOUBLE, 4) AS mean_pool FROM pool"))
def repair_work_by_strategy(spark, sf):
    _, _, g, b = setting(spark, sf)
    e = exact.edges(g)
    two = written(repair.two_hop(e, b), "two-hop")
    return _unions([repair.pools(e, b, st, two).agg(F.countDistinct("u").alias("targets"), F.count(F.lit(1)).alias("candidates"), F.round(F.count(F.lit(1)) / F.countDistinct("u"), 4).alias("mean_pool")).select(F.lit(s).alias("strategy"), "*") for s, st in STRATEGIES.items()])


@query("repair_unreachable_by_strategy", _all_sql("", repaired_sql, ", nl AS (SELECT src, dst FROM g WHERE src NOT IN (SELECT u FROM pruned) UNION ALL SELECT u, unnest(nbrs) FROM pruned) SELECT count(*)::BIGINT AS unreachable FROM b0 WHERE label NOT IN (SELECT dst FROM nl)"))
def repair_unreachable_by_strategy(spark, sf):
    old, incoming, g, b = setting(spark, sf)
    parts = []
    for s, st in STRATEGIES.items():
        new = repair.replaced(g, repair.repair_batch(g, old, b, incoming, st, CAP))
        parts.append(reach.unreachable_degree(old.select("label"), exact.edges(new)).agg(F.count(F.lit(1)).alias("unreachable")).select(F.lit(s).alias("strategy"), "*"))
    return _unions(parts)


@query("stale_in_edges_by_strategy", _all_sql("", lambda s: G8 + targets_sql(s), "SELECT count(*)::BIGINT AS stale FROM g WHERE dst IN (SELECT slot FROM bt) AND src NOT IN (SELECT slot FROM bt) AND NOT EXISTS (SELECT 1 FROM t WHERE t.d = g.dst AND t.u = g.src)"))
def stale_in_edges_by_strategy(spark, sf):
    _, _, g, b = setting(spark, sf)
    e = exact.edges(g)
    return _unions([repair.stale_in_edges(e, b, st.targets).agg(F.count(F.lit(1)).alias("stale")).select(F.lit(s).alias("strategy"), "*") for s, st in STRATEGIES.items()])


@query("twohop_pick_rate", f"{repaired_sql('native')}, picked AS (SELECT u, unnest(nbrs) AS cand FROM pruned), loc AS (SELECT u, dst AS cand FROM t JOIN g ON g.src = t.u UNION SELECT u, dst FROM t JOIN g ON g.src = t.d UNION SELECT u, d FROM t) SELECT count(*)::BIGINT AS picked, count(*) FILTER (WHERE NOT EXISTS (SELECT 1 FROM loc WHERE loc.u = picked.u AND loc.cand = picked.cand))::BIGINT AS from_two_hop FROM picked")
def twohop_pick_rate(spark, sf):
    """How often a candidate that only the two-hop set has is selected."""
    old, incoming, g, b = setting(spark, sf)
    e, t = exact.edges(g), repair.targets(exact.edges(g), b, "out")
    near = t.join(e, F.col("u") == F.col("src")).select("u", F.col("dst").alias("cand")).unionByName(t.join(e, F.col("d") == F.col("src")).select("u", F.col("dst").alias("cand"))).unionByName(t.select("u", F.col("d").alias("cand"))).distinct()
    picked = repair.repair_batch(g, old, b, incoming, STRATEGIES["native"], CAP).select("u", F.explode("nbrs").alias("cand"))
    return picked.join(near.withColumn("near", F.lit(1)), ["u", "cand"], "left").agg(F.count(F.lit(1)).alias("picked"), F.count(F.when(F.col("near").isNull(), 1)).alias("from_two_hop"))


DOUBLED = (4, 8, 16, 32)


@query("work_vs_degree", " UNION ALL ".join(f"SELECT {m} AS m, '{s}' AS strategy, x.* FROM (WITH {g0_sql(m, BASE)}, {_BATCH}{pools_sql(s)} SELECT count(*)::BIGINT AS candidates FROM pool) x" for m in DOUBLED for s in STRATEGIES))
def work_vs_degree(spark, sf):
    """Candidates to evaluate as the degree doubles: about M cubed for the conventional pool, M squared for the local one."""
    old, _, pairs = split(sources.embeddings(spark, sf))
    b, parts = written(pairs, "batch"), []
    g = written(exact.knn_graph(old, DOUBLED[-1]), "g0")
    for m in DOUBLED:
        e = written(exact.edges(g).filter(F.col("place") < m).select("src", "dst"), "edges")
        two = written(repair.two_hop(e, b), "two-hop")
        parts += [repair.pools(e, b, st, two).agg(F.count(F.lit(1)).alias("candidates")).select(F.lit(m).alias("m"), F.lit(s).alias("strategy"), "*") for s, st in STRATEGIES.items()]
    return _unions(parts)


@query("replace_update_g0", f"WITH RECURSIVE {g0_sql(8, BASE)}, {_BATCH}, oc AS (SELECT label, v FROM b0 WHERE label NOT IN (SELECT slot FROM bt)), c AS (SELECT u, cand, d, v FROM (SELECT bt.label AS u, oc.label AS cand, list_distance(e.v, oc.v) AS d, oc.v, row_number() OVER (PARTITION BY bt.label ORDER BY list_distance(e.v, oc.v), oc.label) AS r FROM bt JOIN e USING (label), oc) WHERE r <= 40), {prune_sql(1.0, CAP)} SELECT u, nbrs FROM pruned")
def replace_update_g0(spark, sf):
    """Own lists of the new points: their 40 nearest live occupants, pruned with alpha 1."""
    old, incoming, _, b = setting(spark, sf)
    occ = old.join(F.broadcast(b.select("slot")), F.col("label") == F.col("slot"), "left_anti")
    new = incoming.join(b.select("label"), "label", "left_semi").select(F.col("label").alias("query_id"), "vec")
    found = exact.knn(occ, new, 40).join(occ.select("label", F.col("vec").cast("array<double>").alias("v")), "label")
    c = found.groupBy(F.col("query_id").alias("u")).agg(F.collect_list(F.struct("dist", F.col("label").alias("id"), F.col("v").alias("vec"))).alias("c"))
    return c.select("u", V.rng_prune(F.col("c"), CAP, 1.0).alias("nbrs"))
