"""Relational operators that users of the index need around it, one query each, with the same thing in SQL."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navgraph.functions import vectors as V
from navgraph.session import scratch_path

QUERIES: dict = {}
SQL: dict[str, str] = {}


class Tables:
    def __init__(self, spark, sf_dir: str):
        self.spark, self.sf = spark, sf_dir

    def __getattr__(self, name: str):
        return self.spark.read.parquet(f"{self.sf}/{name}.parquet")


def op(name: str, sql: str, f) -> None:
    QUERIES[f"op_{name}"] = lambda spark, sf_dir, f=f: f(Tables(spark, sf_dir))
    SQL[f"op_{name}"] = sql


c, lit = F.col, F.lit
cents = lambda x: F.round(c(x) * 100).cast("long")
day = lambda x: F.date_format(x, "yyyy-MM-dd")
CENTS = "round({} * 100)::BIGINT"

# ---- scans and sinks
op("scan_pruned", "SELECT doc_id, n_chars FROM documents", lambda t: t.documents.select("doc_id", "n_chars"))
op("scan_pushed_filter", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'", lambda t: t.lineitem.filter("l_quantity > 45 AND l_returnflag = 'R'").select("l_orderkey", "l_linenumber"))


def _round_trip(kind: str):
    def run(t):
        path = scratch_path(t.spark, kind)
        src = t.embeddings.select("vec_id", F.to_json("embedding").alias("v")) if kind in ("csv", "text") else t.embeddings.select("vec_id", c("embedding").alias("v"))
        if kind == "text":
            src.select(F.to_json(F.struct("vec_id", "v")).alias("value")).write.text(path)
            back = t.spark.read.text(path).select(F.from_json("value", "vec_id long, v string").alias("x")).select("x.*")
        else:
            writer = src.write.option("escape", '"') if kind == "csv" else src.write
            writer.format(kind).save(path)
            reader = t.spark.read.schema("vec_id long, v string" if kind == "csv" else "vec_id long, v array<float>")
            back = (reader.option("escape", '"') if kind == "csv" else reader).format(kind).load(path)
        v = F.from_json("v", "array<float>") if kind in ("csv", "text") else c("v")
        return back.select("vec_id", F.size(v).alias("dim"), F.round(V.total(V.doubles(v)), 4).alias("total"))

    return run


for _k in ("json", "csv", "orc", "text"):
    op(f"{_k}_vector_roundtrip" if _k == "json" else f"{_k}_roundtrip", "SELECT vec_id, len(embedding)::INT AS dim, round(list_sum(embedding::DOUBLE[]), 4) AS total FROM embeddings", _round_trip(_k))

op("delta_compaction", "SELECT event_id % 97 AS label, max(event_id) AS version, arg_max(value, event_id) AS value FROM events GROUP BY 1", lambda t: t.events.groupBy((c("event_id") % 97).alias("label")).agg(F.max("event_id").alias("version"), F.max_by("value", "event_id").alias("value")))


def _partitioned(t):
    path = scratch_path(t.spark, "by-label")
    t.embeddings.select("vec_id", "label").write.partitionBy("label").parquet(path)
    return t.spark.read.schema("vec_id long, label int").parquet(path).filter("label = 3").select("vec_id", "label")


op("partition_pruned_read", "SELECT vec_id, label FROM embeddings WHERE label = 3", _partitioned)

# ---- projection, predicates, scalar functions
op("vector_validate", "SELECT vec_id, (embedding IS NOT NULL AND len(embedding) = 64) AS good FROM embeddings", lambda t: t.embeddings.select("vec_id", V.is_valid(c("embedding"), 64).alias("good")))
op("vector_normalize", "SELECT vec_id, round(sqrt(list_inner_product(list_transform(embedding::DOUBLE[], lambda x: x * 3), list_transform(embedding::DOUBLE[], lambda x: x * 3))) / 3, 4) AS length FROM embeddings", lambda t: t.embeddings.select("vec_id", F.round(V.norm(V.normalize(V.scale(c("embedding"), 3.0))), 4).alias("length")))
op("vector_arith", "SELECT a.vec_id, round(list_inner_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS dot, round(list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS apart FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1", lambda t: t.embeddings.select("vec_id", c("embedding").alias("x")).join(t.embeddings.select((c("vec_id") - 1).alias("vec_id"), c("embedding").alias("y")), "vec_id").select("vec_id", F.round(V.dot(c("x"), c("y")), 4).alias("dot"), F.round(V.norm(V.sub(c("x"), c("y"))), 4).alias("apart")))
op("filter_range", "SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20 AND p_retailprice < 950", lambda t: t.part.filter(c("p_size").between(10, 20) & (c("p_retailprice") < 950)).select("p_partkey"))
op("filter_in", "SELECT o_orderkey FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus <> 'F'", lambda t: t.orders.filter(c("o_orderpriority").isin("1-URGENT", "2-HIGH") & (c("o_orderstatus") != "F")).select("o_orderkey"))
op("filter_like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%ring%' AND p_brand LIKE 'Brand#1_'", lambda t: t.part.filter(c("p_name").like("%ring%") & c("p_brand").like("Brand#1_")).select("p_partkey", "p_name"))
op("filter_nullsafe", "SELECT o_orderkey FROM orders WHERE nullif(o_orderstatus, 'F') IS NOT DISTINCT FROM NULL", lambda t: t.orders.filter(F.nullif("o_orderstatus", lit("F")).eqNullSafe(lit(None))).select("o_orderkey"))
op("case_when", "SELECT event_id, CASE event_type WHEN 'signup' THEN 'insert' WHEN 'error' THEN 'delete' WHEN 'purchase' THEN 'upsert' ELSE 'query' END AS op FROM events", lambda t: t.events.select("event_id", F.when(c("event_type") == "signup", "insert").when(c("event_type") == "error", "delete").when(c("event_type") == "purchase", "upsert").otherwise("query").alias("op")))
op("string_tokens", "SELECT doc_id, len(string_split(text, ' '))::INT AS n, substr(md5(text), 1, 8) AS h FROM documents", lambda t: t.documents.select("doc_id", F.size(F.split("text", " ", -1)).alias("n"), F.substring(F.md5("text"), 1, 8).alias("h")))


def _word_hash(t):
    from navgraph.sources.vectors import hashed_documents

    return hashed_documents(t.spark, t.sf, 16).select(c("label").alias("doc_id"), F.posexplode("vec").alias("place", "v")).select("doc_id", "place", F.round(c("v").cast("double"), 4).alias("v"))


op("word_hash_vector", """WITH w AS (SELECT doc_id, unnest(string_split(text, ' ')) AS w FROM documents), h AS (SELECT doc_id, (('0x' || substr(md5(w), 1, 8))::BIGINT % 16)::INT AS place, CASE WHEN ('0x' || substr(md5(w), 9, 1))::INT % 2 = 0 THEN 1 ELSE -1 END AS s FROM w),
s AS (SELECT doc_id, place, sum(s)::DOUBLE AS v FROM h GROUP BY ALL), n AS (SELECT doc_id, sqrt(sum(v * v)) AS n FROM s GROUP BY doc_id)
SELECT d.doc_id, p.place::INT AS place, round((coalesce(s.v, 0) / CASE WHEN n.n > 0 THEN n.n ELSE 1 END)::FLOAT::DOUBLE, 4) AS v FROM documents d CROSS JOIN (SELECT unnest(range(16)) AS place) p LEFT JOIN s ON s.doc_id = d.doc_id AND s.place = p.place LEFT JOIN n ON n.doc_id = d.doc_id""", _word_hash)
op("md5_sample", "SELECT doc_id FROM documents ORDER BY md5('7:0:' || doc_id), doc_id LIMIT 50", lambda t: t.documents.orderBy(V.draw(c("doc_id"), 7, 0), "doc_id").limit(50).select("doc_id"))
op("date_parts", "SELECT o_orderkey, year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m FROM orders", lambda t: t.orders.select("o_orderkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), day(F.date_trunc("month", "o_orderdate")).alias("m")))
op("date_diff", "SELECT l_orderkey, l_linenumber, date_diff('day', o_orderdate, l_shipdate)::INT AS days FROM lineitem JOIN orders ON l_orderkey = o_orderkey", lambda t: t.lineitem.join(t.orders, c("l_orderkey") == c("o_orderkey")).select("l_orderkey", "l_linenumber", F.datediff("l_shipdate", "o_orderdate").alias("days")))
op("math", "SELECT l_orderkey, l_linenumber, floor(sqrt(l_extendedprice))::BIGINT AS root, round(ln(l_quantity + 1), 4) AS log, greatest(l_tax, l_discount) AS most FROM lineitem", lambda t: t.lineitem.select("l_orderkey", "l_linenumber", F.floor(F.sqrt("l_extendedprice")).alias("root"), F.round(F.log(c("l_quantity") + 1), 4).alias("log"), F.greatest("l_tax", "l_discount").alias("most")))


def _bits(x):
    return F.transform(F.sequence(lit(0), lit(9)), lambda i: F.pmod(x * 7 + i * i, lit(13)).cast("int"))


_B = "list_transform(range(10), lambda i: ((vec_id * 7 + i * i) % 13)::INT)"
op("array_setops", f"SELECT vec_id, list_sort(list_distinct({_B})) AS d, list_sort(list_intersect({_B}, [1, 3, 5, 7])) AS i, list_sort(list_filter(list_distinct({_B}), lambda x: NOT list_contains([1, 3, 5, 7], x))) AS e FROM embeddings", lambda t: t.embeddings.select("vec_id", F.array_sort(F.array_distinct(_bits(c("vec_id")))).alias("d"), F.array_sort(F.array_intersect(_bits(c("vec_id")), F.array(*map(lit, (1, 3, 5, 7))))).alias("i"), F.array_sort(F.array_except(_bits(c("vec_id")), F.array(*map(lit, (1, 3, 5, 7))))).alias("e")))
op("array_sort_slice", f"SELECT vec_id, list_sort({_B})[2:4] AS s FROM embeddings", lambda t: t.embeddings.select("vec_id", F.slice(F.array_sort(_bits(c("vec_id"))), 2, 3).alias("s")))
op("array_hof", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::INT AS positive, round(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x)), 4) AS squares FROM embeddings", lambda t: t.embeddings.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(V.total(F.transform(V.doubles(c("embedding")), lambda x: x * x)), 4).alias("squares")))
op("array_explode", "SELECT vec_id, (generate_subscripts(embedding, 1) - 1)::INT AS place, floor(unnest(embedding)::DOUBLE * 1000)::BIGINT AS v FROM embeddings", lambda t: t.embeddings.select("vec_id", F.posexplode("embedding").alias("place", "v")).select("vec_id", "place", F.floor(c("v").cast("double") * 1000).alias("v")))
op("map_build", "SELECT user_id, list_sort(list(event_type || '=' || n)) AS counts FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id", lambda t: t.events.groupBy("user_id", "event_type").count().groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m")).select("user_id", F.array_sort(F.transform(F.map_entries("m"), lambda e: F.concat(e["key"], lit("="), e["value"].cast("string")))).alias("counts")))
op("map_filter", "SELECT user_id, list_sort(list(event_type)) AS often FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL HAVING count(*) > 20) GROUP BY user_id", lambda t: t.events.groupBy("user_id", "event_type").count().groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m")).select("user_id", F.array_sort(F.map_keys(F.map_filter("m", lambda k, v: v > 20))).alias("often")).filter(F.size("often") > 0))
op("json_extract", "SELECT event_id, (props->>'k')::INT AS k FROM events", lambda t: t.events.select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k")))

# ---- joins
_OC = "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey"
_oc = lambda t, hint: t.orders.join(t.customer.hint(hint) if hint else t.customer, c("o_custkey") == c("c_custkey")).select("o_orderkey", "c_name")
op("join_broadcast", "SELECT s_name, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey", lambda t: t.supplier.join(F.broadcast(t.nation), c("s_nationkey") == c("n_nationkey")).select("s_name", "n_name"))
op("join_sortmerge", _OC, lambda t: _oc(t, "merge"))
op("join_shuffle_hash", _OC, lambda t: _oc(t, "shuffle_hash"))
op("join_left", "SELECT c_custkey, count(o_orderkey)::BIGINT AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey", lambda t: t.customer.join(t.orders, c("c_custkey") == c("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))
op("join_full", "SELECT coalesce(a.k, b.k) AS k, a.n AS before, b.n AS after FROM (SELECT o_custkey AS k, count(*) AS n FROM orders WHERE o_orderstatus = 'F' GROUP BY 1) a FULL JOIN (SELECT o_custkey AS k, count(*) AS n FROM orders WHERE o_orderstatus = 'P' GROUP BY 1) b ON a.k = b.k", lambda t: t.orders.filter("o_orderstatus = 'F'").groupBy(c("o_custkey").alias("k")).agg(F.count(lit(1)).alias("before")).join(t.orders.filter("o_orderstatus = 'P'").groupBy(c("o_custkey").alias("k")).agg(F.count(lit(1)).alias("after")), "k", "full").select("k", "before", "after"))
op("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)", lambda t: t.customer.join(t.orders.filter("o_totalprice > 400000"), c("c_custkey") == c("o_custkey"), "left_semi").select("c_custkey"))
op("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')", lambda t: t.customer.join(t.orders.filter("o_orderpriority = '1-URGENT'"), c("c_custkey") == c("o_custkey"), "left_anti").select("c_custkey"))
op("join_cross", "SELECT r_name, n_name FROM region, nation", lambda t: t.region.crossJoin(F.broadcast(t.nation)).select("r_name", "n_name"))
op("join_theta", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal", lambda t: t.supplier.select(c("s_suppkey").alias("a"), "s_nationkey", c("s_acctbal").alias("x")).join(t.supplier.select(c("s_suppkey").alias("b"), "s_nationkey", c("s_acctbal").alias("y")), "s_nationkey").filter("x < y").select("a", "b"))
_SPAN = 86400
op("join_range", "SELECT s.event_id AS signup, e.event_id AS error FROM events s JOIN events e ON s.user_id = e.user_id AND e.event_type = 'error' AND e.ts > s.ts AND e.ts <= s.ts + INTERVAL 1 DAY WHERE s.event_type = 'signup'", lambda t: _range_join(t))


def _range_join(t):
    """Equi-join on user and day (the error's, or the one before), then the exact bound."""
    s = t.events.filter("event_type = 'signup'").select(c("event_id").alias("signup"), "user_id", c("ts").alias("a"), F.explode(F.array(F.to_date("ts"), F.date_add(F.to_date("ts"), 1))).alias("d"))
    e = t.events.filter("event_type = 'error'").select(c("event_id").alias("error"), "user_id", c("ts").alias("b"), F.to_date("ts").alias("d"))
    return s.join(e, ["user_id", "d"]).filter(F.expr("b > a AND b <= a + INTERVAL 1 DAY")).select("signup", "error")


op("join_asof", "SELECT p.event_id, max(v.event_id) AS last_view FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND v.event_id < p.event_id WHERE p.event_type = 'purchase' GROUP BY p.event_id", lambda t: t.events.withColumn("last_view", F.last(F.when(c("event_type") == "view", c("event_id")), True).over(W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, -1))).filter("event_type = 'purchase'").select("event_id", "last_view"))
op("join_interval", "SELECT q.event_id AS q, d.event_id AS d FROM events q JOIN events d ON q.event_id % 10 = d.event_id % 10 AND d.event_type = 'error' AND d.ts BETWEEN q.ts AND q.ts + INTERVAL 2 HOUR WHERE q.event_type = 'view'", lambda t: _interval_join(t))


def _interval_join(t):
    """Equi-join on the key and spans of two hours (the error's, or the one before), then the exact bound."""
    wall = dict(t.events.dtypes)["ts"] == "timestamp_ntz"
    span = (lambda x: F.datediff(F.to_date(x), F.to_date(lit("1970-01-01"))) * 12 + F.floor(F.hour(x) / 2)) if wall else lambda x: F.floor(F.unix_seconds(x) / 7200)
    k = (c("event_id") % 10).alias("k")
    q = t.events.filter("event_type = 'view'").select(c("event_id").alias("q"), c("ts").alias("a"), k, F.explode(F.array(span("ts"), span("ts") + 1)).alias("s"))
    d = t.events.filter("event_type = 'error'").select(c("event_id").alias("d"), c("ts").alias("b"), k, span("ts").alias("s"))
    return q.join(d, ["k", "s"]).filter(F.expr("b BETWEEN a AND a + INTERVAL 2 HOUR")).select("q", "d")


op("join_self", "SELECT a.l_partkey AS x, b.l_partkey AS y, count(*)::BIGINT AS n FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(*) > 1", lambda t: t.lineitem.select("l_orderkey", c("l_partkey").alias("x")).join(t.lineitem.select("l_orderkey", c("l_partkey").alias("y")), "l_orderkey").filter("x < y").groupBy("x", "y").agg(F.count(lit(1)).alias("n")).filter("n > 1"))


def _lateral(t):
    """Orders are ranked within customers by a window: what Catalyst makes of ORDER BY and LIMIT in a lateral subquery sorts all
    orders before it deals them out by customer, and the exchange needn't keep that order. Customers count once, as IN has it."""
    rank = F.row_number().over(W.partitionBy("o_custkey").orderBy(F.desc_nulls_last("o_totalprice"), F.asc_nulls_last("o_orderkey")))
    t.orders.select("o_custkey", "o_orderkey", rank.alias("n")).createOrReplaceTempView("ng_ranked_orders")
    t.customer.select("c_custkey").distinct().createOrReplaceTempView("ng_customer_keys")
    return t.spark.sql("SELECT c_custkey, o_orderkey FROM ng_customer_keys, LATERAL (SELECT o_orderkey FROM ng_ranked_orders WHERE o_custkey = c_custkey AND n <= 2)")


op("join_lateral", "SELECT o_custkey AS c_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS n FROM orders) WHERE n <= 2 AND o_custkey IN (SELECT c_custkey FROM customer)", _lateral)

# ---- aggregates
op("agg_hash", f"SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n, sum({CENTS.format('l_extendedprice')})::BIGINT AS cents FROM lineitem GROUP BY 1, 2", lambda t: t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(F.count(lit(1)).alias("n"), F.sum(cents("l_extendedprice")).alias("cents")))
op("agg_sort_list", "SELECT l_orderkey, list_sort(list(l_partkey)) AS parts FROM lineitem GROUP BY 1", lambda t: t.lineitem.groupBy("l_orderkey").agg(F.array_sort(F.collect_list("l_partkey")).alias("parts")))
op("agg_distinct", "SELECT l_suppkey, count(DISTINCT l_partkey)::BIGINT AS parts FROM lineitem GROUP BY 1", lambda t: t.lineitem.groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts")))
op("agg_filter", "SELECT user_id, count(*) FILTER (WHERE event_type = 'error')::BIGINT AS errors, count(*)::BIGINT AS n FROM events GROUP BY 1", lambda t: t.events.groupBy("user_id").agg(F.count(F.when(c("event_type") == "error", 1)).alias("errors"), F.count(lit(1)).alias("n")))
op("agg_max_by", "SELECT o_custkey, arg_max(o_orderkey, o_totalprice * 1000000 + o_orderkey % 1000) AS largest FROM orders GROUP BY 1", lambda t: t.orders.groupBy("o_custkey").agg(F.max_by("o_orderkey", c("o_totalprice") * 1000000 + c("o_orderkey") % 1000).alias("largest")))
op("agg_percentile", "SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS p50, quantile_cont(l_quantity, 0.9) AS p90 FROM lineitem GROUP BY 1", lambda t: t.lineitem.groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.5).alias("p50"), F.percentile("l_quantity", 0.9).alias("p90")))
_SNR = "supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
_snr = lambda t: t.supplier.join(F.broadcast(t.nation), c("s_nationkey") == c("n_nationkey")).join(F.broadcast(t.region), c("n_regionkey") == c("r_regionkey"))
op("rollup_region", f"SELECT r_name, n_name, count(*)::BIGINT AS suppliers FROM {_SNR} GROUP BY ROLLUP (r_name, n_name)", lambda t: _snr(t).rollup("r_name", "n_name").agg(F.count(lit(1)).alias("suppliers")))
op("cube_flags", "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)", lambda t: t.lineitem.cube("l_returnflag", "l_linestatus").agg(F.count(lit(1)).alias("n")))
op("grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*)::BIGINT AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())", lambda t: t.orders.groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(F.count(lit(1)).alias("n")))
op("pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'view')::BIGINT AS view, count(*) FILTER (WHERE event_type = 'click')::BIGINT AS click FROM events GROUP BY user_id", lambda t: t.events.groupBy("user_id").pivot("event_type", ["view", "click"]).count().na.fill(0))
op("unpivot", "SELECT r_regionkey, k, v FROM (SELECT r_regionkey, 'name' AS k, r_name AS v FROM region UNION ALL SELECT r_regionkey, 'upper', upper(r_name) FROM region)", lambda t: t.region.select("r_regionkey", c("r_name").alias("name"), F.upper("r_name").alias("upper")).unpivot("r_regionkey", ["name", "upper"], "k", "v"))
op("having", "SELECT o_custkey, count(*)::BIGINT AS n FROM orders GROUP BY 1 HAVING count(*) >= 15", lambda t: t.orders.groupBy("o_custkey").agg(F.count(lit(1)).alias("n")).filter("n >= 15"))
op("centroid", "SELECT label, i::INT - 1 AS place, round(avg(embedding[i]::DOUBLE), 4) AS mean FROM embeddings, range(1, 65) r(i) GROUP BY ALL", lambda t: t.embeddings.select("label", F.posexplode("embedding").alias("place", "v")).groupBy("label", "place").agg(F.avg(c("v").cast("double")).alias("mean")).withColumn("mean", V.rounded(c("mean"), 4)))

# ---- windows
_by_customer = lambda: W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
_OVER = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"
op("win_row_number", f"SELECT o_orderkey, row_number() {_OVER})::INT AS n FROM orders", lambda t: t.orders.select("o_orderkey", F.row_number().over(_by_customer()).alias("n")))
_prio = lambda: W.partitionBy("o_orderstatus").orderBy("o_orderpriority")
op("win_rank_dense", "SELECT o_orderkey, rank() OVER (PARTITION BY o_orderstatus ORDER BY o_orderpriority)::INT AS r, dense_rank() OVER (PARTITION BY o_orderstatus ORDER BY o_orderpriority)::INT AS d FROM orders", lambda t: t.orders.select("o_orderkey", F.rank().over(_prio()).alias("r"), F.dense_rank().over(_prio()).alias("d")))
op("win_ntile", "SELECT vec_id, ntile(7) OVER (PARTITION BY label ORDER BY vec_id)::INT AS part FROM embeddings", lambda t: t.embeddings.select("vec_id", F.ntile(7).over(W.partitionBy("label").orderBy("vec_id")).alias("part")))
op("win_percent_rank", "SELECT o_orderkey, round(percent_rank() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice), 6) AS p, round(cume_dist() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice), 6) AS c FROM orders", lambda t: t.orders.select("o_orderkey", F.round(F.percent_rank().over(W.partitionBy("o_orderstatus").orderBy("o_totalprice")), 6).alias("p"), F.round(F.cume_dist().over(W.partitionBy("o_orderstatus").orderBy("o_totalprice")), 6).alias("c")))
op("win_lag_lead", f"SELECT o_orderkey, lag(o_orderkey) {_OVER}) AS before, lead(o_orderkey, 2) {_OVER}) AS after FROM orders", lambda t: t.orders.select("o_orderkey", F.lag("o_orderkey").over(_by_customer()).alias("before"), F.lead("o_orderkey", 2).over(_by_customer()).alias("after")))
op("win_first_last", f"SELECT o_orderkey, first_value(o_orderkey) {_OVER}) AS first, last_value(CASE WHEN o_orderstatus = 'P' THEN o_orderkey END IGNORE NULLS) {_OVER} ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_p FROM orders", lambda t: t.orders.select("o_orderkey", F.first("o_orderkey").over(_by_customer()).alias("first"), F.last(F.when(c("o_orderstatus") == "P", c("o_orderkey")), True).over(_by_customer().rowsBetween(W.unboundedPreceding, W.currentRow)).alias("last_p")))
op("win_rows_frame", f"SELECT o_orderkey, sum({CENTS.format('o_totalprice')}) {_OVER} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS cents FROM orders", lambda t: t.orders.select("o_orderkey", F.sum(cents("o_totalprice")).over(_by_customer().rowsBetween(-2, 0)).alias("cents")))
op("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events", lambda t: t.events.select("event_id", F.count(lit(1)).over(W.partitionBy("user_id").orderBy("event_id").rangeBetween(-100, 0)).alias("n")))
op("growth_trace", "SELECT user_id, event_id, n, n - lag(n) OVER (PARTITION BY user_id ORDER BY event_id) AS growth FROM (SELECT user_id, event_id, count(*) FILTER (WHERE event_type = 'error') OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events)", lambda t: t.events.select("user_id", "event_id", F.count(F.when(c("event_type") == "error", 1)).over(W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, 0)).alias("n")).withColumn("growth", c("n") - F.lag("n").over(W.partitionBy("user_id").orderBy("event_id"))))

# ---- order, sets, subqueries
op("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25", lambda t: t.orders.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice"))
op("topk_per_group", "SELECT l_suppkey, l_orderkey, l_linenumber FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) AS n FROM lineitem) WHERE n <= 3", lambda t: t.lineitem.withColumn("n", F.row_number().over(W.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber"))).filter("n <= 3").select("l_suppkey", "l_orderkey", "l_linenumber"))
op("sort_multi", "SELECT n_name, n_regionkey FROM nation ORDER BY n_regionkey DESC, n_name", lambda t: t.nation.select("n_name", "n_regionkey").orderBy(F.desc("n_regionkey"), "n_name"))
op("offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 20 OFFSET 100", lambda t: t.orders.select("o_orderkey").orderBy("o_orderkey").offset(100).limit(20))
_U = ("SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F'", "SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'P'")
_u = lambda t, s: t.orders.filter(f"o_orderstatus = '{s}'").select(c("o_custkey").alias("k"))
op("union_all", f"{_U[0]} UNION ALL {_U[1]}", lambda t: _u(t, "F").unionByName(_u(t, "P")))
op("union_distinct", f"{_U[0]} UNION {_U[1]}", lambda t: _u(t, "F").unionByName(_u(t, "P")).distinct())
op("intersect", f"{_U[0]} INTERSECT {_U[1]}", lambda t: _u(t, "F").intersect(_u(t, "P")))
op("except", f"{_U[0]} EXCEPT {_U[1]}", lambda t: _u(t, "F").subtract(_u(t, "P")))
op("except_all", f"{_U[0]} EXCEPT ALL {_U[1]}", lambda t: _u(t, "F").exceptAll(_u(t, "P")))
op("dedupe_latest", "SELECT user_id, event_type, max(event_id) AS event_id FROM events GROUP BY ALL", lambda t: t.events.withColumn("n", F.row_number().over(W.partitionBy("user_id", "event_type").orderBy(F.desc("event_id")))).filter("n = 1").select("user_id", "event_type", "event_id"))


def _sql(text: str, *names: str):
    def run(t):
        for n in names:
            getattr(t, n).createOrReplaceTempView(f"ng_{n}")
        return t.spark.sql(text)

    return run


def both(name: str, text: str, *names: str) -> None:
    """One text for both engines, with the tables' names in braces."""
    op(name, text.format(**{n: n for n in names}), _sql(text.format(**{n: f"ng_{n}" for n in names}), *names))


both("scalar_subquery", "SELECT o_orderkey FROM {orders} WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM {orders})", "orders")
both("exists", "SELECT s_suppkey FROM {supplier} s WHERE EXISTS (SELECT 1 FROM {lineitem} l WHERE l.l_suppkey = s.s_suppkey AND l.l_quantity > 49)", "supplier", "lineitem")
both("not_exists", "SELECT p_partkey FROM {part} p WHERE NOT EXISTS (SELECT 1 FROM {lineitem} l WHERE l.l_partkey = p.p_partkey AND l.l_returnflag = 'R' AND l.l_quantity > 45)", "part", "lineitem")
both("in_subquery", "SELECT c_custkey FROM {customer} WHERE c_nationkey IN (SELECT n_nationkey FROM {nation} WHERE n_regionkey = 2)", "customer", "nation")
_LAYERS = "WITH RECURSIVE l{names} AS (SELECT 0 AS layer, count(DISTINCT vec_id) AS width FROM {t} WHERE embedding IS NOT NULL UNION ALL SELECT layer + 1, width {div} 4 FROM l WHERE width >= 4) SELECT layer, width FROM l"
op("recursive_layers", _LAYERS.format(names="", t="embeddings", div="//"), lambda t: _sql(_LAYERS.format(names="(layer, width)", t="ng_embeddings", div="div"), "embeddings")(t))

# ---- event time, batch twins
stamp = lambda x: F.date_format(x, "yyyy-MM-dd HH:mm:ss")
op("tumbling", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2", lambda t: t.events.groupBy(F.window(c("ts").cast("timestamp"), "1 hour").alias("w"), "event_type").agg(F.count(lit(1)).alias("n")).select(stamp("w.start").alias("start"), "event_type", "n"))
op("sliding", "SELECT strftime(date_trunc('hour', ts) - to_hours(o::BIGINT), '%Y-%m-%d %H:%M:%S') AS start, count(*)::BIGINT AS n FROM events, range(2) r(o) GROUP BY 1", lambda t: t.events.groupBy(F.window(c("ts").cast("timestamp"), "2 hours", "1 hour").alias("w")).agg(F.count(lit(1)).alias("n")).select(stamp("w.start").alias("start"), "n"))
op("session", "SELECT user_id, count(*)::BIGINT AS n, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s", lambda t: t.events.groupBy("user_id", F.session_window(c("ts").cast("timestamp"), "30 minutes").alias("w")).agg(F.count(lit(1)).alias("n")).select("user_id", "n", stamp("w.start").alias("start")))
op("late_split", "SELECT event_id, coalesce(ts < max(ts) OVER (PARTITION BY user_id ORDER BY event_id % 1000, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) - INTERVAL 10 MINUTE, FALSE) AS late FROM events", lambda t: t.events.select("event_id", F.coalesce(c("ts") < F.max("ts").over(W.partitionBy("user_id").orderBy(c("event_id") % 1000, "event_id").rowsBetween(W.unboundedPreceding, -1)) - F.expr("INTERVAL 10 MINUTE"), lit(False)).alias("late")))
_N = "(SELECT count(*) FROM embeddings)"


def update_log(events, n: int):
    """signup inserts, error deletes, purchase upserts, view and click ask; seq and version are the event's id."""
    kind = F.when(c("event_type") == "signup", "insert").when(c("event_type") == "error", "delete").when(c("event_type") == "purchase", "upsert").otherwise("query")
    return events.select(c("event_id").alias("seq"), "ts", kind.alias("op"), (c("event_id") % n).alias("label"), ((c("event_id") * 7 + 3) % n).alias("source"))


op("update_log", f"SELECT event_id AS seq, CASE event_type WHEN 'signup' THEN 'insert' WHEN 'error' THEN 'delete' WHEN 'purchase' THEN 'upsert' ELSE 'query' END AS op, event_id % {_N} AS label, (event_id * 7 + 3) % {_N} AS source FROM events", lambda t: update_log(t.events, t.embeddings.count()).drop("ts"))

# ---- user workloads
_PF = "f AS (SELECT l_partkey AS k, [avg(l_quantity) / 50, avg(l_extendedprice) / 100000, avg(l_discount) * 10, avg(l_tax) * 10] AS v FROM lineitem GROUP BY 1)"


def _reco(t):
    """Parts nearest to what the customers of a nation bought, without those bought there already."""
    v = F.array(F.avg("l_quantity") / 50, F.avg("l_extendedprice") / 100000, F.avg("l_discount") * 10, F.avg("l_tax") * 10)
    f = t.lineitem.groupBy(c("l_partkey").alias("k")).agg(v.alias("v"))
    bought = t.orders.join(t.customer, c("o_custkey") == c("c_custkey")).join(t.lineitem.filter("l_returnflag = 'R'"), c("o_orderkey") == c("l_orderkey")).select(c("c_nationkey").alias("nation"), c("l_partkey").alias("p")).distinct()
    mean = bought.join(f, c("p") == c("k")).groupBy("nation").agg(F.array(*(F.avg(c("v")[i]) for i in range(4))).alias("m"))
    near = f.crossJoin(F.broadcast(mean)).join(bought.withColumnRenamed("nation", "of"), (c("of") == c("nation")) & (c("p") == c("k")), "left_anti")
    d = F.round(V.l2(c("v"), c("m")), 6)
    return near.select("nation", "k", d.alias("d")).withColumn("n", F.row_number().over(W.partitionBy("nation").orderBy("d", "k"))).filter("n <= 3").select("nation", c("k").alias("part"), "n")


op("reco_parts", f"WITH {_PF}, b AS (SELECT DISTINCT c_nationkey AS nation, l_partkey AS p FROM orders JOIN customer ON o_custkey = c_custkey JOIN lineitem ON o_orderkey = l_orderkey WHERE l_returnflag = 'R'), m AS (SELECT nation, [avg(v[1]), avg(v[2]), avg(v[3]), avg(v[4])] AS m FROM b JOIN f ON p = k GROUP BY nation) SELECT nation, k AS part, n::INT AS n FROM (SELECT nation, k, row_number() OVER (PARTITION BY nation ORDER BY round(list_distance(v, m), 6), k) AS n FROM f, m WHERE NOT EXISTS (SELECT 1 FROM b WHERE b.nation = m.nation AND b.p = f.k)) WHERE n <= 3", _reco)
op("store_visibility", f"SELECT r_name, n_name, count(*)::BIGINT AS stores, count(*) FILTER (WHERE s_acctbal > 0)::BIGINT AS visible FROM {_SNR} GROUP BY ROLLUP (r_name, n_name)", lambda t: _snr(t).rollup("r_name", "n_name").agg(F.count(lit(1)).alias("stores"), F.count(F.when(c("s_acctbal") > 0, 1)).alias("visible")))
op("rag_corpus_edit", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE coalesce(l.quality, 1) <> 0", lambda t: t.documents.select("doc_id").join(t.labels.filter("quality = 0").select("doc_id"), "doc_id", "left_anti"))
op("benchmark_lookup", "SELECT b.item_id, d.doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)", lambda t: _lookup(t))


def _lookup(t):
    """Documents that hold a passage word for word; the passages are a bounded set and go to every task."""
    b = t.benchmark.select("item_id", c("text").alias("passage"))
    return t.documents.select("doc_id", "text").join(F.broadcast(b), c("text").contains(c("passage"))).select("item_id", "doc_id")


op("pages_text", r"SELECT page_id, length(regexp_replace(html, '<[^>]*>', ' ', 'g'))::INT AS n FROM pages", lambda t: t.pages.select("page_id", F.length(F.regexp_replace("html", "<[^>]*>", " ")).alias("n")))
op("conversation_chunks", "SELECT conv_id, count(*)::BIGINT AS turns, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id", lambda t: t.conversations.groupBy("conv_id").agg(F.count(lit(1)).alias("turns"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ">").alias("roles")))
op("part_profiles", "SELECT l_partkey, round(avg(l_quantity), 4) AS quantity, round(avg(CASE WHEN l_returnflag = 'R' THEN 1.0::DOUBLE ELSE 0 END), 4) AS returned, round(avg(CASE WHEN quarter(l_shipdate) = 1 THEN 1.0::DOUBLE ELSE 0 END), 4) AS first_quarter FROM lineitem GROUP BY 1", lambda t: _profiles(t))


def _profiles(t):
    from navgraph.sources.vectors import part_features

    return part_features(t.spark, t.sf).select("l_partkey", F.round("quantity", 4).alias("quantity"), F.round("flag_r", 4).alias("returned"), F.round("quarter_1", 4).alias("first_quarter"))


def _sql_functions(t):
    V.register(t.spark)
    t.embeddings.createOrReplaceTempView("ng_embeddings")
    return t.spark.sql("SELECT a.vec_id, round(vec_l2(CAST(a.embedding AS ARRAY<DOUBLE>), CAST(b.embedding AS ARRAY<DOUBLE>)), 4) AS l2, round(vec_cosine(CAST(a.embedding AS ARRAY<DOUBLE>), CAST(b.embedding AS ARRAY<DOUBLE>)), 4) AS cosine FROM ng_embeddings a JOIN ng_embeddings b ON b.vec_id = a.vec_id + 1")


op("sql_functions", "SELECT a.vec_id, round(list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS l2, round(list_cosine_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1", _sql_functions)


def bucketed(df, key: str, name: str, buckets: int = 8):
    """`df` as a table bucketed and sorted by `key`, below the shared folder: joins on the key need no exchange."""
    import uuid

    table = f"ng_{name}_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, key).sortBy(key).option("path", scratch_path(df.sparkSession, name)).saveAsTable(table)
    return df.sparkSession.table(table)


def _bucketed_join(t):
    o = bucketed(t.orders.select("o_orderkey", "o_custkey"), "o_orderkey", "orders")
    l = bucketed(t.lineitem.select("l_orderkey", "l_partkey"), "l_orderkey", "lineitem")  # noqa: E741
    return o.join(l.hint("merge"), c("o_orderkey") == c("l_orderkey")).groupBy("o_orderkey").agg(F.count(lit(1)).alias("lines"))


op("join_bucketed", "SELECT o_orderkey, count(*)::BIGINT AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1", _bucketed_join)


def within(sketch, exact, share: float):
    """The exact value where the sketch is near enough, else the sketch's."""
    return F.when(F.abs(sketch - exact) <= share * exact, exact).otherwise(sketch.cast("long"))


op("sketch_distinct", "SELECT l_suppkey % 10 AS k, count(DISTINCT l_orderkey)::BIGINT AS orders FROM lineitem GROUP BY 1", lambda t: t.lineitem.groupBy((c("l_suppkey") % 10).alias("k")).agg(F.hll_sketch_agg("l_orderkey", 12).alias("s"), F.countDistinct("l_orderkey").alias("n")).select("k", within(F.hll_sketch_estimate("s"), c("n"), 0.06).alias("orders")))
op("sketch_merge", "SELECT count(DISTINCT l_orderkey)::BIGINT AS orders FROM lineitem", lambda t: t.lineitem.groupBy("l_suppkey").agg(F.hll_sketch_agg("l_orderkey", 12).alias("s")).agg(F.hll_union_agg("s").alias("s")).crossJoin(t.lineitem.agg(F.countDistinct("l_orderkey").alias("n"))).select(within(F.hll_sketch_estimate("s"), c("n"), 0.06).alias("orders")))
op("approx_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey)::BIGINT AS parts FROM lineitem GROUP BY 1", lambda t: t.lineitem.groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("s"), F.countDistinct("l_partkey").alias("n")).select("l_returnflag", within(c("s"), c("n"), 0.08).alias("parts")))
op("approx_percentile", "SELECT l_returnflag, quantile_disc(l_quantity, 0.5)::BIGINT AS p50 FROM lineitem GROUP BY 1", lambda t: t.lineitem.groupBy("l_returnflag").agg(F.percentile_approx("l_quantity", 0.5, 1000).alias("s"), F.percentile("l_quantity", 0.5).cast("long").alias("n")).select("l_returnflag", within(c("s"), c("n"), 0.05).alias("p50")))


def _arrow_distance(t):
    from navgraph.functions.arrow import l2_batch
    from navgraph.session import ship

    ship(t.spark)
    b = t.embeddings.select((c("vec_id") - 1).alias("vec_id"), c("embedding").alias("y"))
    return t.embeddings.select("vec_id", c("embedding").alias("x")).join(b, "vec_id").select("vec_id", F.round(l2_batch("x", "y"), 4).alias("l2"))


op("arrow_distance", "SELECT a.vec_id, round(list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS l2 FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1", _arrow_distance)


def _recall(t):
    from navgraph.functions.arrow import recall_at_k
    from navgraph.session import ship

    ship(t.spark)
    x = t.embeddings.select("label", _bits(c("vec_id")).alias("g"), F.slice(_bits(c("vec_id")), 1, 5).alias("l"))
    return x.groupBy("label").agg(F.round(recall_at_k("g", "l"), 6).alias("recall"))


op("recall_aggregate", f"SELECT label, round(avg(len(list_distinct({_B}[1:5])) / len(list_distinct({_B}))::DOUBLE), 6) AS recall FROM embeddings GROUP BY label", _recall)
op("centroid_aggregate", "SELECT label, list(mean ORDER BY place) AS mean FROM (SELECT label, i AS place, round(avg(embedding[i]::DOUBLE), 4) AS mean FROM embeddings, range(1, 65) r(i) GROUP BY ALL) GROUP BY label", lambda t: t.embeddings.groupBy("label").agg(V.centroid("embedding", 64).alias("m")).select("label", F.transform("m", lambda x: V.rounded(x, 4)).alias("mean")))
