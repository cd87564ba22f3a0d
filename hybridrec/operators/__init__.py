"""Relational operators around the methods, each with the same result in SQL.

``OPS`` maps a name to (function of (spark, sf_dir), SQL text).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window, functions as F

from hybridrec.functions import M, portable_hash, portable_hash_sql
from hybridrec.sources import table

OPS: dict[str, tuple[Callable, str | None]] = {}


def op(sql: str | None):
    def keep(fn):
        OPS[f"op_{fn.__name__}"] = (fn, sql)
        return fn

    return keep


def r6(c):
    return F.round(c, 6) + F.lit(0.0)


def stars():
    return F.ceil(F.col("l_quantity") / 10).cast("int")


@op("SELECT l_orderkey, l_linenumber, l_partkey, CAST(ceil(l_quantity / 10) AS INTEGER) AS stars, CASE WHEN ceil(l_quantity / 10) = 5 THEN 1 ELSE 0 END AS liked, ROUND(l_extendedprice * (1 - l_discount), 4) + 0.0 AS net FROM lineitem")
def project_case(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", stars().alias("stars"), F.when(stars() == 5, 1).otherwise(0).alias("liked"), (F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4) + F.lit(0.0)).alias("net"))


@op("SELECT p_partkey, p_name FROM part WHERE p_brand IN ('Brand#1', 'Brand#2', 'Brand#11', 'Brand#12') AND p_size BETWEEN 5 AND 30 AND p_name LIKE '%e%' AND regexp_matches(p_name, '^[a-m]') AND NOT (p_size IS NOT DISTINCT FROM NULL)")
def filter_predicates(spark, d):
    p = table(spark, d, "part")
    return p.where(F.col("p_brand").isin("Brand#1", "Brand#2", "Brand#11", "Brand#12") & F.col("p_size").between(5, 30) & F.col("p_name").like("%e%") & F.col("p_name").rlike("^[a-m]") & ~F.col("p_size").eqNullSafe(F.lit(None))).select("p_partkey", "p_name")


_JOIN = "SELECT o_custkey, COUNT(*) AS n, ROUND(SUM(l_quantity), 6) + 0.0 AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey"


def _hinted(spark, d, hint):
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey").hint(hint)
    j = table(spark, d, "lineitem").select("l_orderkey", "l_quantity").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_custkey").agg(F.count("*").alias("n"), r6(F.sum("l_quantity")).alias("quantity"))


@op(_JOIN)
def join_inner_hash(spark, d):
    return _hinted(spark, d, "shuffle_hash")


@op(_JOIN)
def join_merge(spark, d):
    return _hinted(spark, d, "merge")


@op("SELECT n_name, CAST(t.threshold AS DOUBLE) AS threshold, COUNT(*) AS n FROM nation JOIN customer ON n_nationkey = c_nationkey JOIN (VALUES (0.0), (2500.0), (5000.0), (7500.0)) t(threshold) ON c_acctbal > t.threshold GROUP BY ALL")
def join_nested_loop(spark, d):
    t = spark.createDataFrame([(0.0,), (2500.0,), (5000.0,), (7500.0,)], "threshold double")  # four rows
    c = table(spark, d, "customer").join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("n_name", "c_acctbal")
    return c.join(F.broadcast(t), F.col("c_acctbal") > F.col("threshold")).groupBy("n_name", "threshold").agg(F.count("*").alias("n"))


@op("SELECT p_partkey, lang, quality FROM part JOIN (SELECT d.doc_id, lang, quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) x ON (CASE WHEN p_partkey % 7 = 0 THEN NULL ELSE p_partkey END) IS NOT DISTINCT FROM x.doc_id")
def join_nullsafe(spark, d):
    x = table(spark, d, "documents").select("doc_id", "lang").join(table(spark, d, "labels").select("doc_id", "quality"), "doc_id", "left")
    p = table(spark, d, "part").select("p_partkey", F.when(F.col("p_partkey") % 7 == 0, None).otherwise(F.col("p_partkey")).alias("key"))
    return p.join(x, p["key"].eqNullSafe(x["doc_id"])).select("p_partkey", "lang", "quality")


@op("SELECT r_name, n_name, COUNT(*) AS orders, ROUND(SUM(o_totalprice), 2) + 0.0 AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def join_broadcast(spark, d):
    place = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    j = table(spark, d, "orders").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(place), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.groupBy("r_name", "n_name").agg(F.count("*").alias("orders"), (F.round(F.sum("o_totalprice"), 2) + F.lit(0.0)).alias("total"))


@op("SELECT p_partkey FROM part LEFT JOIN documents ON p_partkey = doc_id WHERE doc_id IS NULL")
def join_left_missing(spark, d):
    return table(spark, d, "part").join(table(spark, d, "documents"), F.col("p_partkey") == F.col("doc_id"), "left").where("doc_id is null").select("p_partkey")


@op("SELECT COALESCE(doc_id, vec_id) AS id, doc_id IS NOT NULL AS has_document, vec_id IS NOT NULL AS has_vector FROM documents FULL JOIN embeddings ON doc_id = vec_id")
def join_full(spark, d):
    j = table(spark, d, "documents").select("doc_id").join(table(spark, d, "embeddings").select("vec_id"), F.col("doc_id") == F.col("vec_id"), "full")
    return j.select(F.coalesce("doc_id", "vec_id").alias("id"), F.col("doc_id").isNotNull().alias("has_document"), F.col("vec_id").isNotNull().alias("has_vector"))


@op("SELECT DISTINCT l_partkey FROM lineitem WHERE l_partkey IN (SELECT doc_id FROM documents)")
def join_semi(spark, d):
    return table(spark, d, "lineitem").select("l_partkey").distinct().join(table(spark, d, "documents"), F.col("l_partkey") == F.col("doc_id"), "left_semi")


@op("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority LIKE '1%')")
def join_anti(spark, d):
    return table(spark, d, "customer").join(table(spark, d, "orders").where(F.col("o_orderpriority").like("1%")), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@op("SELECT a.p_partkey AS anchor, COUNT(*) AS near FROM part a JOIN part b ON b.p_retailprice BETWEEN a.p_retailprice - 5 AND a.p_retailprice + 5 AND b.p_partkey <> a.p_partkey WHERE a.p_partkey % 50 = 0 GROUP BY 1")
def join_range(spark, d):
    """Both sides go to bins as wide as the range; a row meets its own bin and its neighbours, so the join is by key."""
    p = table(spark, d, "part").select("p_partkey", "p_retailprice")
    width = 10.0
    a = p.where("p_partkey % 50 = 0").select(F.col("p_partkey").alias("anchor"), F.col("p_retailprice").alias("x"), F.explode(F.array(*[F.floor(F.col("p_retailprice") / width) + k for k in (-1, 0, 1)])).alias("bin"))
    b = p.withColumn("bin", F.floor(F.col("p_retailprice") / width))
    return a.join(b, "bin").where((F.col("p_retailprice") >= F.col("x") - 5) & (F.col("p_retailprice") <= F.col("x") + 5) & (F.col("p_partkey") != F.col("anchor"))).groupBy("anchor").agg(F.count("*").alias("near"))


@op("SELECT v.event_id AS viewed, p.event_id AS bought FROM events v JOIN events p ON v.user_id = p.user_id AND p.ts > v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR WHERE v.event_type = 'view' AND p.event_type = 'purchase'")
def join_interval(spark, d):
    e = table(spark, d, "events")
    v = e.where("event_type = 'view'").select("user_id", F.col("event_id").alias("viewed"), F.col("ts").alias("t0"))
    p = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("bought"), F.col("ts").alias("t1"))
    return v.join(p, "user_id").where((F.col("t1") > F.col("t0")) & (F.col("t1") <= F.col("t0") + F.expr("interval 1 hour"))).select("viewed", "bought")


@op("SELECT p.event_id AS bought, (SELECT c.event_id FROM events c WHERE c.event_type = 'click' AND c.user_id = p.user_id AND (c.ts < p.ts OR (c.ts = p.ts AND c.event_id < p.event_id)) ORDER BY c.ts DESC, c.event_id DESC LIMIT 1) AS clicked FROM events p WHERE p.event_type = 'purchase'")
def join_asof(spark, d):
    """The last click before each purchase: one sort per user and a running last value, no join at all."""
    e = table(spark, d, "events").where(F.col("event_type").isin("click", "purchase"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("clicked", last).where("event_type = 'purchase'").select(F.col("event_id").alias("bought"), "clicked")


@op("WITH e AS MATERIALIZED (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings) SELECT a.vec_id AS user_id, b.vec_id AS item_id, ROUND(list_inner_product(a.v, b.v), 6) + 0.0 AS score FROM e a CROSS JOIN e b WHERE a.vec_id % 50 = 0")
def cross_scores(spark, d):
    """Every fiftieth vector against all rows, in blocks."""
    from hybridrec.evaluation.topk import all_scores

    e = table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    return all_scores(e.where("id % 50 = 0"), e).withColumn("score", r6("score"))


@op(None)
def cross_scores_whole(spark, d):
    """The same scores."""
    return cross_scores(spark, d)


_POS = "p AS (SELECT o_custkey AS user_id, l_partkey AS item_id FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2 HAVING max(ceil(l_quantity / 10)) = 5)"


def _positives(spark, d):
    from hybridrec.interactions import positives

    return positives(spark, d, "quantity")


@op(f"WITH {_POS} SELECT a.item_id AS i, b.item_id AS j, COUNT(*) AS n FROM p a JOIN p b ON a.user_id = b.user_id AND a.item_id < b.item_id GROUP BY 1, 2 HAVING COUNT(*) >= 2")
def self_join_cooc(spark, d):
    p = _positives(spark, d)
    j = p.withColumnRenamed("item_id", "i").join(p.withColumnRenamed("item_id", "j"), "user_id").where("i < j")
    return j.groupBy("i", "j").agg(F.count("*").alias("n")).where("n >= 2")


@op("SELECT o_custkey, COUNT(*) AS n, ROUND(SUM(o_totalprice), 2) + 0.0 AS total, ROUND(SUM(o_totalprice), 2) / COUNT(*) AS mean, MIN(o_totalprice) AS low, MAX(o_totalprice) AS high, ROUND(STDDEV(o_totalprice), 4) + 0.0 AS dev FROM orders GROUP BY 1")
def agg_basic(spark, d):
    x = "o_totalprice"
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"), (F.round(F.sum(x), 2) + F.lit(0.0)).alias("total"), (F.round(F.sum(x), 2) / F.count("*")).alias("mean"), F.min(x).alias("low"), F.max(x).alias("high"), (F.round(F.stddev(x), 4) + F.lit(0.0)).alias("dev"))


@op("SELECT o_custkey, COUNT(*) AS n FROM orders GROUP BY 1 HAVING COUNT(*) > 10")
def agg_having(spark, d):
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 10")


@op("SELECT l_partkey, COUNT(*) AS n, ROUND(SUM(l_quantity), 6) + 0.0 AS q FROM lineitem GROUP BY 1")
def agg_two_phase(spark, d):
    """Salted in two steps, as for a key that holds a third of all rows."""
    salted = table(spark, d, "lineitem").withColumn("salt", F.pmod(F.xxhash64("l_orderkey"), F.lit(8)))
    first = salted.groupBy("l_partkey", "salt").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))
    return first.groupBy("l_partkey").agg(F.sum("n").alias("n"), r6(F.sum("q")).alias("q"))


@op(f"WITH {_POS} SELECT user_id, string_agg(item_id, ',' ORDER BY item_id) AS items FROM p GROUP BY 1")
def agg_sort(spark, d):
    return _positives(spark, d).groupBy("user_id").agg(F.array_join(F.sort_array(F.collect_list("item_id")).cast("array<string>"), ",").alias("items"))


@op("SELECT p_brand, COUNT(DISTINCT o_custkey) AS users FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1")
def agg_distinct(spark, d):
    j = table(spark, d, "lineitem").join(table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(table(spark, d, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    return j.groupBy("p_brand").agg(F.count_distinct("o_custkey").alias("users"))


@op(None)
def agg_approx_distinct(spark, d):
    j = table(spark, d, "lineitem").join(table(spark, d, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    return j.groupBy("p_brand").agg(F.approx_count_distinct("l_suppkey").alias("suppliers"))


@op("SELECT c_mktsegment, COUNT(*) FILTER (o_totalprice > 100000) AS large, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS best, min_by(o_orderkey, (o_totalprice, o_orderkey)) AS least, bool_and(o_totalprice > 0) AS all_paid FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def agg_conditional(spark, d):
    j = table(spark, d, "orders").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    by = F.struct("o_totalprice", "o_orderkey")
    return j.groupBy("c_mktsegment").agg(F.count_if(F.col("o_totalprice") > 100000).alias("large"), F.max_by("o_orderkey", by).alias("best"), F.min_by("o_orderkey", by).alias("least"), F.bool_and(F.col("o_totalprice") > 0).alias("all_paid"))


@op("SELECT ROUND(quantile_cont(n, 0.5), 6) + 0.0 AS p50, ROUND(quantile_cont(n, 0.9), 6) + 0.0 AS p90 FROM (SELECT COUNT(*) AS n FROM lineitem GROUP BY l_partkey)")
def agg_percentile(spark, d):
    n = table(spark, d, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n"))
    return n.agg(r6(F.percentile("n", 0.5)).alias("p50"), r6(F.percentile("n", 0.9)).alias("p90"))


_CUBE = "SELECT r_name, c_mktsegment, CAST(GROUPING(r_name) * 2 + GROUPING(c_mktsegment) AS BIGINT) AS level, COUNT(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY {}"


def _placed(spark, d):
    return table(spark, d, "orders").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("r_name", "c_mktsegment", "o_totalprice")



@op(_CUBE.format("GROUPING SETS ((r_name), (c_mktsegment), ())"))
def grouping_sets(spark, d):
    return _placed(spark, d).groupingSets([[F.col("r_name")], [F.col("c_mktsegment")], []], F.col("r_name"), F.col("c_mktsegment")).agg(F.grouping_id().cast("bigint").alias("level"), F.count("*").alias("n"))


@op(_CUBE.format("CUBE (r_name, c_mktsegment)"))
def cube(spark, d):
    return _placed(spark, d).cube("r_name", "c_mktsegment").agg(F.grouping_id().cast("bigint").alias("level"), F.count("*").alias("n"))


@op(_CUBE.format("ROLLUP (r_name, c_mktsegment)"))
def rollup(spark, d):
    return _placed(spark, d).rollup("r_name", "c_mktsegment").agg(F.grouping_id().cast("bigint").alias("level"), F.count("*").alias("n"))


@op("SELECT user_id, COUNT(*) FILTER (event_type = 'click') AS click, COUNT(*) FILTER (event_type = 'purchase') AS purchase, COUNT(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1")
def pivot(spark, d):
    return table(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "purchase", "view"]).agg(F.count(F.lit(1))).na.fill(0)


@op("SELECT p_partkey, 'size' AS field, CAST(p_size AS DOUBLE) AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def unpivot(spark, d):
    p = table(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return p.unpivot("p_partkey", ["size", "price"], "field", "value")


@op("WITH c AS (SELECT p_brand, l_partkey, COUNT(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2) SELECT p_brand, l_partkey, n, row_number() OVER (PARTITION BY p_brand ORDER BY n DESC, l_partkey) AS rn, rank() OVER (PARTITION BY p_brand ORDER BY n DESC) AS rk, dense_rank() OVER (PARTITION BY p_brand ORDER BY n DESC) AS dr, ntile(4) OVER (PARTITION BY p_brand ORDER BY n DESC, l_partkey) AS quarter, ROUND(percent_rank() OVER (PARTITION BY p_brand ORDER BY n DESC), 6) + 0.0 AS pr, ROUND(cume_dist() OVER (PARTITION BY p_brand ORDER BY n DESC), 6) + 0.0 AS cd FROM c")
def window_rank(spark, d):
    c = table(spark, d, "lineitem").join(table(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand", "l_partkey").agg(F.count("*").alias("n"))
    w, u = Window.partitionBy("p_brand").orderBy(F.desc("n")), Window.partitionBy("p_brand").orderBy(F.desc("n"), "l_partkey")
    return c.select("p_brand", "l_partkey", "n", F.row_number().over(u).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(u).alias("quarter"), r6(F.percent_rank().over(w)).alias("pr"), r6(F.cume_dist().over(w)).alias("cd"))


@op("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second, last_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_offset(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    e = "event_id"
    return table(spark, d, "events").select(e, F.lag(e).over(w).alias("before"), F.lead(e).over(w).alias("after"), F.first(e).over(w).alias("first"), F.nth_value(e, 2).over(whole).alias("second"), F.last(e).over(whole).alias("last"))


@op("SELECT event_id, ROUND(AVG(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 6 PRECEDING AND CURRENT ROW), 6) + 0.0 AS moving, ROUND(SUM(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 4) + 0.0 AS tail, COUNT(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS near FROM events")
def window_frames(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    near = Window.partitionBy("user_id").orderBy("event_id").rangeBetween(-500, 0)
    return table(spark, d, "events").select("event_id", r6(F.avg("value").over(w.rowsBetween(-6, 0))).alias("moving"), (F.round(F.sum("value").over(w.rowsBetween(1, Window.unboundedFollowing)), 4) + F.lit(0.0)).alias("tail"), F.count("*").over(near).alias("near"))


@op("SELECT l_partkey, COUNT(*) AS n FROM lineitem GROUP BY 1 ORDER BY n DESC, l_partkey LIMIT 20 OFFSET 5")
def sort_limit(spark, d):
    return table(spark, d, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_partkey").offset(5).limit(20)


@op("SELECT o_custkey, o_orderkey, o_totalprice FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def topk_per_group(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey", "o_totalprice")


_A, _B = "SELECT l_partkey AS id FROM lineitem WHERE l_quantity > 40", "SELECT l_partkey AS id FROM lineitem WHERE l_discount > 0.05"


def _sides(spark, d):
    line = table(spark, d, "lineitem")
    return line.where("l_quantity > 40").select(F.col("l_partkey").alias("id")), line.where("l_discount > 0.05D").select(F.col("l_partkey").alias("id"))


for _name, _sql, _fn in (
    ("union", "UNION", lambda a, b: a.union(b).distinct()), ("union_all", "UNION ALL", lambda a, b: a.union(b)),
    ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    OPS[f"op_set_{_name}"] = ((lambda spark, d, fn=_fn: fn(*_sides(spark, d))), f"({_A}) {_sql} ({_B})")


def _sql_op(name: str, text: str, tables: tuple[str, ...], duck: str | None = None):
    """An operator that is SQL by nature: the session runs the text over temporary views."""

    def run(spark, d):
        return spark.sql(text, **{t: table(spark, d, t) for t in tables})

    OPS[f"op_{name}"] = (run, (duck or text).replace("{", "").replace("}", ""))


_sql_op("subquery_scalar", "SELECT o_custkey, n FROM (SELECT o_custkey, COUNT(*) AS n FROM {orders} GROUP BY o_custkey) AS c WHERE n > (SELECT AVG(n) FROM (SELECT COUNT(*) AS n FROM {orders} GROUP BY o_custkey) AS m)", ("orders",))
_sql_op("subquery_exists", "SELECT c_custkey FROM {customer} AS c WHERE EXISTS (SELECT 1 FROM {orders} AS o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 200000)", ("customer", "orders"))
_sql_op("subquery_in", "SELECT p_partkey FROM {part} AS p WHERE p_partkey IN (SELECT l_partkey FROM {lineitem} AS l WHERE l_quantity = 50)", ("part", "lineitem"))
_sql_op("cte", "WITH a AS (SELECT o_custkey, COUNT(*) AS n FROM {orders} AS o GROUP BY o_custkey), b AS (SELECT n, COUNT(*) AS users FROM a GROUP BY n) SELECT n, users FROM b", ("orders",))


@op("SELECT c.c_custkey, o.o_orderkey FROM customer AS c, LATERAL (SELECT o_orderkey FROM orders AS x WHERE x.o_custkey = c.c_custkey ORDER BY o_orderdate DESC, o_orderkey DESC LIMIT 1) AS o")
def subquery_lateral(spark, d):
    """Spark's own plan for an ordered LIMIT in a lateral subquery sorts before the exchange by customer and numbers rows after it, which loses the order of large tables."""
    last = table(spark, d, "orders").groupBy("o_custkey").agg(F.max(F.struct("o_orderdate", "o_orderkey")).alias("last"))
    return table(spark, d, "customer").join(last, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", F.col("last.o_orderkey").alias("o_orderkey"))


@op("SELECT p_partkey, upper(trim(p_name)) AS name, length(p_name) AS size, substring(p_name, 2, 4) AS part4, regexp_replace(p_type, '[AEIOU]', '*', 'g') AS masked, split_part(p_name, ' ', 1) AS first, concat_ws('-', p_brand, p_type) AS both, translate(p_name, 'abc', 'xyz') AS moved, CAST(levenshtein(p_name, p_type) AS INTEGER) AS distance FROM part")
def string(spark, d):
    n = F.col("p_name")
    return table(spark, d, "part").select("p_partkey", F.upper(F.trim(n)).alias("name"), F.length(n).cast("bigint").alias("size"), F.substring(n, 2, 4).alias("part4"), F.regexp_replace("p_type", "[AEIOU]", "*").alias("masked"), F.split_part(n, F.lit(" "), F.lit(1)).alias("first"), F.concat_ws("-", "p_brand", "p_type").alias("both"), F.translate(n, "abc", "xyz").alias("moved"), F.levenshtein(n, F.col("p_type")).alias("distance"))


@op("SELECT page_id, url, length(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \\t\\n\\r]+', ' ', 'g')) AS chars FROM pages")
def strip_html(spark, d):
    bare = F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), "[ \\t\\n\\r]+", " ")
    return table(spark, d, "pages").select("page_id", "url", F.length(bare).cast("bigint").alias("chars"))


@op("SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, COUNT(*) AS n, CAST(SUM(date_diff('day', CAST(o_orderdate AS DATE), DATE '2000-01-01')) AS BIGINT) AS age FROM orders GROUP BY 1, 2")
def date(spark, d):
    o = F.col("o_orderdate")
    return table(spark, d, "orders").groupBy(F.year(o).alias("y"), F.month(o).alias("m")).agg(F.count("*").alias("n"), F.sum(F.date_diff(F.lit("2000-01-01").cast("date"), o.cast("date"))).alias("age"))


@op(f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, ROUND(ln(l_extendedprice) + sqrt(l_quantity) + pow(l_discount, 2) + exp(l_tax), 6) + 0.0 AS x, CAST(floor(l_quantity) AS BIGINT) % 7 AS m, sign(l_discount - 0.05) AS s, greatest(l_discount, l_tax) AS g, {portable_hash_sql('l_orderkey', 'l_linenumber', 5)} AS h FROM lineitem")
def math(spark, d):
    c = F.col
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", r6(F.ln("l_extendedprice") + F.sqrt("l_quantity") + F.pow("l_discount", F.lit(2)) + F.exp("l_tax")).alias("x"), (F.floor("l_quantity") % 7).alias("m"), F.signum(c("l_discount") - 0.05).cast("tinyint").alias("s"), F.greatest("l_discount", "l_tax").alias("g"), portable_hash(c("l_orderkey"), c("l_linenumber"), 5).alias("h"))


@op("WITH e AS MATERIALIZED (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings) SELECT vec_id, ROUND(sqrt(list_sum(list_transform(v, lambda x: x * x))), 6) + 0.0 AS norm, len(list_filter(v, lambda x: x > 0)) AS positive, ROUND(list_max(v), 6) + 0.0 AS top, ROUND(list_sum(v[1:8]), 6) + 0.0 AS head FROM e")
def array(spark, d):
    v = F.col("embedding").cast("array<double>")
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    return table(spark, d, "embeddings").select("vec_id", r6(F.sqrt(total(F.transform(v, lambda x: x * x)))).alias("norm"), F.size(F.filter(v, lambda x: x > 0)).cast("bigint").alias("positive"), r6(F.array_max(v)).alias("top"), r6(total(F.slice(v, 1, 8))).alias("head"))


@op("SELECT user_id, event_type AS key, COUNT(*) AS value FROM events GROUP BY 1, 2 HAVING COUNT(*) > 1")
def map(spark, d):
    n = table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.explode(F.map_filter("m", lambda k, v: v > 1)))


@op("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def struct_json(spark, d):
    return table(spark, d, "events").select("event_id", F.from_json("props", "k bigint").getField("k").alias("k"))


@op(f"SELECT l_orderkey, l_partkey, COUNT(*) AS n FROM lineitem WHERE {portable_hash_sql('l_orderkey', 'l_partkey', 9)} < {M // 10} GROUP BY 1, 2")
def sample_hash(spark, d):
    return table(spark, d, "lineitem").where(portable_hash(F.col("l_orderkey"), F.col("l_partkey"), 9) < M // 10).groupBy("l_orderkey", "l_partkey").agg(F.count("*").alias("n"))


@op(f"WITH {_POS}, n AS (SELECT COUNT(*) AS n FROM part), t AS (SELECT user_id, item_id AS i, {portable_hash_sql('user_id', 'item_id', 23)} % n.n AS j FROM p, n) SELECT user_id, i, j FROM t WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.user_id = t.user_id AND p.item_id = t.j)")
def negatives(spark, d):
    n = table(spark, d, "part").agg(F.count("*").alias("n"))
    p = _positives(spark, d)
    t = p.crossJoin(F.broadcast(n)).select("user_id", F.col("item_id").alias("i"), (portable_hash(F.col("user_id"), F.col("item_id"), 23) % F.col("n")).alias("j"))
    return t.join(p.withColumnRenamed("item_id", "j"), ["user_id", "j"], "left_anti").select("user_id", "i", "j")


@op("SELECT lang, COUNT(DISTINCT text) AS texts, COUNT(*) AS docs, SUM(COALESCE(quality, -1)) AS q FROM (SELECT d.*, quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) GROUP BY 1")
def dedup_nulls(spark, d):
    docs = table(spark, d, "documents").join(table(spark, d, "labels").select("doc_id", "quality"), "doc_id", "left").na.fill({"quality": -1})
    firsts = docs.groupBy("lang", F.xxhash64("text").alias("h"), F.md5(F.col("text").cast("binary")).alias("m")).agg(F.count("*").alias("c"), F.sum("quality").alias("q"))
    return firsts.groupBy("lang").agg(F.count("*").alias("texts"), F.sum("c").alias("docs"), F.sum("q").alias("q"))


def queries() -> dict[str, Callable[..., DataFrame]]:
    return {n: fn for n, (fn, _) in OPS.items()}


def oracle_sql() -> dict[str, str]:
    return {n: sql for n, (_, sql) in OPS.items() if sql}
