"""General operators around the methods, as queries with DuckDB SQL: scans, joins, aggregates, windows, sets, functions."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import shared_path, table


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int = 8) -> DataFrame:
    """Inner equi-join whose left key may be hot: left rows get a salt from all their columns, right rows one copy a salt."""
    names = left.columns
    left = left.withColumn("_s", F.pmod(F.xxhash64(*names), F.lit(salts)).cast("int"))
    right = right.withColumn("_s", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return left.join(right, [key, "_s"]).drop("_s")


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, value: str) -> DataFrame:
    """left with the `value` of the latest right row of the same key at or before it: one union, one sort a key."""
    cols = left.columns
    a = left.select(*cols, F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("_o"))
    b = right.select(*[F.col(c) if c in (by, on) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in cols], value, F.lit(0).alias("_o"))
    w = Window.partitionBy(by).orderBy(on, "_o").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_o = 1").drop("_o")


def range_join(points: DataFrame, ranges: DataFrame, at: str, lo: str, hi: str, width: int) -> DataFrame:
    """Points with the ranges [lo, hi) that hold them: equi-join on bins of `width`, then the exact test."""
    p = points.withColumn("_b", F.floor(F.col(at) / width))
    r = ranges.where(F.col(lo) < F.col(hi)).withColumn("_b", F.explode(F.sequence(F.floor(F.col(lo) / width), F.ceil(F.col(hi) / width) - 1)))
    return p.join(r, "_b").where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("_b")


Q: dict = {}
S: dict[str, str] = {}


def op(sql: str | None = None):
    def keep(f):
        Q[f"op_{f.__name__}"] = f
        if sql:
            S[f"op_{f.__name__}"] = sql
        return f

    return keep


t = table


@op("SELECT l_orderkey, l_quantity FROM lineitem WHERE year(l_shipdate) = 1997 AND l_quantity < 5")
def scan_pushdown(spark, sf):
    return t(spark, sf, "lineitem").where((F.col("l_shipdate") >= F.lit("1997-01-01").cast("timestamp_ntz")) & (F.col("l_shipdate") < F.lit("1998-01-01").cast("timestamp_ntz")) & (F.col("l_quantity") < 5)).select("l_orderkey", "l_quantity")


@op("SELECT c_custkey AS id, upper(c_name) AS big_name, c_acctbal * 2 AS twice FROM customer")
def projection(spark, sf):
    return t(spark, sf, "customer").withColumns({"twice": F.col("c_acctbal") * 2, "big_name": F.upper("c_name")}).withColumnsRenamed({"c_custkey": "id"}).select("id", "big_name", "twice")


@op("SELECT p_partkey, p_brand FROM part WHERE p_size BETWEEN 5 AND 15 AND p_brand IN ('Brand#11', 'Brand#22', 'Brand#33') AND p_type LIKE '%E%' OR regexp_matches(p_name, '^a')")
def filters(spark, sf):
    return t(spark, sf, "part").where((F.col("p_size").between(5, 15) & F.col("p_brand").isin("Brand#11", "Brand#22", "Brand#33") & F.col("p_type").like("%E%")) | F.col("p_name").rlike("^a")).select("p_partkey", "p_brand")


@op("SELECT doc_id, CASE WHEN quality = 1 AND toxic = 0 THEN 'good' WHEN toxic = 1 THEN 'toxic' ELSE 'poor' END AS kind, coalesce(nullif(quality, 0), -1) AS q FROM labels")
def conditional(spark, sf):
    return t(spark, sf, "labels").select("doc_id", F.when(F.expr("quality = 1 AND toxic = 0"), "good").when(F.col("toxic") == 1, "toxic").otherwise("poor").alias("kind"), F.coalesce(F.nullif(F.col("quality"), F.lit(0)), F.lit(-1)).alias("q"))


@op("SELECT o_orderpriority, count(*) AS n, sum(l_quantity) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_merge(spark, sf):
    o, x = t(spark, sf, "orders"), t(spark, sf, "lineitem").hint("merge")
    return o.join(x, o.o_orderkey == x.l_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))


@op("SELECT o_orderpriority, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING' GROUP BY 1")
def join_hash(spark, sf):
    o, c = t(spark, sf, "orders"), t(spark, sf, "customer").where("c_mktsegment = 'BUILDING'").hint("shuffle_hash")
    return o.join(c, o.o_custkey == c.c_custkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@op("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def join_broadcast(spark, sf):
    c, n = t(spark, sf, "customer"), t(spark, sf, "nation")
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count("*").alias("n"))  # twenty-five rows


@op("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left_outer(spark, sf):
    c, o = t(spark, sf, "customer"), t(spark, sf, "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@op("SELECT coalesce(d.doc_id, l.doc_id) AS id, d.doc_id IS NULL AS only_label, l.doc_id IS NULL AS only_doc FROM (SELECT doc_id FROM documents) d FULL JOIN (SELECT doc_id FROM labels) l ON d.doc_id = l.doc_id")
def join_full_outer(spark, sf):
    d, x = t(spark, sf, "documents").select("doc_id"), t(spark, sf, "labels").select(F.col("doc_id").alias("l"))
    return d.join(x, d.doc_id == x.l, "full").select(F.coalesce("doc_id", "l").alias("id"), F.col("doc_id").isNull().alias("only_label"), F.col("l").isNull().alias("only_doc"))


@op("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")
def join_semi(spark, sf):
    c, o = t(spark, sf, "customer"), t(spark, sf, "orders").where("o_totalprice > 300000")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi").select("c_custkey")


@op("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def join_anti(spark, sf):
    c, o = t(spark, sf, "customer"), t(spark, sf, "orders").where("o_totalprice > 300000")
    return c.join(o, c.c_custkey == o.o_custkey, "left_anti").select("c_custkey")


@op("SELECT a.n_name AS a, b.r_name AS b FROM nation a JOIN region b ON length(a.n_name) > length(b.r_name) AND a.n_nationkey > b.r_regionkey")
def join_theta(spark, sf):
    a, b = t(spark, sf, "nation"), t(spark, sf, "region")
    return a.join(F.broadcast(b), (F.length("n_name") > F.length("r_name")) & (F.col("n_nationkey") > F.col("r_regionkey"))).select(F.col("n_name").alias("a"), F.col("r_name").alias("b"))  # five rows


@op("SELECT event_id, lo FROM events JOIN (SELECT (i * 25.0)::DOUBLE AS lo, (i * 25.0 + 10)::DOUBLE AS hi FROM range(0, 40) r(i)) x ON value >= lo AND value < hi")
def join_range_bins(spark, sf):
    r = spark.range(40).select((F.col("id") * 25.0).alias("lo"), (F.col("id") * 25.0 + 10).alias("hi"))
    return range_join(t(spark, sf, "events").select("event_id", "value"), r, "value", "lo", "hi", 50).select("event_id", "lo")


@op("SELECT e.event_id, p.event_id AS latest FROM (SELECT * FROM events WHERE event_type = 'click') e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'login') p ON e.user_id = p.user_id AND e.ts >= p.ts")
def join_asof(spark, sf):
    e = t(spark, sf, "events")
    right = e.where("event_type = 'login'").groupBy("user_id", "ts").agg(F.max("event_id").alias("latest"))
    return asof_join(e.where("event_type = 'click'").select("event_id", "user_id", "ts"), right, "user_id", "ts", "latest").select("event_id", "latest")


@op("SELECT c.event_id AS click, e.event_id AS error FROM events c JOIN events e ON c.user_id = e.user_id AND c.event_type = 'click' AND e.event_type = 'error' AND e.ts > c.ts AND e.ts <= c.ts + INTERVAL 10 MINUTE")
def join_interval(spark, sf):
    e = t(spark, sf, "events")
    a, b = e.where("event_type = 'click'").select("user_id", F.col("ts").alias("t0"), F.col("event_id").alias("click")), e.where("event_type = 'error'").select(F.col("user_id").alias("u"), F.col("ts").alias("t1"), F.col("event_id").alias("error"))
    return a.join(b, (F.col("user_id") == F.col("u")) & (F.col("t1") > F.col("t0")) & (F.col("t1") <= F.expr("t0 + INTERVAL 10 MINUTES"))).select("click", "error")


@op("SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 3)")
def join_lateral_top(spark, sf):
    """The rank is taken by a window with its own order: a LIMIT inside LATERAL becomes one without, behind a shuffle that keeps no order."""
    t(spark, sf, "customer").createOrReplaceTempView("_lat_customer")
    t(spark, sf, "orders").createOrReplaceTempView("_lat_orders")
    ranked = "SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey NULLS LAST) AS r FROM _lat_orders"
    return spark.sql(f"SELECT c_custkey, o_orderkey FROM _lat_customer, LATERAL (SELECT o_orderkey FROM ({ranked}) WHERE o_custkey = c_custkey AND r <= 3)")


@op("SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def join_self(spark, sf):
    n = t(spark, sf, "nation")
    return n.alias("a").join(n.alias("b"), F.expr("a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"))


@op("SELECT r_name, p_size, count(*) AS n FROM region, (SELECT DISTINCT p_size FROM part) GROUP BY ALL")
def cross_small(spark, sf):
    return t(spark, sf, "part").select("p_size").distinct().crossJoin(F.broadcast(t(spark, sf, "region"))).groupBy("r_name", "p_size").agg(F.count("*").alias("n"))  # five rows


@op("SELECT s_nationkey, count(*) AS n, sum(l_quantity) AS q FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def join_salted(spark, sf):
    x = t(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.col("l_suppkey").alias("k"), "l_quantity")
    return salted_join(x, t(spark, sf, "supplier").select(F.col("s_suppkey").alias("k"), "s_nationkey"), "k").groupBy("s_nationkey").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))


@op("SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS q, round(avg(l_discount), 6) AS d, min(l_tax) AS lo, max(l_tax) AS hi, round(stddev(l_quantity), 4) AS s, count_if(l_quantity > 25)::BIGINT AS many FROM lineitem GROUP BY ALL")
def aggregate(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"), F.round(F.avg("l_discount"), 6).alias("d"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"), F.round(F.stddev("l_quantity"), 4).alias("s"), F.count_if(F.col("l_quantity") > 25).alias("many"))


@op("SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def aggregate_distinct(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_suppkey").alias("suppliers"), F.count_distinct("l_partkey").alias("parts"))


@op()
def aggregate_sketches(spark, sf):
    x = t(spark, sf, "lineitem")
    return x.groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("approx_parts"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 14)).alias("hll_parts"), F.percentile_approx("l_quantity", 0.5, 1000).alias("median"))


@op("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names, count(*) AS n FROM nation GROUP BY 1")
def aggregate_lists(spark, sf):
    return t(spark, sf, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"), F.count("*").alias("n"))


@op("SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY 1")
def aggregate_argmax(spark, sf):
    k = F.struct("o_totalprice", "o_orderkey")
    return t(spark, sf, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", k).alias("dearest"), F.min_by("o_orderkey", k).alias("cheapest"))


@op("SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping_id(o_orderstatus, o_orderpriority) AS level FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def rollup(spark, sf):
    return t(spark, sf, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


@op("SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
def cube(spark, sf):
    return t(spark, sf, "documents").cube("lang", "source").agg(F.count("*").alias("n"))


@op("SELECT p_brand, p_size, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_size))")
def grouping_sets(spark, sf):
    return t(spark, sf, "part").groupingSets([["p_brand"], ["p_size"]], "p_brand", "p_size").agg(F.count("*").alias("n"))


@op("SELECT o_orderpriority, count_if(o_orderstatus = 'F')::BIGINT AS f, count_if(o_orderstatus = 'O')::BIGINT AS o, count_if(o_orderstatus = 'P')::BIGINT AS p FROM orders GROUP BY 1")
def pivot(spark, sf):
    return t(spark, sf, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0).withColumnsRenamed({"F": "f", "O": "o", "P": "p"})


@op("SELECT doc_id, 'quality' AS measure, quality AS v FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def unpivot(spark, sf):
    return t(spark, sf, "labels").unpivot("doc_id", ["quality", "toxic"], "measure", "v")


@op("SELECT o_orderkey, (row_number() OVER w)::INT AS rn, (rank() OVER v)::INT AS rk, (dense_rank() OVER v)::INT AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, (ntile(4) OVER w)::INT AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderstatus)")
def window_ranks(spark, sf):
    w, v = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderstatus")
    return t(spark, sf, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.ntile(4).over(w).alias("nt"))


@op("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_offsets(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(spark, sf, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(w).alias("second"))


@op("SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY epoch(o_orderdate)::BIGINT RANGE BETWEEN 604800 PRECEDING AND CURRENT ROW), 4) AS week, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS last3 FROM orders")
def window_frames(spark, sf):
    day = Window.partitionBy("o_custkey").orderBy(F.col("o_orderdate").cast("timestamp").cast("long")).rangeBetween(-604800, 0)
    rows = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return t(spark, sf, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(day), 4).alias("week"), F.count("*").over(rows).alias("last3"))


@op("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC NULLS LAST, o_orderkey LIMIT 10 OFFSET 5")
def sort_limit(spark, sf):
    return t(spark, sf, "orders").orderBy(F.desc_nulls_last("o_totalprice"), "o_orderkey").offset(5).limit(10).select("o_orderkey", "o_totalprice")


@op("SELECT p_brand, p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 2")
def top_per_key(spark, sf):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t(spark, sf, "part").withColumn("r", F.row_number().over(w)).where("r <= 2").select("p_brand", "p_partkey")


@op("(SELECT c_custkey AS k FROM customer INTERSECT SELECT o_custkey FROM orders) EXCEPT SELECT user_id FROM events")
def set_operations(spark, sf):
    c, o, e = t(spark, sf, "customer").select(F.col("c_custkey").alias("k")), t(spark, sf, "orders").select("o_custkey"), t(spark, sf, "events").select("user_id")
    return c.intersect(o).subtract(e)


@op("SELECT n_regionkey AS k FROM nation EXCEPT ALL SELECT r_regionkey FROM region UNION ALL SELECT r_regionkey FROM region")
def set_operations_all(spark, sf):
    r, n = t(spark, sf, "region").select(F.col("r_regionkey").alias("k")), t(spark, sf, "nation").select(F.col("n_regionkey").alias("k"))
    return n.exceptAll(r).unionByName(r)


@op("SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY md5(text) HAVING count(*) > 1")
def deduplicate(spark, sf):
    return t(spark, sf, "documents").groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).where("copies > 1").drop("h")


@op("SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.9 FROM orders) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 5000)")
def subqueries(spark, sf):
    o, c = t(spark, sf, "orders"), t(spark, sf, "customer").where("c_acctbal > 5000")
    mean = o.agg((F.avg("o_totalprice") * 1.9).alias("m")).scalar()
    return o.where(F.col("o_totalprice") > mean).join(c, o.o_custkey == c.c_custkey, "left_semi").select("o_orderkey")


@op("WITH RECURSIVE r(n, f) AS (SELECT 1, 1::BIGINT UNION ALL SELECT n + 1, f * (n + 1) FROM r WHERE n < 12) SELECT * FROM r")
def recursive_cte(spark, sf):
    return spark.sql("WITH RECURSIVE r(n, f) AS (SELECT 1, CAST(1 AS BIGINT) UNION ALL SELECT n + 1, f * (n + 1) FROM r WHERE n < 12) SELECT * FROM r")


@op("SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F' AND o_totalprice > 200000")
def parameters(spark, sf):
    return spark.sql("SELECT o_orderkey FROM {orders} WHERE o_orderstatus = :s AND o_totalprice > :p", args={"s": "F", "p": 200000}, orders=t(spark, sf, "orders"))


@op("SELECT c_custkey, lower(trim(c_name)) AS a, substr(c_name, 1, 3) AS b, split_part(c_name, '#', 1) AS c, regexp_extract(c_name, '([0-9]+)', 1) AS d, regexp_replace(c_name, '0+', 'o', 'g') AS e, levenshtein(c_mktsegment, 'BUILDING')::INT AS f, translate(c_mktsegment, 'AEIOU', 'aeiou') AS g, len(regexp_extract_all(c_name, '0'))::INT AS h FROM customer")
def strings(spark, sf):
    return t(spark, sf, "customer").select("c_custkey", F.lower(F.trim("c_name")).alias("a"), F.substring("c_name", 1, 3).alias("b"), F.split_part("c_name", F.lit("#"), F.lit(1)).alias("c"), F.regexp_extract("c_name", "([0-9]+)", 1).alias("d"), F.regexp_replace("c_name", "0+", "o").alias("e"), F.levenshtein("c_mktsegment", F.lit("BUILDING")).alias("f"), F.translate("c_mktsegment", "AEIOU", "aeiou").alias("g"), F.regexp_count("c_name", F.lit("0")).alias("h"))


@op("SELECT o_orderkey, date_trunc('month', o_orderdate) AS m, year(o_orderdate)::INT AS y, weekofyear(o_orderdate)::INT AS w, date_diff('day', TIMESTAMP '1995-01-01', o_orderdate)::INT AS d FROM orders")
def dates(spark, sf):
    d = F.col("o_orderdate")
    return t(spark, sf, "orders").select("o_orderkey", F.date_trunc("month", d).cast("timestamp_ntz").alias("m"), F.year(d).alias("y"), F.weekofyear(d).alias("w"), F.datediff(d, F.lit("1995-01-01")).alias("d"))


@op("SELECT p_partkey, round(p_retailprice / 7, 3) AS a, ceil(p_retailprice)::BIGINT AS b, round(ln(p_retailprice), 6) AS c, round(sqrt(p_retailprice), 6) AS d, ((-p_size % 7) + 7) % 7 AS e, greatest(p_size, 25) AS f FROM part")
def numbers(spark, sf):
    p = F.col("p_retailprice")
    return t(spark, sf, "part").select("p_partkey", F.round(p / 7, 3).alias("a"), F.ceil(p).alias("b"), F.round(F.log(p), 6).alias("c"), F.round(F.sqrt(p), 6).alias("d"), F.pmod(-F.col("p_size"), F.lit(7)).alias("e"), F.greatest("p_size", F.lit(25)).alias("f"))


@op("SELECT doc_id, len(list_distinct(w))::INT AS n_words, array_to_string(list_sort(list_distinct(list_filter(w, lambda x: length(x) > 14))), ' ') AS long_words FROM (SELECT doc_id, string_split(text, ' ') AS w FROM documents)")
def arrays(spark, sf):
    w = F.split("text", " ")
    return t(spark, sf, "documents").select("doc_id", F.size(F.array_distinct(w)).alias("n_words"), F.array_join(F.array_sort(F.array_distinct(F.filter(w, lambda x: F.length(x) > 14))), " ").alias("long_words"))


@op("SELECT n_regionkey, count(*) AS n, sum(length(n_name))::BIGINT AS chars FROM nation GROUP BY 1")
def maps(spark, sf):
    m = t(spark, sf, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_name", F.length("n_name").alias("k")))).alias("m"))
    values = F.map_values(F.transform_values("m", lambda k, v: v.cast("long")))
    return m.select("n_regionkey", F.size("m").cast("long").alias("n"), F.aggregate(values, F.lit(0).cast("long"), lambda a, x: a + x).alias("chars"))


@op("SELECT o_orderkey, o_orderstatus AS status, o_totalprice * 2 AS price FROM orders")
def structs(spark, sf):
    s = F.struct(F.col("o_orderstatus").alias("status"), F.col("o_totalprice").alias("price"), F.lit(1).alias("gone"))
    return t(spark, sf, "orders").select("o_orderkey", s.withField("price", F.col("o_totalprice") * 2).dropFields("gone").alias("s")).select("o_orderkey", "s.*")


@op("SELECT event_id, (props->>'k')::BIGINT AS k FROM events")
def json_fields(spark, sf):
    return t(spark, sf, "events").select("event_id", F.from_json("props", "k long").getField("k").alias("k"))


@op("SELECT event_id, (props->>'k')::BIGINT AS k FROM events")
def variant_fields(spark, sf):
    return t(spark, sf, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@op("SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents")
def hashes(spark, sf):
    return t(spark, sf, "documents").select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"))


@op(r"SELECT page_id, regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '\s+', ' ', 'g') AS plain FROM pages")
def html_cleanup(spark, sf):
    return t(spark, sf, "pages").select("page_id", F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), r"\s+", " ").alias("plain"))


@op("SELECT doc_id, length(text) - length(replace(text, ' ', '')) AS spaces FROM documents")
def scalar_udf(spark, sf):

    @F.pandas_udf("long")
    def spaces(s: pd.Series) -> pd.Series:
        return s.str.count(" ")

    return t(spark, sf, "documents").select("doc_id", spaces("text").alias("spaces"))


@op("SELECT o_custkey, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY 1")
def grouped_map(spark, sf):

    def one(x: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"o_custkey": [x.o_custkey.iloc[0]], "n": [len(x)], "total": [round(float(x.o_totalprice.sum()), 2)]})

    return t(spark, sf, "orders").select("o_custkey", "o_totalprice").groupBy("o_custkey").applyInPandas(one, "o_custkey long, n long, total double")


@op("SELECT doc_id, length(text) AS n FROM documents")
def batch_map(spark, sf):
    import pyarrow as pa
    import pyarrow.compute as pc

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.cast(pc.utf8_length(b.column(1)), pa.int64())], names=["doc_id", "n"])

    return t(spark, sf, "documents").select("doc_id", "text").mapInArrow(run, "doc_id long, n long")


@op("SELECT o_orderkey FROM orders WHERE (o_orderkey * 7919) % 100 < 10")
def sample_hash(spark, sf):
    return t(spark, sf, "orders").where((F.col("o_orderkey") * 7919) % 100 < 10).select("o_orderkey")


@op("SELECT 'all' AS part, count(*) AS n, sum(o_orderkey)::BIGINT AS s FROM orders")
def repartitions(spark, sf):
    x = t(spark, sf, "orders").select("o_orderkey").repartitionByRange(8, "o_orderkey").sortWithinPartitions("o_orderkey").coalesce(4)
    return x.agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("s")).select(F.lit("all").alias("part"), "n", "s")


@op("SELECT doc_id, CASE WHEN doc_id % 5 = 0 THEN 0 ELSE quality END AS q FROM labels WHERE doc_id % 7 <> 0")
def nulls_and_nans(spark, sf):
    x = t(spark, sf, "labels").select("doc_id", F.when(F.col("doc_id") % 5 != 0, F.col("quality")).alias("q"), F.when(F.col("doc_id") % 7 == 0, F.lit(float("nan"))).otherwise(F.lit(1.0)).alias("z"))
    return x.where(~F.isnan("z")).na.fill({"q": 0}).select("doc_id", "q")


@op("SELECT o_orderstatus, o_custkey, count(*) AS n FROM orders GROUP BY 1, 2")
def bucketed_aggregate(spark, sf):
    """A table in buckets of a key: the aggregate by it needs no shuffle."""
    name = f"slicelink_bucketed_{uuid.uuid4().hex}"
    rows = t(spark, sf, "orders").select("o_custkey", "o_orderstatus")
    rows.write.bucketBy(8, "o_custkey").sortBy("o_custkey").option("path", shared_path(spark, "bucketed")).saveAsTable(name)
    return spark.table(name).groupBy("o_custkey", "o_orderstatus").agg(F.count("*").alias("n"))


@op("SELECT count(*) AS n_rows, sum(o_orderkey)::BIGINT AS keys, max(o_totalprice) AS dearest FROM orders")
def observe(spark, sf):
    """Measures taken while rows pass to a sink: no pass of its own."""
    from pyspark.sql import Observation

    seen = Observation()
    t(spark, sf, "orders").observe(seen, F.count("*").alias("n_rows"), F.sum("o_orderkey").alias("keys"), F.max("o_totalprice").alias("dearest")).write.format("noop").mode("overwrite").save()
    got = seen.get
    return spark.createDataFrame([(got["n_rows"], got["keys"], got["dearest"])], "n_rows long, keys long, dearest double")


@op("SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F'")
def sample_by(spark, sf):
    """Stratified sampling; the shares are all and none here, so that SQL can follow it."""
    return t(spark, sf, "orders").sampleBy("o_orderstatus", {"F": 1.0, "O": 0.0}, 7).select("o_orderkey")


def queries() -> dict:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    return dict(S)
