"""The relational operators and functions that users of the methods need, one query each."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from mlcurate.io import table
from mlcurate.workloads.registry import query


def t(spark, sf_dir, name):
    return table(spark, sf_dir, name)


@query("SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_discount BETWEEN 0.05 AND 0.07 AND l_quantity < 24")
def op_scan_pruned(s, d):
    x = t(s, d, "lineitem")
    return x.where((F.col("l_shipdate") >= F.lit("1996-01-01").cast("timestamp")) & F.col("l_discount").between(0.05, 0.07) & (F.col("l_quantity") < 24)).select("l_orderkey", "l_linenumber", "l_extendedprice")


@query("SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band, o_orderpriority LIKE '1%' AS urgent FROM orders WHERE o_orderstatus IN ('F', 'O')")
def op_project_filter(s, d):
    p = F.col("o_totalprice")
    return t(s, d, "orders").where(F.col("o_orderstatus").isin("F", "O")).select("o_orderkey", F.when(p > 200000, "high").when(p > 100000, "mid").otherwise("low").alias("band"), F.col("o_orderpriority").like("1%").alias("urgent"))


@query("SELECT c_custkey, o_orderkey FROM customer JOIN orders ON c_custkey = o_custkey WHERE c_acctbal > 5000")
def op_join_inner(s, d):
    return t(s, d, "customer").where("c_acctbal > 5000").join(t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def op_join_left(s, d):
    return t(s, d, "customer").join(t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("SELECT coalesce(a.k, b.k) AS k, a.n AS n_customers, b.n AS n_suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_acctbal > 0 GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) b ON a.k = b.k")
def op_join_full(s, d):
    a = t(s, d, "customer").where("c_acctbal > 0").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("n_customers"))
    return a.join(t(s, d, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("n_suppliers")), "k", "full")


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def op_join_semi(s, d):
    return t(s, d, "documents").select("doc_id").join(t(s, d, "labels").where("quality = 1"), "doc_id", "left_semi")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti(s, d):
    return t(s, d, "documents").select("doc_id").join(t(s, d, "labels"), "doc_id", "left_anti")


@query("SELECT c_custkey, round(c_acctbal - (SELECT avg(c_acctbal) FROM customer), 4) AS above FROM customer")
def op_join_cross_stats(s, d):
    c = t(s, d, "customer")
    return c.crossJoin(F.broadcast(c.agg(F.avg("c_acctbal").alias("m")))).select("c_custkey", F.round(F.col("c_acctbal") - F.col("m"), 4).alias("above"))


@query("SELECT b.name, count(*) AS n FROM part JOIN (VALUES ('small', 1, 10), ('mid', 11, 30), ('large', 31, 50)) b(name, lo, hi) ON p_size BETWEEN lo AND hi GROUP BY b.name")
def op_join_range(s, d):
    """Range join with a handful of bins, which are broadcast."""
    b = s.createDataFrame([("small", 1, 10), ("mid", 11, 30), ("large", 31, 50)], "name string, lo int, hi int")
    return t(s, d, "part").join(F.broadcast(b), F.col("p_size").between(F.col("lo"), F.col("hi"))).groupBy("name").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT e.event_id, max(p.event_id) AS before_id FROM (SELECT * FROM events WHERE event_type = 'error') e LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') p ON p.user_id = e.user_id AND p.ts = (SELECT max(ts) FROM events q WHERE q.user_id = e.user_id AND q.event_type = 'click' AND q.ts <= e.ts) GROUP BY e.event_id")
def op_join_asof(s, d):
    """Each error with the user's last click before it: one ordered pass per user instead of a join of all pairs."""
    e = t(s, d, "events").where("event_type in ('click', 'error')")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("before_id", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), True).over(w)).where("event_type = 'error'").select("event_id", "before_id")


@query("SELECT r_name, count(*) AS n FROM region JOIN nation ON contains(lower(n_name), lower(left(r_name, 1))) GROUP BY r_name")
def op_join_theta(s, d):
    return F.broadcast(t(s, d, "region")).join(t(s, d, "nation"), F.lower("n_name").contains(F.lower(F.left("r_name", F.lit(1))))).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS sum_qty, round(avg(l_extendedprice), 4) AS avg_price, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, count(*) AS n, count(*) FILTER (l_tax > 0.04) AS taxed, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY ALL")
def op_agg_basic(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("sum_qty"), F.round(F.avg("l_extendedprice"), 4).alias("avg_price"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"), F.count(F.lit(1)).alias("n"), F.count_if(F.col("l_tax") > 0.04).alias("taxed"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"))


@query("SELECT o_orderpriority, count(DISTINCT o_custkey) AS n_cust, max_by(o_orderkey, o_totalprice) AS top_order FROM orders GROUP BY o_orderpriority")
def op_agg_distinct(s, d):
    return t(s, d, "orders").groupBy("o_orderpriority").agg(F.countDistinct("o_custkey").alias("n_cust"), F.max_by("o_orderkey", "o_totalprice").alias("top_order"))


@query()
def op_agg_sketches(s, d):
    """Mergeable sketches for numbers that exact aggregates would shuffle whole."""
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_extendedprice", 0.5, 1000).alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("orders"))


@query("SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY ROLLUP (c_mktsegment, c_nationkey)")
def op_rollup(s, d):
    return t(s, d, "customer").rollup("c_mktsegment", "c_nationkey").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def op_cube(s, d):
    return t(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source))")
def op_grouping_sets(s, d):
    return t(s, d, "documents").groupingSets([["lang"], ["source"]], "lang", "source").agg(F.count(F.lit(1)).alias("n")).select("lang", "source", "n")


@query("SELECT o_orderstatus, count(*) FILTER (o_orderpriority LIKE '1%') AS urgent, count(*) FILTER (o_orderpriority LIKE '5%') AS low FROM orders GROUP BY o_orderstatus")
def op_pivot(s, d):
    x = t(s, d, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).count()
    return x.select("o_orderstatus", F.coalesce("1-URGENT", F.lit(0)).alias("urgent"), F.coalesce("5-LOW", F.lit(0)).alias("low"))


@query("SELECT p_partkey, unnest(['size', 'price']) AS name, unnest([p_size::DOUBLE, p_retailprice]) AS value FROM part")
def op_unpivot(s, d):
    x = t(s, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return x.unpivot("p_partkey", ["size", "price"], "name", "value")


@query("SELECT lang, round(quantile_cont(n_chars, 0.5), 4) AS p50, round(quantile_cont(n_chars, 0.9), 4) AS p90 FROM documents GROUP BY lang")
def op_percentile(s, d):
    return t(s, d, "documents").groupBy("lang").agg(F.round(F.percentile("n_chars", 0.5), 4).alias("p50"), F.round(F.percentile("n_chars", 0.9), 4).alias("p90"))


@query("SELECT c_custkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, ntile(4) OVER w AS quart FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)")
def op_win_rank(s, d):
    w = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    return t(s, d, "customer").select("c_custkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.ntile(4).over(w).cast("long").alias("quart"))


@query("SELECT event_id, lag(event_id) OVER w AS prev, lead(event_id) OVER w AS next, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_win_lag(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(s, d, "events").select("event_id", F.lag("event_id").over(w).alias("prev"), F.lead("event_id").over(w).alias("next"), F.first("event_id").over(w).alias("first"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean3 FROM events")
def op_win_frame_rows(s, d):
    return t(s, d, "events").select("event_id", F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)), 6).alias("mean3"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS last_hour FROM events")
def op_win_frame_range(s, d):
    return t(s, d, "events").select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("last_hour"))


@query("SELECT lang, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM documents GROUP BY lang")
def op_win_ratio(s, d):
    x = t(s, d, "documents").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))
    return x.select("lang", "n", F.round(F.col("n") / F.sum("n").over(Window.partitionBy()), 6).alias("share"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def op_topk(s, d):
    return t(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("SELECT lang, doc_id, n_chars FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) <= 3")
def op_topk_group(s, d):
    w = Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")
    return t(s, d, "documents").select("lang", "doc_id", "n_chars").withColumn("r", F.row_number().over(w)).where("r <= 3").drop("r")


@query("SELECT doc_id FROM documents WHERE substr(md5(doc_id::VARCHAR), 1, 1) < '4'")
def op_sample_hash(s, d):
    """A repeatable sample by hash."""
    return t(s, d, "documents").where(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 1) < "4").select("doc_id")


@query("SELECT c_nationkey AS k FROM customer WHERE c_acctbal < 0 UNION SELECT s_nationkey FROM supplier WHERE s_acctbal < 0")
def op_union(s, d):
    return t(s, d, "customer").where("c_acctbal < 0").select(F.col("c_nationkey").alias("k")).union(t(s, d, "supplier").where("s_acctbal < 0").select("s_nationkey")).distinct()


@query("SELECT o_custkey AS k FROM orders INTERSECT SELECT c_custkey FROM customer WHERE c_acctbal > 0")
def op_intersect(s, d):
    return t(s, d, "orders").select(F.col("o_custkey").alias("k")).intersect(t(s, d, "customer").where("c_acctbal > 0").select("c_custkey"))


@query("SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders")
def op_except(s, d):
    return t(s, d, "customer").select(F.col("c_custkey").alias("k")).exceptAll(t(s, d, "orders").select("o_custkey")).distinct()


@query("SELECT p_partkey, upper(p_name) AS u, substr(p_name, 1, 4) AS pre, string_split(p_name, ' ')[1] AS first, regexp_replace(p_name, '[aeiou]', '*', 'g') AS masked, length(p_name)::BIGINT AS n, md5(p_name) AS h, lpad(p_partkey::VARCHAR, 8, '0') AS padded FROM part")
def op_string(s, d):
    n = F.col("p_name")
    return t(s, d, "part").select("p_partkey", F.upper(n).alias("u"), F.substring(n, 1, 4).alias("pre"), F.split(n, " ")[0].alias("first"), F.regexp_replace(n, "[aeiou]", "*").alias("masked"), F.length(n).cast("long").alias("n"), F.md5(n).alias("h"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("padded"))


@query("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]*([^?#]*)', 1) AS path, nullif(regexp_extract(url, '[?]([^#]*)', 1), '') AS query FROM pages")
def op_url(s, d):
    u = F.col("url")
    return t(s, d, "pages").select("page_id", F.try_parse_url(u, F.lit("HOST")).alias("host"), F.try_parse_url(u, F.lit("PATH")).alias("path"), F.try_parse_url(u, F.lit("QUERY")).alias("query"))


@query("SELECT o_orderkey, extract(year FROM o_orderdate)::BIGINT AS y, extract(quarter FROM o_orderdate)::BIGINT AS q, date_trunc('month', o_orderdate)::DATE AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS days FROM orders")
def op_date(s, d):
    x = F.col("o_orderdate")
    return t(s, d, "orders").select("o_orderkey", F.year(x).cast("long").alias("y"), F.quarter(x).cast("long").alias("q"), F.date_trunc("month", x).cast("date").alias("m"), F.datediff(x, F.lit("1992-01-01").cast("date")).cast("long").alias("days"))


@query("SELECT p_partkey, round(ln(p_retailprice), 6) AS l, round(sqrt(p_size), 6) AS r, p_partkey % 7 AS k, greatest(p_size, 25) AS g, round(exp(-p_size / 10), 6) AS e FROM part")
def op_math(s, d):
    return t(s, d, "part").select("p_partkey", F.round(F.ln("p_retailprice"), 6).alias("l"), F.round(F.sqrt("p_size"), 6).alias("r"), F.pmod("p_partkey", F.lit(7)).alias("k"), F.greatest("p_size", F.lit(25)).alias("g"), F.round(F.exp(-F.col("p_size") / 10), 6).alias("e"))


@query("SELECT vec_id, label, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm2, len(list_filter(embedding, lambda x: x > 0))::BIGINT AS positive FROM embeddings")
def op_array(s, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return t(s, d, "embeddings").select("vec_id", "label", F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x * x), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


@query("SELECT conv_id, count(*) FILTER (role = 'user') AS n_user, count(*) FILTER (role = 'assistant') AS n_assistant FROM conversations GROUP BY conv_id")
def op_map(s, d):
    """Counts by role as a map, read back by key."""
    x = t(s, d, "conversations").groupBy("conv_id", "role").agg(F.count(F.lit(1)).alias("n")).groupBy("conv_id").agg(F.map_from_entries(F.collect_list(F.struct("role", "n"))).alias("m"))
    at = lambda k: F.coalesce(F.try_element_at("m", F.lit(k)), F.lit(0))
    return x.select("conv_id", at("user").alias("n_user"), at("assistant").alias("n_assistant"))


@query("SELECT event_id, (props->>'k')::BIGINT AS k FROM events")
def op_json(s, d):
    return t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
def op_subquery_correlated(s, d):
    o = t(s, d, "orders")
    o.createOrReplaceTempView("__orders")
    return s.sql("SELECT o_orderkey FROM __orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM __orders i WHERE i.o_custkey = o.o_custkey)")


@query("SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
def op_subquery_exists(s, d):
    big = t(s, d, "orders").where("o_totalprice > 200000")
    return t(s, d, "customer").join(big, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("SELECT n_name, x.c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 1) x")
def op_subquery_lateral(s, d):
    best = t(s, d, "customer").groupBy("c_nationkey").agg(F.max_by("c_custkey", F.struct("c_acctbal", -F.col("c_custkey"))).alias("c_custkey"))
    return t(s, d, "nation").join(best, F.col("n_nationkey") == F.col("c_nationkey")).select("n_name", "c_custkey")


@query("WITH RECURSIVE w AS (SELECT 1 AS i UNION ALL SELECT i + 1 FROM w WHERE i < 10) SELECT i::INT AS i, count(*) AS n FROM w JOIN part ON p_size = i GROUP BY i")
def op_recursive(s, d):
    t(s, d, "part").createOrReplaceTempView("__part")
    return s.sql("WITH RECURSIVE w AS (SELECT 1 AS i UNION ALL SELECT i + 1 FROM w WHERE i < 10) SELECT i, count(*) AS n FROM w JOIN __part ON p_size = i GROUP BY i")
