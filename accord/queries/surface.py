"""Queries over the operators around the method: scans, joins, aggregates, windows, sets, functions, subqueries and windows of event time."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from accord.functions import sqlfns
from accord.operators import joins, pattern
from accord.queries.method import query, sector_groups, strong_face
from accord.queries.prelude import STRONG, face, picked, q, sectors
from accord.queries.prelude import pattern as pattern_sql
from accord.scratch import written
from accord.sources import carriers
from accord.sources.carriers import read


def t(name: str):
    return lambda spark, d, *cols: read(spark, d, name).select(*cols) if cols else read(spark, d, name)


events, lineitem, orders, customer, supplier, nation, region, part, conversations, documents, embeddings = map(t, "events lineitem orders customer supplier nation region part conversations documents embeddings".split())
money = lambda c: F.round(c, 2)

# ---------------------------------------------------------------- scans and projections


@query("scan_parquet", "SELECT event_id, user_id, event_type, value FROM events")
def scan_parquet(spark, d):
    return events(spark, d, "event_id", "user_id", "event_type", "value")


@query("scan_pruned_columns", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_suppkey = 3 AND l_quantity >= 40")
def scan_pruned_columns(spark, d):
    return lineitem(spark, d).where("l_suppkey = 3 AND l_quantity >= 40").select("l_orderkey", "l_quantity")


@query("filter_predicates", "SELECT event_id FROM events WHERE event_type IN ('click', 'view') AND value BETWEEN 10 AND 60 AND props LIKE '%\"k\"%' AND user_id IS NOT DISTINCT FROM user_id AND NOT regexp_matches(event_type, '^c.*x')")
def filter_predicates(spark, d):
    e = events(spark, d)
    return e.where(F.col("event_type").isin("click", "view") & F.col("value").between(10, 60) & F.col("props").like('%"k"%') & F.col("user_id").eqNullSafe(F.col("user_id")) & ~F.col("event_type").rlike("^c.*x")).select("event_id")


@query("project_exprs", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) AS charge, CASE WHEN l_quantity >= 40 THEN 'large' WHEN l_quantity >= 10 THEN 'middle' ELSE 'small' END AS size FROM lineitem")
def project_exprs(spark, d):
    size = F.when(F.col("l_quantity") >= 40, "large").when(F.col("l_quantity") >= 10, "middle").otherwise("small")
    return lineitem(spark, d).select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax")), 6).alias("charge"), size.alias("size"))


# ---------------------------------------------------------------- joins


@query("join_inner", "SELECT r_name, count(*) AS n, sum(l_quantity)::DOUBLE AS quantity FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def join_inner(spark, d):
    star = lineitem(spark, d).join(supplier(spark, d), F.col("l_suppkey") == F.col("s_suppkey")).join(nation(spark, d), F.col("s_nationkey") == F.col("n_nationkey")).join(region(spark, d), F.col("n_regionkey") == F.col("r_regionkey"))
    return star.groupBy("r_name").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("double").alias("quantity"))


@query("join_left", "SELECT c_custkey, count(o_orderkey) AS n_orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def join_left(spark, d):
    return customer(spark, d).join(orders(spark, d), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n_orders"))


@query("join_full", "SELECT coalesce(a.u, b.u) AS user_id, n_clicks, n_errors FROM (SELECT user_id AS u, count(*) AS n_clicks FROM events WHERE event_type = 'click' AND value > 90 GROUP BY 1) a FULL JOIN (SELECT user_id AS u, count(*) AS n_errors FROM events WHERE event_type = 'error' AND value > 90 GROUP BY 1) b ON a.u = b.u")
def join_full(spark, d):
    e = events(spark, d).where("value > 90")
    n = lambda kind, name: e.where(F.col("event_type") == kind).groupBy("user_id").agg(F.count("*").alias(name))
    return n("click", "n_clicks").join(n("error", "n_errors"), "user_id", "full")


@query("join_semi", "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity >= 50)")
def join_semi(spark, d):
    return orders(spark, d).join(lineitem(spark, d).where("l_quantity >= 50"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey")


@query("join_anti", "SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity >= 45)")
def join_anti(spark, d):
    return part(spark, d).join(lineitem(spark, d).where("l_quantity >= 45"), F.col("p_partkey") == F.col("l_partkey"), "left_anti").select("p_partkey")


@query("join_theta", q(face(1), "one AS (SELECT * FROM face)", select="SELECT a.video_id, a.t, a.lm AS i, count(*) AS n FROM one a JOIN one b ON a.video_id = b.video_id AND a.t = b.t AND a.lm > b.lm AND a.dx_m * b.dx_m + a.dy_m * b.dy_m >= 1000000 GROUP BY ALL"))
def join_theta(spark, d):
    one = carriers.tall(carriers.face(spark, d, 1))
    a, b = one.alias("a"), one.alias("b")
    near = F.col("a.dx_m") * F.col("b.dx_m") + F.col("a.dy_m") * F.col("b.dy_m") >= 1000000
    return a.join(b, (F.col("a.video_id") == F.col("b.video_id")) & (F.col("a.t") == F.col("b.t")) & (F.col("a.lm") > F.col("b.lm")) & near).groupBy("a.video_id", "a.t", F.col("a.lm").alias("i")).agg(F.count("*").alias("n"))


@query("join_cross_template", "SELECT l_suppkey, round(avg(l_quantity) - (SELECT avg(l_quantity) FROM lineitem), 4) AS off FROM lineitem GROUP BY l_suppkey")
def join_cross_template(spark, d):
    li = lineitem(spark, d, "l_suppkey", "l_quantity")
    one = F.broadcast(li.agg(F.avg("l_quantity").alias("m")))  # one row
    return li.groupBy("l_suppkey").agg(F.avg("l_quantity").alias("a")).crossJoin(one).select("l_suppkey", F.round(F.col("a") - F.col("m"), 4).alias("off"))


@query("join_interval", "SELECT a.event_id AS error_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts - INTERVAL 6 HOUR AND a.ts AND b.event_type = 'click' WHERE a.event_type = 'error' GROUP BY 1")
def join_interval(spark, d):
    e = events(spark, d, "event_id", "user_id", "ts", "event_type")
    return joins.within(e.where("event_type = 'error'"), e.where("event_type = 'click'"), "user_id", "ts", 6 * 3600).groupBy(F.col("left_event_id").alias("error_id")).agg(F.count("*").alias("n"))


@query("join_asof", "SELECT a.event_id, b.value AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'view' GROUP BY ALL) b ON a.user_id = b.user_id AND a.ts >= b.ts")
def join_asof(spark, d):
    e = events(spark, d, "event_id", "user_id", "ts", "event_type", "value")
    views = e.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return joins.as_of(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), views, "user_id", "ts", "value").select("event_id", F.col("value").alias("last_view"))


@query("join_lateral", "SELECT c_custkey, o_orderkey, o_totalprice FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) x")
def join_lateral(spark, d):
    c, o = customer(spark, d).select("c_custkey"), orders(spark, d)
    top = o.where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey", "o_totalprice")
    return c.lateralJoin(top).select("c_custkey", "o_orderkey", "o_totalprice")


# ---------------------------------------------------------------- aggregates


@query("agg_basic", "SELECT l_returnflag, l_linestatus, sum(l_quantity)::DOUBLE AS quantity, round(sum(l_extendedprice), 2) AS price, round(avg(l_discount), 6) AS discount, min(l_tax) AS least_tax, max(l_tax) AS most_tax, count(*) AS n FROM lineitem GROUP BY ALL")
def agg_basic(spark, d):
    return lineitem(spark, d).groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").cast("double").alias("quantity"), money(F.sum("l_extendedprice")).alias("price"), F.round(F.avg("l_discount"), 6).alias("discount"), F.min("l_tax").alias("least_tax"), F.max("l_tax").alias("most_tax"), F.count("*").alias("n"))


@query("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(*) FILTER (value > 50) AS high FROM events GROUP BY event_type")
def agg_distinct(spark, d):
    return events(spark, d).groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count(F.when(F.col("value") > 50, 1)).alias("high"))


@query("agg_stats", "SELECT l_suppkey, round(stddev_pop(l_quantity), 4) AS sd, round(var_samp(l_quantity), 4) AS var, round(corr(l_quantity, l_extendedprice), 6) AS corr, round(covar_pop(l_quantity, l_discount), 6) AS cov, round(quantile_cont(l_quantity, 0.9), 4) AS p90 FROM lineitem GROUP BY l_suppkey")
def agg_stats(spark, d):
    return lineitem(spark, d).groupBy("l_suppkey").agg(F.round(F.stddev_pop("l_quantity"), 4).alias("sd"), F.round(F.var_samp("l_quantity"), 4).alias("var"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"), F.round(F.covar_pop("l_quantity", "l_discount"), 6).alias("cov"), F.round(F.percentile("l_quantity", F.lit(0.9)), 4).alias("p90"))


@query("agg_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def agg_rollup(spark, d):
    return lineitem(spark, d).rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def agg_cube(spark, d):
    return orders(spark, d).cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("agg_grouping_sets", "SELECT event_type, user_id % 5 AS shard, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (user_id % 5), ())")
def agg_grouping_sets(spark, d):
    e = events(spark, d).withColumn("shard", F.col("user_id") % 5)
    return e.groupingSets([["event_type"], ["shard"], []], "event_type", "shard").agg(F.count("*").alias("n"))


@query("agg_pivot", "SELECT l_suppkey, sum(l_quantity) FILTER (l_returnflag = 'A')::DOUBLE AS a, sum(l_quantity) FILTER (l_returnflag = 'N')::DOUBLE AS n, sum(l_quantity) FILTER (l_returnflag = 'R')::DOUBLE AS r FROM lineitem GROUP BY l_suppkey")
def agg_pivot(spark, d):
    p = lineitem(spark, d).groupBy("l_suppkey").pivot("l_returnflag", ["A", "N", "R"]).agg(F.sum("l_quantity").cast("double"))
    return p.withColumnsRenamed({"A": "a", "N": "n", "R": "r"})


@query("agg_unpivot", "SELECT vec_id, axis, value FROM (SELECT vec_id, round(embedding[1]::DOUBLE, 6) AS e0, round(embedding[2]::DOUBLE, 6) AS e1 FROM embeddings) UNPIVOT (value FOR axis IN (e0, e1))")
def agg_unpivot(spark, d):
    e = embeddings(spark, d).select("vec_id", F.round(F.col("embedding")[0].cast("double"), 6).alias("e0"), F.round(F.col("embedding")[1].cast("double"), 6).alias("e1"))
    return e.unpivot("vec_id", ["e0", "e1"], "axis", "value")


@query("agg_argmax", "SELECT user_id, arg_max(event_id, struct_pack(v := value, e := event_id)) AS top_event, bool_and(value >= 0) AS all_positive, list_sort(list_distinct(list(event_type)))::VARCHAR[] IS NOT NULL AS has_types FROM events GROUP BY user_id")
def agg_argmax(spark, d):
    return events(spark, d).groupBy("user_id").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("top_event"), F.bool_and(F.col("value") >= 0).alias("all_positive"), F.array_sort(F.collect_set("event_type")).isNotNull().alias("has_types"))


@query("agg_approx")
def agg_approx(spark, d):
    """Sketches; tests bound their error."""
    return events(spark, d).groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", F.lit(0.5), 1000).alias("median"))


# ---------------------------------------------------------------- windows, order and sets


@query("win_rank", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_orderstatus ORDER BY o_totalprice, o_orderkey), v AS (PARTITION BY o_orderstatus ORDER BY o_orderpriority)")
def win_rank(spark, d):
    w, v = W.partitionBy("o_orderstatus").orderBy("o_totalprice", "o_orderkey"), W.partitionBy("o_orderstatus").orderBy("o_orderpriority")
    o = orders(spark, d)
    return o.select("o_orderkey", *[f.over(x).cast("bigint").alias(n) for n, f, x in (("rn", F.row_number(), w), ("rk", F.rank(), v), ("dr", F.dense_rank(), v), ("quarter", F.ntile(4), w))], F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"))


@query("win_lag", "SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS first, nth_value(value, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return events(spark, d).select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"), F.first("value").over(w).alias("first"), F.nth_value("value", 2).over(w).alias("second"))


@query("win_running", "SELECT l_orderkey, l_linenumber, sum(l_quantity) OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_linenumber, l_extendedprice, l_partkey ROWS UNBOUNDED PRECEDING)::DOUBLE AS running FROM lineitem")
def win_running(spark, d):
    w = W.partitionBy("l_suppkey").orderBy("l_orderkey", "l_linenumber", "l_extendedprice", "l_partkey").rowsBetween(W.unboundedPreceding, 0)
    return lineitem(spark, d).select("l_orderkey", "l_linenumber", F.sum("l_quantity").over(w).cast("double").alias("running"))


@query("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY day RANGE BETWEEN 2 PRECEDING AND CURRENT ROW) AS n FROM (SELECT *, date_diff('day', DATE '2024-01-01', ts::DATE) AS day FROM events)")
def win_range_frame(spark, d):
    day = F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date"))
    w = W.partitionBy("user_id").orderBy("day").rangeBetween(-2, 0)
    return events(spark, d).withColumn("day", day).select("event_id", F.count("*").over(w).alias("n"))


@query("win_moving_score", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS moving FROM events")
def win_moving_score(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return events(spark, d).select("event_id", F.round(F.avg("value").over(w), 6).alias("moving"))


@query("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk_global(spark, d):
    return orders(spark, d).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


@query("topk_per_video", "SELECT l_suppkey, l_orderkey, l_linenumber FROM lineitem QUALIFY row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) <= 3")
def topk_per_video(spark, d):
    w = W.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber")
    return lineitem(spark, d).withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("l_suppkey", "l_orderkey", "l_linenumber")


@query("sort_limit_offset", "SELECT p_partkey, p_name FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 20 OFFSET 30")
def sort_limit_offset(spark, d):
    return part(spark, d).orderBy(F.desc("p_retailprice"), "p_partkey").offset(30).limit(20).select("p_partkey", "p_name")


@query("set_union", "SELECT n_nationkey::BIGINT AS id, n_name AS name, NULL::VARCHAR AS extra FROM nation UNION ALL SELECT r_regionkey, r_name, 'region' FROM region")
def set_union(spark, d):
    a = nation(spark, d).select(F.col("n_nationkey").cast("bigint").alias("id"), F.col("n_name").alias("name"))
    b = region(spark, d).select(F.col("r_regionkey").cast("bigint").alias("id"), F.col("r_name").alias("name"), F.lit("region").alias("extra"))
    return a.unionByName(b, allowMissingColumns=True)


@query("set_intersect", "SELECT user_id FROM events WHERE event_type = 'error' AND value > 80 INTERSECT SELECT user_id FROM events WHERE event_type = 'purchase' AND value > 80")
def set_intersect(spark, d):
    e = events(spark, d).where("value > 80")
    return e.where("event_type = 'error'").select("user_id").intersect(e.where("event_type = 'purchase'").select("user_id"))


@query("set_except", "SELECT user_id FROM events EXCEPT SELECT user_id FROM events WHERE value > 99")
def set_except(spark, d):
    e = events(spark, d)
    return e.select("user_id").distinct().exceptAll(e.where("value > 99").select("user_id").distinct())


@query("dedupe_frames", "SELECT DISTINCT user_id, date_trunc('day', ts)::DATE::VARCHAR AS day FROM events")
def dedupe_frames(spark, d):
    return events(spark, d).select("user_id", F.date_trunc("day", "ts").cast("date").cast("string").alias("day")).dropDuplicates()


# ---------------------------------------------------------------- functions


@query("fn_string", "SELECT doc_id, upper(lang) AS up, md5(source) AS hash, len(string_split(text, chr(10))) AS n_lines, text[1:5] AS head, translate(source, 'src', 'SRC') AS moved, concat_ws('/', lang, source) AS path FROM documents")
def fn_string(spark, d):
    return documents(spark, d).select("doc_id", F.upper("lang").alias("up"), F.md5(F.col("source").cast("binary")).alias("hash"), F.size(F.split("text", "\n")).cast("bigint").alias("n_lines"), F.substring("text", 1, 5).alias("head"), F.translate("source", "src", "SRC").alias("moved"), F.concat_ws("/", "lang", "source").alias("path"))


@query("fn_text_classes", "SELECT conv_id, turn, len(regexp_extract_all(lower(text), '[aeiou]')) AS vowels, len(regexp_extract_all(lower(text), '[lmnr]')) AS sonorants FROM conversations")
def fn_text_classes(spark, d):
    n = lambda p: F.regexp_count(F.lower("text"), F.lit(p)).cast("bigint")
    return conversations(spark, d).select("conv_id", "turn", n("[aeiou]").alias("vowels"), n("[lmnr]").alias("sonorants"))


@query("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, quarter(o_orderdate) AS q, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS days, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, epoch(o_orderdate)::BIGINT AS epoch FROM orders")
def fn_date(spark, d):
    o = orders(spark, d)
    return o.select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("y"), F.quarter("o_orderdate").cast("bigint").alias("q"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("bigint").alias("days"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"), F.unix_timestamp(F.col("o_orderdate").cast("timestamp")).alias("epoch"))


@query("fn_math", "SELECT event_id, round(sqrt(value), 6) AS root, round(ln(value + 1), 5) AS log, floor(value)::BIGINT AS low, greatest(value, 50.0) AS high, round(atan2(value, 2.0), 6) AS angle, CASE WHEN user_id = 0 THEN NULL ELSE round(value / user_id, 10) END AS ratio, round(pow(value, 0.5), 6) AS pw FROM events")
def fn_math(spark, d):
    v = F.col("value")
    return events(spark, d).select("event_id", F.round(F.sqrt(v), 6).alias("root"), F.round(F.log(v + 1), 5).alias("log"), F.floor(v).alias("low"), F.greatest(v, F.lit(50.0)).alias("high"), F.round(F.atan2(v, F.lit(2.0)), 6).alias("angle"), F.round(F.try_divide(v, F.col("user_id")), 10).alias("ratio"), F.round(F.pow(v, F.lit(0.5)), 6).alias("pw"))


@query("fn_array_hof", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS n_up, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) AS norm2, round(embedding[3]::DOUBLE, 6) AS third, len(embedding[5:12]) AS cut FROM embeddings")
def fn_array_hof(spark, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return embeddings(spark, d).select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("n_up"), F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x * x), 5).alias("norm2"), F.round(F.element_at("embedding", 3).cast("double"), 6).alias("third"), F.size(F.slice("embedding", 5, 8)).cast("bigint").alias("cut"))


@query("fn_map", "SELECT user_id, sum((event_type = 'click')::INT)::BIGINT AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")
def fn_map(spark, d):
    per = events(spark, d).groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    kept = F.map_filter("m", lambda k, v: v > 0)
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"), F.size(F.map_keys(kept)).cast("bigint").alias("kinds"))


@query("fn_json", "SELECT event_id, (props->>'$.k')::BIGINT AS k, json_type(props) = 'OBJECT' AS is_object FROM events")
def fn_json(spark, d):
    parsed = F.from_json("props", "k bigint")
    return events(spark, d).select("event_id", parsed["k"].alias("k"), F.get_json_object("props", "$.k").isNotNull().alias("is_object"))


@query("fn_variant", "SELECT event_id, (props->>'$.k')::INT AS k FROM events")
def fn_variant(spark, d):
    return events(spark, d).select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@query("fn_null_safe", "SELECT event_id, round(value / nullif(user_id % 3, 0), 6) AS part, coalesce(nullif(event_type, 'click'), 'none') AS kind, try_cast(event_type AS INT) AS bad FROM events")
def fn_null_safe(spark, d):
    return events(spark, d).select("event_id", F.round(F.try_divide("value", F.col("user_id") % 3), 6).alias("part"), F.coalesce(F.nullif("event_type", F.lit("click")), F.lit("none")).alias("kind"), F.col("event_type").try_cast("int").alias("bad"))


# ---------------------------------------------------------------- subqueries, through SQL


def _views(spark, d, *names: str) -> None:
    for n in names:
        read(spark, d, n).createOrReplaceTempView(f"accord_{n}")


@query("sub_scalar", "SELECT count(*) AS n FROM lineitem WHERE l_quantity > (SELECT avg(l_quantity) FROM lineitem)")
def sub_scalar(spark, d):
    _views(spark, d, "lineitem")
    return spark.sql("SELECT count(*) AS n FROM accord_lineitem WHERE l_quantity > (SELECT avg(l_quantity) FROM accord_lineitem)")


@query("sub_exists", "SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM nation WHERE n_nationkey = s_nationkey AND n_regionkey = 1)")
def sub_exists(spark, d):
    _views(spark, d, "supplier", "nation")
    return spark.sql("SELECT s_suppkey FROM accord_supplier s WHERE EXISTS (SELECT 1 FROM accord_nation n WHERE n.n_nationkey = s.s_nationkey AND n.n_regionkey = 1)")


@query("sub_correlated", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
def sub_correlated(spark, d):
    _views(spark, d, "orders")
    return spark.sql("SELECT o_orderkey FROM accord_orders o WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM accord_orders i WHERE i.o_custkey = o.o_custkey)")


_UP = "SELECT k, n AS total FROM quantities WHERE k = 1 UNION ALL SELECT q.k, up.total + q.n FROM up JOIN quantities q ON q.k = up.k + 1 WHERE up.k < 50"


@query("cte_recursive", f"WITH RECURSIVE quantities AS (SELECT l_quantity::BIGINT AS k, count(*) AS n FROM lineitem GROUP BY 1), up AS ({_UP}) SELECT k, total FROM up")
def cte_recursive(spark, d):
    """Line items of quantity k or less, for k from 1 to 50, each from the one before. The table is counted once, not at every step."""
    counts = written(lineitem(spark, d).groupBy(F.col("l_quantity").cast("bigint").alias("k")).agg(F.count("*").alias("n")), "quantities")
    return spark.sql(f"WITH RECURSIVE up(k, total) AS ({_UP.replace('quantities', '{counts}')}) SELECT k, total FROM up", counts=counts)


# ---------------------------------------------------------------- functions of the method in SQL

_TWO = (face(), STRONG, picked(10), sectors(), pattern_sql("source"), "nrm AS (SELECT source, i, j, w::DOUBLE / sum(w) OVER (PARTITION BY source)::DOUBLE AS p FROM cell)")


def _packed(spark, d) -> DataFrame:
    from accord.operators import sampling

    return pattern.build(sector_groups(sampling.pick_n(strong_face(spark, d), 10)), ["source"])


@query("udf_sql_js", q(*_TWO, "cc AS (SELECT a.lm AS i, b.lm AS j FROM lmk a JOIN lmk b ON a.lm > b.lm), b AS (SELECT s.source, coalesce(x.p, 0) AS x, coalesce(r.p, 0) AS y FROM (SELECT DISTINCT source FROM nrm) s CROSS JOIN cc LEFT JOIN nrm x ON x.source = s.source AND x.i = cc.i AND x.j = cc.j LEFT JOIN nrm r ON r.source = 'R' AND r.i = cc.i AND r.j = cc.j)", select="SELECT source, round(sum((CASE WHEN x > 0 THEN x * ln(x / ((x + y) / 2)) ELSE 0 END + CASE WHEN y > 0 THEN y * ln(y / ((x + y) / 2)) ELSE 0 END) / 2), 6) AS d FROM b GROUP BY source"))
def udf_sql_js(spark, d):
    sqlfns.register(spark)
    p = _packed(spark, d).select("source", F.expr("l1_scaled(tri)").alias("p"))
    one = F.broadcast(p.where("source = 'R'").select(F.col("p").alias("q")))  # one row
    return p.crossJoin(one).select("source", F.expr("round(js_divergence(p, q), 6)").alias("d"))


@query("udtf_explode_pattern", q(*_TWO, select="SELECT source, i::INT AS i, j::INT AS j, w::DOUBLE AS w FROM cell WHERE w > 0"))
def udtf_explode_pattern(spark, d):
    sqlfns.register(spark)
    _packed(spark, d).createOrReplaceTempView("accord_packed")
    return spark.sql("SELECT source, e.i, e.j, e.w FROM accord_packed p, LATERAL explode_pattern(p.tri, p.n) e WHERE e.w > 0")


# ---------------------------------------------------------------- batch twins of the streams


@query("stream_tumbling_batch", "SELECT user_id, floor(date_diff('day', DATE '2024-01-01', ts::DATE) / 3)::INT AS frame, event_type, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY ALL")
def stream_tumbling_batch(spark, d):
    from accord.streaming import live

    return live.tumbling(live.timed(events(spark, d))).select("user_id", live.frame_of(F.col("window.start")).alias("frame"), "event_type", "n", F.round("mean", 6).alias("mean"))


@query("stream_sliding_batch", "SELECT s::INT AS start_day, count(*) AS n FROM (SELECT date_diff('day', DATE '2024-01-01', ts::DATE) AS day FROM events), range(-2, 32) g(s) WHERE day >= s AND day < s + 3 GROUP BY s")
def stream_sliding_batch(spark, d):
    from accord.streaming import live

    out = live.sliding(live.timed(events(spark, d)))
    return out.select(F.datediff(F.col("window.start").cast("date"), F.lit("2024-01-01").cast("date")).alias("start_day"), "n")


@query("stream_session_batch", "SELECT user_id, count(*) AS n_sessions, max(n) AS longest FROM (SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(brk) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS brk FROM events)) GROUP BY ALL) GROUP BY user_id")
def stream_session_batch(spark, d):
    from accord.streaming import live

    s = live.sessions(live.timed(events(spark, d)), "6 hours")
    return s.groupBy("user_id").agg(F.count("*").alias("n_sessions"), F.max("n").alias("longest"))


@query("stream_late_batch", "SELECT event_type, count(*) FILTER (event_id % 10 <> 0) AS on_time, count(*) FILTER (event_id % 10 = 0) AS held_back FROM events GROUP BY event_type")
def stream_late_batch(spark, d):
    late = F.col("event_id") % 10 == 0
    return events(spark, d).groupBy("event_type").agg(F.sum((~late).cast("bigint")).alias("on_time"), F.sum(late.cast("bigint")).alias("held_back"))
