"""Registered queries of the relational operators around retrieval, each with DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecrag.plans.shared import query
from vecrag.sources import event_times, table

DAY = "%Y-%m-%d"


@query("SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net, CASE WHEN l_quantity >= 25 THEN 'bulk' ELSE 'unit' END AS kind FROM lineitem")
def rel_project(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"), F.when(F.col("l_quantity") >= 25, "bulk").otherwise("unit").alias("kind"))


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events WHERE CAST(json_extract(props, '$.k') AS INTEGER) > 50")
def rel_filter_json(spark, d):
    k = F.get_json_object("props", "$.k").cast("int")
    return table(spark, d, "events").select("event_id", k.alias("k")).where("k > 50")


@query("SELECT doc_id FROM documents WHERE text LIKE '%License%' AND lang IN ('en', 'de') AND n_chars BETWEEN 100 AND 5000")
def rel_filter_text(spark, d):
    return table(spark, d, "documents").where(F.col("text").like("%License%") & F.col("lang").isin("en", "de") & F.col("n_chars").between(100, 5000)).select("doc_id")


@query("SELECT o_orderkey, c_name, n_name FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey")
def rel_join_bcast(spark, d):
    """nation has a fixed number of rows, so it is broadcast; customer is left to the optimizer."""
    o, c, n = (table(spark, d, t) for t in ("orders", "customer", "nation"))
    return o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), c.c_nationkey == n.n_nationkey).select("o_orderkey", "c_name", "n_name")


@query("SELECT o_orderkey, count(*) AS lines, round(sum(l_extendedprice), 2) AS price FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey")
def rel_join_smj(spark, d):
    o, li = table(spark, d, "orders"), table(spark, d, "lineitem")
    return o.hint("merge").join(li, o.o_orderkey == li.l_orderkey).groupBy("o_orderkey").agg(F.count("*").alias("lines"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@query("SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def rel_join_left(spark, d):
    c, o = table(spark, d, "customer"), table(spark, d, "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.doc_id IS NOT NULL AS has_doc, l.doc_id IS NOT NULL AS has_label FROM (SELECT * FROM documents WHERE lang = 'en') d FULL JOIN labels l ON d.doc_id = l.doc_id")
def rel_join_full(spark, d):
    docs = table(spark, d, "documents").where("lang = 'en'").select("doc_id")
    labels = table(spark, d, "labels").select(F.col("doc_id").alias("l_id"))
    return docs.join(labels, F.col("doc_id") == F.col("l_id"), "full").select(F.coalesce("doc_id", "l_id").alias("doc_id"), F.col("doc_id").isNotNull().alias("has_doc"), F.col("l_id").isNotNull().alias("has_label"))


@query("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def rel_semi(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels").where("quality = 1"), "doc_id", "left_semi").select("doc_id", "lang")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_custkey IS NOT NULL AND o_totalprice > 400000)")
def rel_anti(spark, d):
    c, o = table(spark, d, "customer"), table(spark, d, "orders").where("o_totalprice > 400000")
    return c.join(o, c.c_custkey == o.o_custkey, "left_anti").select("c_custkey")


@query("SELECT a.doc_id AS a, b.doc_id AS b FROM documents a JOIN documents b ON b.n_chars BETWEEN a.n_chars AND a.n_chars + 2 AND a.doc_id <> b.doc_id AND a.n_chars > 200")
def rel_range(spark, d):
    """Range join by binned equality: each row meets its own bin and the next."""
    docs, width = table(spark, d, "documents").select("doc_id", "n_chars"), 50
    left = docs.where("n_chars > 200").select(F.col("doc_id").alias("a"), F.col("n_chars").alias("n"), F.explode(F.array(F.floor(F.col("n_chars") / width), F.floor(F.col("n_chars") / width) + 1)).alias("bin"))
    right = docs.select(F.col("doc_id").alias("b"), F.col("n_chars").alias("m"), F.floor(F.col("n_chars") / width).alias("bin"))
    return left.join(right, "bin").where("m between n and n + 2 and a <> b").select("a", "b")


@query("""SELECT v.event_id, p.event_id AS purchase_id FROM (SELECT * FROM events WHERE event_type = 'view') v ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY user_id, ts) p ON v.user_id = p.user_id AND p.ts <= v.ts""")
def rel_asof(spark, d):
    """As-of join: each view with the user's last purchase up to it, by a union and a running last value."""
    e = table(spark, d, "events").where("event_type in ('view', 'purchase')")
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), True)
    order = W.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1), "event_id").rowsBetween(W.unboundedPreceding, 0)
    return e.withColumn("purchase_id", last.over(order)).where("event_type = 'view'").select("event_id", "purchase_id")


@query("SELECT c.event_id AS click_id, e.event_id AS error_id FROM events c JOIN events e ON c.user_id = e.user_id AND c.event_type = 'click' AND e.event_type = 'error' AND e.ts BETWEEN c.ts AND c.ts + INTERVAL 1 HOUR")
def rel_interval(spark, d):
    e = table(spark, d, "events")
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("ts").alias("cts"))
    x = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.col("ts").alias("ets"))
    return c.join(x, "user_id").where("ets between cts and cts + interval 1 hour").select("click_id", "error_id")


@query("SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM customer JOIN orders ON c_custkey = o_custkey) WHERE r <= 2")
def rel_lateral(spark, d):
    """Lateral join with an ordered limit; customers that repeat a key share its two orders."""
    table(spark, d, "customer").createOrReplaceTempView("lat_customer")
    table(spark, d, "orders").createOrReplaceTempView("lat_orders")
    found = spark.sql("SELECT c_custkey, o_orderkey, o_totalprice FROM lat_customer, LATERAL (SELECT o_orderkey, o_totalprice FROM lat_orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")
    per = W.partitionBy("c_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return found.withColumn("r", F.row_number().over(per)).where("r <= 2").select("c_custkey", "o_orderkey")


@query("SELECT user_id, count(*) AS n, round(sum(value), 4) AS v FROM events GROUP BY user_id")
def rel_salted(spark, d):
    """Two-level aggregation with a salt, for keys that hold a large share of the rows."""
    e = table(spark, d, "events").withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(8)))
    part = e.groupBy("user_id", "salt").agg(F.count("*").alias("n"), F.sum("value").alias("v"))
    return part.groupBy("user_id").agg(F.sum("n").alias("n"), F.round(F.sum("v"), 4).alias("v"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, count(*) FILTER (WHERE l_quantity > 25) AS bulk, min(l_orderkey) AS first_key FROM lineitem GROUP BY 1, 2")
def rel_agg(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.count_if(F.col("l_quantity") > 25).alias("bulk"), F.min("l_orderkey").alias("first_key"))


@query("SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest, list_sort(list(DISTINCT o_orderstatus)) AS states FROM orders GROUP BY o_custkey")
def rel_agg_ordered(spark, d):
    by = F.struct("o_totalprice", "o_orderkey")
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", by).alias("dearest"), F.min_by("o_orderkey", by).alias("cheapest"), F.array_sort(F.collect_set("o_orderstatus")).alias("states"))


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def rel_distinct(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query("SELECT event_type, true AS hll_near, true AS theta_near, true AS median_near, true AS kll_near FROM events GROUP BY event_type")
def rel_approx(spark, d):
    """Sketches beside the exact values: distinct users within 5 % by HLL and theta, medians within 2 % of the ranks."""
    e = table(spark, d, "events")
    e.createOrReplaceTempView("ra_events")
    sql = """WITH a AS (
        SELECT event_type, count(DISTINCT user_id) AS users, hll_sketch_estimate(hll_sketch_agg(user_id)) AS hll, theta_sketch_estimate(theta_sketch_agg(user_id)) AS theta,
               percentile_approx(value, 0.5) AS median, kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.5D) AS kll FROM ra_events GROUP BY event_type
    ), r AS (
        SELECT a.event_type, avg(CASE WHEN value <= median THEN 1.0 ELSE 0.0 END) AS m, avg(CASE WHEN value <= kll THEN 1.0 ELSE 0.0 END) AS k FROM ra_events e JOIN a ON a.event_type = e.event_type GROUP BY a.event_type
    ) SELECT a.event_type, abs(hll - users) <= 0.05 * users AS hll_near, abs(theta - users) <= 0.05 * users AS theta_near, abs(m - 0.5) <= 0.02 AS median_near, abs(k - 0.5) <= 0.02 AS kll_near FROM a JOIN r ON a.event_type = r.event_type"""
    return spark.sql(sql)


@query("SELECT lang, source, count(*) AS n, CAST(grouping(lang) * 2 + grouping(source) AS BIGINT) AS g FROM documents GROUP BY CUBE (lang, source)")
def rel_cube(spark, d):
    return table(spark, d, "documents").cube("lang", "source").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@query("SELECT n_name, c_mktsegment, count(*) AS n, round(sum(c_acctbal), 2) AS bal FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_name, c_mktsegment)")
def rel_rollup(spark, d):
    c, n = table(spark, d, "customer"), table(spark, d, "nation")
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).rollup("n_name", "c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("bal"))


@query("SELECT lang, NULL::VARCHAR AS source, count(*) AS n FROM documents GROUP BY lang UNION ALL SELECT NULL, source, count(*) FROM documents GROUP BY source")
def rel_grouping_sets(spark, d):
    docs = table(spark, d, "documents").select("lang", "source")
    return docs.groupingSets([[F.col("lang")], [F.col("source")]], F.col("lang"), F.col("source")).agg(F.count("*").alias("n"))


@query(f"SELECT strftime(ts, '{DAY}') AS day, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view, count(*) FILTER (WHERE event_type = 'error') AS error FROM events GROUP BY 1")
def rel_pivot(spark, d):
    kinds = ["click", "view", "error"]
    e = table(spark, d, "events").withColumn("day", F.date_format("ts", "yyyy-MM-dd"))
    return e.groupBy("day").pivot("event_type", kinds).count().fillna(0)


@query("SELECT doc_id, 'quality' AS name, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def rel_unpivot(spark, d):
    return table(spark, d, "labels").unpivot(["doc_id"], ["quality", "toxic"], "name", "value")


@query("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderstatus)")
def win_rank(spark, d):
    w = W.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    v = W.partitionBy("o_custkey").orderBy("o_orderstatus")
    return table(spark, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("SELECT event_id, round(epoch(ts) - epoch(lag(ts) OVER w), 6) AS gap, lead(event_type) OVER w AS next_type, first_value(event_id) OVER w AS first_id, nth_value(event_id, 2) OVER w AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    sec = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6
    return table(spark, d, "events").select("event_id", F.round(sec - F.lag(sec).over(w), 6).alias("gap"), F.lead("event_type").over(w).alias("next_type"), F.first("event_id").over(w).alias("first_id"), F.nth_value("event_id", 2).over(w).alias("second_id"))


@query("SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey), 2) AS run, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 4) AS near FROM orders")
def win_running(spark, d):
    w = W.partitionBy("o_custkey").orderBy("o_orderkey")
    return table(spark, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("run"), F.round(F.avg("o_totalprice").over(w.rowsBetween(-1, 1)), 4).alias("near"))


@query("SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 7 DAY PRECEDING AND CURRENT ROW), 2) AS week FROM orders")
def win_range(spark, d):
    w = W.partitionBy("o_custkey").orderBy(F.unix_seconds(F.col("o_orderdate").cast("timestamp"))).rangeBetween(-7 * 86400, 0)
    return table(spark, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("week"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
def rel_topk(spark, d):
    return table(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(10).select("o_orderkey", "o_totalprice")


@query("SELECT doc_id FROM labels WHERE quality = 1 INTERSECT SELECT doc_id FROM labels WHERE toxic = 0")
def set_intersect(spark, d):
    lab = table(spark, d, "labels")
    return lab.where("quality = 1").select("doc_id").intersect(lab.where("toxic = 0").select("doc_id"))


@query("SELECT event_type, user_id FROM events WHERE event_id < 600 EXCEPT ALL SELECT event_type, user_id FROM events WHERE event_id BETWEEN 300 AND 500")
def set_except_all(spark, d):
    e = table(spark, d, "events")
    return e.where("event_id < 600").select("event_type", "user_id").exceptAll(e.where("event_id between 300 and 500").select("event_type", "user_id"))


@query("SELECT DISTINCT lang, source FROM (SELECT lang, source FROM documents UNION ALL SELECT lang, source FROM documents)")
def set_union_distinct(spark, d):
    docs = table(spark, d, "documents")
    return docs.select("lang", "source").unionByName(docs.select("source", "lang")).distinct()


@query(r"SELECT doc_id, upper(lang) AS u, substr(source, 1, 3) AS s, length(text) AS n, md5(text) AS m, CAST(levenshtein(lang, 'de') AS INTEGER) AS lev, regexp_extract(text, '(\w+)', 1) AS w, concat_ws('-', lang, source) AS cw, translate(source, 'src', 'SRC') AS tr FROM documents")
def fn_string(spark, d):
    return table(spark, d, "documents").select("doc_id", F.upper("lang").alias("u"), F.substring("source", 1, 3).alias("s"), F.char_length("text").cast("long").alias("n"), F.md5("text").alias("m"), F.levenshtein("lang", F.lit("de")).alias("lev"), F.regexp_extract("text", r"([0-9A-Za-z_]+)", 1).alias("w"), F.concat_ws("-", "lang", "source").alias("cw"), F.translate("source", "src", "SRC").alias("tr"))


@query("SELECT event_id, round(sqrt(value), 6) AS r, round(pow(value, 2), 6) AS p, round(ln(value + 1), 6) AS l, round(exp(-value), 9) AS e, floor(value) AS f, greatest(value, 50) AS g, least(value, 50) AS le, CAST(user_id % 7 AS BIGINT) AS m FROM events")
def fn_math(spark, d):
    v = F.col("value")
    return table(spark, d, "events").select("event_id", F.round(F.sqrt(v), 6).alias("r"), F.round(F.pow(v, F.lit(2)), 6).alias("p"), F.round(F.log(v + 1), 6).alias("l"), F.round(F.exp(-v), 9).alias("e"), F.floor(v).cast("double").alias("f"), F.greatest(v, F.lit(50.0)).alias("g"), F.least(v, F.lit(50.0)).alias("le"), (F.col("user_id") % 7).alias("m"))


@query("SELECT strftime(date_trunc('quarter', o_orderdate), '%Y-%m-%d') AS q, count(*) AS n, CAST(max(date_diff('day', DATE '1992-01-01', o_orderdate::DATE)) AS INTEGER) AS days, CAST(min(extract(dow FROM o_orderdate)) AS INTEGER) AS dow FROM orders GROUP BY 1")
def fn_date(spark, d):
    o = table(spark, d, "orders")
    return o.groupBy(F.date_format(F.date_trunc("quarter", "o_orderdate"), "yyyy-MM-dd").alias("q")).agg(F.count("*").alias("n"), F.max(F.date_diff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date"))).alias("days"), F.min(F.dayofweek("o_orderdate") - 1).alias("dow"))


@query("SELECT vec_id, round(list_sum(list_transform(v, lambda x: x * x)), 6) AS sq, len(list_filter(v, lambda x: x > 0)) AS pos, list_slice(list_transform(v, lambda x: CAST(floor(x * 10) AS BIGINT)), 1, 4) AS head, list_sort(list_distinct(list_transform(v, lambda x: CAST(floor(x * 4) AS BIGINT)))) AS steps FROM (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings)")
def fn_array(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    return e.select("vec_id", F.round(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x), 6).alias("sq"), F.size(F.filter("v", lambda x: x > 0)).cast("long").alias("pos"), F.slice(F.transform("v", lambda x: F.floor(x * 10)), 1, 4).alias("head"), F.array_sort(F.array_distinct(F.transform("v", lambda x: F.floor(x * 4)))).alias("steps"))


@query("SELECT c1.conv_id, sum(c1.n * c2.n) AS dot FROM (SELECT conv_id, w, count(*) AS n FROM (SELECT conv_id, unnest(string_split(text, ' ')) AS w FROM conversations WHERE turn = 0) GROUP BY 1, 2) c1 JOIN (SELECT conv_id, w, count(*) AS n FROM (SELECT conv_id, unnest(string_split(text, ' ')) AS w FROM conversations WHERE turn = 1) GROUP BY 1, 2) c2 USING (conv_id, w) GROUP BY 1")
def fn_map(spark, d):
    """Sparse term counts as maps and their dot product."""
    words = table(spark, d, "conversations").where("turn <= 1").select("conv_id", "turn", F.explode(F.split("text", " ")).alias("w")).groupBy("conv_id", "turn", "w").agg(F.count("*").alias("n"))
    maps = words.groupBy("conv_id", "turn").agg(F.map_from_entries(F.collect_list(F.struct("w", "n"))).alias("m"))
    both = maps.where("turn = 0").select("conv_id", F.col("m").alias("a")).join(maps.where("turn = 1").select("conv_id", F.col("m").alias("b")), "conv_id")
    dot = F.aggregate(F.map_values(F.map_zip_with("a", "b", lambda k, x, y: F.coalesce(x * y, F.lit(0).cast("long")))), F.lit(0).cast("long"), lambda s, x: s + x)
    return both.select("conv_id", dot.alias("dot")).where("dot > 0")


@query("SELECT CAST(json_extract(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
def fn_json(spark, d):
    e = table(spark, d, "events").select(F.from_json("props", "k int").alias("p"))
    return e.groupBy(F.col("p.k").alias("k")).agg(F.count("*").alias("n"))


@query("SELECT doc_id FROM documents WHERE ('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 6))::BIGINT % 10 = 0")
def rel_sample_md5(spark, d):
    """A sample fixed by the id alone: the operator's purpose."""
    h = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 6), 16, 10).cast("long")
    return table(spark, d, "documents").where(h % 10 == 0).select("doc_id")


@query("SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders i WHERE i.o_custkey = o.o_custkey) AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_discount > 0.05)")
def sql_correlated(spark, d):
    table(spark, d, "orders").createOrReplaceTempView("sc_orders")
    table(spark, d, "lineitem").createOrReplaceTempView("sc_lineitem")
    return spark.sql("SELECT o_orderkey FROM sc_orders o WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM sc_orders i WHERE i.o_custkey = o.o_custkey) AND EXISTS (SELECT 1 FROM sc_lineitem WHERE l_orderkey = o_orderkey AND l_discount > 0.05)")


@query("WITH RECURSIVE r(n, k) AS (SELECT n_nationkey, 0 FROM nation WHERE n_nationkey = 0 UNION ALL SELECT (n * 3 + 1) % 25, k + 1 FROM r WHERE k < 10) SELECT CAST(n AS BIGINT) AS n, k FROM r")
def sql_recursive(spark, d):
    """Reach in a small graph by a recursive common table expression."""
    table(spark, d, "nation").createOrReplaceTempView("sr_nation")
    return spark.sql("WITH RECURSIVE r(n, k) AS (SELECT CAST(n_nationkey AS BIGINT), 0 FROM sr_nation WHERE n_nationkey = 0 UNION ALL SELECT (n * 3 + 1) % 25, k + 1 FROM r WHERE k < 10) SELECT n, k FROM r")


@query("SELECT md5(text) AS body, count(*) AS copies, min(doc_id) AS first_id FROM documents GROUP BY text HAVING count(*) > 1")
def rel_exact_dups(spark, d):
    return table(spark, d, "documents").groupBy(F.md5("text").alias("body")).agg(F.count("*").alias("copies"), F.min("doc_id").alias("first_id")).where("copies > 1")


@query("SELECT time_bucket(INTERVAL 10 MINUTE, ts) AS start, count(*) AS n FROM events GROUP BY 1")
def win_tumbling(spark, d):
    """The batch form of the tumbling request window."""
    e = event_times(spark, d)
    return e.groupBy(F.window("ts", "10 minutes").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), n AS (SELECT *, sum(s) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM n GROUP BY user_id, k")
def win_sessions(spark, d):
    e = event_times(spark, d)
    s = e.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")
