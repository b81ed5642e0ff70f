"""Relational operators around the methods: joins, windows, sets, grouping sets and functions on the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..sources.tables import table
from .queries import query, r6


@query("r_filter_project", "SELECT doc_id, upper(lang) AS code, n_chars FROM documents WHERE lang IN ('de', 'fr') AND n_chars BETWEEN 500 AND 5000 AND text LIKE '%der%' AND regexp_matches(text, '[0-9]')")
def filter_project(spark, d):
    x = table(spark, d, "documents")
    return x.where(F.col("lang").isin("de", "fr") & F.col("n_chars").between(500, 5000) & F.col("text").like("%der%") & F.col("text").rlike("[0-9]")).select("doc_id", F.upper("lang").alias("code"), "n_chars")


@query("r_star_join", "SELECT r_name, n_name, count(*) AS orders, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def star_join(spark, d):
    nations = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    c = table(spark, d, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey"))  # nations and regions: fixed tables of 25 and 5 rows
    return table(spark, d, "orders").join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("r_name", "n_name").agg(F.count("*").alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("r_outer_join", "SELECT quality, toxic, count(*) AS docs FROM documents LEFT JOIN labels USING (doc_id) GROUP BY ALL")
def outer_join(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left").groupBy("quality", "toxic").agg(F.count("*").alias("docs"))


@query("r_semi_anti", "SELECT (SELECT count(*) FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)) AS labelled, (SELECT count(*) FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)) AS bare")
def semi_anti(spark, d):
    x, y = table(spark, d, "documents").select("doc_id"), table(spark, d, "labels").select("doc_id")
    return x.join(y, "doc_id", "left_semi").agg(F.count("*").alias("labelled")).crossJoin(F.broadcast(x.join(y, "doc_id", "left_anti").agg(F.count("*").alias("bare"))))


@query("r_full_join", "SELECT count(*) AS n, count(a.user_id) AS events_side, count(c_custkey) AS customer_side FROM (SELECT DISTINCT user_id FROM events) a FULL JOIN customer ON a.user_id = c_custkey")
def full_join(spark, d):
    a = table(spark, d, "events").select("user_id").distinct()
    return a.join(table(spark, d, "customer"), F.col("user_id") == F.col("c_custkey"), "full").agg(F.count("*").alias("n"), F.count("user_id").alias("events_side"), F.count("c_custkey").alias("customer_side"))


@query("r_range_join", "WITH cells AS (SELECT CAST(i AS INTEGER) AS cell, i * 20.0 AS lo, (i + 1) * 20.0 AS hi FROM range(0, 10) t(i)) SELECT cell, count(*) AS n, round(avg(value), 6) AS mean FROM events JOIN cells ON value >= lo AND value < hi GROUP BY cell")
def range_join(spark, d):
    cells = spark.range(10).select(F.col("id").cast("int").alias("cell"), (F.col("id") * 20.0).alias("lo"), ((F.col("id") + 1) * 20.0).alias("hi"))
    e = table(spark, d, "events").withColumn("bucket", F.floor(F.col("value") / 20))
    return e.join(F.broadcast(cells), (F.col("bucket") == F.col("cell")) & (F.col("value") >= F.col("lo")) & (F.col("value") < F.col("hi"))).groupBy("cell").agg(F.count("*").alias("n"), r6(F.avg("value")).alias("mean"))


@query("r_asof_join", "SELECT event_id, o_orderkey FROM events ASOF LEFT JOIN (SELECT o_custkey, max(o_orderkey) AS o_orderkey, o_orderdate FROM orders GROUP BY o_custkey, o_orderdate) o ON user_id = o_custkey AND ts >= o_orderdate")
def asof_join(spark, d):
    """Each event's latest order: one union, one ordered window; no range comparison."""
    e = table(spark, d, "events").select(F.col("user_id").alias("k"), "ts", F.lit(1).alias("side"), "event_id", F.lit(None).cast("long").alias("o_orderkey"))
    o = table(spark, d, "orders").groupBy(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts")).agg(F.max("o_orderkey").alias("o_orderkey")).select("k", "ts", F.lit(0).alias("side"), F.lit(None).cast("long").alias("event_id"), "o_orderkey")
    last = F.last("o_orderkey", ignorenulls=True).over(Window.partitionBy("k").orderBy("ts", "side"))
    return e.unionByName(o).withColumn("found", last).where("side = 1").select("event_id", F.col("found").alias("o_orderkey"))


@query("r_grouping_sets", "SELECT lang, source, count(*) AS docs, CAST(grouping(lang, source) AS INTEGER) AS level FROM documents GROUP BY ROLLUP (lang, source)")
def grouping_sets(spark, d):
    return table(spark, d, "documents").rollup("lang", "source").agg(F.count("*").alias("docs"), F.grouping_id().cast("int").alias("level"))


@query("r_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def cube(spark, d):
    return table(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("r_pivot", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'error') AS error, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY user_id")
def pivot(spark, d):
    return table(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "error", "view"]).count().na.fill(0)


@query("r_unpivot", "SELECT doc_id, unnest(['quality', 'toxic']) AS label, unnest([quality, toxic]) AS value FROM labels")
def unpivot(spark, d):
    return table(spark, d, "labels").unpivot("doc_id", ["quality", "toxic"], "label", "value")


@query("r_window_functions", "SELECT o_orderkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(ntile(4) OVER w AS INTEGER) AS quarter, round(sum(o_totalprice) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving, lag(o_orderkey) OVER w AS before, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def window_functions(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(spark, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.ntile(4).over(w).alias("quarter"), F.round(F.sum("o_totalprice").over(w.rowsBetween(-2, 0)), 4).alias("moving"), F.lag("o_orderkey").over(w).alias("before"), r6(F.percent_rank().over(w)).alias("pr"), r6(F.cume_dist().over(w)).alias("cd"))


@query("r_top_k", "SELECT o_custkey, o_orderkey, o_totalprice FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def top_k(spark, d):
    """A top-k report: two dearest orders of each customer."""
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, d, "orders").withColumn("k", F.row_number().over(w)).where("k <= 2").select("o_custkey", "o_orderkey", "o_totalprice")


@query("r_set_operations", "WITH a AS (SELECT DISTINCT unnest(string_split(lower(text), ' ')) AS w FROM benchmark), b AS (SELECT DISTINCT unnest(string_split(lower(text), ' ')) AS w FROM conversations) SELECT (SELECT count(*) FROM (SELECT w FROM a INTERSECT SELECT w FROM b)) AS shared, (SELECT count(*) FROM (SELECT w FROM a EXCEPT SELECT w FROM b)) AS only_a, (SELECT count(*) FROM (SELECT w FROM a UNION SELECT w FROM b)) AS either")
def set_operations(spark, d):
    words = lambda n: table(spark, d, n).select(F.explode(F.split(F.lower("text"), " ")).alias("w")).distinct()
    a, b = words("benchmark"), words("conversations")
    count = lambda x, name: x.agg(F.count("*").alias(name))
    return count(a.intersect(b), "shared").crossJoin(F.broadcast(count(a.exceptAll(b), "only_a"))).crossJoin(F.broadcast(count(a.union(b).distinct(), "either")))


@query("r_aggregates", "SELECT event_type, count(*) AS n, count(DISTINCT user_id) AS users, round(stddev_samp(value), 6) AS spread, min_by(event_id, value) AS least, max_by(event_id, value) AS most, round(quantile_cont(value, 0.5), 6) AS median, round(regr_slope(value, event_id), 9) AS slope, round(corr(value, event_id), 6) AS corr FROM events GROUP BY event_type")
def aggregates(spark, d):
    """Of events with equal values the first by id is the least, and the most: as the SQL meets them in the table."""
    e = table(spark, d, "events")
    known = lambda sign: F.when(F.col("value").isNotNull() & F.col("event_id").isNotNull(), F.struct("value", (sign * F.col("event_id")).alias("id")))
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users"), r6(F.stddev_samp("value")).alias("spread"), F.min_by("event_id", known(1)).alias("least"), F.max_by("event_id", known(-1)).alias("most"), r6(F.percentile("value", 0.5)).alias("median"), F.round(F.regr_slope("value", "event_id"), 9).alias("slope"), r6(F.corr("value", "event_id")).alias("corr"))


@query("r_json_and_arrays", "SELECT CAST(json_extract(props, '$.k') AS INTEGER) % 10 AS k, count(*) AS n, max(len(range(0, CAST(json_extract(props, '$.k') AS INTEGER)))) AS longest FROM events GROUP BY 1")
def json_and_arrays(spark, d):
    e = table(spark, d, "events").select(F.from_json("props", "k int")["k"].alias("v"))
    return e.groupBy((F.col("v") % 10).alias("k")).agg(F.count("*").alias("n"), F.max(F.size(F.when(F.col("v") > 0, F.sequence(F.lit(0), F.col("v") - 1)).otherwise(F.array()))).cast("long").alias("longest"))


@query("r_strings_and_dates", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n, min(lpad(CAST(o_orderkey AS VARCHAR), 10, '0')) AS first_key, max(levenshtein(o_orderstatus, 'OPEN')) AS far, min(date_diff('day', DATE '1992-01-01', o_orderdate::DATE)) AS days FROM orders GROUP BY 1")
def strings_and_dates(spark, d):
    o = table(spark, d, "orders")
    return o.groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count("*").alias("n"), F.min(F.lpad(F.col("o_orderkey").cast("string"), 10, "0")).alias("first_key"), F.max(F.levenshtein("o_orderstatus", F.lit("OPEN"))).cast("long").alias("far"), F.min(F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date"))).cast("long").alias("days"))


@query("r_scalar_subquery", "SELECT count(*) AS above FROM documents WHERE n_chars > (SELECT avg(n_chars) FROM documents)")
def scalar_subquery(spark, d):
    x = table(spark, d, "documents")
    return x.crossJoin(F.broadcast(x.agg(F.avg("n_chars").alias("mean")))).where("n_chars > mean").agg(F.count("*").alias("above"))


@query("r_hash_sample", "SELECT count(*) AS n FROM documents WHERE CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8) AS BIGINT) < 429496729")
def hash_sample(spark, d):
    """The sampling operator: a tenth of the sequences, the same in any engine, whole sequences kept."""
    h = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8), 16, 10).cast("long")
    return table(spark, d, "documents").where(h < 429496729).agg(F.count("*").alias("n"))
