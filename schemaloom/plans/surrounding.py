"""Relational operators around the methods: scans, filters, joins, aggregates, windows, sets, scalars, graphs."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from schemaloom.operators import hierarchy as h
from schemaloom.plans.registry import TABLES, query, sql_query, table
from schemaloom.sources import corpora, repository
from schemaloom.sources import fixtures as fx
from schemaloom.sources.shared import shared_path

LAKE = " UNION ALL ".join(f"SELECT '{t}' AS table_name, count(*) AS n_rows FROM {t}" for t in TABLES)


@query("s_scan_lake", LAKE)
def scan_lake(spark, sf_dir):
    out = None
    for t in TABLES:
        one = table(spark, sf_dir, t).agg(F.count("*").alias("n_rows")).select(F.lit(t).alias("table_name"), "n_rows")
        out = one if out is None else out.unionByName(one)
    return out


@query("s_scan_csv", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
def scan_csv(spark, sf_dir):
    path = shared_path(spark, "csv")
    table(spark, sf_dir, "nation").write.csv(path, header=True)
    return spark.read.csv(path, header=True, inferSchema=True)


@query("s_scan_json", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
def scan_json(spark, sf_dir):
    path = shared_path(spark, "json")
    table(spark, sf_dir, "nation").write.json(path)
    return spark.read.schema("n_nationkey int, n_name string, n_regionkey int").json(path)


@query("s_sink_partitioned", "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_orderstatus = 'F' GROUP BY o_orderstatus")
def sink_partitioned(spark, sf_dir):
    path = shared_path(spark, "partitioned")
    table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).where("o_orderstatus = 'F'").groupBy("o_orderstatus").agg(F.count("*").alias("n"))


sql_query("s_filter_range", "SELECT o_orderkey, o_totalprice FROM {orders} WHERE o_totalprice BETWEEN 100000 AND 150000")
sql_query("s_filter_in", "SELECT p_partkey, p_type FROM {part} WHERE p_brand IN ('Brand#11', 'Brand#12', 'Brand#23')")
sql_query("s_filter_like", "SELECT c_custkey, c_name FROM {customer} WHERE c_name LIKE 'Customer#00000%'")
sql_query("s_filter_null", "SELECT doc_id FROM {documents} WHERE text IS NULL OR trim(text) = '' OR lang = 'es'")
sql_query("s_case_band", "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'low' ELSE 'high' END AS band FROM {customer}")
sql_query("s_join_chain", """
SELECT r_name, CAST(round(sum(l_extendedprice * (1 - l_discount)), 0) AS BIGINT) AS revenue
FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey JOIN {customer} ON o_custkey = c_custkey
JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey GROUP BY r_name""")
for hint in ("hash", "broadcast", "merge"):
    kind = {"hash": "shuffle_hash", "broadcast": "broadcast", "merge": "merge"}[hint]

    @query(f"s_join_{hint}", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
    def joined(spark, sf_dir, kind=kind):
        small = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment").hint(kind)
        both = table(spark, sf_dir, "orders").select("o_custkey").join(small, F.col("o_custkey") == F.col("c_custkey"))
        return both.groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("s_join_semi", "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def join_semi(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey")
    return table(spark, sf_dir, "orders").select("o_orderkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi")


@query("s_join_anti", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def join_anti(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey")
    return table(spark, sf_dir, "orders").select("o_orderkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left_anti")


@query("s_join_left", "SELECT d.doc_id, d.lang, l.quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def join_left(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", "lang").join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left")


sql_query("s_join_full", "SELECT coalesce(a.k, b.k) AS k, a.n AS customers, b.n AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM {customer} GROUP BY c_nationkey) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM {supplier} GROUP BY s_nationkey) b ON a.k = b.k")
sql_query("s_join_self", "SELECT a.n_name AS a, b.n_name AS b, a.n_regionkey FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
sql_query("s_join_theta", "SELECT a.p_partkey, count(*) AS dearer FROM {part} a JOIN (SELECT p_brand, p_type, max(p_retailprice) AS top FROM {part} GROUP BY p_brand, p_type) b ON a.p_brand = b.p_brand AND b.top > a.p_retailprice GROUP BY a.p_partkey")


@query("s_join_interval", """
SELECT s.event_id AS signup_id, e.event_id FROM events s JOIN events e ON s.user_id = e.user_id AND e.ts > s.ts AND e.ts <= s.ts + INTERVAL 10 MINUTE WHERE s.event_type = 'signup'""")
def join_interval(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    s = e.where("event_type = 'signup'").select(F.col("event_id").alias("signup_id"), F.col("user_id").alias("u"), F.col("ts").alias("at"))
    late = F.col("at") + F.expr("INTERVAL 10 MINUTE")
    return e.join(s, (F.col("user_id") == F.col("u")) & (F.col("ts") > F.col("at")) & (F.col("ts") <= late)).select("signup_id", "event_id")


@query("s_join_range", """
SELECT d.k AS span, count(*) AS n FROM (SELECT DISTINCT date_trunc('hour', ts) - INTERVAL 20 MINUTE AS low, date_trunc('hour', ts) + INTERVAL 20 MINUTE AS high, date_trunc('hour', ts)::VARCHAR AS k FROM events) d JOIN events e ON e.ts >= d.low AND e.ts < d.high GROUP BY d.k""")
def join_range(spark, sf_dir):
    """Events within twenty minutes of a full hour. A range join on a bucket key: a span goes to each hour that it
    touches, and the predicate is checked inside."""
    e = table(spark, sf_dir, "events").select("ts", F.date_trunc("hour", "ts").alias("h"))
    spans = e.select("h").distinct().select(F.date_format("h", "yyyy-MM-dd HH:mm:ss").alias("span"), (F.col("h") - F.expr("INTERVAL 20 MINUTE")).alias("low"), (F.col("h") + F.expr("INTERVAL 20 MINUTE")).alias("high"))
    touched = spans.withColumn("h", F.explode(F.array_distinct(F.array(F.date_trunc("hour", "low"), F.date_trunc("hour", "high")))))
    return e.join(touched, "h").where((F.col("ts") >= F.col("low")) & (F.col("ts") < F.col("high"))).groupBy("span").agg(F.count("*").alias("n"))


@query("s_join_asof", """
SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS purchase_id FROM events""")
def join_asof(spark, sf_dir):
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    bought = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    return table(spark, sf_dir, "events").select("event_id", F.last(bought, ignorenulls=True).over(before).alias("purchase_id"))


sql_query("s_join_cross", "SELECT r_name, g.theta FROM {region} CROSS JOIN (SELECT * FROM (VALUES (5), (9), (10)) AS v(theta)) g")
sql_query(
    "s_lateral_top",
    "SELECT o.o_orderkey, t.l_linenumber, t.l_extendedprice FROM {orders} o JOIN (SELECT l_orderkey, l_linenumber, l_extendedprice, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_extendedprice DESC, l_linenumber) AS k FROM {lineitem}) t ON t.l_orderkey = o.o_orderkey AND t.k <= 3",
    "SELECT o_orderkey, l_linenumber, l_extendedprice FROM orders, LATERAL (SELECT l_linenumber, l_extendedprice FROM lineitem WHERE l_orderkey = o_orderkey ORDER BY l_extendedprice DESC, l_linenumber LIMIT 3) t",
)
sql_query("s_agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM {lineitem} GROUP BY l_returnflag, l_linestatus")
sql_query("s_agg_distinct", "SELECT l_partkey, count(DISTINCT l_suppkey) AS suppliers FROM {lineitem} GROUP BY l_partkey")
sql_query("s_agg_filter", "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS done, count(*) FILTER (WHERE o_totalprice > 200000) AS large FROM {orders} GROUP BY o_orderpriority")
sql_query("s_agg_rollup", "SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM {orders} GROUP BY ROLLUP (o_orderpriority, o_orderstatus)")
sql_query("s_agg_cube", "SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM {orders} GROUP BY CUBE (o_orderpriority, o_orderstatus)")
sql_query("s_agg_sets", "SELECT year(o_orderdate) AS y, o_orderpriority, count(*) AS n FROM {orders} GROUP BY GROUPING SETS ((year(o_orderdate)), (o_orderpriority), ())")
sql_query("s_agg_stats", "SELECT l_returnflag, round(var_samp(l_quantity), 4) AS v, round(corr(l_quantity, l_extendedprice), 6) AS c FROM {lineitem} GROUP BY l_returnflag")
sql_query("s_agg_mode", "SELECT c_nationkey, max(c_mktsegment) AS segment FROM (SELECT c_nationkey, c_mktsegment, rank() OVER (PARTITION BY c_nationkey ORDER BY n DESC) AS k FROM (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM {customer} GROUP BY c_nationkey, c_mktsegment) a) b WHERE k = 1 GROUP BY c_nationkey")


@query("s_agg_collect", "SELECT p_type, array_to_string(list_sort(list(DISTINCT p_brand)), ',') AS brands FROM part GROUP BY p_type")
def agg_collect(spark, sf_dir):
    return table(spark, sf_dir, "part").groupBy("p_type").agg(F.array_join(F.sort_array(F.collect_set("p_brand")), ",").alias("brands"))


@query("s_agg_sketch")
def agg_sketch(spark, sf_dir):
    """Approximate distinct users and quantiles; tests hold them against exact ones."""
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", 0.5, 10_000).alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users_hll"))


@query("s_pivot", "SELECT CAST(ts AS DATE)::VARCHAR AS day, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase, count(*) FILTER (event_type = 'signup') AS signup FROM events GROUP BY 1")
def pivot(spark, sf_dir):
    e = table(spark, sf_dir, "events").select(F.date_format("ts", "yyyy-MM-dd").alias("day"), "event_type")
    wide = e.groupBy("day").pivot("event_type", ["click", "purchase", "signup"]).agg(F.count(F.lit(1)))
    return wide.select("day", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("click", "purchase", "signup")))


@query("s_unpivot", "SELECT c_custkey, 'name' AS header, c_name AS value FROM customer UNION ALL SELECT c_custkey, 'mktsegment', c_mktsegment FROM customer UNION ALL SELECT c_custkey, 'nationkey', CAST(c_nationkey AS VARCHAR) FROM customer")
def unpivot(spark, sf_dir):
    c = table(spark, sf_dir, "customer").select("c_custkey", F.col("c_name").alias("name"), F.col("c_mktsegment").alias("mktsegment"), F.col("c_nationkey").cast("string").alias("nationkey"))
    return c.unpivot("c_custkey", ["name", "mktsegment", "nationkey"], "header", "value")


for name, expr in {"rank": "rank()", "dense": "dense_rank()", "ntile": "ntile(4)"}.items():
    sql_query(f"s_win_{name}", f"SELECT c_custkey, CAST({expr} OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS BIGINT) AS r FROM {{customer}}")
sql_query("s_win_pct", "SELECT c_custkey, round(percent_rank() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey), 6) AS r FROM {customer}")
sql_query("s_win_lag", "SELECT event_id, value - lag(value) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS step FROM {events}")
sql_query("s_win_running", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS nth, max(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS top FROM {orders}")
sql_query("s_win_moving", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 6 PRECEDING AND CURRENT ROW) AS top FROM {events}")
sql_query("s_win_range", "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM {events}")
sql_query("s_win_first_last", "SELECT DISTINCT user_id, first_value(event_type) OVER w AS first_type, last_value(event_type) OVER w AS last_type FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
sql_query("s_sessionize", "SELECT user_id, s AS session_no, count(*) AS n FROM (SELECT user_id, CAST(sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS s FROM (SELECT user_id, ts, event_id, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > ts - INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM {events}) a) b GROUP BY user_id, s")
sql_query("s_topk_global", "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
sql_query("s_topk_group", "SELECT o_orderpriority, o_orderkey FROM (SELECT o_orderpriority, o_orderkey, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS k FROM {orders}) t WHERE k <= 5")
sql_query("s_limit_offset", "SELECT o_orderkey FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 10")
sql_query("s_set_union", "SELECT c_nationkey AS k FROM {customer} UNION SELECT s_nationkey FROM {supplier}")
sql_query("s_set_intersect", "SELECT c_nationkey AS k FROM {customer} INTERSECT SELECT s_nationkey FROM {supplier}")
sql_query("s_set_except", "SELECT n_nationkey AS k FROM {nation} EXCEPT SELECT s_nationkey FROM {supplier} WHERE s_acctbal < 0")
sql_query("s_set_all", "SELECT c_nationkey AS k FROM {customer} EXCEPT ALL SELECT s_nationkey FROM {supplier}")
sql_query("s_str_distance", "SELECT p_partkey, CAST(levenshtein(p_brand, p_type) AS BIGINT) AS d FROM {part}")
sql_query("s_str_regex", "SELECT p_partkey, CAST(regexp_extract(p_brand, '([0-9]+)', 1) AS INT) AS brand_no FROM {part}")


@query("s_str_tokens", "SELECT w AS token, count(*) AS n FROM (SELECT unnest(string_split(lower(p_name), ' ')) AS w FROM part) GROUP BY w")
def str_tokens(spark, sf_dir):
    return table(spark, sf_dir, "part").select(F.explode(F.split(F.lower("p_name"), " ")).alias("token")).groupBy("token").agg(F.count("*").alias("n"))


@query("s_str_grams", "SELECT substr(n_name, k, 3) AS gram, count(*) AS n FROM (SELECT n_name, unnest(range(1, length(n_name) - 1)) AS k FROM nation WHERE length(n_name) >= 3) GROUP BY 1")
def str_grams(spark, sf_dir):
    n = table(spark, sf_dir, "nation").where("length(n_name) >= 3")
    return n.select(F.explode(F.expr("transform(sequence(1, length(n_name) - 2), k -> substr(n_name, k, 3))")).alias("gram")).groupBy("gram").agg(F.count("*").alias("n"))


sql_query("s_date_parts", "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n FROM {orders} GROUP BY year(o_orderdate), month(o_orderdate)")
sql_query("s_date_diff", "SELECT l_orderkey, l_linenumber, CAST(datediff(CAST(l_shipdate AS DATE), CAST(o_orderdate AS DATE)) AS BIGINT) AS lag FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey", "SELECT l_orderkey, l_linenumber, datediff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS lag FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey")
sql_query("s_math_mix", "SELECT p_partkey, round(ln(p_retailprice), 6) AS l, round(sqrt(p_retailprice), 6) AS r, p_size % 7 AS m FROM {part}")


@query("s_date_trunc", "SELECT CAST(ts AS DATE)::VARCHAR AS day, count(*) AS n FROM events GROUP BY 1")
def date_trunc(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n"))


@query("s_arr_cosine", "SELECT a.vec_id AS a, b.vec_id AS b, round(list_sum(list_transform(range(1, 65), lambda k: CAST(a.embedding[k] AS DOUBLE) * CAST(b.embedding[k] AS DOUBLE))), 4) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def arr_cosine(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    other = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("x").alias("y"))
    dot = F.aggregate(F.zip_with("x", "y", lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    return e.join(other, "vec_id").select(F.col("vec_id").alias("a"), (F.col("vec_id") + 1).alias("b"), F.round(dot, 4).alias("cosine"))


@query("s_arr_topdims", "SELECT vec_id, CAST(list_position(embedding, list_max(embedding)) AS BIGINT) AS dim FROM embeddings")
def arr_topdims(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", F.array_position("embedding", F.array_max("embedding")).cast("long").alias("dim"))


@query("s_json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def json_props(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("s_map_props", "SELECT count(*) AS n, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS total FROM events")
def map_props(spark, sf_dir):
    m = table(spark, sf_dir, "events").select(F.from_json("props", "map<string,bigint>").alias("m"))
    return m.agg(F.count("*").alias("n"), F.sum(F.try_element_at("m", F.lit("k"))).alias("total"))


sql_query("s_html_title", "SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title FROM {pages}")


@query("s_html_links", "SELECT page_id, CAST(len(regexp_extract_all(html, '<a ')) AS BIGINT) AS links FROM pages")
def html_links(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit("<a "), F.lit(0))).cast("long").alias("links"))


sql_query("s_url_host", "SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, count(*) AS n FROM {pages} GROUP BY regexp_extract(url, '^[a-z]+://([^/]+)', 1)")
sql_query("s_subquery_exists", "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 250000)")
sql_query("s_subquery_scalar", "SELECT c_custkey FROM {customer} WHERE c_acctbal > (SELECT avg(c_acctbal) FROM {customer})")


# --- sources, exports, functions of one's own -------------------------------------------------------------------------

PLACES = tuple(x for x in corpora.WEB if x.name in ("region", "nation"))


def place_cells(spark, sf_dir) -> DataFrame:
    return corpora.cells(spark, sf_dir, PLACES).select(F.concat_ws(".", "base", "k").alias("table_id"), F.col("column").alias("header"), "value")


PLACE_CELLS = " UNION ALL ".join(f"SELECT concat_ws('.', '{x.name}', k) AS table_id, '{c}' AS header, CAST({c} AS VARCHAR) AS value FROM ({x.twin()})" for x in PLACES for c, _, _ in x.columns)


@query("s_source_repo", f"SELECT table_id, header, count(*) AS n FROM ({PLACE_CELLS}) WHERE table_id IN ('nation.0', 'region.all') GROUP BY 1, 2")
def source_repo(spark, sf_dir):
    """Tables of a folder, of which two are wanted: no other file is opened."""
    path = shared_path(spark, "repository")
    repository.write(place_cells(spark, sf_dir), path)
    return repository.read(spark, path, ["nation.0", "region.all"]).groupBy("table_id", "header").agg(F.count("*").alias("n"))


@query("s_export_json", f"SELECT table_id, json_array_length(doc, '$.columns') AS n FROM (SELECT table_id, to_json({{'columns': list_sort(list(DISTINCT header))}}) AS doc FROM ({PLACE_CELLS}) GROUP BY table_id)")
def export_json(spark, sf_dir):
    """Each table's schema as nested JSON, read back."""
    doc = F.to_json(F.struct(F.sort_array(F.collect_set("header")).alias("columns"))).alias("doc")
    docs = place_cells(spark, sf_dir).groupBy("table_id").agg(doc)
    return docs.select("table_id", F.json_array_length(F.get_json_object("doc", "$.columns")).cast("bigint").alias("n"))


@query("s_export_dot", f"SELECT 'digraph {{' || string_agg('\"' || child || '\" -> \"' || parent || '\";', ' ' ORDER BY child, parent) || '}}' AS dot FROM {fx.EDGES}")
def export_dot(spark, sf_dir):
    """A hierarchy as one text for a graph drawer; hierarchies are small."""
    line = F.format_string('"%s" -> "%s";', "child", "parent")
    held = fx.relation(spark, fx.EDGES).agg(F.sort_array(F.collect_list(F.struct("child", "parent", line.alias("line")))).alias("x"))
    return held.select(F.concat(F.lit("digraph {"), F.array_join(F.transform("x", lambda r: r["line"]), " "), F.lit("}")).alias("dot"))


LAYOUT = corpora.layout(corpora.WEB)


@query("s_project_headers", "SELECT DISTINCT base, \"column\", lower(regexp_replace(header, '[^A-Za-z0-9]+', ' ', 'g')) AS words FROM " + corpora.layout_sql(corpora.WEB))
def project_headers(spark, sf_dir):
    held = spark.createDataFrame(LAYOUT, corpora.LAYOUT)
    return held.select("base", "column", F.lower(F.regexp_replace("header", "[^A-Za-z0-9]+", " ")).alias("words")).distinct()


@query("s_arr_sets", """
WITH w AS (SELECT doc_id, list_distinct(list_filter(string_split(lower(coalesce(text, '')), ' '), lambda x: x <> '')) AS ws FROM documents)
SELECT a.doc_id, len(list_intersect(a.ws, b.ws)) AS common, len(a.ws) + len(b.ws) - len(list_intersect(a.ws, b.ws)) AS either FROM w a JOIN w b ON b.doc_id = a.doc_id + 1""")
def arr_sets(spark, sf_dir):
    """Words that a document shares with the next one by id."""
    words = F.array_distinct(F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), " "), lambda x: x != ""))
    d = table(spark, sf_dir, "documents").select("doc_id", words.alias("a"))
    other = d.select((F.col("doc_id") - 1).alias("doc_id"), F.col("a").alias("b"))
    common = F.size(F.array_intersect("a", "b"))
    return d.join(other, "doc_id").select("doc_id", common.cast("bigint").alias("common"), (F.size("a") + F.size("b") - common).cast("bigint").alias("either"))


sql_query("s_json_schema", "SELECT count(*) AS n, CAST(sum(from_json(props, 'k BIGINT').k) AS BIGINT) AS total FROM {events}", "SELECT count(*) AS n, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS total FROM events")


@query("s_components", f"""
WITH RECURSIVE e AS (SELECT child AS a, parent AS b FROM {fx.EDGES} WHERE parent <> 'Thing' UNION SELECT parent, child FROM {fx.EDGES} WHERE parent <> 'Thing'),
n AS (SELECT DISTINCT a AS t FROM e), r(t, o) AS (SELECT t, t FROM n UNION SELECT r.t, e.b FROM r JOIN e ON e.a = r.o) SELECT t AS item, min(o) AS cluster FROM r GROUP BY t""")
def components(spark, sf_dir):
    """Connected parts of a hierarchy without its root."""
    from schemaloom.operators.affinity import single_links

    edges = fx.relation(spark, fx.EDGES).where(F.col("parent") != h.ROOT)
    items = edges.select(F.explode(F.array("child", "parent")).alias("item")).distinct()
    return single_links(items, edges.select(F.col("child").alias("a"), F.col("parent").alias("b"), F.lit(1.0).alias("sim")), 1.0)


@query("s_udf_scalar", f"SELECT path_no, count(*) AS steps FROM {fx.TREE} GROUP BY path_no")
def udf_scalar(spark, sf_dir):
    """A vectorised function of one's own over paths."""

    @F.pandas_udf("long")
    def steps(path: pd.Series) -> pd.Series:
        return path.str.count(">") + 1

    paths = fx.relation(spark, fx.TREE).groupBy("path_no").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("pos", "gt_type"))), lambda x: x["gt_type"]), ">").alias("path"))
    return paths.select("path_no", steps("path").alias("steps"))


@query("s_udaf_mean_vector", "SELECT label, round(avg(CAST(embedding[1] AS DOUBLE)), 5) AS first, round(avg(CAST(embedding[64] AS DOUBLE)), 5) AS last FROM embeddings GROUP BY label")
def udaf_mean_vector(spark, sf_dir):
    """Mean vectors by label: sums of arrays place by place, combined before the shuffle."""
    e = table(spark, sf_dir, "embeddings").select("label", F.posexplode(F.col("embedding").cast("array<double>")).alias("at", "x"))
    mean = e.groupBy("label", "at").agg(F.avg("x").alias("x")).where("at IN (0, 63)")
    return mean.groupBy("label").agg(F.round(F.max(F.when(F.col("at") == 0, F.col("x"))), 5).alias("first"), F.round(F.max(F.when(F.col("at") == 63, F.col("x"))), 5).alias("last"))


PATH_STEPS = f"SELECT table_id, CAST(k AS INTEGER) AS pos, string_split(path, '>')[k] AS type_name FROM (SELECT table_id, path, unnest(range(1, len(string_split(path, '>')) + 1)) AS k FROM {fx.PATHS} WHERE path_no = 1)"


@query("s_udtf_path", PATH_STEPS)
def udtf_path(spark, sf_dir):
    """A table function of one's own: a path's steps as rows."""

    class Steps:
        def eval(self, path: str):
            for k, t in enumerate(path.split(">"), 1):
                yield k, t

    spark.udtf.register("path_steps", F.udtf(Steps, returnType="pos int, type_name string"))
    held = spark.sql(f"SELECT table_id, path FROM {fx.PATHS} WHERE path_no = 1")
    return spark.sql("SELECT table_id, s.pos, s.type_name FROM {held} t, LATERAL path_steps(t.path) s", held=held)


@query("s_annotate", f"""
WITH c AS ({PLACE_CELLS}), q AS (SELECT DISTINCT lower(header) AS header FROM (SELECT 'n_name' AS header UNION ALL SELECT 'n_regionkey')), t AS (SELECT DISTINCT table_id, header FROM c)
SELECT table_id, shared FROM (SELECT table_id, count(*) AS shared, row_number() OVER (ORDER BY count(*) DESC, table_id) AS r FROM t JOIN q USING (header) GROUP BY table_id) WHERE r = 1""")
def annotate(spark, sf_dir):
    """The table whose headers an unseen one shares most: its type would be the unseen table's."""
    held = place_cells(spark, sf_dir).select("table_id", "header").distinct()
    asked = spark.createDataFrame([("n_name",), ("n_regionkey",)], "header string")
    shared = held.join(F.broadcast(asked), "header").groupBy("table_id").agg(F.count("*").alias("shared"))
    return shared.orderBy(F.desc("shared"), "table_id").limit(1)


@query("s_table_query", f"""
WITH v AS (SELECT DISTINCT table_id, value FROM ({PLACE_CELLS})) SELECT y.table_id, count(*) AS shared FROM v x JOIN v y ON x.value = y.value AND x.table_id = 'region.all' AND y.table_id <> x.table_id GROUP BY 1""")
def table_query(spark, sf_dir):
    """Tables by the number of values that they share with one."""
    v = place_cells(spark, sf_dir).select("table_id", "value").distinct()
    asked = v.where("table_id = 'region.all'").select("value")
    return v.where("table_id <> 'region.all'").join(asked, "value").groupBy("table_id").agg(F.count("*").alias("shared"))
