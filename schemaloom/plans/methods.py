"""Sampling, profiles, measures and exact cardinalities over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.operators import hierarchy as h
from schemaloom.operators import measures as m
from schemaloom.operators import sampling as s
from schemaloom.plans.registry import query, sql_query, table
from schemaloom.sources import fixtures as fx
from schemaloom.sources import fragments as fr

# --- sampling and profiles -------------------------------------------------------------------------------------------


def sampled(name: str):
    b = fr.BY_NAME[name]
    cols = ", ".join(f"CAST({c} AS VARCHAR)" for c in b.columns)

    @query(f"g_sample_rows_{name}", f"""
SELECT DISTINCT k, digest FROM (SELECT k, digest, dense_rank() OVER (PARTITION BY k ORDER BY digest) AS r FROM (
  SELECT {b.split} AS k, md5(concat_ws('|', '0', {cols})) AS digest FROM {name} {b.join})) WHERE r <= 5""")
    def rows(spark, sf_dir):
        return s.sample_rows(fr.keyed(spark, sf_dir, b), "k", list(b.columns)).select("k", "digest")

    turned = " UNION ALL ".join(f"SELECT k, '{c}' AS header, CAST({c} AS VARCHAR) AS value FROM b" for c in b.columns)

    @query(f"g_sample_values_{name}", f"""
WITH b AS (SELECT *, {b.split} AS k FROM {name} {b.join}), l AS ({turned})
SELECT DISTINCT k, header, value FROM (SELECT *, dense_rank() OVER (PARTITION BY k, header ORDER BY md5(concat_ws('|', '0', value))) AS r FROM l WHERE trim(value) <> '') WHERE r <= 5""")
    def values(spark, sf_dir):
        return s.sample_values(fr.keyed(spark, sf_dir, b), "k", list(b.columns))

    v = "CASE WHEN trim(value) <> '' THEN value END"
    profile = f"""
WITH b AS (SELECT *, {b.split} AS k FROM {name} {b.join}), l AS ({turned}),
a AS (SELECT k, header, count(*) AS cells, count({v}) AS f, count(DISTINCT {v}) AS d, count(*) FILTER (trim(value) <> '' AND contains(value, ';')) AS mu,
  count(*) FILTER (trim(value) <> '' AND regexp_matches(value, '^-?[0-9]+(\\.[0-9]+)?$')) AS dg, count(*) FILTER (trim(value) <> '' AND regexp_matches(value, '^[0-9]{{4}}-[0-9]{{2}}-[0-9]{{2}}')) AS dt, sum(length({v})) AS ch FROM l GROUP BY k, header),
p AS (SELECT k, header, cells, round((cells - f) / cells, 6) AS rho_null, CASE WHEN f > 0 THEN round(mu / f, 6) END AS rho_multi, round(d / cells, 6) AS rho_uniq,
  CASE WHEN f > 0 THEN round(dg / f, 6) END AS digits, CASE WHEN f > 0 THEN round(dt / f, 6) END AS dates, CASE WHEN f > 0 THEN round(ch / f, 6) END AS chars FROM a)"""

    @query(f"g_profile_{name}", f"{profile} SELECT k, header, cells, rho_null, rho_multi, rho_uniq FROM p")
    def profiled(spark, sf_dir):
        return s.profile(fr.keyed(spark, sf_dir, b), "k", list(b.columns)).select("k", "header", "cells", "rho_null", "rho_multi", "rho_uniq")

    @query(f"g_kind_{name}", f"""{profile} SELECT k, header, CASE WHEN dates >= 0.95 THEN 'date' WHEN digits >= 0.95 AND rho_uniq >= 0.95 THEN 'identifier' WHEN digits >= 0.95 THEN 'number' WHEN chars > 60 THEN 'text' ELSE 'entity' END AS kind FROM p""")
    def kinds(spark, sf_dir):
        return s.profile(fr.keyed(spark, sf_dir, b), "k", list(b.columns)).select("k", "header", s.kind().alias("kind"))


for base in ("nation", "customer", "orders", "part"):
    sampled(base)


@query("g_sample_tables", f"SELECT base, table_id FROM (SELECT base, table_id, row_number() OVER (PARTITION BY base ORDER BY md5(concat_ws('|', '0', table_id)), table_id) AS r FROM ({fr.REPOSITORY_SQL})) WHERE r <= 5")
def sample_tables(spark, sf_dir):
    return s.sample_tables(fr.repository(spark, sf_dir).select("base", "table_id"), "base", "table_id")


sql_query("g_multi", "SELECT event_id, size(split(props, ';')) > 1 AS multi FROM {events}", "SELECT event_id, len(string_split(props, ';')) > 1 AS multi FROM {events}")

# --- the repository ---------------------------------------------------------------------------------------------------


@query("w_repo_web_stats", f"SELECT variant, count(*) AS n_tables, CAST(sum(n_cols) AS BIGINT) AS n_columns, count(DISTINCT path) AS n_leaves FROM ({fr.REPOSITORY_SQL}) GROUP BY variant")
def repo_web_stats(spark, sf_dir):
    return fr.repository(spark, sf_dir).groupBy("variant").agg(F.count("*").alias("n_tables"), F.sum("n_cols").alias("n_columns"), F.count_distinct("path").alias("n_leaves"))


@query("m_long_tail", f"SELECT split_part(path, '>', 1) AS top, count(*) AS n_tables FROM ({fr.REPOSITORY_SQL}) GROUP BY 1")
def long_tail(spark, sf_dir):
    return fr.repository(spark, sf_dir).groupBy(F.split_part("path", F.lit(">"), F.lit(1)).alias("top")).agg(F.count("*").alias("n_tables"))


@query("w_truth_edges", f"""
SELECT child, parent, CAST(sum(n) AS BIGINT) AS weight FROM (
  SELECT ts[k + 1] AS child, ts[k] AS parent, 3 AS n FROM (SELECT ts, unnest(range(1, len(ts))) AS k FROM (SELECT string_split('Thing>' || path, '>') AS ts FROM ({fr.FRAGMENTS_SQL})))) GROUP BY child, parent""")
def truth_edges(spark, sf_dir):
    return truth(fr.repository(spark, sf_dir))


def truth(repo: DataFrame) -> DataFrame:
    return h.merge_edges(h.path_edges(repo.select("table_id", F.lit(1).alias("path_no"), F.split("path", ">").alias("path"))))


# --- measures ---------------------------------------------------------------------------------------------------------


def clusters(spark):
    return fx.relation(spark, fx.CLUSTERS)


def pair_sql(source: str, p: str, t: str) -> str:
    c2 = lambda n: f"coalesce(sum({n} * ({n} - 1) // 2), 0)"
    return f"""
WITH c AS (SELECT {p} AS p, {t} AS t, count(*) AS n FROM {source} GROUP BY 1, 2),
tp AS (SELECT {c2('n')} AS v FROM c), pp AS (SELECT {c2('n')} AS v FROM (SELECT sum(n) AS n FROM c GROUP BY p)), tt AS (SELECT {c2('n')} AS v FROM (SELECT sum(n) AS n FROM c GROUP BY t)), al AS (SELECT {c2('n')} AS v FROM (SELECT sum(n) AS n FROM c)),
counts AS (SELECT CAST(tp.v AS BIGINT) AS tp, CAST(pp.v - tp.v AS BIGINT) AS fp, CAST(tt.v - tp.v AS BIGINT) AS fn, CAST(al.v - pp.v - tt.v + tp.v AS BIGINT) AS tn FROM tp, pp, tt, al)"""


def purity_sql(source: str, p: str, t: str, value: str) -> str:
    return f"WITH c AS (SELECT {p} AS p, {t} AS t, count(*) AS n FROM {source} GROUP BY 1, 2), k AS (SELECT max(n) AS most, sum(n) AS n FROM c GROUP BY p) SELECT round({value}, 6) AS value FROM k"


@query("m_pair_counts", pair_sql(fx.CLUSTERS, "predicted", "truth") + " SELECT * FROM counts")
def pair_counts(spark, sf_dir):
    return m.pair_counts(clusters(spark))


@query("m_rand_index", pair_sql(fx.CLUSTERS, "predicted", "truth") + " SELECT round((tp + tn) / (tp + fp + fn + tn), 6) AS value FROM counts")
def rand_index(spark, sf_dir):
    return m.rand_index(clusters(spark))


@query("m_rand_index_customer", pair_sql("customer", "c_mktsegment", "c_nationkey") + " SELECT round((tp + tn) / (tp + fp + fn + tn), 6) AS value FROM counts")
def rand_index_customer(spark, sf_dir):
    return m.rand_index(table(spark, sf_dir, "customer"), "c_mktsegment", "c_nationkey")


@query("m_purity", purity_sql(fx.CLUSTERS, "predicted", "truth", "avg(most / n)"))
def purity(spark, sf_dir):
    return m.purity(clusters(spark))


@query("m_purity_weighted", purity_sql(fx.CLUSTERS, "predicted", "truth", "sum(most) / sum(n)"))
def purity_weighted(spark, sf_dir):
    return m.purity(clusters(spark), macro=False)


@query("m_purity_customer", purity_sql("customer", "c_mktsegment", "c_nationkey", "avg(most / n)"))
def purity_customer(spark, sf_dir):
    return m.purity(table(spark, sf_dir, "customer"), "c_mktsegment", "c_nationkey")


OVERLAP = "(VALUES ('a', 'x'), ('a', 'y'), ('b', 'x'), ('c', 'y'), ('d', 'z')) v(item, cluster)"
OVERLAP_TRUTH = "(VALUES ('a', 'g'), ('b', 'g'), ('c', 'h'), ('d', 'h')) v(item, cluster)"


@query("m_rand_overlap", f"""
WITH i AS (SELECT DISTINCT item FROM {OVERLAP}),
pr AS (SELECT a.item AS x, b.item AS y FROM i a JOIN i b ON a.item < b.item),
p AS (SELECT DISTINCT a.item AS x, b.item AS y FROM {OVERLAP.replace('v(', 'a(')} JOIN {OVERLAP.replace('v(', 'b(')} ON a.cluster = b.cluster AND a.item < b.item),
t AS (SELECT DISTINCT a.item AS x, b.item AS y FROM {OVERLAP_TRUTH.replace('v(', 'a(')} JOIN {OVERLAP_TRUTH.replace('v(', 'b(')} ON a.cluster = b.cluster AND a.item < b.item)
SELECT round(avg(CASE WHEN (p.x IS NULL) = (t.x IS NULL) THEN 1 ELSE 0 END), 6) AS value FROM pr LEFT JOIN p ON p.x = pr.x AND p.y = pr.y LEFT JOIN t ON t.x = pr.x AND t.y = pr.y""")
def rand_overlap(spark, sf_dir):
    p, t = spark.sql(f"SELECT * FROM {OVERLAP}"), spark.sql(f"SELECT * FROM {OVERLAP_TRUTH}")
    return m.rand_index_overlap(p.select("item"), p, t)


@query("m_type_count", f"SELECT count(DISTINCT t) AS value FROM (SELECT child AS t FROM {fx.EDGES} UNION ALL SELECT parent FROM {fx.EDGES}) WHERE t <> 'Thing'")
def type_count(spark, sf_dir):
    return m.type_count(fx.relation(spark, fx.EDGES))


@query("m_depth", f"WITH RECURSIVE r(t, d) AS (SELECT child, 1 FROM {fx.EDGES} WHERE parent = 'Thing' UNION ALL SELECT e.child, d + 1 FROM r JOIN {fx.EDGES} e ON e.parent = r.t) SELECT CAST(max(d) AS INTEGER) AS value FROM r")
def depth(spark, sf_dir):
    return h.levels(fx.relation(spark, fx.EDGES)).agg(F.max("level").alias("value"))


@query("m_paths", f"""
WITH RECURSIVE r(t, path) AS (SELECT child, child FROM {fx.EDGES} WHERE parent = 'Thing' UNION ALL SELECT e.child, path || '>' || e.child FROM r JOIN {fx.EDGES} e ON e.parent = r.t)
SELECT path FROM r WHERE NOT EXISTS (SELECT 1 FROM {fx.EDGES} e WHERE e.parent = r.t)""")
def complete_paths(spark, sf_dir):
    return m.complete_paths(fx.relation(spark, fx.EDGES)).select(F.col("path_no").alias("path")).distinct()


@query("m_align", f"SELECT c_mktsegment AS type_name, gt_type FROM (SELECT c_mktsegment, CAST(c_nationkey AS VARCHAR) AS gt_type, row_number() OVER (PARTITION BY c_mktsegment ORDER BY count(*) DESC, CAST(c_nationkey AS VARCHAR)) AS k FROM customer GROUP BY c_mktsegment, c_nationkey) WHERE k = 1")
def align(spark, sf_dir):
    c = table(spark, sf_dir, "customer")
    return m.align_types(c.select(F.col("c_mktsegment").alias("type_name"), F.col("c_custkey").alias("table_id")), c.select(F.col("c_custkey").alias("table_id"), F.col("c_nationkey").cast("string").alias("gt_type")))


#: The longest chain of a path whose members are equal to or below the one before, by recursion over positions.
CHAINS = f"""
WITH RECURSIVE t AS (SELECT CAST(path_no AS VARCHAR) AS path_no, pos, gt_type FROM {fx.TREE}), g AS (SELECT child, parent FROM {fx.TREE_TRUTH}),
up(d, a) AS (SELECT child, parent FROM g UNION SELECT up.d, g.parent FROM up JOIN g ON g.child = up.a),
chain(path_no, pos, gt_type, n) AS (SELECT path_no, pos, gt_type, 1 FROM t UNION ALL SELECT t.path_no, t.pos, t.gt_type, n + 1 FROM chain c JOIN t ON t.path_no = c.path_no AND t.pos > c.pos AND (t.gt_type = c.gt_type OR EXISTS (SELECT 1 FROM up WHERE d = t.gt_type AND a = c.gt_type))),
scores AS (SELECT t.path_no, round(max(n) / count(DISTINCT t.pos), 6) AS score, max(n) / count(DISTINCT t.pos) AS exact FROM t JOIN chain USING (path_no) GROUP BY t.path_no)"""


@query("m_tree_score_path", f"{CHAINS} SELECT path_no, score FROM scores")
def tree_score_path(spark, sf_dir):
    rows = fx.relation(spark, fx.TREE)
    return m.tree_scores(rows, fx.relation(spark, fx.TREE_TRUTH)).withColumn("score", F.round("score", 6))


@query("m_tree_score", f"{CHAINS} SELECT round(avg(exact), 6) AS value FROM scores")
def tree_score(spark, sf_dir):
    rows = fx.relation(spark, fx.TREE)
    return m.tree_scores(rows, fx.relation(spark, fx.TREE_TRUTH)).agg(F.round(F.avg("score"), 6).alias("value"))


@query("m_prf", f"""
WITH p AS (SELECT DISTINCT src, dst FROM {fx.RELATIONS} WHERE predicted = 1), t AS (SELECT DISTINCT src, dst FROM {fx.RELATIONS} WHERE truth = 1),
c AS (SELECT (SELECT count(*) FROM p JOIN t USING (src, dst)) AS hit, (SELECT count(*) FROM p) AS np, (SELECT count(*) FROM t) AS nt)
SELECT round(hit / np, 6) AS p, round(hit / nt, 6) AS r, round(2 * hit / (np + nt), 6) AS f1 FROM c""")
def prf(spark, sf_dir):
    rows = fx.relation(spark, fx.RELATIONS)
    return m.precision_recall_f1(rows.where("predicted = 1"), rows.where("truth = 1"), ["src", "dst"])


@query("m_card_acc", f"""
SELECT round(avg(CASE WHEN p.cardinality = t.cardinality THEN 1 ELSE 0 END), 6) AS value FROM {fx.RELATIONS} p JOIN {fx.RELATIONS} t ON p.src = t.src AND p.attr = t.attr AND p.dst = t.dst WHERE p.predicted = 1 AND t.truth = 1""")
def card_acc(spark, sf_dir):
    rows = fx.relation(spark, fx.RELATIONS)
    on = ["src", "attr", "dst"]
    return m.cardinality_accuracy(rows.where("predicted = 1").select(*on, "cardinality"), rows.where("truth = 1").select(*on, "cardinality"), on)


# formulas on printed or literal numbers; the workloads compute their own
sql_query("m_cost_rollup", f"SELECT corpus, stage, CAST(sum(calls) AS BIGINT) AS calls, CAST(sum(milli_usd) AS BIGINT) AS milli_usd FROM {fx.LEDGER} GROUP BY ROLLUP (corpus, stage)")
sql_query("m_best_two", f"SELECT method, config, corpus, CAST(place AS INT) AS place FROM (SELECT method, config, corpus, dense_rank() OVER (PARTITION BY method, corpus ORDER BY score DESC) AS place FROM {fx.TREE_SCORES}) t WHERE place <= 2")
sql_query("m_spread", f"SELECT method, corpus, CAST(max(score) - min(score) AS INT) AS spread FROM {fx.TREE_SCORES} GROUP BY method, corpus")
sql_query("m_gains", f"SELECT a.corpus, a.method AS better, b.method AS base, CAST(a.best - b.best AS INT) AS gain FROM (SELECT method, corpus, max(score) AS best FROM {fx.TREE_SCORES} GROUP BY method, corpus) a JOIN (SELECT method, corpus, max(score) AS best FROM {fx.TREE_SCORES} GROUP BY method, corpus) b ON a.corpus = b.corpus AND a.best > b.best")
sql_query("m_gains_same", f"SELECT a.corpus, a.config, CAST(a.score - b.score AS INT) AS gain FROM {fx.TREE_SCORES} a JOIN {fx.TREE_SCORES} b ON a.corpus = b.corpus AND a.config = b.config WHERE a.method = 'path-first' AND b.method = 'type-then-taxonomy'")
sql_query("m_slope", "SELECT round(regr_slope(ln(t), ln(n)), 6) AS value FROM (SELECT * FROM (VALUES (1000, 10.0), (2000, 21.0), (5000, 52.0), (10000, 110.0)) AS v(n, t)) s")
sql_query("g_runs_mean", "SELECT event_type AS run, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS dev FROM {events} GROUP BY event_type")

# --- relationships and cardinalities ----------------------------------------------------------------------------------

CARD = "SELECT CASE WHEN o > 1 AND b > 1 THEN 'm:n' ELSE (CASE WHEN b > 1 THEN 'n' ELSE '1' END) || ':' || (CASE WHEN o > 1 THEN 'n' ELSE '1' END) END AS cardinality FROM (SELECT max(n) AS o FROM (SELECT count(*) AS n FROM p GROUP BY a)), (SELECT max(n) AS b FROM (SELECT count(*) AS n FROM p GROUP BY b))"
JOINS = {
    "customer_nation": ("customer", "c_custkey", "c_nationkey"), "orders_customer": ("orders", "o_orderkey", "o_custkey"), "nation_region": ("nation", "n_nationkey", "n_regionkey"), "supplier_nation": ("supplier", "s_suppkey", "s_nationkey"),
    "part_supplier": ("lineitem", "l_partkey", "l_suppkey"), "region_nation": ("nation", "n_regionkey", "n_nationkey"), "label_document": ("labels", "doc_id", "doc_id + 0"),
}
for name, (source, a, b) in JOINS.items():

    @query(f"p_card_exact_{name}", f"WITH p AS (SELECT DISTINCT {a} AS a, {b} AS b FROM {source}) {CARD}")
    def card_exact(spark, sf_dir, source=source, a=a, b=b):
        return s.exact_cardinality(table(spark, sf_dir, source).select(F.expr(a).alias("a"), F.expr(b).alias("b")), "a", "b")


@query("p_card_rule", f"""
SELECT rel, CASE WHEN uniq_pct IS NULL OR null_pct IS NULL THEN NULL WHEN multi_pct >= 50 AND uniq_pct >= 80 THEN '1:n' WHEN multi_pct >= 50 THEN 'm:n' WHEN uniq_pct >= 80 THEN '1:1' ELSE 'n:1' END AS cardinality FROM {fx.CARD_STATS}""")
def card_rule(spark, sf_dir):
    rows = fx.relation(spark, fx.CARD_STATS)
    return rows.select("rel", s.rule_cardinality(F.col("uniq_pct") / 100, F.col("multi_pct") / 100, F.col("null_pct") / 100).alias("cardinality"))


@query("p_descendants", f"WITH RECURSIVE r(t, top) AS (SELECT child, child FROM {fx.EDGES} WHERE parent = 'Thing' UNION SELECT e.child, top FROM r JOIN {fx.EDGES} e ON e.parent = r.t) SELECT top, t AS candidate FROM r")
def descendants(spark, sf_dir):
    edges = fx.relation(spark, fx.EDGES)
    tops = h.top_level(edges).withColumnRenamed("type_name", "top")
    below = h.reach(edges).join(tops, F.col("ancestor") == F.col("top")).select("top", F.col("descendant").alias("candidate"))
    return below.union(tops.select("top", F.col("top").alias("candidate")))
