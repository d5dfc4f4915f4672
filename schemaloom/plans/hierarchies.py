"""Path-first types and hierarchy, on the worked examples."""

from __future__ import annotations

from pyspark.sql import functions as F

from schemaloom.operators import hierarchy as h
from schemaloom.plans.registry import query, table
from schemaloom.sources import fixtures as fx

STEPS = f"""
p AS (SELECT table_id, path_no, string_split('Thing>' || path, '>') AS ts FROM {fx.PATHS}),
steps AS (SELECT DISTINCT table_id, path_no, ts[k + 1] AS child, ts[k] AS parent FROM (SELECT *, unnest(range(1, len(ts))) AS k FROM p))"""
MERGED = f"{STEPS}, merged AS (SELECT child, parent, count(*) AS weight FROM steps GROUP BY child, parent)"
PRUNED = f"""{MERGED}, pruned AS (
  SELECT child, parent, weight FROM (SELECT *, row_number() OVER (PARTITION BY least(child, parent), greatest(child, parent) ORDER BY weight DESC, parent) AS k FROM merged WHERE child <> parent) WHERE k = 1)"""
VERIFIED = f"{PRUNED}, verified AS (SELECT p.* FROM pruned p WHERE NOT EXISTS (SELECT 1 FROM {fx.VERDICTS} v WHERE v.child = p.child AND v.parent = p.parent AND lower(verdict) = 'no'))"
REACH = f"""RECURSIVE e AS (SELECT * FROM {fx.EDGES}), r(descendant, ancestor, dist) AS (
  SELECT child, parent, 1 FROM e UNION SELECT r.descendant, e.parent, r.dist + 1 FROM r JOIN e ON r.ancestor = e.child)"""


def merged(spark):
    return h.merge_edges(h.path_edges(fx.paths(spark)))


def pruned(spark):
    return h.prune_inverse(h.prune_self_loops(merged(spark)))


def verified(spark):
    return h.verify_edges(pruned(spark), fx.relation(spark, fx.VERDICTS))


def edges(spark):
    return fx.relation(spark, fx.EDGES)


#: Answers that name a path, written out for each part.
PART_ANSWERS = "SELECT CAST(p_partkey AS STRING) AS ask_id, concat('It lists ', p_name, '. Thing -> Product -> Part -> ', p_type, ' -> ', p_name, ' -> ', p_brand) AS text FROM {part}"


@query("g_extract_paths", f"""
SELECT ask_id, array_to_string(list_filter(best, lambda t: t <> 'Thing')[1:5], '>') AS path FROM (
  SELECT ask_id, list_reduce(list_transform(found, lambda x: list_transform(string_split(x, '->'), lambda t: trim(t))), lambda a, b: CASE WHEN len(b) > len(a) THEN b ELSE a END) AS best
  FROM (SELECT ask_id, regexp_extract_all(text, '[A-Za-z][A-Za-z ]*(?:-> *[A-Za-z][A-Za-z ]*)+') AS found FROM ({PART_ANSWERS.replace('{part}', 'part')})) WHERE len(found) > 0)""")
def extract_paths(spark, sf_dir):
    found = spark.sql(PART_ANSWERS, part=table(spark, sf_dir, "part")).withColumn("path", h.extract_path(F.col("text")))
    return found.where("path IS NOT NULL").select("ask_id", F.array_join("path", ">").alias("path"))


@query("g_malformed", "SELECT page_id, len(ts) <> len(list_distinct(ts)) AS malformed FROM (SELECT page_id, string_split(url, '/') AS ts FROM pages)")
def malformed(spark, sf_dir):
    """Paths of web addresses that name a step twice."""
    return table(spark, sf_dir, "pages").select("page_id", h.malformed(F.split("url", "/")).alias("malformed"))


@query("p_align_names", f"""
SELECT name, regexp_replace(array_to_string(list_transform(string_split(trim(regexp_replace(name, '[ _-]+', ' ', 'g')), ' '), lambda w: upper(w[1:1]) || lower(w[2:])), ''), '([^s])s$', '\\1') AS aligned FROM {fx.SPELLINGS}""")
def align_names(spark, sf_dir):
    return fx.relation(spark, fx.SPELLINGS).select("name", h.align_name(F.col("name")).alias("aligned"))


@query("p_path_edges", f"WITH {STEPS} SELECT table_id, path_no, child, parent FROM steps")
def path_edges(spark, sf_dir):
    return h.path_edges(fx.paths(spark))


@query("p_edge_weights", f"WITH {MERGED} SELECT * FROM merged")
def edge_weights(spark, sf_dir):
    return merged(spark)


@query("p_edge_weights_by_table", f"WITH {STEPS} SELECT child, parent, count(DISTINCT table_id) AS weight FROM steps GROUP BY child, parent")
def edge_weights_by_table(spark, sf_dir):
    return h.merge_edges(h.path_edges(fx.paths(spark)), "table")


@query("p_prune_self", f"WITH {MERGED} SELECT * FROM merged WHERE child <> parent")
def prune_self(spark, sf_dir):
    return h.prune_self_loops(merged(spark))


@query("p_prune_inverse", f"WITH {PRUNED} SELECT * FROM pruned")
def prune_inverse(spark, sf_dir):
    return pruned(spark)


@query("p_verify", f"WITH {VERIFIED} SELECT * FROM verified")
def verify(spark, sf_dir):
    return verified(spark)


@query("p_noverify", f"WITH {PRUNED} SELECT * FROM pruned")
def noverify(spark, sf_dir):
    return pruned(spark)


@query("p_acyclic")
def acyclic(spark, sf_dir):
    return h.attach_orphans(h.break_cycles(verified(spark)))


@query("p_top_level", f"SELECT child AS type_name FROM {fx.EDGES} WHERE parent = 'Thing'")
def top_level(spark, sf_dir):
    return h.top_level(edges(spark))


@query("p_closure", f"WITH {REACH} SELECT descendant, ancestor, min(dist)::INTEGER AS dist FROM r GROUP BY descendant, ancestor")
def closure(spark, sf_dir):
    return h.reach(edges(spark))


@query("s_recursive", f"WITH {REACH} SELECT descendant, ancestor, min(dist)::INTEGER AS dist FROM r GROUP BY descendant, ancestor")
def recursive(spark, sf_dir):
    text = f"WITH RECURSIVE r(descendant, ancestor, dist) AS (SELECT child, parent, 1 FROM {fx.EDGES} UNION ALL SELECT r.descendant, e.parent, r.dist + 1 FROM r JOIN {fx.EDGES} e ON r.ancestor = e.child) SELECT descendant, ancestor, min(dist) AS dist FROM r GROUP BY descendant, ancestor"
    return spark.sql(text)


@query("s_levels", f"WITH {REACH} SELECT descendant AS type_name, max(dist)::INTEGER AS level FROM r WHERE ancestor = 'Thing' GROUP BY descendant")
def levels(spark, sf_dir):
    return h.levels(edges(spark))


@query("s_cycle", f"WITH {REACH} SELECT count(*) AS on_cycles FROM r WHERE descendant = ancestor")
def cycle(spark, sf_dir):
    return h.reach(edges(spark)).where("descendant = ancestor").agg(F.count("*").alias("on_cycles"))


@query("p_leaf_types", f"SELECT DISTINCT list_last(string_split(path, '>')) AS type_name, table_id FROM {fx.PATHS}")
def leaf_types(spark, sf_dir):
    return h.leaf_types(fx.paths(spark))


@query("p_type_tables", f"""
WITH {REACH}, leaf AS (SELECT DISTINCT list_last(string_split(path, '>')) AS type_name, table_id FROM {fx.PATHS})
SELECT type_name, table_id FROM leaf UNION SELECT ancestor, table_id FROM leaf JOIN r ON r.descendant = leaf.type_name WHERE ancestor <> 'Thing'""")
def type_tables(spark, sf_dir):
    return h.type_tables(fx.paths(spark), edges(spark))


@query("p_lca", f"""
WITH {REACH}, items AS (SELECT * FROM (VALUES ('c1', 'Soloist'), ('c1', 'Band'), ('c2', 'Country'), ('c3', 'Country'), ('c3', 'Concert'), ('c4', 'Person'), ('c4', 'Soloist')) v(item, type_name)),
up AS (SELECT descendant, ancestor FROM r UNION SELECT child, child FROM e UNION SELECT parent, parent FROM e),
lv AS (SELECT descendant AS t, max(dist) AS level FROM r WHERE ancestor = 'Thing' GROUP BY descendant),
c AS (SELECT item, ancestor FROM items JOIN up ON type_name = descendant GROUP BY item, ancestor HAVING count(*) = (SELECT count(*) FROM items i WHERE i.item = items.item))
SELECT item, type_name FROM (SELECT item, ancestor AS type_name, row_number() OVER (PARTITION BY item ORDER BY coalesce(level, 0) DESC, ancestor) AS k FROM c LEFT JOIN lv ON t = ancestor) WHERE k = 1""")
def lca(spark, sf_dir):
    items = spark.sql("SELECT * FROM (VALUES ('c1', 'Soloist'), ('c1', 'Band'), ('c2', 'Country'), ('c3', 'Country'), ('c3', 'Concert'), ('c4', 'Person'), ('c4', 'Soloist')) v(item, type_name)")
    return h.common_ancestor(items, edges(spark))


def promoted(theta: float):
    a = f"(SELECT * FROM {fx.CHILD_ATTRS})"

    @query(f"p_promote_{round(100 * theta)}", f"""
SELECT child AS type_name, attr AS attr_name, FALSE AS inherited FROM {a}
UNION ALL SELECT parent, attr, TRUE FROM {a} x GROUP BY parent, attr HAVING count(DISTINCT child) >= {theta} * (SELECT count(DISTINCT child) FROM {a} y WHERE y.parent = x.parent)""")
    def run(spark, sf_dir):
        rows = fx.relation(spark, fx.CHILD_ATTRS)
        tree = rows.select("child", "parent").distinct().union(rows.select("parent", F.lit(h.ROOT)).distinct()).withColumn("weight", F.lit(1))
        return h.promote(rows.select(F.col("child").alias("type_name"), F.col("attr").alias("attr_name")), tree, theta)


for share in (0.5, 0.9, 1.0):
    promoted(share)
