"""The path-first method's steps over whole corpora, every answer through the completer protocol."""

from __future__ import annotations

from pyspark.sql import functions as F

from schemaloom.operators import asks, attributes, relations
from schemaloom.operators import hierarchy as h
from schemaloom.operators.lexicon import DENOTES, KINDS, USUAL, Lexicon
from schemaloom.plans import runs
from schemaloom.plans.registry import query, table, values
from schemaloom.sources import corpora
from schemaloom.sources import fragments as fr
from schemaloom.sources.shared import cut, shared_path

NOISE, WRONG = runs.NOISE, runs.WRONG
HEADERS = f"SELECT concat_ws('_', f.base, k, l.variant) AS table_id, l.header FROM ({fr.FRAGMENTS_SQL}) f JOIN {corpora.layout_sql(corpora.WEB)} ON l.base = f.base"

# --- first step -------------------------------------------------------------------------------------------------------


#: What users said and what was answered next, in the conversations given.
TURNS = "SELECT CONCAT_WS('.', u.conv_id, u.turn) AS ask_id, u.conv_id, u.turn, u.text AS prompt, a.text FROM {c} u JOIN {c} a ON a.conv_id = u.conv_id AND a.turn = u.turn + 1 WHERE u.role = 'user' AND a.role = 'assistant' AND u.text IS NOT NULL AND a.text IS NOT NULL"


@query("g_replay", f"SELECT ask_id, first_value(text) OVER (PARTITION BY prompt ORDER BY conv_id, turn, text) AS text FROM ({TURNS.format(c='conversations')})")
def replay(spark, sf_dir):
    """Answers that were given before, found again by their prompts' digests; of one prompt's several answers the first.
    They lie in the cache that asks are held against, so that none is asked anew."""
    turns = spark.sql(TURNS, c=table(spark, sf_dir, "conversations"))
    given = turns.groupBy(F.md5("prompt").alias("digest")).agg(F.min(F.struct("conv_id", "turn", "text"))["text"].alias("text"))
    cache = shared_path(spark, "replayed")
    given.write.parquet(cache)
    return asks.ask(turns.select("ask_id", "prompt"), asks.ReplayCompleter({}), cache)


PATHS = asks.paths_sql(fr.REPOSITORY_SQL, NOISE)
for constraint in asks.CONSTRAINTS:

    @query(f"p_constraint_{constraint}", f"SELECT table_id, array_to_string(p, '>') AS path FROM ({asks.paths_sql(fr.REPOSITORY_SQL, NOISE, constraint)})")
    def constrained(spark, sf_dir, constraint=constraint):
        return runs.types(spark, sf_dir, "web", constraint)[0].select("table_id", F.array_join("path", ">").alias("path"))


@query("p_table_paths", f"SELECT table_id, 1 AS path_no, array_to_string(p, '>') AS path FROM ({PATHS})")
def table_paths(spark, sf_dir):
    return runs.types(spark, sf_dir, "web")[0].select("table_id", "path_no", F.array_join("path", ">").alias("path"))


@query("g_rejects", f"SELECT table_id FROM ({fr.REPOSITORY_SQL}) WHERE table_id NOT IN (SELECT table_id FROM ({PATHS}))")
def rejects(spark, sf_dir):
    """Tables whose answers stayed malformed after three attempts."""
    return runs.types(spark, sf_dir, "web")[2].select("table_id")


@query("g_lexicon", f"WITH {asks.step1_sql(fr.REPOSITORY_SQL, HEADERS, NOISE, WRONG)} SELECT p.child, p.parent, CASE WHEN k.child IS NULL THEN 'no' ELSE 'yes' END AS verdict FROM pruned p LEFT JOIN kept k ON k.child = p.child AND k.parent = p.parent WHERE p.parent <> 'Thing'")
def lexicon_verdicts(spark, sf_dir):
    """The word lists' verdicts on the merged edges of the web corpus."""
    paths = runs.types(spark, sf_dir, "web")[0]
    edges = h.prune_inverse(h.prune_self_loops(h.merge_edges(h.path_edges(paths))))
    return asks.verdicts(cut(edges), paths, runs.tables(spark, sf_dir, "web"), runs.lexicon())


@query("p_step1", f"WITH {asks.step1_sql(fr.REPOSITORY_SQL, HEADERS, NOISE, WRONG)} SELECT child, parent, weight FROM edges")
def step1(spark, sf_dir):
    return runs.types(spark, sf_dir, "web")[1]


@query("p_step1_unverified", f"WITH {asks.step1_sql(fr.REPOSITORY_SQL, HEADERS, NOISE, WRONG, False)} SELECT child, parent, weight FROM edges")
def step1_unverified(spark, sf_dir):
    return runs.types(spark, sf_dir, "web", verify=False)[1]


# --- second step ------------------------------------------------------------------------------------------------------

WEB_COLUMNS = corpora.columns_sql("web")
USUAL_SQL = "CASE {h} " + " ".join(f"WHEN '{a}' THEN '{b}'" for a, b in USUAL.items()) + " ELSE {h} END"
ROLE_SQL = "array_to_string(list_transform(string_split(" + USUAL_SQL.format(h="header") + ", '_'), lambda x: upper(substr(x, 1, 1)) || substr(x, 2)), '')"
KIND_SQL = "CASE kind " + " ".join(f"WHEN '{k}' THEN [{', '.join(repr(x) for x in v)}]" for k, v in KINDS.items()) + " END"
strike = asks.strike_sql
COLUMN_PATHS = f"""SELECT col, n AS path_no, CASE WHEN n = 0 THEN p ELSE list_concat(list_slice(p, 1, len(p) - 1), ['Code']) END AS p FROM (
  SELECT col, unnest(CASE WHEN second THEN [0, 1] ELSE [0] END) AS n, p FROM (
    SELECT col, {strike('col', 'second', NOISE)} AS second, CASE WHEN {strike('col', 'early', NOISE)} THEN {KIND_SQL} ELSE list_concat({KIND_SQL}, [{ROLE_SQL}]) END AS p FROM ({WEB_COLUMNS})))"""


@query("p_column_paths", f"SELECT col, path_no, array_to_string(p, '>') AS path FROM ({COLUMN_PATHS})")
def column_paths(spark, sf_dir):
    return runs.attributes_of(spark, sf_dir, "web")["paths"].select("col", "path_no", F.array_join("path", ">").alias("path"))


COLUMN_EDGES = f"SELECT child, parent, count(*) AS weight FROM (SELECT DISTINCT col, path_no, ts[k + 1] AS child, ts[k] AS parent FROM (SELECT col, path_no, ts, unnest(range(1, len(ts))) AS k FROM (SELECT col, path_no, list_concat(['Thing'], p) AS ts FROM ({COLUMN_PATHS})))) GROUP BY 1, 2"


@query("p_column_hierarchy", COLUMN_EDGES)
def column_hierarchy(spark, sf_dir):
    return runs.attributes_of(spark, sf_dir, "web")["hierarchy"]


#: semantic types; a WITH RECURSIVE list
SEMANTIC = f"""
ce AS MATERIALIZED ({COLUMN_EDGES}), cp AS MATERIALIZED ({COLUMN_PATHS}),
ways(d, a) AS (SELECT child, parent FROM ce UNION SELECT w.d, e.parent FROM ways w JOIN ce e ON e.child = w.a),
deep(t, l) AS (SELECT child, 1 FROM ce WHERE parent = 'Thing' UNION SELECT e.child, l + 1 FROM deep JOIN ce e ON e.parent = t),
lv AS (SELECT t, max(l) AS l FROM deep GROUP BY t),
leaves AS (SELECT DISTINCT col, p[len(p)] AS t FROM cp), wanted AS (SELECT col, count(*) AS n FROM leaves GROUP BY col),
up AS (SELECT DISTINCT d, a FROM ways UNION SELECT child, child FROM ce UNION SELECT 'Thing', 'Thing'),
common AS (SELECT col, a, count(*) AS m FROM leaves JOIN up ON d = t GROUP BY 1, 2),
semantic AS (SELECT col, a AS sem_type FROM (SELECT c.col, a, row_number() OVER (PARTITION BY c.col ORDER BY coalesce(l, 0) DESC, a) AS r FROM common c JOIN wanted w ON w.col = c.col AND m = n LEFT JOIN lv ON lv.t = a) WHERE r = 1),
cols AS MATERIALIZED ({WEB_COLUMNS}), owner AS (SELECT table_id, p[len(p)] AS type_name FROM ({PATHS})),
grouped AS (SELECT DISTINCT type_name, sem_type, cols.col, header, kind FROM owner JOIN cols USING (table_id) JOIN semantic USING (col)),
named AS (SELECT *, lower(CASE WHEN {strike("concat_ws('|', type_name, col)", 'raw', 50)} THEN header ELSE {USUAL_SQL.format(h='header')} END) AS name FROM grouped),
resolved AS (SELECT *, CASE WHEN {strike("concat_ws('|', type_name, sem_type, '0', name)", 'unmerged', NOISE)} THEN name ELSE {USUAL_SQL.format(h='name')} END AS attr_name FROM named)"""


@query("p_semantic_types", f"WITH RECURSIVE {SEMANTIC} SELECT col, sem_type FROM semantic")
def semantic(spark, sf_dir):
    return runs.attributes_of(spark, sf_dir, "web")["semantic"]


@query("p_semantic_groups", f"WITH RECURSIVE {SEMANTIC} SELECT type_name, sem_type, count(*) AS n_columns FROM grouped GROUP BY 1, 2")
def semantic_groups(spark, sf_dir):
    return runs.attributes_of(spark, sf_dir, "web")["groups"].groupBy("type_name", "sem_type").agg(F.count("*").alias("n_columns"))


@query("p_attr_names", f"WITH RECURSIVE {SEMANTIC} SELECT type_name, sem_type, col, name FROM named")
def attr_names(spark, sf_dir):
    return runs.attributes_of(spark, sf_dir, "web")["resolved"].select("type_name", "sem_type", "col", "name")


@query("p_resolve", f"WITH RECURSIVE {SEMANTIC} SELECT type_name, sem_type, col, attr_name FROM resolved")
def resolve(spark, sf_dir):
    return runs.attributes_of(spark, sf_dir, "web")["resolved"].select("type_name", "sem_type", "col", "attr_name")


@query("p_local_attrs", f"WITH RECURSIVE {SEMANTIC} SELECT DISTINCT type_name, attr_name FROM resolved")
def local_attrs(spark, sf_dir):
    return runs.attributes_of(spark, sf_dir, "web")["local"]


@query("p_attr_domain", f"""WITH RECURSIVE {SEMANTIC},
kinds AS (SELECT type_name, attr_name, kind, row_number() OVER (PARTITION BY type_name, attr_name ORDER BY count(*) DESC, kind) AS r FROM resolved GROUP BY type_name, attr_name, kind),
{asks.step1_sql(fr.REPOSITORY_SQL, HEADERS, NOISE, WRONG)}
SELECT k.type_name, k.attr_name, CASE WHEN kind = 'entity' AND e.child IS NOT NULL THEN e.child ELSE kind END AS domain FROM kinds k LEFT JOIN (SELECT DISTINCT child FROM edges) e ON lower(e.child) = lower(regexp_replace(replace(k.attr_name, '_', ''), '([^s])s$', '\\1')) WHERE r = 1""")
def attr_domain(spark, sf_dir):
    return attributes.domains(runs.attributes_of(spark, sf_dir, "web")["resolved"], runs.columns(spark, sf_dir, "web"), runs.types(spark, sf_dir, "web")[1])


@query("p_unify_siblings", f"""WITH RECURSIVE {SEMANTIC}, {asks.step1_sql(fr.REPOSITORY_SQL, HEADERS, NOISE, WRONG)},
held AS (SELECT DISTINCT l.type_name, attr_name AS name, coalesce(e.parent, 'Thing') AS owner FROM resolved l LEFT JOIN (SELECT child, parent FROM edges WHERE parent <> 'Thing') e ON e.child = l.type_name)
SELECT DISTINCT type_name, CASE WHEN {strike("concat_ws('|', owner, '0', name)", 'unmerged', NOISE)} THEN name ELSE {USUAL_SQL.format(h='name')} END AS attr_name FROM held""")
def unify(spark, sf_dir):
    """Names of one meaning among sibling types made one before they are counted."""
    found = runs.attributes_of(spark, sf_dir, "web")
    return attributes.unify_across(found["local"], runs.types(spark, sf_dir, "web")[1], runs.lexicon())


@query("p_step2")
def step2(spark, sf_dir):
    """(owner, attr_name, n_columns): the attributes of the web corpus at the types that own them after promotion."""
    return runs.attributes_of(spark, sf_dir, "web")["clusters"].groupBy("owner", "attr_name").agg(F.count("*").alias("n_columns"))


@query("g_column_context", f"""
SELECT table_id, count(*) AS n_columns FROM ({WEB_COLUMNS}) GROUP BY table_id""")
def column_context(spark, sf_dir):
    """Every column with the rows around it; counted for each table."""
    held = attributes.column_context(runs.columns(spark, sf_dir, "web"), runs.tables(spark, sf_dir, "web"))
    return held.where("size(around) > 0").groupBy("table_id").agg(F.count("*").alias("n_columns"))


# --- third step, on the wide corpus with its true attributes ----------------------------------------------------------

WIDE_COLUMNS = corpora.columns_sql("wide")
OWNED = f"SELECT col, table_id, base, k, kind, rho_null, rho_multi, rho_uniq, \"column\", {USUAL_SQL.format(h='header')} AS attr_name, string_split(path, '>')[-1] AS owner FROM ({WIDE_COLUMNS})"
ENTITY = f"""o AS MATERIALIZED ({OWNED}), ent AS (SELECT owner, attr_name FROM o GROUP BY 1, 2 HAVING 2 * count(*) FILTER (kind = 'entity') > count(*) AND attr_name <> 'name')"""
DENOTED = values([(a, t, d) for a, (t, d) in DENOTES.items()], "attr_name, best_top, best")
TOPS = f"tops AS (SELECT DISTINCT string_split(path, '>')[1] AS top FROM ({corpora.fragments_sql(corpora.WIDE)}))"
PICKED = f"""{ENTITY}, {TOPS},
ranked AS (SELECT owner, e.attr_name, best_top, best, top, row_number() OVER (PARTITION BY owner, e.attr_name ORDER BY CASE WHEN top = best_top THEN 0 ELSE 1 END, top) - 1 AS r, count(*) OVER (PARTITION BY owner, e.attr_name) AS n,
  {strike("concat_ws('|', owner, e.attr_name)", 'top', NOISE)} AS hit FROM ent e LEFT JOIN (SELECT * FROM {DENOTED}) dn ON dn.attr_name = e.attr_name, tops),
placed AS (SELECT owner, attr_name, best_top, best, top, CASE WHEN hit AND n > 1 THEN (r + n - 1) % n ELSE r END AS place FROM ranked),
picked AS (SELECT owner, attr_name, best AS dst FROM placed WHERE place < 3 AND top = best_top)"""

def clusters(spark, sf_dir):
    """(col, attr_name, owner) by the true types and headers of the wide corpus."""
    usual = F.create_map(*(F.lit(x) for pair in USUAL.items() for x in pair))
    name = F.coalesce(F.try_element_at(usual, F.col("header")), F.col("header"))
    return runs.columns(spark, sf_dir, "wide").select("col", name.alias("attr_name"), F.element_at(F.split("path", ">"), -1).alias("owner"))


def wide_edges(spark, sf_dir):
    make = lambda: cut(h.merge_edges(h.path_edges(runs.tables(spark, sf_dir, "wide").select("table_id", F.lit(1).alias("path_no"), F.split("path", ">").alias("path")))))
    return runs.once(spark, ("wide edges", sf_dir), make)


def wide_values(spark, sf_dir):
    make = lambda: cut(relations.attribute_values(relations.entity_attributes(clusters(spark, sf_dir), runs.columns(spark, sf_dir, "wide")), runs.columns(spark, sf_dir, "wide")))
    return runs.once(spark, ("wide values", sf_dir), make)


@query("p_entity_attrs", f"WITH {ENTITY} SELECT owner, attr_name FROM ent")
def entity_attrs(spark, sf_dir):
    return relations.entity_attributes(clusters(spark, sf_dir), runs.columns(spark, sf_dir, "wide")).select("owner", "attr_name").distinct()


CELLS_WIDE = " UNION ALL ".join(f"SELECT '{x.name}' AS base, '{c}' AS \"column\", CAST({c} AS VARCHAR) AS value FROM ({x.twin()}) WHERE trim(CAST({c} AS VARCHAR)) <> ''" for x in corpora.WIDE for c, _, _ in x.columns)


@query("p_attr_values", f"""WITH {ENTITY}, src AS (SELECT DISTINCT e.owner, e.attr_name, o.base, o."column" FROM ent e JOIN o ON o.owner = e.owner AND o.attr_name = e.attr_name),
v AS (SELECT DISTINCT owner, attr_name, value FROM src JOIN ({CELLS_WIDE}) c ON c.base = src.base AND c."column" = src."column")
SELECT owner, attr_name, value FROM (SELECT *, row_number() OVER (PARTITION BY owner, attr_name ORDER BY md5(concat_ws('|', '0', value))) AS r FROM v) WHERE r <= 5""")
def attr_values(spark, sf_dir):
    return wide_values(spark, sf_dir).select("owner", "attr_name", F.explode("values").alias("value"))


def ranked_tops(spark, sf_dir):
    make = lambda: cut(relations.top_k_types(wide_values(spark, sf_dir), wide_edges(spark, sf_dir), runs.lexicon()))
    return runs.once(spark, ("wide tops", sf_dir), make)


@query("p_topk_types", f"WITH {PICKED} SELECT owner, attr_name, CAST(place AS INTEGER) AS place, top FROM placed WHERE place < 3")
def topk_types(spark, sf_dir):
    return ranked_tops(spark, sf_dir)


for refine in ("union", "per_top"):

    @query(f"p_select_type_{refine}", f"WITH {PICKED} SELECT owner, attr_name, dst FROM picked")
    def select_type(spark, sf_dir, refine=refine):
        found = relations.candidates(ranked_tops(spark, sf_dir), wide_edges(spark, sf_dir))
        return relations.select_type(wide_values(spark, sf_dir), cut(found), Lexicon(), refine)


def related(spark, sf_dir):
    links = select_type(spark, sf_dir, "union").where("owner <> dst").withColumnRenamed("owner", "src")
    return runs.once(spark, ("wide links", sf_dir), lambda: cut(links))


@query("p_predicate", f"WITH {PICKED} SELECT owner, attr_name, dst, 'has ' || attr_name AS predicate FROM picked WHERE owner <> dst")
def predicate(spark, sf_dir):
    return relations.predicates(related(spark, sf_dir).withColumnRenamed("src", "owner"), runs.lexicon())


@query("p_step3_rel", f"WITH {PICKED} SELECT owner AS src, attr_name, dst, 'has ' || attr_name AS predicate FROM picked WHERE owner <> dst")
def step3_rel(spark, sf_dir):
    class Sure(Lexicon):  # the first ask errs at its rate, the second doesn't
        def strike(self, key, kind, rate=None):
            return kind == "top" and super().strike(key, kind, rate)

    return relations.infer_relationships(clusters(spark, sf_dir), runs.columns(spark, sf_dir, "wide"), wide_edges(spark, sf_dir), Sure(NOISE))


EVIDENCE = f"""{PICKED}, rel AS (SELECT owner AS src, attr_name, dst FROM picked WHERE owner <> dst),
tab AS (SELECT src, r.attr_name, dst, rho_null, rho_multi, rho_uniq, row_number() OVER (PARTITION BY src, r.attr_name, dst ORDER BY md5(concat_ws('|', '0', table_id)), col) AS n FROM rel r JOIN o ON o.owner = src AND o.attr_name = r.attr_name),
ev AS (SELECT src, attr_name, dst, count(*) AS tables, round(avg(coalesce(rho_null, 0)), 6) AS "null", round(avg(coalesce(rho_multi, 0)), 6) AS multi, round(avg(rho_uniq), 6) AS uniq FROM tab WHERE n <= 5 GROUP BY 1, 2, 3)"""


@query("p_evidence", f'WITH {EVIDENCE} SELECT src, attr_name, dst, tables, "null" AS rho_null, multi AS rho_multi, uniq AS rho_uniq FROM ev')
def evidence(spark, sf_dir):
    found = relations.evidence(related(spark, sf_dir), clusters(spark, sf_dir), runs.columns(spark, sf_dir, "wide"))
    return found.select("src", "attr_name", "dst", "tables", F.col("null").alias("rho_null"), F.col("multi").alias("rho_multi"), F.col("uniq").alias("rho_uniq"))


CARD_RULE = "CASE WHEN multi >= 0.5 THEN CASE WHEN uniq >= 0.8 THEN '1:n' ELSE 'm:n' END WHEN uniq >= 0.8 THEN '1:1' ELSE 'n:1' END"


def carded(spark, sf_dir, shown):
    on, of, cols = related(spark, sf_dir), clusters(spark, sf_dir), runs.columns(spark, sf_dir, "wide")
    return relations.infer_cardinality(on, relations.evidence(on, of, cols), relations.evidence_rows(on, of, cols), runs.lexicon(), shown)


@query("p_cardinality", f"WITH {EVIDENCE} SELECT src, attr_name, dst, {CARD_RULE} AS cardinality FROM ev")
def cardinality(spark, sf_dir):
    return carded(spark, sf_dir, "both")


@query("p_card_stats_only", f"WITH {EVIDENCE} SELECT src, attr_name, dst, {CARD_RULE} AS cardinality FROM ev")
def card_stats_only(spark, sf_dir):
    return carded(spark, sf_dir, "stats")


ROWS = f"""{EVIDENCE}, src AS (SELECT DISTINCT src, r.attr_name, dst, o.base, o.k, o."column", o.table_id, o.col FROM rel r JOIN o ON o.owner = r.src AND o.attr_name = r.attr_name),
cw AS ({" UNION ALL ".join(f"SELECT DISTINCT '{x.name}' AS base, k, '{c}' AS col_, CAST({c} AS VARCHAR) AS value FROM ({x.twin()}) WHERE trim(CAST({c} AS VARCHAR)) <> ''" for x in corpora.WIDE for c, _, _ in x.columns)}),
five AS (SELECT * FROM (SELECT base, k, col_, value, row_number() OVER (PARTITION BY base, k, col_ ORDER BY md5(concat_ws('|', '0', value))) AS n FROM cw) WHERE n <= 5),
shown AS (SELECT src, attr_name, dst, value, row_number() OVER (PARTITION BY src, attr_name, dst ORDER BY md5(concat_ws('|', '0', value, table_id))) AS n FROM src JOIN five ON five.base = src.base AND five.k = src.k AND five.col_ = src."column")"""


@query("p_evidence_rows", f"WITH {ROWS} SELECT src, attr_name, dst, string_agg(value, '|' ORDER BY n) AS shown FROM shown WHERE n <= 5 GROUP BY 1, 2, 3")
def evidence_rows(spark, sf_dir):
    found = relations.evidence_rows(related(spark, sf_dir), clusters(spark, sf_dir), runs.columns(spark, sf_dir, "wide"))
    return found.select("src", "attr_name", "dst", F.array_join("rows", "|").alias("shown"))


@query("p_card_rows_only", f"WITH {ROWS} SELECT src, attr_name, dst, CASE WHEN count(DISTINCT value) / count(*) >= 0.8 THEN '1:1' ELSE 'n:1' END AS cardinality FROM shown WHERE n <= 5 GROUP BY 1, 2, 3")
def card_rows_only(spark, sf_dir):
    return carded(spark, sf_dir, "rows")
