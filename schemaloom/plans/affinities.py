"""The affinity method and table search over the given tables: every base, every value."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from schemaloom.operators import affinity as a
from schemaloom.operators import postings as po
from schemaloom.plans import runs
from schemaloom.plans.registry import query, table
from schemaloom.sources import corpora
from schemaloom.sources import fragments as fr
from schemaloom.sources.shared import cut

DENSE = runs.DENSE


def cells(spark, sf_dir) -> DataFrame:
    """(item, header, value, n): distinct values of every column of every fragment, with how often they stand there.
    Summed before the shuffle; blank cells are left out."""
    def make():
        held = corpora.cells(spark, sf_dir, corpora.WEB).where("trim(value) <> ''").where(~F.col("column").isin(*DENSE))
        names = spark.createDataFrame([(x.name, c, h) for x in corpora.WEB for c, h, _ in x.columns], "base string, column string, header string")
        counted = held.groupBy("base", "k", "column", "value").agg(F.count("*").alias("n")).join(F.broadcast(names), ["base", "column"])
        return cut(counted.select(F.concat_ws(".", "base", "k", "header").alias("item"), "header", "value", "n"))

    return runs.once(spark, ("cells", sf_dir), make)


def cells_of(spark, sf_dir, base: str, headers: tuple[str, ...] = ()) -> DataFrame:
    """(item, value) of one base's columns, of the given headers or of all, as in cells() but with repeats."""
    source = next(x for x in corpora.WEB if x.name == base)
    kept = replace(source, columns=tuple(x for x in source.columns if x[0] not in DENSE and (not headers or x[1] in headers)))
    names = F.create_map(*(F.lit(x) for c, h, _ in kept.columns for x in (c, h)))
    return corpora.cells(spark, sf_dir, (kept,)).where("trim(value) <> ''").select(F.concat_ws(".", "base", "k", names[F.col("column")]).alias("item"), "value")


CELLS = "SELECT item, header, value, count(*) AS n FROM (" + " UNION ALL ".join(
    f"SELECT concat_ws('.', '{x.name}', k, '{h}') AS item, '{h}' AS header, CAST({c} AS VARCHAR) AS value FROM ({x.twin()})" for x in corpora.WEB for c, h, _ in x.columns if c not in DENSE
) + ") WHERE trim(value) <> '' GROUP BY 1, 2, 3"
WORDS = f"SELECT item, term, CAST(sum(n) AS DOUBLE) AS w FROM (SELECT item, n, unnest(regexp_split_to_array(lower(value), '[^a-z0-9]+')) AS term FROM ({CELLS}) UNION ALL SELECT item, n, unnest(regexp_split_to_array(header, '[^a-z0-9]+')) FROM (SELECT item, header, sum(n) AS n FROM ({CELLS}) GROUP BY 1, 2)) WHERE term <> '' GROUP BY item, term"
GRAMS = f"SELECT item, term, CAST(sum(n) AS DOUBLE) AS w FROM (SELECT item, n, substr(value, k, 3) AS term FROM (SELECT item, value, n, unnest(range(1, length(value) - 1)) AS k FROM ({CELLS}) WHERE length(value) BETWEEN 3 AND 64)) GROUP BY item, term"
VALUES = f"SELECT item, value AS term, 1.0::DOUBLE AS w FROM ({CELLS})"
IDF = f"SELECT t.item, t.term, round(w * i, 6) AS w FROM t JOIN (SELECT term, ln((SELECT count(DISTINCT item) FROM t) / count(*)) AS i FROM t GROUP BY term) USING (term) WHERE w * i <> 0"
COSINE = "u AS (SELECT item, term, w / sqrt(sum(w * w) OVER (PARTITION BY item)) AS w FROM v), pairs AS (SELECT x.item AS a, y.item AS b, round(sum(x.w * y.w) + 1e-9, 4) AS sim FROM u x JOIN u y ON x.term = y.term AND x.item < y.item GROUP BY 1, 2 HAVING sum(x.w * y.w) > 0)"


def words(spark, sf_dir):
    return runs.once(spark, ("words", sf_dir), lambda: cut(a.word_terms(cells(spark, sf_dir))))


@query("a_enc_words", WORDS)
def enc_words(spark, sf_dir):
    return words(spark, sf_dir)


def grams(spark, sf_dir):
    return runs.once(spark, ("grams", sf_dir), lambda: cut(a.gram_terms(cells(spark, sf_dir).where("length(value) <= 64"))))


@query("a_enc_grams", f"SELECT item, count(*) AS terms, CAST(sum(w) AS BIGINT) AS total FROM ({GRAMS}) GROUP BY item")
def enc_grams(spark, sf_dir):
    """Trigrams of names and codes: values of up to 64 characters, as longer ones are texts."""
    return grams(spark, sf_dir).groupBy("item").agg(F.count("*").alias("terms"), F.sum("w").cast("long").alias("total"))


@query("a_enc_proto", f"SELECT item, CAST('0x' || substr(md5(term), 1, 6) AS INTEGER) % 16 AS proto, sum(w) AS w FROM ({GRAMS}) GROUP BY 1, 2")
def enc_proto(spark, sf_dir):
    """Trigram counts dealt to sixteen seeded prototypes, as cluster assignments would be."""
    return a.prototypes(grams(spark, sf_dir), 16).select("item", F.col("term").cast("int").alias("proto"), "w")


@query("a_enc_values", f"SELECT item, count(*) AS terms FROM ({VALUES}) GROUP BY item")
def enc_values(spark, sf_dir):
    return a.value_terms(cells(spark, sf_dir)).groupBy("item").agg(F.count("*").alias("terms"))


@query("a_enc_idf", f"WITH t AS ({WORDS}) {IDF}")
def enc_idf(spark, sf_dir):
    return a.idf(words(spark, sf_dir)).withColumn("w", F.round("w", 6))


VIEWS = f"SELECT item, view, value FROM (SELECT item, view, value, row_number() OVER (PARTITION BY item, view ORDER BY md5(concat_ws('|', view, value))) AS r FROM ({CELLS}), (VALUES (1), (2)) s(view)) WHERE r <= 5"


@query("a_enc_views", VIEWS)
def enc_views(spark, sf_dir):
    """Two seeded samples of five values of each column: two views of one thing."""
    return a.views(cells(spark, sf_dir))


@query("a_view_pairs", f"""WITH t AS (SELECT item, view, value AS term FROM ({VIEWS})), s AS (SELECT item, view, count(*) AS n FROM t GROUP BY 1, 2)
SELECT x.item, round(count(*) / sqrt(max(sx.n) * max(sy.n)), 6) AS sim FROM t x JOIN t y ON x.item = y.item AND x.term = y.term AND x.view = 1 AND y.view = 2 JOIN s sx ON sx.item = x.item AND sx.view = 1 JOIN s sy ON sy.item = x.item AND sy.view = 2 GROUP BY x.item""")
def view_pairs(spark, sf_dir):
    """How alike a column's two views are: the positive pairs that contrastive training would take."""
    v = a.views(cells(spark, sf_dir))
    n = v.groupBy("item").agg(F.count_if(F.col("view") == 1).alias("n1"), F.count_if(F.col("view") == 2).alias("n2"))
    both = v.groupBy("item", "value").agg(F.count("*").alias("c")).where("c = 2").groupBy("item").agg(F.count("*").alias("m"))
    return both.join(n, "item").select("item", F.round(F.col("m") / F.sqrt(F.col("n1") * F.col("n2")), 6).alias("sim"))


@query("a_enc_join", f"""WITH v AS (SELECT item, value FROM ({CELLS})), n AS (SELECT item, count(*) AS n FROM v GROUP BY item)
SELECT x.item AS a, y.item AS b, round(count(*) / max(n.n), 6) AS containment FROM v x JOIN v y ON x.value = y.value AND x.item <> y.item JOIN n ON n.item = x.item GROUP BY 1, 2 HAVING count(*) / max(n.n) > 0.9""")
def enc_join(spark, sf_dir):
    """Pairs of columns of which one's values stand in the other, which training for joins would take."""
    return a.containments(cells(spark, sf_dir).select("item", "value"), 0.9)


def word_lists(spark, sf_dir) -> DataFrame:
    """words() as postings: the words themselves are not written."""
    return runs.tallied(spark, sf_dir, "web")[1]


def column_pairs(spark, sf_dir):
    def make():
        lists = word_lists(spark, sf_dir)
        return cut(po.cosine_pairs(lists, po.norms(lists)).withColumn("sim", F.round(F.col("sim") + 1e-9, 4)))

    return runs.once(spark, ("column pairs", sf_dir), make)


@query("a_pairs_columns", f"WITH v AS ({WORDS}), {COSINE} SELECT a, b, sim FROM pairs")
def pairs_columns(spark, sf_dir):
    return column_pairs(spark, sf_dir)


@query("a_enc_pair", f"WITH v AS ({WORDS}), {COSINE} SELECT a, b FROM pairs WHERE sim >= 0.5 AND split_part(a, '.', -1) = split_part(b, '.', -1)")
def enc_pair(spark, sf_dir):
    """A decision for each two columns instead of vectors: alike in words and of one header."""
    last = lambda c: F.element_at(F.split(c, "\\."), -1)
    return column_pairs(spark, sf_dir).where((F.col("sim") >= 0.5) & (last("a") == last("b"))).select("a", "b")


# --- tables -----------------------------------------------------------------------------------------------------------


def weights(spark, sf_dir, corpus: str = "web") -> DataFrame:
    """(col, table_id, header, kind, weight): every column with its share in its table's vector."""
    return a.subjectness(runs.stats(spark, sf_dir, corpus), "table_id")


PROFILED = f"SELECT * FROM ({corpora.columns_sql('web')})"
SUBJECT = f"""SELECT col, table_id, base, k, "column", header, kind, CASE WHEN total > 0 THEN score / total ELSE 1.0 / n END AS weight FROM (
  SELECT *, sum(score) OVER (PARTITION BY table_id) AS total, count(*) OVER (PARTITION BY table_id) AS n FROM (
    SELECT *, CASE WHEN kind = 'entity' THEN greatest(rho_uniq - rho_null, 0) / sqrt(1 + pos - lead) ELSE 0 END AS score FROM (
      SELECT *, min(CASE WHEN kind = 'entity' THEN pos END) OVER (PARTITION BY table_id) AS lead FROM ({PROFILED}))))"""


@query("a_subjectness", f"SELECT col, round(weight, 6) AS weight FROM ({SUBJECT})")
def subjectness(spark, sf_dir):
    return weights(spark, sf_dir).select("col", F.round("weight", 6).alias("weight"))


def full_tables(spark, sf_dir) -> DataFrame:
    """(item, table_id, weight) of the full variant's columns: items as in cells()."""
    held = weights(spark, sf_dir).where("variant = 'full'")
    return held.select(F.concat_ws(".", "base", "k", "header").alias("item"), F.concat_ws(".", "base", "k").alias("table_id"), "weight")


def table_lists(spark, sf_dir, flat: bool = False) -> DataFrame:
    """Table vectors as postings: the columns' words, rare ones heavier, at unit length, times the column's weight."""
    def make():
        owner = full_tables(spark, sf_dir)
        if flat:
            owner = owner.withColumn("weight", 1 / F.count("*").over(Window.partitionBy("table_id")))
        lists = word_lists(spark, sf_dir)
        rare = po.rare(lists, len(po.items_of(lists)))
        lengths = po.norms(rare)
        return cut(po.grouped(rare, {r.item: (r.table_id, r.weight / lengths[r.item]) for r in owner.collect() if r.item in lengths}))

    return runs.once(spark, ("table lists", sf_dir, flat), make)


OWNER = f"SELECT concat_ws('.', base, k, header) AS item, concat_ws('.', base, k) AS table_id, weight FROM ({SUBJECT}) WHERE table_id LIKE '%_full'"
TABLE_TERMS = "SELECT o.table_id AS item, term, sum(w / norm * {weight}) AS w FROM i JOIN (SELECT item, sqrt(sum(w * w)) AS norm FROM i GROUP BY item) USING (item) JOIN o USING (item) GROUP BY 1, 2"
I = f"t AS MATERIALIZED ({WORDS}), i AS (SELECT t.item, t.term, w * x AS w FROM t JOIN (SELECT term, ln((SELECT count(DISTINCT item) FROM t) / count(*)) AS x FROM t GROUP BY term) USING (term) WHERE w * x <> 0)"
WEIGHTED = f"{I}, o AS ({OWNER}), v AS MATERIALIZED ({TABLE_TERMS.format(weight='weight')})"
FLAT = f"{I}, o AS (SELECT item, table_id, 1 / count(*) OVER (PARTITION BY table_id) AS weight FROM ({OWNER})), v AS MATERIALIZED ({TABLE_TERMS.format(weight='weight')})"
ROUNDED = "SELECT item, count(*) AS terms, round(sum(w), 3) AS total FROM v GROUP BY item"


def summed_lists(lists: DataFrame) -> DataFrame:
    return lists.select(F.explode("held").alias("h"), "n").groupBy("h.item").agg(F.sum("n").alias("terms"), F.round(F.sum(F.col("n") * F.col("h.w")), 3).alias("total"))


@query("a_table_vectors", f"WITH {WEIGHTED} {ROUNDED}")
def table_vectors(spark, sf_dir):
    """Table vectors weighted by subjectness, summed up."""
    return summed_lists(table_lists(spark, sf_dir))


@query("a_table_vectors_flat", f"WITH {FLAT} {ROUNDED}")
def table_vectors_flat(spark, sf_dir):
    return summed_lists(table_lists(spark, sf_dir, True))


def table_pairs(spark, sf_dir):
    def make():
        lists = table_lists(spark, sf_dir)
        return cut(po.cosine_pairs(lists, po.norms(lists)).withColumn("sim", F.round(F.col("sim") + 1e-9, 4)))

    return runs.once(spark, ("table pairs", sf_dir), make)


@query("a_pairs_tables", f"WITH {WEIGHTED}, {COSINE} SELECT a, b, sim FROM pairs")
def pairs_tables(spark, sf_dir):
    return table_pairs(spark, sf_dir)


# --- the four steps ---------------------------------------------------------------------------------------------------

#: Similarities from which tables and columns are one cluster.
TABLES_AT, COLUMNS_AT = 0.3, 0.5
LINKED = "e AS (SELECT a, b FROM {pairs} WHERE sim >= {least} UNION SELECT b, a FROM {pairs} WHERE sim >= {least}), r(item, other) AS (SELECT item, item FROM {items} UNION SELECT r.item, e.b FROM r JOIN e ON e.a = r.other), found AS (SELECT item, min(other) AS cluster FROM r GROUP BY item)"
STEP1 = f"{WEIGHTED}, {COSINE.replace('pairs AS', 'pairs AS MATERIALIZED')}, names AS (SELECT DISTINCT item FROM v), {LINKED.format(pairs='pairs', least=TABLES_AT, items='names')}"


def step1(spark, sf_dir):
    make = lambda: a.single_links(table_lists(spark, sf_dir).select(F.explode("held").alias("h")).select("h.item").distinct(), table_pairs(spark, sf_dir), TABLES_AT)
    return runs.once(spark, ("affinity 1", sf_dir), make)


@query("a_step1_single", f"WITH RECURSIVE {STEP1} SELECT item, cluster FROM found")
def step1_single(spark, sf_dir):
    """Top-level types: tables joined by the similarity of their weighted vectors."""
    return step1(spark, sf_dir)


def step2(spark, sf_dir):
    """(item, cluster): columns joined within a top-level type alone."""
    def make():
        of = step1(spark, sf_dir).select(F.col("item").alias("table_id"), F.col("cluster").alias("top"))
        tops = full_tables(spark, sf_dir).join(of, "table_id").select("item", "top")
        pairs = column_pairs(spark, sf_dir).join(tops.select(F.col("item").alias("a"), F.col("top").alias("ta")), "a").join(tops.select(F.col("item").alias("b"), F.col("top").alias("tb")), "b").where("ta = tb").select("a", "b", "sim")
        return cut(a.single_links(tops.select("item"), pairs, COLUMNS_AT).join(tops, "item"))

    return runs.once(spark, ("affinity 2", sf_dir), make)


STEP2 = f"""{STEP1}, towner AS (SELECT o.item, f.cluster AS top FROM o JOIN found f ON f.item = o.table_id),
cu AS (SELECT item, term, w / sqrt(sum(w * w) OVER (PARTITION BY item)) AS w FROM t),
cpairs AS MATERIALIZED (SELECT x.item AS a, y.item AS b, round(sum(x.w * y.w) + 1e-9, 4) AS sim FROM cu x JOIN towner tx ON tx.item = x.item JOIN cu y ON x.term = y.term AND x.item < y.item JOIN towner ty ON ty.item = y.item AND ty.top = tx.top GROUP BY 1, 2),
ce AS (SELECT a, b FROM cpairs WHERE sim >= {COLUMNS_AT} UNION SELECT b, a FROM cpairs WHERE sim >= {COLUMNS_AT}),
cr(item, other) AS (SELECT item, item FROM towner UNION SELECT cr.item, ce.b FROM cr JOIN ce ON ce.a = cr.other), cfound AS (SELECT cr.item, min(other) AS cluster, any_value(top) AS top FROM cr JOIN towner USING (item) GROUP BY cr.item)"""


@query("a_step2_single", f"WITH RECURSIVE {STEP2} SELECT item, cluster, top FROM cfound")
def step2_single(spark, sf_dir):
    return step2(spark, sf_dir)


def attribute_columns(spark, sf_dir):
    """(type_name, attr_id, col, table_id, kind, weight) by the second step's clusters."""
    held = weights(spark, sf_dir).where("variant = 'full'").select(F.concat_ws(".", "base", "k", "header").alias("col"), F.concat_ws(".", "base", "k").alias("table_id"), "kind", "weight")
    found = step2(spark, sf_dir).select(F.col("top").alias("type_name"), F.col("cluster").alias("attr_id"), F.col("item").alias("col"))
    return found.join(held, "col")


@query("a_subject_attr", f"WITH RECURSIVE {STEP2} SELECT top AS type_name, cluster AS attr_id, bool_and(kind = 'entity' AND weight >= 0.5) AS is_subject FROM cfound JOIN (SELECT concat_ws('.', base, k, header) AS item, kind, weight FROM ({SUBJECT}) WHERE table_id LIKE '%_full') USING (item) GROUP BY 1, 2")
def subject_attr(spark, sf_dir):
    held = attribute_columns(spark, sf_dir)
    return a.subject_attributes(held.select("type_name", "attr_id", "col"), held.select("col", "kind", "weight"))


def attribute_sets(spark, sf_dir):
    held = attribute_columns(spark, sf_dir)
    return a.table_attribute_sets(held.select("type_name", "attr_id", "col"), held.select("col", "table_id"))


@query("a_attr_sets", f"WITH RECURSIVE {STEP2} SELECT c.top AS type_name, o.table_id AS item, string_agg(DISTINCT c.cluster, ',' ORDER BY c.cluster) AS elements FROM cfound c JOIN o USING (item) GROUP BY 1, 2")
def attr_sets(spark, sf_dir):
    return attribute_sets(spark, sf_dir).withColumn("elements", F.array_join("elements", ","))


def header_sets(spark, sf_dir) -> DataFrame:
    """(type_name, item, elements): every table of the web corpus with its headers, below its inferred top-level type."""
    paths, _, _ = runs.types(spark, sf_dir, "web")
    return runs.tables(spark, sf_dir, "web").join(paths.select("table_id", F.element_at("path", 1).alias("type_name")), "table_id").select("type_name", F.col("table_id").alias("item"), F.col("headers").alias("elements"))


@query("a_silhouette")
def silhouette(spark, sf_dir):
    return a.silhouettes(header_sets(spark, sf_dir))


@query("a_step3")
def step3(spark, sf_dir):
    """Subtypes of each inferred top-level type from its tables' attribute sets."""
    return a.hierarchy(header_sets(spark, sf_dir))


@query("a_step3_grid")
def step3_grid(spark, sf_dir):
    return a.hierarchy(header_sets(spark, sf_dir), heights="grid")


@query("a_step3_attrs")
def step3_attrs(spark, sf_dir):
    """The same from the second step's attributes."""
    return a.hierarchy(attribute_sets(spark, sf_dir))


def link_columns(spark, sf_dir):
    """(col, type_name, attr_id, is_subject) of the wide corpus by its true types and headers: links are tested apart
    from the steps before."""
    held = weights(spark, sf_dir, "wide").where("variant = 'full'")
    leaf = F.element_at(F.split("path", ">"), -1)
    return held.select(F.concat_ws(".", "base", "k", "header").alias("col"), leaf.alias("type_name"), F.col("header").alias("attr_id"), (F.col("header") == "name").alias("is_subject"))


def wide_sims(spark, sf_dir):
    """Cosine of the value sets of the wide corpus's entity columns."""
    def make():
        kinds = runs.stats(spark, sf_dir, "wide").where("variant = 'full' AND kind = 'entity'").select("base", "k", "column", "header")
        held = corpora.cells(spark, sf_dir, corpora.WIDE).where("trim(value) <> ''").join(F.broadcast(kinds), ["base", "k", "column"])
        terms = held.select(F.concat_ws(".", "base", "k", "header").alias("item"), "header", "value").distinct()
        return cut(a.cosine_pairs(a.value_terms(terms)).withColumn("sim", F.round("sim", 6)))

    return runs.once(spark, ("wide sims", sf_dir), make)


WIDE_HELD = " UNION ALL ".join(f"SELECT DISTINCT '{x.name}' AS base, k, '{c}' AS \"column\", CAST({c} AS VARCHAR) AS value FROM ({x.twin()}) WHERE trim(CAST({c} AS VARCHAR)) <> ''" for x in corpora.WIDE for c, _, _ in x.columns)
WIDE_SIMS = f"""wk AS MATERIALIZED (SELECT DISTINCT base, k, "column", header, kind, string_split(path, '>')[-1] AS leaf FROM ({corpora.columns_sql('wide')}) WHERE variant = 'full'),
wt AS (SELECT DISTINCT concat_ws('.', h.base, h.k, header) AS item, value FROM ({WIDE_HELD}) h JOIN wk ON wk.base = h.base AND wk.k = h.k AND wk."column" = h."column" WHERE kind = 'entity'),
wn AS (SELECT item, count(*) AS n FROM wt GROUP BY item),
ws AS MATERIALIZED (SELECT a, b, round(m / sqrt(x.n * y.n), 6) AS sim FROM (SELECT x.item AS a, y.item AS b, count(*) AS m FROM wt x JOIN wt y ON x.value = y.value AND x.item < y.item GROUP BY 1, 2) JOIN wn x ON x.item = a JOIN wn y ON y.item = b),
wc AS (SELECT concat_ws('.', base, k, header) AS col, leaf AS type_name, header AS attr_id, header = 'name' AS is_subject FROM wk)"""
WIDE_LINKS = """s2 AS (SELECT a, b FROM ws WHERE sim > {d1} UNION ALL SELECT b, a FROM ws WHERE sim > {d1}), size AS (SELECT type_name, attr_id, count(*) AS total FROM wc WHERE NOT is_subject GROUP BY 1, 2),
linked AS (SELECT o.type_name AS src_type, o.attr_id, u.type_name AS dst_type, count(DISTINCT o.col) AS covered FROM s2 JOIN wc u ON u.col = s2.a AND u.is_subject JOIN wc o ON o.col = s2.b AND NOT o.is_subject WHERE o.type_name <> u.type_name GROUP BY 1, 2, 3)
SELECT src_type, linked.attr_id, dst_type, covered, total FROM linked JOIN size ON size.type_name = src_type AND size.attr_id = linked.attr_id WHERE covered / total > {d2}"""


@query("a_step4_links", f"WITH {WIDE_SIMS}, {WIDE_LINKS.format(d1=0.3, d2=0.0)}")
def step4_links(spark, sf_dir):
    """Links of the wide corpus by shared values."""
    return a.subject_links(link_columns(spark, sf_dir), wide_sims(spark, sf_dir), 0.3, 0.0)


@query("a_links_lineage", f"WITH {WIDE_SIMS}, base AS ({WIDE_LINKS.format(d1=0.3, d2=0.0).replace('s2 AS', 'WITH s2 AS', 1)}) SELECT * FROM base WHERE NOT (src_type = 'Country' AND dst_type = 'Region')")
def links_lineage(spark, sf_dir):
    """The same without links between a type and its ancestor, had countries been regions."""
    lineage = spark.createDataFrame([("Country", "Region")], "descendant string, ancestor string")
    return a.subject_links(link_columns(spark, sf_dir), wide_sims(spark, sf_dir), 0.3, 0.0, lineage)


def true_links(spark):
    rows = [(x.path.strip("'").split(">")[-1], d) for x in corpora.WIDE for _, _, d in x.columns if d]
    return spark.createDataFrame(rows, "src_type string, dst_type string").distinct()


GRID1, GRID2 = [0.1, 0.2, 0.3, 0.45, 0.6, 0.75], [0.0, 0.15, 0.3, 0.5]
TRUE_LINKS = "(VALUES " + ", ".join(sorted({f"('{x.path.strip(chr(39)).split('>')[-1]}', '{d}')" for x in corpora.WIDE for _, _, d in x.columns if d})) + ") tl(src_type, dst_type)"
GRID = "(VALUES " + ", ".join(f"({x}, {y})" for x in GRID1 for y in GRID2) + ") g(d1, d2)"


@query("a_tune_links", f"""WITH {WIDE_SIMS}, s2 AS (SELECT a, b, sim FROM ws UNION ALL SELECT b, a, sim FROM ws), size AS (SELECT type_name, attr_id, count(*) AS total FROM wc WHERE NOT is_subject GROUP BY 1, 2),
best AS (SELECT o.type_name AS src_type, o.attr_id, u.type_name AS dst_type, o.col, max(sim) AS sim FROM s2 JOIN wc u ON u.col = s2.a AND u.is_subject JOIN wc o ON o.col = s2.b AND NOT o.is_subject WHERE o.type_name <> u.type_name GROUP BY 1, 2, 3, 4),
found AS (SELECT DISTINCT d1, d2, src_type, dst_type FROM (SELECT d1, d2, src_type, attr_id, dst_type, count(*) AS covered FROM best, {GRID} WHERE sim > d1 GROUP BY ALL) JOIN size ON size.type_name = src_type AND size.attr_id = best.attr_id WHERE covered / total > d2),
h AS (SELECT d1, d2, count(*) AS n, count(tl.src_type) AS hits FROM found f LEFT JOIN {TRUE_LINKS} ON tl.src_type = f.src_type AND tl.dst_type = f.dst_type GROUP BY 1, 2),
x AS (SELECT g.d1, g.d2, coalesce(hits / n, 0) AS p, coalesce(hits, 0) / (SELECT count(*) FROM {TRUE_LINKS}) AS r FROM {GRID} LEFT JOIN h ON h.d1 = g.d1 AND h.d2 = g.d2)
SELECT CAST(d1 AS DOUBLE) AS d1, CAST(d2 AS DOUBLE) AS d2, round(p, 6) AS p, round(r, 6) AS r, round(CASE WHEN p + r > 0 THEN 2 * p * r / (p + r) ELSE 0 END, 6) AS f1, p > 0.5 AND r > 0.05 AS feasible FROM x""".replace("GROUP BY ALL) JOIN size ON size.type_name = src_type AND size.attr_id = best.attr_id", "GROUP BY ALL) c JOIN size ON size.type_name = src_type AND size.attr_id = c.attr_id"))
def tune_links(spark, sf_dir):
    return a.tune_links(link_columns(spark, sf_dir), wide_sims(spark, sf_dir), true_links(spark), GRID1, GRID2)


@query("a_names", """WITH n AS (SELECT cluster, split_part(item, '.', 1) AS name, count(*) AS n FROM (""" + f"WITH RECURSIVE {STEP1} SELECT item, cluster FROM found" + """) GROUP BY 1, 2)
SELECT cluster, name FROM (SELECT *, row_number() OVER (PARTITION BY cluster ORDER BY n DESC, name) AS r FROM n) WHERE r = 1""")
def names(spark, sf_dir):
    """A name after the fact for each cluster of tables: the base that most of its tables are cut from, as a file's name
    would tell."""
    return a.cluster_names(step1(spark, sf_dir).select("cluster", F.split_part("item", F.lit("."), F.lit(1)).alias("name")))


def whole(spark, sf_dir) -> dict[str, DataFrame]:
    """The method from end to end on the web corpus: top-level types, attributes, subtypes, links."""
    columns = attribute_columns(spark, sf_dir)
    subjects = a.subject_attributes(columns.select("type_name", "attr_id", "col"), columns.select("col", "kind", "weight"))
    marked = columns.join(subjects, ["type_name", "attr_id"]).select("col", "type_name", "attr_id", "is_subject")
    return {"types": step1(spark, sf_dir), "attributes": columns, "hierarchy": a.hierarchy(attribute_sets(spark, sf_dir)), "links": a.subject_links(marked, column_pairs(spark, sf_dir), 0.75, 0.15)}


@query("a_pipeline")
def pipeline(spark, sf_dir):
    """(part, n) of the whole method's schema."""
    found = whole(spark, sf_dir)
    count = lambda part, df: df.agg(F.count("*").alias("n")).select(F.lit(part).alias("part"), "n")
    parts = [count("top types", found["types"].select("cluster").distinct()), count("attributes", found["attributes"].select("type_name", "attr_id").distinct()), count("subtypes", found["hierarchy"].select("type_name", "node").distinct()), count("links", found["links"])]
    return reduce(DataFrame.unionByName, parts)


# --- header overlap ---------------------------------------------------------------------------------------------------

HEADERS = f"SELECT DISTINCT concat_ws('_', f.base, k, l.variant) AS item, l.header AS element FROM ({fr.FRAGMENTS_SQL}) f JOIN {corpora.layout_sql(corpora.WEB)} ON l.base = f.base"


def headers(spark, sf_dir) -> DataFrame:
    """(item, element): the headers of every table of the web corpus."""
    return corpora.tables(spark, sf_dir, "web").select(F.col("table_id").alias("item"), F.explode("headers").alias("element"))


JACCARD = f"WITH m AS MATERIALIZED ({HEADERS}), n AS (SELECT item, count(*) AS n FROM m GROUP BY item), p AS (SELECT x.item AS a, y.item AS b, count(*) AS c FROM m x JOIN m y ON x.element = y.element AND x.item < y.item GROUP BY 1, 2) SELECT a, b, round(c / (na.n + nb.n - c), 6) AS sim FROM p JOIN n na ON na.item = a JOIN n nb ON nb.item = b"


@query("a_jaccard", JACCARD)
def jaccard(spark, sf_dir):
    return a.jaccard_pairs(headers(spark, sf_dir))


def overlapping(least: float) -> str:
    return f"""
WITH RECURSIVE pairs AS MATERIALIZED ({JACCARD}), e AS (SELECT a, b FROM pairs WHERE sim >= {least} UNION SELECT b, a FROM pairs WHERE sim >= {least}),
i AS (SELECT DISTINCT item FROM ({HEADERS})), r(item, other) AS (SELECT item, item FROM i UNION SELECT r.item, e.b FROM r JOIN e ON e.a = r.other)
SELECT item, min(other) AS cluster FROM r GROUP BY item"""


@query("b_header_jaccard", overlapping(0.3))
def header_jaccard(spark, sf_dir):
    held = headers(spark, sf_dir)
    return a.single_links(held.select("item"), a.jaccard_pairs(held), 0.3)


@query("a_components", overlapping(0.2))
def components(spark, sf_dir):
    held = headers(spark, sf_dir)
    return a.single_links(held.select("item"), a.jaccard_pairs(held), 0.2)


for name, d1, d2 in (("gen", 0.75, 0.15), ("join", 0.75, 0.20), ("con", 0.45, 0.0), ("swap", 0.30, 0.0)):

    @query(f"a_links_{name}", f"WITH {WIDE_SIMS}, {WIDE_LINKS.format(d1=d1, d2=d2)}")
    def links(spark, sf_dir, d1=d1, d2=d2):
        """Links of the wide corpus at the thresholds of each encoder."""
        return a.subject_links(link_columns(spark, sf_dir), wide_sims(spark, sf_dir), d1, d2)


@query("a_given_cosine_topk", """
SELECT q, b FROM (SELECT a.vec_id AS q, b.vec_id AS b, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_sum(list_transform(range(1, 65), lambda k: CAST(a.embedding[k] AS DOUBLE) * CAST(b.embedding[k] AS DOUBLE))), 4) DESC, b.vec_id) AS r
FROM embeddings a JOIN embeddings b ON a.vec_id % 100 = 0 AND a.vec_id <> b.vec_id) WHERE r <= 3""")
def given_cosine_topk(spark, sf_dir):
    """A stated query set, one row in a hundred, against all rows, in blocks of queries of a stated size."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    return a.nearest(e, e.where("vec_id % 100 = 0"), 3).select("q", "b")


@query("s_joinable", """
WITH k AS (SELECT 'orders.custkey' AS col, o_custkey AS v FROM orders UNION SELECT 'customer.custkey', c_custkey FROM customer UNION SELECT 'events.user_id', user_id FROM events UNION SELECT 'lineitem.orderkey', l_orderkey FROM lineitem UNION SELECT 'orders.orderkey', o_orderkey FROM orders),
n AS (SELECT col, count(*) AS n FROM k GROUP BY col)
SELECT x.col AS a, y.col AS b, round(count(*) / max(n.n), 6) AS containment FROM k x JOIN k y ON x.v = y.v AND x.col <> y.col JOIN n ON n.col = x.col WHERE n.n >= 20 GROUP BY 1, 2 HAVING count(*) / max(n.n) >= 0.9""")
def joinable(spark, sf_dir):
    parts = [("orders", "o_custkey", "orders.custkey"), ("customer", "c_custkey", "customer.custkey"), ("events", "user_id", "events.user_id"), ("lineitem", "l_orderkey", "lineitem.orderkey"), ("orders", "o_orderkey", "orders.orderkey")]
    keys = None
    for t, c, name in parts:
        one = table(spark, sf_dir, t).select(F.lit(name).alias("col"), F.col(c).alias("v")).distinct()
        keys = one if keys is None else keys.union(one)
    n = keys.groupBy("col").agg(F.count("*").alias("n")).where("n >= 20")
    both = keys.select(F.col("col").alias("a"), "v").join(keys.select(F.col("col").alias("b"), "v"), "v").where("a <> b").groupBy("a", "b").agg(F.count("*").alias("m"))
    return both.join(n, F.col("a") == F.col("col")).select("a", "b", F.round(F.col("m") / F.col("n"), 6).alias("containment")).where("containment >= 0.9")


SEARCHED = " UNION ALL ".join(f"SELECT '{x.name}' AS base, k, '{h}' AS header, CAST({c} AS VARCHAR) AS value FROM ({x.twin()})" for x in corpora.WEB for c, h, _ in x.columns if c not in DENSE)


def keyword_search(spark, sf_dir, word: str) -> DataFrame:
    """(base, k, header, hits): every column with the word in its header or in cells, with the number of cells. Each scan
    filters on its own; hits are counted before the shuffle."""
    held = corpora.cells(spark, sf_dir, corpora.WEB).where(~F.col("column").isin(*DENSE))
    names = spark.createDataFrame([(x.name, c, h) for x in corpora.WEB for c, h, _ in x.columns], "base string, column string, header string")
    hit = held.join(F.broadcast(names), ["base", "column"]).where(F.lower("value").contains(word) | F.lower("header").contains(word))
    return hit.groupBy("base", "k", "header").agg(F.count_if(F.lower("value").contains(word)).alias("hits"))


@query("b_keyword", f"SELECT DISTINCT base, k FROM ({SEARCHED}) WHERE contains(lower(value), 'customer') OR contains(lower(header), 'customer')")
def keyword(spark, sf_dir):
    return keyword_search(spark, sf_dir, "customer").select("base", "k").distinct()


@query("s_search", f"SELECT base, k, header, count(*) FILTER (contains(lower(value), 'key')) AS hits FROM ({SEARCHED}) WHERE contains(lower(value), 'key') OR contains(header, 'key') GROUP BY 1, 2, 3")
def search(spark, sf_dir):
    return keyword_search(spark, sf_dir, "key")


@query("s_navigate", f"SELECT DISTINCT a.base AS a, b.base AS b FROM ({fr.FRAGMENTS_SQL}) a JOIN ({fr.FRAGMENTS_SQL}) b ON split_part(a.path, '>', 1) = split_part(b.path, '>', 1) AND a.base < b.base")
def navigate(spark, sf_dir):
    f = fr.fragments(spark, sf_dir).select("base", F.split_part("path", F.lit(">"), F.lit(1)).alias("top")).distinct()
    other = f.select(F.col("base").alias("b"), "top")
    return f.join(other, "top").where("base < b").select(F.col("base").alias("a"), "b").distinct()
