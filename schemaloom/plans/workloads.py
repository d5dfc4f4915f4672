"""Experiments over the corpora, computed from the library's own runs with stand-in completers and encoders.

What they score tests plumbing, measures and costs; it says nothing about trained models. Every completer sees prompts
alone; true types are read by the measures only.
"""

from __future__ import annotations

import time
import zlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from schemaloom.operators import affinity, asks, attributes, baselines, clustering, relations
from schemaloom.operators import hierarchy as h
from schemaloom.operators import measures as m
from schemaloom.operators.lexicon import Lexicon
from schemaloom.plans import affinities, inference, runs
from schemaloom.plans.registry import query
from schemaloom.sources import corpora
from schemaloom.sources import fragments as fr
from schemaloom.sources.shared import cut

CORPORA = ("web", "wide", "multi")
#: Similarity of table vectors from which tables are one type.
TABLES_AT = 0.6

# --- corpora ----------------------------------------------------------------------------------------------------------


def stats_sql(name: str) -> str:
    sources = corpora.FINE if name == "large" else corpora.CORPORA[name]
    shape = "(VALUES " + ", ".join(f"('{x.name}', '{v}', {len(cs)})" for x in sources for v, cs in corpora.variants(x, name)) + ") w(base, variant, n_cols)"
    return f"SELECT f.base, count(*) AS n_tables, CAST(sum(n_cols) AS BIGINT) AS n_columns, count(DISTINCT path) AS n_leaves FROM ({corpora.fragments_sql(sources)}) f JOIN {shape} ON w.base = f.base GROUP BY f.base"


for corpus_name in ("wide", "multi", "large"):

    @query(f"w_repo_{corpus_name}_stats", stats_sql(corpus_name))
    def repo_stats(spark, sf_dir, name=corpus_name):
        held = corpora.tables(spark, sf_dir, name)
        return held.groupBy("base").agg(F.count("*").alias("n_tables"), F.sum(F.size("headers")).cast("long").alias("n_columns"), F.count_distinct("path").alias("n_leaves"))


# --- affinity on any corpus -------------------------------------------------------------------------------------------


def value_vectors(spark, sf_dir: str, corpus: str) -> DataFrame:
    """(base, k, column, vector): hashed unit vectors of every column's words, rare ones heavier, or of its dense vectors."""
    return runs.vectors(spark, sf_dir, corpus)


def table_vectors(columns: DataFrame, vectors: DataFrame, size: int = 256) -> DataFrame:
    """(item, vector) of tables: their columns' vectors and hashed headers by weight. columns: (table_id, base, k, column,
    header, weight)."""
    held = corpora.met(columns, vectors, ["base", "k", "column"], "left").groupBy("table_id").agg(F.collect_list(F.struct("weight", "header", "vector")).alias("parts"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = np.zeros((len(frame), size), np.float32)
            for row, parts in enumerate(frame["parts"]):
                for part in parts:
                    if part["vector"] is not None:
                        out[row] += part["weight"] * np.asarray(part["vector"], np.float32)
                    code = zlib.crc32(part["header"].encode())
                    out[row, code % size] += (1 if code >> 31 else -1) / len(parts)
            yield pd.DataFrame({"item": frame["table_id"], "vector": list(out / np.maximum(1e-12, np.linalg.norm(out, axis=1, keepdims=True)))})

    return held.mapInPandas(run, "item string, vector array<float>")


def affinity_types(spark, sf_dir: str, corpus: str, weighted: bool = True) -> DataFrame:
    """(table_id, cluster) by blocked products of table vectors."""
    def make():
        columns = affinity.subjectness(runs.stats(spark, sf_dir, corpus), "table_id")
        if not weighted:
            columns = columns.withColumn("weight", 1 / F.count("*").over(Window.partitionBy("table_id")))
        vectors = cut(table_vectors(columns, value_vectors(spark, sf_dir, corpus)))
        links = clustering.near_links(vectors, TABLES_AT).withColumn("sim", F.lit(1.0))
        return cut(affinity.single_links(vectors.select("item"), cut(links), 1.0).select(F.col("item").alias("table_id"), "cluster"))

    return runs.once(spark, ("affinity types", sf_dir, corpus, weighted), make)


def affinity_hierarchy(spark, sf_dir: str, corpus: str, delta: float = 0.15) -> tuple[DataFrame, DataFrame]:
    """(edges, (type_name, table_id)): clusters of tables with their subtypes from header sets."""
    def make():
        of = affinity_types(spark, sf_dir, corpus)
        sets = of.join(runs.tables(spark, sf_dir, corpus).select("table_id", "headers"), "table_id").select(F.col("cluster").alias("type_name"), F.col("table_id").alias("item"), F.col("headers").alias("elements"))
        nodes = cut(affinity.hierarchy(sets, delta))
        label = lambda c: F.concat_ws(" / ", "type_name", c)
        size = of.groupBy("cluster").agg(F.count("*").alias("weight"))
        low = nodes.groupBy("type_name", "node", "parent").agg(F.count("*").alias("weight")).select(label("node").alias("child"), F.when(F.col("parent").isNull(), F.col("type_name")).otherwise(label("parent")).alias("parent"), "weight")
        edges = low.union(size.select(F.col("cluster").alias("child"), F.lit(h.ROOT).alias("parent"), "weight"))
        members = of.select(F.col("cluster").alias("type_name"), "table_id").union(nodes.select(label("node"), "item")).distinct()
        return cut(edges), cut(members)

    return runs.once(spark, ("affinity hierarchy", sf_dir, corpus, delta), make)


# --- measures over runs -----------------------------------------------------------------------------------------------


def truth_edges(tables: DataFrame) -> DataFrame:
    return h.merge_edges(h.path_edges(tables.select("table_id", F.lit(1).alias("path_no"), F.split("path", ">").alias("path"))))


def grouped(tables: DataFrame, found: DataFrame, **labels: str) -> DataFrame:
    """One row of RI and purity; found: (table_id, predicted). A table without a prediction is a class of its own."""
    items = tables.select("table_id", F.split_part("path", F.lit(">"), F.lit(1)).alias("truth")).join(found, "table_id", "left").withColumn("predicted", F.coalesce("predicted", "table_id"))
    row = m.rand_index(items).withColumnRenamed("value", "ri").crossJoin(m.purity(items).withColumnRenamed("value", "purity"))
    return row.select(*(F.lit(v).alias(k) for k, v in labels.items()), "ri", "purity")


def shaped(tables: DataFrame, edges: DataFrame, members: DataFrame, **labels: str) -> DataFrame:
    """One row of tree score, type count and depth; members: (type_name, table_id)."""
    leaf = tables.select("table_id", F.element_at(F.split("path", ">"), -1).alias("gt_type"))
    aligned = m.complete_paths(edges).join(m.align_types(members, leaf), "type_name", "left")
    row = m.tree_scores(aligned, truth_edges(tables)).agg(F.round(F.avg("score"), 6).alias("tree_score")).crossJoin(m.type_count(edges).withColumnRenamed("value", "types")).crossJoin(h.levels(edges).agg(F.max("level").alias("depth")))
    return row.select(*(F.lit(v).alias(k) for k, v in labels.items()), "tree_score", "types", "depth")


def tops_of(paths: DataFrame, edges: DataFrame) -> DataFrame:
    """(table_id, predicted): the first top-level type above each table."""
    return h.type_tables(paths, edges).join(h.top_level(edges), "type_name").groupBy("table_id").agg(F.min("type_name").alias("predicted"))


def taxonomy(spark, sf_dir: str, corpus: str) -> tuple[DataFrame, DataFrame]:
    """(types, edges) of the type-then-taxonomy baseline."""
    def make():
        types = cut(baselines.table_types(runs.tables(spark, sf_dir, corpus), runs.lexicon()))
        return types, cut(h.break_cycles(baselines.type_taxonomy(types, runs.lexicon())))

    return runs.once(spark, ("taxonomy", sf_dir, corpus), make)


def member_paths(types: DataFrame) -> DataFrame:
    return types.select("table_id", F.lit(1).alias("path_no"), F.array("type_name").alias("path"))


def union(rows: list[DataFrame]) -> DataFrame:
    return cut(reduce(DataFrame.unionByName, rows))


@query("b_type_taxonomy")
def type_taxonomy(spark, sf_dir):
    return taxonomy(spark, sf_dir, "web")[1]


@query("b_taxonomy_pairwise")
def taxonomy_pairwise(spark, sf_dir):
    return baselines.pairwise_taxonomy(taxonomy(spark, sf_dir, "web")[0], runs.lexicon())


USUAL = inference.USUAL_SQL
NAMED = f"SELECT col, lower(CASE WHEN {asks.strike_sql('col', 'raw', 50)} THEN header ELSE {USUAL.format(h='header')} END) AS name FROM ({corpora.columns_sql('web')})"


@query("b_name_group", f"SELECT col, name, CASE WHEN {asks.strike_sql('name', 'unmerged', runs.NOISE)} THEN name ELSE {USUAL.format(h='name')} END AS attr_name FROM ({NAMED})")
def name_group(spark, sf_dir):
    return baselines.name_group(runs.columns(spark, sf_dir, "web"), runs.lexicon())


@query("b_direct_group", f"SELECT col, {USUAL.format(h='header')} AS attr_name FROM ({corpora.columns_sql('multi')})")
def direct_group(spark, sf_dir):
    """One prompt for every column of the smallest corpus; larger ones are refused."""
    return baselines.direct_group(runs.columns(spark, sf_dir, "multi"), Lexicon())


TABLE_VALUES = " UNION ALL ".join(f"SELECT DISTINCT concat_ws('.', '{x.name}', k) AS table_id, CAST({c} AS VARCHAR) AS value FROM ({x.twin()}) WHERE trim(CAST({c} AS VARCHAR)) <> ''" for x in corpora.WEB for c, _, _ in x.columns if c not in affinities.DENSE)


@query("b_table_query", f"""WITH v AS MATERIALIZED (SELECT DISTINCT table_id, value FROM ({TABLE_VALUES})),
s AS (SELECT x.table_id AS q, y.table_id, count(*) AS shared FROM v x JOIN v y ON x.value = y.value AND x.table_id <> y.table_id WHERE x.table_id LIKE 'nation.%' OR x.table_id LIKE 'customer.%' GROUP BY 1, 2)
SELECT q, table_id, shared, place FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY shared DESC, table_id) AS place FROM s) WHERE place <= 5""")
def table_query(spark, sf_dir):
    """Tables that share most values with each fragment of customers and nations."""
    held = affinities.cells(spark, sf_dir).select(F.regexp_extract("item", r"^(.*)\.[^.]*$", 1).alias("table_id"), "value").distinct()
    return baselines.table_query(held, held.where("table_id LIKE 'nation.%' OR table_id LIKE 'customer.%'").select("table_id"))


# --- result tables ----------------------------------------------------------------------------------------------------


def top_types_of(spark, sf_dir: str, corpus: str) -> list[DataFrame]:
    """A row for each method and setting on a corpus; methods share its tables and profiles alone, and are made at once."""
    tables = runs.tables(spark, sf_dir, corpus)

    def scored(found: DataFrame, method: str, config: str) -> DataFrame:
        return cut(grouped(tables, found, corpus=corpus, method=method, config=config))

    def asked(constraint: str) -> DataFrame:
        paths, edges, _ = runs.types(spark, sf_dir, corpus, constraint)
        return scored(tops_of(paths, edges), "path-first", constraint)

    def near() -> list[DataFrame]:
        return [scored(affinity_types(spark, sf_dir, corpus, weighted).withColumnRenamed("cluster", "predicted"), "affinity", config) for config, weighted in (("weighted", True), ("flat", False))]

    def typed() -> list[DataFrame]:
        types, edges = taxonomy(spark, sf_dir, corpus)
        return [scored(tops_of(member_paths(types), edges), "type-then-taxonomy", "bfs")]

    return sum(runs.together(spark, near, typed, lambda: [asked(c) for c in asks.CONSTRAINTS]), [])


@query("w_top_types")
def top_types(spark, sf_dir):
    """Every corpus, the large one too; the smaller one is taken from the web's tables, so one thread has both."""
    held = runs.together(spark, *(lambda names=names: [row for x in names for row in top_types_of(spark, sf_dir, x)] for names in (("web", "multi"), ("wide",), ("large",))))
    return union(sum(held, []))


@query("w_hierarchy")
def hierarchies(spark, sf_dir):
    def make():
        rows = []
        for corpus in CORPORA:
            tables = runs.tables(spark, sf_dir, corpus)
            paths, edges, _ = runs.types(spark, sf_dir, corpus)
            rows.append(shaped(tables, edges, h.type_tables(paths, edges), corpus=corpus, method="path-first"))
            rows.append(shaped(tables, *affinity_hierarchy(spark, sf_dir, corpus), corpus=corpus, method="affinity"))
            types, below = taxonomy(spark, sf_dir, corpus)
            rows.append(shaped(tables, below, h.type_tables(member_paths(types), below), corpus=corpus, method="type-then-taxonomy"))
        return union(rows)

    return runs.once(spark, ("w_hierarchy", sf_dir), make)


@query("b_compare")
def compare(spark, sf_dir):
    """The methods' tree scores side by side, from own runs."""
    return hierarchies(spark, sf_dir).groupBy("corpus").pivot("method", ["path-first", "affinity", "type-then-taxonomy"]).agg(F.first("tree_score"))


def ablated(spark, sf_dir: str, corpus: str, label: str, constraint: str, verify: bool) -> DataFrame:
    tables = runs.tables(spark, sf_dir, corpus)
    paths, edges, _ = runs.types(spark, sf_dir, corpus, constraint, verify)
    one = grouped(tables, tops_of(paths, edges), corpus=corpus, config=label)
    return one.join(shaped(tables, edges, h.type_tables(paths, edges), corpus=corpus, config=label), ["corpus", "config"])


@query("w_ablate_constraints")
def ablate_constraints(spark, sf_dir):
    return union([ablated(spark, sf_dir, "web", c, c, True) for c in asks.CONSTRAINTS])


@query("w_ablate_verify")
def ablate_verify(spark, sf_dir):
    return union([ablated(spark, sf_dir, corpus, label, "none", verify) for corpus in CORPORA for label, verify in (("without", False), ("with", True))])


def inferred_attributes(spark, sf_dir: str, corpus: str) -> DataFrame:
    """(corpus, method, ri, purity) of columns."""
    columns = runs.columns(spark, sf_dir, corpus)
    truth = columns.select("col", F.col("attribute").alias("truth"))
    first = runs.attributes_of(spark, sf_dir, corpus)["clusters"].groupBy("col").agg(F.min(F.concat_ws(".", "owner", "attr_name")).alias("predicted"))
    named = baselines.name_group(columns, runs.lexicon()).select("col", F.col("attr_name").alias("predicted"))
    of = affinity_types(spark, sf_dir, corpus)
    vectors = corpora.met(columns.join(of, "table_id"), value_vectors(spark, sf_dir, corpus), ["base", "k", "column"]).select(F.col("col").alias("item"), "vector", "cluster")
    links = cut(clustering.near_links(cut(vectors), 0.8, "cluster").withColumn("sim", F.lit(1.0)))
    near = affinity.single_links(columns.select(F.col("col").alias("item")), links, 1.0).select(F.col("item").alias("col"), F.col("cluster").alias("predicted"))
    rows = []
    for method, found in (("path-first", first), ("affinity", near), ("name-then-group", named)):
        items = truth.join(found, "col", "left").withColumn("predicted", F.coalesce("predicted", "col"))
        row = m.rand_index(items).withColumnRenamed("value", "ri").crossJoin(m.purity(items).withColumnRenamed("value", "purity"))
        rows.append(row.select(F.lit(corpus).alias("corpus"), F.lit(method).alias("method"), "ri", "purity"))
    return union(rows)


@query("w_attributes")
def attributes_table(spark, sf_dir):
    # the smaller corpus is taken from the web's tables
    held = runs.together(spark, *(lambda names=names: [inferred_attributes(spark, sf_dir, x) for x in names] for names in (("web", "multi"), ("wide",))))
    return union(sum(held, []))


def true_relations(spark) -> DataFrame:
    return affinities.true_links(spark).select(F.col("src_type").alias("src"), F.col("dst_type").alias("dst"))


def asked_relations(spark, sf_dir: str) -> tuple[DataFrame, list]:
    clusters, columns, edges = runs.attributes_of(spark, sf_dir, "wide")["clusters"], runs.columns(spark, sf_dir, "wide"), runs.types(spark, sf_dir, "wide")[1]
    return runs.ledgered(spark, ("relations", sf_dir), lambda: relations.infer_relationships(clusters, columns, edges, runs.lexicon()))


def found_relations(spark, sf_dir: str) -> DataFrame:
    """(src, attr_name, dst, predicate) of the wide corpus by all three steps."""
    return asked_relations(spark, sf_dir)[0]


def aligned_relations(spark, sf_dir: str) -> DataFrame:
    """found_relations with the true types that most of each type's tables have."""
    paths, edges, _ = runs.types(spark, sf_dir, "wide")
    leaf = runs.tables(spark, sf_dir, "wide").select("table_id", F.element_at(F.split("path", ">"), -1).alias("gt_type"))
    to = cut(m.align_types(h.type_tables(paths, edges), leaf))
    of = lambda c, n: to.select(F.col("type_name").alias(c), F.col("gt_type").alias(n))
    return found_relations(spark, sf_dir).join(of("src", "s"), "src").join(of("dst", "d"), "dst").select(F.col("src").alias("own_src"), F.col("dst").alias("own_dst"), "attr_name", F.col("s").alias("src"), F.col("d").alias("dst"))


@query("w_relationships")
def relationships(spark, sf_dir):
    truth = true_relations(spark)
    links = affinity.subject_links(affinities.link_columns(spark, sf_dir), affinities.wide_sims(spark, sf_dir), 0.3, 0.0).select(F.col("src_type").alias("src"), F.col("dst_type").alias("dst"))
    rows = [("path-first", aligned_relations(spark, sf_dir)), ("affinity", links)]
    return union([m.precision_recall_f1(found, truth, ["src", "dst"]).select(F.lit("wide").alias("corpus"), F.lit(method).alias("method"), "p", "r", "f1") for method, found in rows])


@query("w_cardinality")
def cardinalities(spark, sf_dir):
    """Accuracy over the relationships that were found rightly, by what the asks show; all of them are n:1 in truth."""
    held = aligned_relations(spark, sf_dir).join(true_relations(spark), ["src", "dst"], "left_semi")
    found = runs.attributes_of(spark, sf_dir, "wide")
    columns = runs.columns(spark, sf_dir, "wide")
    rel = cut(held.select(F.col("own_src").alias("src"), "attr_name", F.col("own_dst").alias("dst")).distinct())
    clusters = found["clusters"].select("col", "attr_name", "owner")
    stats, rows = cut(relations.evidence(rel, clusters, columns)), cut(relations.evidence_rows(rel, clusters, columns))
    truth = rel.withColumn("cardinality", F.lit("n:1"))
    out = [m.cardinality_accuracy(relations.infer_cardinality(rel, stats, rows, runs.lexicon(), shown), truth, ["src", "attr_name", "dst"]).select(F.lit(shown).alias("shown"), F.col("value").alias("accuracy")) for shown in ("both", "stats", "rows")]
    return union(out)


# --- tuning, costs, times, cases --------------------------------------------------------------------------------------

DELTAS = [round(0.05 * k, 2) for k in range(1, 11)]


@query("a_tune_delta_table")
def tune_delta(spark, sf_dir):
    """(delta, tree_score, types, depth) on the development corpus."""
    def make():
        tables = runs.tables(spark, sf_dir, "web")
        return union([shaped(tables, *affinity_hierarchy(spark, sf_dir, "web", d), delta=d) for d in DELTAS])

    return runs.once(spark, ("tune delta", sf_dir), make)


@query("w_tuned")
def tuned(spark, sf_dir):
    """What is chosen on the development corpora, frozen for the others: the delta with the best tree score, of equal ones
    the smallest; link thresholds with the best F1 among the feasible."""
    delta = tune_delta(spark, sf_dir).orderBy(F.desc("tree_score"), "delta").limit(1).select(F.lit("delta").alias("parameter"), F.col("delta").cast("string").alias("value"))
    links = affinities.tune_links(spark, sf_dir).where("feasible").orderBy(F.desc("f1"), "d1", "d2").limit(1).select(F.lit("links").alias("parameter"), F.concat_ws("/", "d1", "d2").alias("value"))
    return delta.union(links)


@query("w_cost")
def cost(spark, sf_dir):
    """(corpus, stage, calls, prompt_tokens, answer_tokens) from the asks that the runs made, with sums; four characters
    count as a token. Each step's asks count once, whether it was made for this or before."""
    def ledgers(*names: str) -> list[tuple[str, list]]:
        return [(x, runs.asked_types(spark, sf_dir, x)[1] + runs.asked_attributes(spark, sf_dir, x)[1] + (asked_relations(spark, sf_dir)[1] if x == "wide" else [])) for x in names]

    rows = []
    # the smaller corpus is taken from the web's tables
    for corpus, held in sum(runs.together(spark, lambda: ledgers("web", "multi"), lambda: ledgers("wide")), []):
        rows += [df.select(F.lit(corpus).alias("corpus"), F.lit(stage).alias("stage"), "prompt_chars", "answer_chars") for stage, df in held]
    every = reduce(DataFrame.unionByName, rows)
    return every.rollup("corpus", "stage").agg(F.count("*").alias("calls"), F.ceil(F.sum("prompt_chars") / 4).alias("prompt_tokens"), F.ceil(F.sum("answer_chars") / 4).alias("answer_tokens"))


def timed(spark, stages: list[tuple[str, object]], **labels) -> list[tuple]:
    out = []
    for stage, run in stages:
        began = time.perf_counter()
        run()
        out.append((*labels.values(), stage, round(time.perf_counter() - began, 3)))
    return out


#: Tables of the large corpus that a point of the curve takes, by hash.
CURVE = (1000, 3000, 10_000)


@query("w_runtime")
def runtime(spark, sf_dir):
    """(method, tables, stage, seconds) of types and hierarchies as the large corpus grows."""
    def make():
        every = runs.tables(spark, sf_dir, "large")
        ranked = cut(every.withColumn("_r", F.row_number().over(Window.orderBy(F.md5("table_id")))))
        sources = corpora.FINE
        shape = spark.createDataFrame(corpora.layout(sources, "large"), corpora.LAYOUT)
        stats = runs.tallied(spark, sf_dir, "large")[0].join(F.broadcast(shape), ["base", "column"]).withColumn("table_id", corpora.table_id())
        columns, values = cut(affinity.subjectness(stats, "table_id")), value_vectors(spark, sf_dir, "large")
        rows: list[tuple] = []
        for n in CURVE:
            tables = cut(ranked.where(F.col("_r") <= n).drop("_r"))
            held: dict[str, object] = {}

            def put(name, make_):
                held[name] = make_()

            some = columns.join(tables.select("table_id"), "table_id", "left_semi")
            rows += timed(spark, [("types", lambda: put("paths", lambda: asks.infer_types(tables, runs.lexicon())))], method="path-first", tables=tables.count())
            rows += timed(spark, [
                ("vectors", lambda: put("vectors", lambda: cut(table_vectors(some, values)))),
                ("types", lambda: put("of", lambda: cut(affinity.single_links(held["vectors"].select("item"), cut(clustering.near_links(held["vectors"], TABLES_AT).withColumn("sim", F.lit(1.0))), 1.0)))),
                ("hierarchy", lambda: put("nodes", lambda: cut(affinity.hierarchy(held["of"].join(tables.select(F.col("table_id").alias("item"), F.col("headers").alias("elements")), "item").select(F.col("cluster").alias("type_name"), "item", "elements"))))),
            ], method="affinity", tables=tables.count())
        return spark.createDataFrame(rows, "method string, tables long, stage string, seconds double")

    return runs.once(spark, ("runtime", sf_dir), make)


@query("m_slope_runs")
def slope_runs(spark, sf_dir):
    """(method, slope): how time grows with tables, as a power, from the curve's points."""
    total = runtime(spark, sf_dir).groupBy("method", "tables").agg(F.sum("seconds").alias("t"))
    return total.groupBy("method").agg(F.round(F.regr_slope(F.log("t"), F.log("tables")), 3).alias("slope"))


@query("w_case_subtree", f"""WITH RECURSIVE {asks.step1_sql(fr.REPOSITORY_SQL, inference.HEADERS, runs.NOISE, runs.WRONG)},
below(t) AS (SELECT child FROM edges WHERE parent = 'CreativeWork' UNION SELECT e.child FROM below JOIN edges e ON e.parent = t) SELECT child, parent FROM edges WHERE child IN (SELECT t FROM below)""")
def case_subtree(spark, sf_dir):
    """The inferred hierarchy below creative works."""
    edges = runs.types(spark, sf_dir, "web")[1]
    below = h.reach(edges).where("ancestor = 'CreativeWork'").select(F.col("descendant").alias("child"))
    return edges.join(below, "child", "left_semi").select("child", "parent")


@query("w_case_schema")
def case_schema(spark, sf_dir):
    """(part, name, detail): top-level types of the wide corpus with their attributes and relationships."""
    found = runs.attributes_of(spark, sf_dir, "wide")
    tops = h.top_level(runs.types(spark, sf_dir, "wide")[1]).select(F.lit("type").alias("part"), F.col("type_name").alias("name"), F.lit("").alias("detail"))
    attrs = found["owners"].select("owner", "attr_name").distinct().select(F.lit("attribute").alias("part"), F.col("owner").alias("name"), F.col("attr_name").alias("detail"))
    rels = found_relations(spark, sf_dir).select(F.lit("relationship").alias("part"), F.col("src").alias("name"), F.concat_ws(" -> ", "attr_name", "dst").alias("detail"))
    return tops.union(attrs).union(rels)


@query("w_failures")
def failures(spark, sf_dir):
    """(case, n): known hard cases, counted on own runs: tables whose top-level type twins another's, tables of one true
    type under several inferred ones, numeric columns in a foreign attribute, columns that share values with another
    type's key only."""
    tables, (paths, edges, _) = runs.tables(spark, sf_dir, "web"), runs.types(spark, sf_dir, "web")
    leaf = tables.select("table_id", F.element_at(F.split("path", ">"), -1).alias("gt_type"))
    tops = tops_of(paths, edges)
    over = h.type_tables(paths, edges).join(h.top_level(edges), "type_name").groupBy("table_id").agg(F.count("*").alias("n")).where("n > 1")
    split = tops.join(leaf, "table_id").groupBy("gt_type").agg(F.count_distinct("predicted").alias("n")).where("n > 1")
    columns = runs.columns(spark, sf_dir, "web")
    clusters = runs.attributes_of(spark, sf_dir, "web")["clusters"].join(columns.select("col", "attribute", "kind"), "col")
    mixed = clusters.where("kind IN ('number', 'identifier')").groupBy("owner", "attr_name").agg(F.count_distinct("attribute").alias("n")).where("n > 1")
    trap = affinity.containments_of(affinities.cells_of(spark, sf_dir, "events", ("user_id",)), affinities.cells_of(spark, sf_dir, "customer"), 0.9)
    count = lambda case, df: df.agg(F.count("*").alias("n")).select(F.lit(case).alias("case"), "n")
    return union([count("tables under several top types", over), count("true types under several top types", split), count("mixed numeric attributes", mixed), count("joins by values alone", trap)])

