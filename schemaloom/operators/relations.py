"""Relationships between types through attributes that hold entities, and their cardinalities from evidence."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from schemaloom.operators import hierarchy as h
from schemaloom.operators.asks import Completer, answers
from schemaloom.operators.sampling import digest
from schemaloom.sources.shared import cut

SUBJECT = "name"
CARDINALITIES = ("1:1", "1:n", "n:1", "m:n")


def entity_attributes(clusters: DataFrame, columns: DataFrame) -> DataFrame:
    """(owner, attr_name, col) of attributes most of whose columns hold entities; a type's own name is no relationship.
    clusters: (col, attr_name, owner)."""
    held = clusters.select("col", "attr_name", "owner").distinct().join(columns.select("col", "kind"), "col")
    share = held.groupBy("owner", "attr_name").agg((F.count_if(F.col("kind") == "entity") * 2 > F.count("*")).alias("entity"))
    return held.join(share.where("entity").drop("entity"), ["owner", "attr_name"]).where(F.col("attr_name") != SUBJECT).select("owner", "attr_name", "col")


def attribute_values(attributes: DataFrame, columns: DataFrame, k: int = 5) -> DataFrame:
    """(owner, attr_name, values): k distinct values over all of an attribute's columns, by hash. Each column brings its
    own sample, so nothing but samples is shuffled."""
    long = attributes.join(columns.select("col", F.explode("samples").alias("value")), "col").select("owner", "attr_name", "value").distinct()
    order = Window.partitionBy("owner", "attr_name").orderBy(digest("value"))
    top = long.withColumn("_k", F.row_number().over(order)).where(F.col("_k") <= k)
    return top.groupBy("owner", "attr_name").agg(F.transform(F.sort_array(F.collect_list(F.struct("_k", "value"))), lambda x: x["value"]).alias("values"))


def top_k_types(values: DataFrame, edges: DataFrame, completer: Completer, k: int = 3) -> DataFrame:
    """(owner, attr_name, place, top): the top-level types that an attribute's values may denote, best first; names that
    the hierarchy lacks are left out."""
    tops = h.top_level(edges)
    listed = tops.agg(F.sort_array(F.collect_set("type_name")).alias("tops"))
    rows = values.crossJoin(listed).select(F.concat_ws("|", "owner", "attr_name").alias("ask"), "owner", F.col("attr_name").alias("attr"), "values", "tops", F.lit(k).alias("k"))
    said = answers(rows, "top_types", ["attr", "values", "tops", "k"], completer)
    picked = said.select("owner", F.col("attr").alias("attr_name"), F.posexplode(F.slice(F.transform(F.split("text", ","), lambda x: F.trim(x)), 1, k)).alias("place", "top"))
    return picked.join(tops.withColumnRenamed("type_name", "top"), "top", "left_semi").select("owner", "attr_name", "place", "top")


def candidates(tops: DataFrame, edges: DataFrame) -> DataFrame:
    """tops with `candidate`: each top-level type and all below it."""
    ways = h.reach(edges).select(F.col("ancestor").alias("top"), F.col("descendant").alias("candidate"))
    return tops.join(ways, "top").unionByName(tops.withColumn("candidate", F.col("top")))


def select_type(values: DataFrame, found: DataFrame, completer: Completer, refine: str = "union") -> DataFrame:
    """(owner, attr_name, dst): one candidate or none for each attribute, from all candidates at once ('union'), or from
    each top-level type's in turn, best first, until one answers ('per_top'). found: top_k_types with candidates."""
    if refine not in ("union", "per_top"):
        raise ValueError(f"refine is union or per_top, not {refine}")
    by = ["owner", "attr_name", *(["place"] if refine == "per_top" else [])]
    groups = found.groupBy(*by).agg(F.sort_array(F.collect_set("candidate")).alias("candidates"))
    rows = groups.join(values, ["owner", "attr_name"]).withColumn("ask", F.concat_ws("|", *by)).withColumn("attr", F.col("attr_name"))
    said = answers(rows, "pick_type", ["attr", "values", "candidates"], completer).withColumn("dst", F.trim("text"))
    valid = said.where(F.array_contains("candidates", F.col("dst")))
    if refine == "union":
        return valid.select("owner", "attr_name", "dst")
    return valid.groupBy("owner", "attr_name").agg(F.min_by("dst", "place").alias("dst"))


def predicates(links: DataFrame, completer: Completer) -> DataFrame:
    """links with a short label for how the source relates to the target."""
    rows = links.withColumn("ask", F.concat_ws("|", "owner", "attr_name", "dst")).withColumn("attr", F.col("attr_name"))
    said = answers(rows, "predicate", ["owner", "attr", "dst"], completer)
    return said.select("owner", "attr_name", "dst", F.trim("text").alias("predicate"))


def infer_relationships(clusters: DataFrame, columns: DataFrame, edges: DataFrame, completer: Completer, k: int = 3, refine: str = "union") -> DataFrame:
    """(src, attr_name, dst, predicate), each once; a type doesn't relate to itself through its own attribute."""
    values = cut(attribute_values(entity_attributes(clusters, columns), columns))
    found = candidates(top_k_types(values, edges, completer, k), edges)
    links = select_type(values, cut(found), completer, refine).where("owner <> dst").distinct()
    return cut(predicates(links, completer).withColumnRenamed("owner", "src"))


def evidence(relations: DataFrame, clusters: DataFrame, columns: DataFrame, tables: int = 5) -> DataFrame:
    """(src, attr_name, dst, tables, null, multi, uniq): the mean shares of missing, listed and distinct values over k
    sampled tables that have the attribute. columns: (col, table_id, rho_null, rho_multi, rho_uniq)."""
    held = relations.join(clusters.select(F.col("owner").alias("src"), "attr_name", "col"), ["src", "attr_name"]).join(columns.select("col", "table_id", "rho_null", "rho_multi", "rho_uniq"), "col")
    order = Window.partitionBy("src", "attr_name", "dst").orderBy(digest("table_id"), "col")
    some = held.withColumn("_k", F.row_number().over(order)).where(F.col("_k") <= tables)
    mean = lambda c: F.round(F.avg(F.coalesce(c, F.lit(0.0))), 6)
    return some.groupBy("src", "attr_name", "dst").agg(F.count("*").alias("tables"), mean("rho_null").alias("null"), mean("rho_multi").alias("multi"), mean("rho_uniq").alias("uniq"))


def evidence_rows(relations: DataFrame, clusters: DataFrame, columns: DataFrame, k: int = 5) -> DataFrame:
    """(src, attr_name, dst, rows): k sampled values of the attribute with what stands beside them: the first sample of
    each other column of the same table."""
    held = relations.join(clusters.select(F.col("owner").alias("src"), "attr_name", "col"), ["src", "attr_name"])
    values = held.join(columns.select("col", "table_id", F.explode("samples").alias("value")), "col")
    order = Window.partitionBy("src", "attr_name", "dst").orderBy(digest("value", "table_id"))
    some = values.withColumn("_k", F.row_number().over(order)).where(F.col("_k") <= k)
    return some.groupBy("src", "attr_name", "dst").agg(F.transform(F.sort_array(F.collect_list(F.struct("_k", "value"))), lambda x: x["value"]).alias("rows"))


def infer_cardinality(relations: DataFrame, stats: DataFrame, rows: DataFrame, completer: Completer, shown: str = "both") -> DataFrame:
    """(src, attr_name, dst, cardinality) by an ask for each relationship; shown: the evidence in it: stats, rows or both.
    Answers that are none of the four are left out."""
    if shown not in ("both", "stats", "rows"):
        raise ValueError(f"shown is both, stats or rows, not {shown}")
    on = ["src", "attr_name", "dst"]
    held = relations.select(*on).join(stats, on, "left").join(rows, on, "left").withColumn("ask", F.concat_ws("|", *on))
    held = held.withColumn("stats", F.struct("null", "multi", "uniq")).select(*on, "ask", "stats", "rows")
    fields = {"both": ["stats", "rows"], "stats": ["stats"], "rows": ["rows"]}[shown]
    said = answers(held, "cardinality", [*on, *fields], completer)
    return said.select(*on, F.trim("text").alias("cardinality")).where(F.col("cardinality").isin(*CARDINALITIES))
