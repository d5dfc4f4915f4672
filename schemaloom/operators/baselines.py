"""Methods to compare with: taxonomies over types of single tables, attributes named before they are grouped, one prompt
for everything, table search by values."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from schemaloom.operators import asks
from schemaloom.operators.attributes import parse_mapping
from schemaloom.operators.hierarchy import ROOT
from schemaloom.sources.shared import cut

#: Types that a taxonomy may have: its prompts list them all, and the driver walks it.
MOST_TYPES = 5_000
#: Characters that fit into one prompt.
CONTEXT = 200_000


def table_types(tables: DataFrame, completer: asks.Completer) -> DataFrame:
    """(table_id, type_name): one type for each table, asked apart."""
    rows = tables.select(F.col("table_id").alias("ask"), "headers", "rows")
    return asks.answers(rows, "leaf_types", ["headers", "rows"], completer).select(F.col("ask").alias("table_id"), F.trim("text").alias("type_name"))


def listed(types: DataFrame) -> list[str]:
    found = [r.type_name for r in types.select("type_name").distinct().orderBy("type_name").limit(MOST_TYPES + 1).collect()]
    if len(found) > MOST_TYPES:
        raise ValueError(f"more than {MOST_TYPES} types")
    return found


def type_taxonomy(types: DataFrame, completer: asks.Completer, most_rounds: int = 16) -> DataFrame:
    """(child, parent, weight): is-a among the tables' types, breadth first from the root: every node of a level is asked
    which of the remaining types are directly below it. A type that several nodes claim hangs under each; what nobody
    claims hangs under the root. Weights count tables."""
    spark = types.sparkSession
    every = listed(types)
    remaining, level, edges = set(every), [ROOT], []
    for _ in range(most_rounds):
        if not level or not remaining:
            break
        rows = spark.createDataFrame([(x, x, sorted(remaining), every) for x in level], "ask string, node string, remaining array<string>, types array<string>")
        said = asks.answers(rows, "taxonomy_children", ["node", "remaining", "types"], completer).select("node", "text").collect()
        found = sorted({(c.strip(), r.node) for r in said for c in r.text.split(",") if c.strip() in remaining and c.strip() != r.node})
        edges += found
        level = sorted({c for c, _ in found})
        remaining -= set(level)
    edges += [(x, ROOT) for x in sorted(remaining)]
    weights = types.groupBy(F.col("type_name").alias("child")).agg(F.count("*").alias("weight"))
    return spark.createDataFrame(edges, "child string, parent string").join(weights, "child").select("child", "parent", "weight")


def pairwise_taxonomy(types: DataFrame, completer: asks.Completer, most_pairs: int = 250_000) -> DataFrame:
    """The same from a yes or no for every ordered pair of types, direct edges alone: an ask that the others imply goes.
    Its asks are the square of the types, which bounds them."""
    spark = types.sparkSession
    every = listed(types)
    if len(every) ** 2 > most_pairs:
        raise ValueError(f"{len(every)} types make too many pairs")
    rows = spark.createDataFrame([(f"{a}|{b}", a, b) for a in every for b in every if a != b], "ask string, child string, parent string")
    yes = asks.answers(rows, "is_a", ["child", "parent"], completer).where("lower(trim(text)) = 'yes'").select("child", "parent")
    yes = cut(yes)
    between = yes.alias("x").join(yes.alias("y"), F.expr("x.parent = y.child")).select(F.col("x.child").alias("child"), F.col("y.parent").alias("parent")).distinct()
    direct = yes.join(between, ["child", "parent"], "left_anti")
    weights = types.groupBy(F.col("type_name").alias("child")).agg(F.count("*").alias("weight"))
    rooted = weights.join(direct.select("child").distinct(), "child", "left_anti").select("child", F.lit(ROOT).alias("parent"), "weight")
    return direct.join(weights, "child").select("child", "parent", "weight").union(rooted)


def name_group(columns: DataFrame, completer: asks.Completer) -> DataFrame:
    """(col, name, attr_name): each column is named apart; then all distinct names are grouped at once, whatever they
    belong to. columns: (col, header, kind, samples). Raises if the names don't fit into a prompt."""
    rows = columns.select(F.col("col").alias("ask"), "header", "kind", F.col("samples").alias("values"))
    named = asks.answers(rows, "attr_name", ["header", "kind", "values"], completer).select(F.col("ask").alias("col"), F.lower(F.trim("text")).alias("name"))
    names = named.agg(F.sort_array(F.collect_set("name")).alias("names"), F.sum(F.length("name")).alias("chars"))
    if (named.select("name").distinct().agg(F.sum(F.length("name"))).first()[0] or 0) > CONTEXT:
        raise ValueError("the names don't fit into one prompt")
    said = asks.answers(names.select(F.lit("all").alias("ask"), "names"), "group_names", ["names"], completer)
    mapped = said.select(F.inline(parse_mapping(F.col("text")))).dropDuplicates(["name"])
    return named.join(mapped, "name", "left").select("col", "name", F.coalesce("attr_name", "name").alias("attr_name"))


def direct_group(columns: DataFrame, completer: asks.Completer, context: int = CONTEXT) -> DataFrame:
    """(col, attr_name) from one prompt that holds every column. Raises if it doesn't fit, which is what speaks against
    it."""
    shown = F.to_json(F.struct("col", "header", "samples"))
    size = columns.agg(F.sum(F.length(shown))).first()[0] or 0
    if size > context:
        raise ValueError(f"{size} characters don't fit into one prompt of {context}")
    rows = [r.asDict() for r in columns.select("col", "header").orderBy("col").collect()]
    prompt = f"[group_names]\n{asks.TEMPLATES['group_names']}\n" + json.dumps({"ask": "all", "names": sorted({r["header"] for r in rows})})
    text = completer.complete([prompt])[0]
    to = {a.strip(): b.strip() for a, _, b in (x.partition("=>") for x in text.split(";")) if b}
    return columns.sparkSession.createDataFrame([(r["col"], to.get(r["header"], r["header"])) for r in rows], "col string, attr_name string")


def table_query(values: DataFrame, queries: DataFrame, k: int = 5) -> DataFrame:
    """(q, table_id, shared, place): the k tables that share most distinct values with a query table, over an inverted
    join. values: (table_id, value), distinct; queries: (table_id), a stated set. Values met in one table alone are out
    before the join."""
    common = values.groupBy("value").agg(F.count("*").alias("n")).where("n > 1").select("value")
    held = values.join(common, "value")
    asked = held.join(queries.distinct(), "table_id", "left_semi").select(F.col("table_id").alias("q"), "value")
    shared = asked.join(held, "value").where("q <> table_id").groupBy("q", "table_id").agg(F.count("*").alias("shared"))
    order = Window.partitionBy("q").orderBy(F.desc("shared"), "table_id")
    return shared.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k)
