"""Conceptual attributes: what columns hold, groups of one meaning below a type, names, promotion, domains."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from schemaloom.operators import hierarchy as h
from schemaloom.operators.asks import Completer, answers
from schemaloom.sources.shared import cut

#: Names of one semantic group that a single ask may hold; a larger group is asked about in parts.
GROUP_NAMES = 200


def column_context(columns: DataFrame, rows: DataFrame) -> DataFrame:
    """columns with `around`, the table's sampled rows, in which the column's values stand. rows: (table_id, rows)."""
    return columns.join(rows.select("table_id", F.col("rows").alias("around")), "table_id", "left")


def extract_paths(text: Column, max_types: int = 5, root: str = h.ROOT) -> Column:
    """Every arrow-separated path in free text that repeats no type, without the root, cut after max_types."""
    found = F.regexp_extract_all(text, F.lit(r"[A-Za-z][A-Za-z_ ]*(?:-> *[A-Za-z][A-Za-z_ ]*)+"), F.lit(0))
    found = F.transform(found, lambda x: F.regexp_replace(x, f"^.* {root} *->", f"{root} ->"))  # words before the root are no type
    paths = F.transform(found, lambda x: F.slice(F.filter(F.transform(F.split(x, "->"), lambda t: F.trim(t)), lambda t: t != root), 1, max_types))
    return F.array_distinct(F.filter(paths, lambda p: (F.size(p) > 0) & ~h.malformed(p)))


def infer_column_paths(columns: DataFrame, completer: Completer) -> DataFrame:
    """(col, path_no, path): columns: (col, header, kind, samples, around or not). One ask a column."""
    more = [c for c in ("around",) if c in columns.columns]
    rows = columns.select(F.col("col").alias("ask"), "header", "kind", F.col("samples").alias("values"), *more)
    said = answers(rows, "column_path", ["header", "kind", "values", *more], completer)
    return said.select(F.col("ask").alias("col"), F.posexplode(extract_paths(F.col("text"))).alias("path_no", "path"))


def column_hierarchy(paths: DataFrame) -> DataFrame:
    """Semantic types of columns as one hierarchy: merged and pruned, not verified."""
    edges = h.merge_edges(h.path_edges(paths.withColumnRenamed("col", "table_id")))
    return h.attach_orphans(h.break_cycles(cut(h.prune_inverse(h.prune_self_loops(edges)))))


def semantic_types(paths: DataFrame, edges: DataFrame) -> DataFrame:
    """(col, sem_type): the deepest common ancestor of a column's most specific types."""
    leaves = paths.select(F.col("col").alias("item"), F.element_at("path", -1).alias("type_name")).distinct()
    return h.common_ancestor(leaves, edges).select(F.col("item").alias("col"), F.col("type_name").alias("sem_type"))


def semantic_groups(owners: DataFrame, columns: DataFrame, semantic: DataFrame) -> DataFrame:
    """(type_name, sem_type, col): columns of a type's tables by what they hold. owners: (table_id, type_name)."""
    return owners.join(columns.select("table_id", "col"), "table_id").join(semantic, "col").select("type_name", "sem_type", "col").distinct()


def name_attributes(groups: DataFrame, columns: DataFrame, completer: Completer) -> DataFrame:
    """(type_name, sem_type, col, name): the role of each column for its owner, one ask each. columns: with around or not."""
    more = [c for c in ("around",) if c in columns.columns]
    rows = groups.join(columns.select("col", "header", "kind", F.col("samples").alias("values"), *more), "col").withColumn("ask", F.concat_ws("|", "type_name", "col"))
    said = answers(rows, "attr_name", ["header", "type_name", "sem_type", "kind", "values", *more], completer)
    return said.select("type_name", "sem_type", "col", F.lower(F.trim("text")).alias("name"))


def parse_mapping(text: Column) -> Column:
    """An array of (name, unified) from 'name => unified; ...'."""
    parts = F.filter(F.split(text, ";"), lambda x: x.contains("=>"))
    return F.transform(parts, lambda x: F.struct(F.trim(F.split_part(x, F.lit("=>"), F.lit(1))).alias("name"), F.trim(F.split_part(x, F.lit("=>"), F.lit(2))).alias("attr_name")))


def resolve_names(names: DataFrame, completer: Completer, by: tuple[str, ...] = ("type_name", "sem_type")) -> DataFrame:
    """names with attr_name: names of one meaning get one name, within a semantic group alone. Distinct names of a group
    go in one ask, or by hash in several where they are too many; a name that the answer leaves out stays."""
    distinct = names.select(*by, "name").distinct()
    sizes = distinct.groupBy(*by).agg(F.ceil(F.count("*") / GROUP_NAMES).alias("parts"))
    dealt = distinct.join(sizes, list(by)).withColumn("part", F.pmod(F.xxhash64("name"), "parts"))
    groups = dealt.groupBy(*by, "part").agg(F.sort_array(F.collect_list("name")).alias("names")).withColumn("ask", F.concat_ws("|", *by, "part"))
    said = answers(groups, "resolve", ["names"], completer)
    mapped = said.select(*by, F.inline(parse_mapping(F.col("text")))).dropDuplicates([*by, "name"])
    return names.join(mapped, [*by, "name"], "left").withColumn("attr_name", F.coalesce("attr_name", "name"))


def local_attributes(resolved: DataFrame) -> DataFrame:
    """(type_name, attr_name): every group's attributes of a type together."""
    return resolved.select("type_name", "attr_name").distinct()


def unify_across(attributes: DataFrame, edges: DataFrame, completer: Completer, root: str = h.ROOT) -> DataFrame:
    """attributes with names that sibling types use for one meaning made one, an ask for each parent; what siblings share
    can then be counted."""
    steps = edges.where(F.col("parent") != root).select(F.col("child").alias("type_name"), F.col("parent").alias("owner")).distinct()
    held = attributes.join(steps, "type_name", "left").withColumn("owner", F.coalesce("owner", F.lit(root)))
    named = resolve_names(held.withColumnRenamed("attr_name", "name"), completer, ("owner",))
    return named.select("type_name", "attr_name").distinct()


def owners_above(attributes: DataFrame, edges: DataFrame, theta: float = 0.9) -> tuple[DataFrame, DataFrame]:
    """(promoted attributes, (type_name, attr_name, owner)): for each attribute of a type the highest type above it that
    the attribute was promoted to, or the type itself."""
    up = cut(h.promote(attributes, edges, theta))
    ways = h.reach(edges).select(F.col("descendant").alias("type_name"), F.col("ancestor").alias("owner")).union(attributes.select("type_name", F.col("type_name").alias("owner")).distinct())
    deep = h.levels(edges).withColumnRenamed("type_name", "owner")
    held = up.select(F.col("type_name").alias("owner"), "attr_name")
    order = Window.partitionBy("type_name", "attr_name").orderBy(F.coalesce("level", F.lit(99)), "owner")
    found = attributes.join(ways, "type_name").join(held, ["owner", "attr_name"]).join(deep, "owner", "left")
    return up, found.withColumn("_k", F.row_number().over(order)).where("_k = 1").select("type_name", "attr_name", "owner")


def domains(resolved: DataFrame, columns: DataFrame, edges: DataFrame) -> DataFrame:
    """(type_name, attr_name, domain): the type of the hierarchy that bears the attribute's name, or else the kind that
    most of its columns have; of equally common kinds the first by name."""
    counted = resolved.join(columns.select("col", "kind"), "col").groupBy("type_name", "attr_name", "kind").agg(F.count("*").alias("n"))
    order = Window.partitionBy("type_name", "attr_name").orderBy(F.desc("n"), "kind")
    first = counted.withColumn("_k", F.row_number().over(order)).where("_k = 1")
    types = edges.select(F.col("child").alias("named")).distinct()
    same = F.lower(h.align_name(F.col("attr_name"))) == F.lower("named")
    return first.join(types, same, "left").select("type_name", "attr_name", F.when(F.col("named").isNotNull() & (F.col("kind") == "entity"), F.col("named")).otherwise(F.col("kind")).alias("domain"))


def infer_attributes(columns: DataFrame, owners: DataFrame, edges: DataFrame, completer: Completer, theta: float = 0.9) -> dict[str, DataFrame]:
    """The whole second step. columns: (col, table_id, header, kind, samples, around or not); owners: (table_id, type_name), the most
    specific type of each table; edges: its hierarchy. Gives paths, hierarchy, semantic, groups, named, resolved,
    local, promoted, owners and clusters (col, type_name, attr_name, owner)."""
    paths = cut(infer_column_paths(columns, completer))
    own = cut(column_hierarchy(paths))
    semantic = cut(semantic_types(paths, own))
    groups = cut(semantic_groups(owners, columns, semantic))
    named = name_attributes(groups, columns, completer)
    resolved = cut(resolve_names(named, completer))
    local = cut(local_attributes(resolved))
    promoted, above = owners_above(local, edges, theta)
    above = cut(above)
    clusters = cut(resolved.join(above, ["type_name", "attr_name"]).select("col", "type_name", "attr_name", "owner"))
    return {"paths": paths, "hierarchy": own, "semantic": semantic, "groups": groups, "named": named, "resolved": resolved, "local": local, "promoted": promoted, "owners": above, "clusters": clusters}
