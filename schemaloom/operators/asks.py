"""Asks to a text completer: prompts, answers, a cache that survives, and the first step's asks."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager
from contextvars import ContextVar
from typing import Protocol

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from schemaloom.operators.hierarchy import ROOT, attach_orphans, break_cycles, extract_path, malformed, merge_edges, path_edges, prune_inverse, prune_self_loops, verify_edges
from schemaloom.operators.lexicon import ABSTRACT, TWINS
from schemaloom.sources.shared import cut

CONSTRAINTS = ("none", "abstract", "converge", "leaf_first", "full")
#: What each stage asks for. A prompt is the stage in brackets, add-ons and this text, and the ask's JSON as its last line.
TEMPLATES = {
    "type_path": "Root type: Thing. Give one or more is-a paths of at most 5 types for the table below, from general to specific, joined by '->'.",
    "leaf_types": "Name the most specific entity types of the table below.",
    "column_path": "Root type: Thing. Give is-a paths for what the column below holds, given its header, five values and the rows around them.",
    "verify": "Is every instance of the first type also one of the second, as far as their tables' headers tell? Answer yes or no.",
    "attr_name": "Name the role that this column plays for its owner, in a few words.",
    "resolve": "Map these names, which stand in one semantic group, to one name for each meaning, as 'name => unified name', with semicolons between.",
    "top_types": "Of the listed general types, name at most k that the values may denote, best first, with commas between.",
    "pick_type": "Which one of the candidate types do the values denote? Answer a candidate or none.",
    "predicate": "Give a short label for how the source type relates to the target through this attribute.",
    "cardinality": "Is the relationship 1:1, 1:n, n:1 or m:n, given these shares and rows?",
    "taxonomy_children": "Which of the remaining types are direct subtypes of the given one? Answer with commas between, or none.",
    "is_a": "Is every instance of the first type also one of the second? Answer yes or no.",
    "group_names": "Group names of one meaning and give each group one name, as 'name => unified name', with semicolons between.",
    "cluster_name": "Name the kind of thing that tables with these headers list.",
}
ADD_ONS = {
    "none": "", "abstract": "Don't use types as general as Object, Entity or Concept.", "converge": "Let general types be few: reuse one for tables of a kind.",
    "leaf_first": "The paths must end in the given leaf types.", "full": "The paths must end in the given leaf types. Let general types be few: reuse one for tables of a kind.",
}


class Completer(Protocol):
    def complete(self, prompts: list[str]) -> list[str]: ...


def render_prompt(stage: str, payload: Column, constraint: str = "none") -> Column:
    return F.concat(F.lit("\n".join(x for x in (f"[{stage}]", ADD_ONS[constraint], TEMPLATES[stage]) if x) + "\n"), payload)


def ask(asks: DataFrame, completer: Completer, cache: str | None = None, per_batch: int = 32) -> DataFrame:
    """(ask_id, text): answers of asks (ask_id, prompt). Prompts alike are asked once. With a cache folder only asks
    that it lacks are made, and their answers are added, so a run that broke off goes on where it stood."""
    spark = asks.sparkSession
    keyed = asks.withColumn("digest", F.md5("prompt"))
    fresh = keyed.select("digest", "prompt").dropDuplicates(["digest"])
    known = None
    if cache:
        try:
            known = spark.read.schema("digest string, text string").parquet(cache)
            fresh = fresh.join(known, "digest", "left_anti")
        except Exception as missing:
            if "PATH_NOT_FOUND" not in str(missing):
                raise

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            texts: list[str] = []
            for at in range(0, len(frame), per_batch):
                texts += completer.complete(frame["prompt"].iloc[at : at + per_batch].tolist())
            yield pd.DataFrame({"digest": frame["digest"], "text": texts})

    answers = fresh.mapInPandas(run, "digest string, text string")
    if cache:
        answers.write.mode("append").parquet(cache)
        answers = spark.read.schema("digest string, text string").parquet(cache)
    return keyed.select("ask_id", "digest").join(answers, "digest").select("ask_id", "text")


class ReplayCompleter:
    """Answers that were given before, by prompt."""

    def __init__(self, answers: dict[str, str]):
        self.answers = answers

    def complete(self, prompts: list[str]) -> list[str]:
        return [self.answers.get(p, "") for p in prompts]


class EndpointCompleter:
    """A user's function from a prompt to a text."""

    def __init__(self, call: Callable[[str, float], str], temperature: float = 0.1):
        self.call, self.temperature = call, temperature

    def complete(self, prompts: list[str]) -> list[str]:
        return [self.call(p, self.temperature) for p in prompts]


_LEDGERS: ContextVar[tuple[list, ...]] = ContextVar("ledgers", default=())


@contextmanager
def ledger() -> Iterator[list]:
    """Inside, every stage that this thread asks adds (stage, one row a call with prompt_chars and answer_chars)."""
    held: list = []
    before = _LEDGERS.set((*_LEDGERS.get(), held))
    try:
        yield held
    finally:
        _LEDGERS.reset(before)


def answers(rows: DataFrame, stage: str, fields: list[str], completer: Completer, constraint: str = "none", cache: str | None = None) -> DataFrame:
    """rows with the answers' text, each row asked once and the answers written; rows: `ask`, its key, and the payload's
    fields. Null fields are left out of the payload."""
    asked = rows.select("ask", render_prompt(stage, F.to_json(F.struct("ask", *fields)), constraint).alias("prompt"))
    found = ask(asked.select(F.col("ask").alias("ask_id"), "prompt"), completer, cache).withColumnRenamed("ask_id", "ask")
    out = cut(rows.join(found, "ask"))
    for held in _LEDGERS.get():
        held.append((stage, asked.join(out.select("ask", "text"), "ask").select(F.length("prompt").alias("prompt_chars"), F.length("text").alias("answer_chars"))))
    return out


def ask_until_valid(rows: DataFrame, stage: str, fields: list[str], completer: Completer, parse: Column, valid: Column, constraint: str = "none", most_attempts: int = 3) -> tuple[DataFrame, DataFrame]:
    """(rows with `parsed`, rows whose last answer was still not valid, with its text). parse reads the column text, valid
    the column parsed; only what is not valid is asked again, with the number of the attempt."""
    good, open_ = None, rows
    for attempt in range(most_attempts):
        found = answers(open_.withColumn("attempt", F.lit(attempt)), stage, [*fields, "attempt"], completer, constraint).withColumn("parsed", parse)
        found = cut(found)
        ok = F.coalesce(valid, F.lit(False))
        part = found.where(ok).drop("text", "attempt")
        good = part if good is None else good.unionByName(part)
        bad = found.where(~ok)
        open_ = bad.drop("text", "parsed", "attempt")
        if bad.isEmpty():
            break
    return good, bad.drop("parsed", "attempt")


def infer_table_paths(tables: DataFrame, completer: Completer, constraint: str = "none", max_types: int = 5, most_attempts: int = 3) -> tuple[DataFrame, DataFrame]:
    """((table_id, path_no, path), (table_id, text) of what stayed malformed). tables: (table_id, headers, rows). The
    leaf-first constraints take two rounds: the most specific types, then paths that end in them."""
    rows, fields = tables.select(F.col("table_id").alias("ask"), "headers", "rows"), ["headers", "rows"]
    if constraint in ("leaf_first", "full"):
        rows = answers(rows, "leaf_types", fields, completer).withColumnRenamed("text", "leaf")
        fields = [*fields, "leaf"]
    good, bad = ask_until_valid(rows, "type_path", fields, completer, extract_path(F.col("text"), max_types), F.col("parsed").isNotNull() & ~malformed(F.col("parsed")), constraint, most_attempts)
    return good.select(F.col("ask").alias("table_id"), F.lit(1).alias("path_no"), F.col("parsed").alias("path")), bad.select(F.col("ask").alias("table_id"), "text")


def verdicts(edges: DataFrame, paths: DataFrame, tables: DataFrame, completer: Completer) -> DataFrame:
    """(child, parent, verdict) of every edge below the root's. The completer is shown which headers at least half of the
    parent's tables have, and which any of the child's has."""
    through = paths.select("table_id", F.explode("path").alias("type_name")).distinct()
    sizes = through.groupBy("type_name").agg(F.count("*").alias("tables"))
    counts = through.join(tables.select("table_id", F.explode(F.array_distinct("headers")).alias("header")), "table_id").groupBy("type_name", "header").agg(F.count("*").alias("n")).join(sizes, "type_name")
    held = cut(counts.groupBy("type_name").agg(F.sort_array(F.collect_set("header")).alias("own"), F.sort_array(F.collect_set(F.when(F.col("n") * 2 >= F.col("tables"), F.col("header")))).alias("core")))
    empty = F.array().cast("array<string>")
    of = lambda side, c: held.select(F.col("type_name").alias(side), F.col(c).alias(f"{side}_headers"))
    rows = edges.where(F.col("parent") != ROOT).select("child", "parent").join(of("child", "own"), "child", "left").join(of("parent", "core"), "parent", "left")
    rows = rows.select(F.concat_ws("|", "child", "parent").alias("ask"), "child", "parent", F.coalesce("child_headers", empty).alias("child_headers"), F.coalesce("parent_headers", empty).alias("parent_headers"))
    said = answers(rows, "verify", ["child", "parent", "child_headers", "parent_headers"], completer)
    return said.select("child", "parent", F.lower(F.trim("text")).alias("verdict"))


def infer_types(tables: DataFrame, completer: Completer, constraint: str = "none", verify: bool = True) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(paths, hierarchy, rejects): the path-first method's first step, every answer through `ask`."""
    paths, rejects = infer_table_paths(tables, completer, constraint)
    paths = cut(paths)
    edges = cut(prune_inverse(prune_self_loops(merge_edges(path_edges(paths)))))
    if verify:
        edges = verify_edges(edges, verdicts(edges, paths, tables, completer))
    return paths, cut(attach_orphans(break_cycles(edges))), rejects


# --- the same, stated in SQL for the word-list completer ---------------------------------------------------------------


def strike_sql(key: str, kind: str, rate: int) -> str:
    return f"(CAST('0x' || substr(md5(concat_ws('|', '0', {key}, '{kind}')), 1, 6) AS INTEGER) % 100 < {rate})"


def paths_sql(repository: str, noise: int, constraint: str = "none") -> str:
    """table_id, p (list of types): what the word lists answer about the tables of `repository` (table_id, path, variant)."""
    s = lambda kind, *cured: "FALSE" if constraint in cured else strike_sql("table_id", kind, noise)
    twin = "CASE p[1] " + " ".join(f"WHEN '{a}' THEN '{b}'" for a, b in TWINS.items()) + " ELSE p[1] END"
    steps = (
        "CASE WHEN variant = 'narrow' THEN list_slice(string_split(path, '>'), 1, 2) ELSE string_split(path, '>') END",
        f"CASE WHEN {s('early', 'leaf_first', 'full')} AND len(p) > 1 THEN list_slice(p, 1, len(p) - 1) ELSE p END",
        f"CASE WHEN {s('twin', 'converge', 'full')} THEN list_concat([{twin}], list_slice(p, 2, len(p))) ELSE p END",
        f"CASE WHEN {s('abstract', 'abstract')} THEN list_concat(['{ABSTRACT}'], p) ELSE p END",
        f"CASE WHEN {s('wrong')} THEN list_concat(['Activity'], list_filter(p, lambda t: t <> 'Activity')) ELSE p END",
        f"CASE WHEN {s('inverse')} AND len(p) > 2 THEN list_concat(list_slice(p, 1, len(p) - 2), [p[len(p)], p[len(p) - 1]]) ELSE p END",
    )
    out = f"SELECT table_id, {steps[0]} AS p FROM ({repository})"
    for step in steps[1:]:
        out = f"SELECT table_id, {step} AS p FROM ({out})"
    gone = " AND ".join(strike_sql("table_id", f"repeat {k}", noise) for k in range(3))
    return f"SELECT table_id, list_slice(p, 1, 5) AS p FROM ({out}) WHERE len(p) >= 5 OR NOT ({gone})"


def step1_sql(repository: str, headers: str, noise: int, wrong_verdicts: int, verify: bool = True, constraint: str = "none") -> str:
    """A WITH list that ends in edges(child, parent, weight); headers: (table_id, header). It states no cycle breaking:
    the answers that it replays make none."""
    asked = f"""
core AS (SELECT t.type_name, h.header, count(*) AS n, any_value(tables) AS tables FROM through t JOIN ({headers}) h USING (table_id) JOIN sizes USING (type_name) GROUP BY 1, 2),
verdict AS (SELECT child, parent, count(c.header) AS needed, count(o.header) AS there FROM pruned LEFT JOIN (SELECT * FROM core WHERE 2 * n >= tables) c ON c.type_name = parent LEFT JOIN core o ON o.type_name = child AND o.header = c.header WHERE parent <> 'Thing' GROUP BY 1, 2),
kept AS (SELECT p.* FROM pruned p LEFT JOIN verdict v ON v.child = p.child AND v.parent = p.parent WHERE v.child IS NULL OR (2 * there >= needed) <> {strike_sql("concat_ws('|', p.child, p.parent)", 'verdict', wrong_verdicts)})"""
    return f"""
paths AS ({paths_sql(repository, noise, constraint)}),
steps AS (SELECT DISTINCT table_id, ts[k + 1] AS child, ts[k] AS parent FROM (SELECT table_id, ts, unnest(range(1, len(ts))) AS k FROM (SELECT table_id, list_concat(['Thing'], p) AS ts FROM paths))),
weighed AS (SELECT child, parent, count(*) AS weight FROM steps WHERE child <> parent GROUP BY 1, 2),
pruned AS (SELECT child, parent, weight FROM (SELECT *, row_number() OVER (PARTITION BY least(child, parent), greatest(child, parent) ORDER BY weight DESC, parent) AS r FROM weighed) WHERE r = 1),
through AS (SELECT DISTINCT table_id, unnest(p) AS type_name FROM paths), sizes AS (SELECT type_name, count(*) AS tables FROM through GROUP BY 1),{asked if verify else "kept AS (SELECT * FROM pruned)"},
edges AS (SELECT child, parent, weight FROM kept UNION ALL SELECT parent, 'Thing', max(weight) FROM kept WHERE parent <> 'Thing' AND parent NOT IN (SELECT child FROM kept) GROUP BY parent)"""
