"""The table repository that the given tables are cut into, with its true types.

A fragment is the part of a base table that shares one value of a split expression. Headers lose the base's prefix;
three variants of each fragment keep them, rename them, or drop some columns.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from schemaloom.registry import table

VARIANTS = ("full", "renamed", "narrow")


@dataclass(frozen=True)
class Base:
    """columns: those of the parquet table; split: SQL over them (both engines); types: path below the root; leaf: what
    follows the split value in the name of the lowest type, or None."""

    name: str
    prefix: str
    columns: tuple[str, ...]
    split: str
    types: tuple[str, ...]
    leaf: str | None = None
    join: str = ""
    split_columns: tuple[str, ...] = ()
    numeric: tuple[str, ...] = ()

    def header(self, column: str) -> str:
        return column.removeprefix(self.prefix)

    def narrow(self) -> tuple[str, ...]:
        """First the split columns, then the last numeric one that is left, go, while two columns stay."""
        left = list(self.columns)
        for c in [*self.split_columns, *[x for x in self.columns if x in self.numeric and x not in self.split_columns][-1:]]:
            if c in left and len(left) > 2:
                left.remove(c)
        return tuple(left)

    def key_sql(self) -> str:
        return f"SELECT {self.split} AS k FROM {self.name} {self.join}"

    def path_sql(self) -> str:
        """The true path of a fragment with key k."""
        fixed = ">".join(self.types)
        return f"'{fixed}'" if self.leaf is None else f"concat('{fixed}>', upper(substr(k, 1, 1)), lower(substr(k, 2)), '{self.leaf}')"


def _base(name: str, prefix: str, columns: str, split: str, types: str, leaf: str | None = None, numeric: str = "", split_columns: str = "", join: str = "") -> Base:
    return Base(name, prefix, tuple(columns.split()), split, tuple(types.split(">")), leaf, join, tuple(split_columns.split()), tuple(numeric.split()))


BASES = (
    _base("region", "r_", "r_regionkey r_name", "'all'", "Place>Region", numeric="r_regionkey"),
    _base("nation", "n_", "n_nationkey n_name n_regionkey", "CAST(n_regionkey AS STRING)", "Place>Country", numeric="n_nationkey n_regionkey", split_columns="n_regionkey"),
    _base("customer", "c_", "c_custkey c_name c_nationkey c_acctbal c_mktsegment", "c_mktsegment", "Agent>Customer", "Customer", "c_custkey c_nationkey c_acctbal", "c_mktsegment"),
    _base("supplier", "s_", "s_suppkey s_name s_nationkey s_acctbal", "CAST(n_regionkey AS STRING)", "Agent>Supplier", numeric="s_suppkey s_nationkey s_acctbal", split_columns="s_nationkey", join="JOIN nation ON s_nationkey = n_nationkey"),
    _base("part", "p_", "p_partkey p_name p_brand p_type p_size p_retailprice", "p_type", "Product>Part", "Part", "p_partkey p_size p_retailprice", "p_type"),
    _base("orders", "o_", "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority", "o_orderpriority", "Transaction>Order", numeric="o_orderkey o_custkey o_totalprice", split_columns="o_orderpriority"),
    _base("lineitem", "l_", "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate", "concat(l_returnflag, '-', l_linestatus)", "Transaction>OrderLine", numeric="l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax", split_columns="l_returnflag l_linestatus"),
    _base("events", "", "event_id ts user_id event_type value props", "event_type", "Activity>UserEvent", "Event", "event_id user_id value", "event_type"),
    _base("documents", "", "doc_id text lang source n_chars", "lang", "CreativeWork>Document", "Document", "doc_id n_chars", "lang"),
    _base("pages", "", "page_id url html", "regexp_extract(html, '<html lang=\"([a-z]+)\"', 1)", "CreativeWork>WebPage", numeric="page_id"),
    _base("benchmark", "", "item_id text", "'all'", "CreativeWork>Passage", numeric="item_id"),
    _base("conversations", "", "conv_id turn role text", "role", "CreativeWork>Message", "Message", "conv_id turn", "role"),
    _base("labels", "", "doc_id quality toxic", "CAST(quality AS STRING)", "Intangible>Annotation", numeric="doc_id quality toxic", split_columns="quality"),
    _base("embeddings", "", "vec_id embedding label", "CAST(label AS STRING)", "Intangible>Vector", numeric="vec_id label", split_columns="label"),
)
BY_NAME = {b.name: b for b in BASES}
#: Headers that the renamed variant replaces.
SYNONYMS = {"name": "title", "acctbal": "balance", "nationkey": "country_ref", "orderdate": "placed_on", "custkey": "client_no", "totalprice": "amount", "text": "body", "type": "kind"}


def keyed(spark: SparkSession, sf_dir: str, base: Base) -> DataFrame:
    """A base table's columns with the fragment's key k."""
    df = table(spark, sf_dir, base.name)
    if base.join:
        df = df.join(table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey"), F.col("s_nationkey") == F.col("n_nationkey"))
    return df.select(*base.columns, F.expr(base.split).alias("k"))


def fragments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(base, k, n_rows, path) of each fragment: one pass over each table, counted before the shuffle."""
    every = [keyed(spark, sf_dir, b).groupBy("k").agg(F.count("*").alias("n_rows")).select(F.lit(b.name).alias("base"), "k", "n_rows", F.expr(b.path_sql()).alias("path")) for b in BASES]
    return reduce(DataFrame.unionByName, every)


FRAGMENTS_SQL = " UNION ALL ".join(f"SELECT '{b.name}' AS base, k, n AS n_rows, {b.path_sql()} AS path FROM (SELECT k, count(*) AS n FROM ({b.key_sql()}) GROUP BY k)" for b in BASES)


def widths() -> Iterator[tuple[str, str, int]]:
    """(base, variant, columns)."""
    for b in BASES:
        for v in VARIANTS:
            yield b.name, v, len(b.narrow() if v == "narrow" else b.columns)


def repository(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(table_id, base, k, variant, n_rows, n_cols, path): every fragment in every variant."""
    wide = spark.createDataFrame(list(widths()), "base string, variant string, n_cols int")
    return fragments(spark, sf_dir).join(F.broadcast(wide), "base").select(F.concat_ws("_", "base", "k", "variant").alias("table_id"), "base", "k", "variant", "n_rows", "n_cols", "path")


WIDTHS_SQL = "(VALUES " + ", ".join(f"('{b}', '{v}', {n})" for b, v, n in widths()) + ")"
REPOSITORY_SQL = f"SELECT concat_ws('_', f.base, k, variant) AS table_id, f.base, k, variant, n_rows, n_cols, path FROM ({FRAGMENTS_SQL}) f JOIN {WIDTHS_SQL} w(base, variant, n_cols) ON f.base = w.base"
