"""Where queries and their DuckDB twins are registered."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def query(name: str, oracle: str | None = None):
    """Registers a function (spark, sf_dir) under a name, with the SQL that DuckDB holds it against."""

    def put(f):
        if name in QUERIES:
            raise ValueError(f"two queries are named {name}")
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return put


def sql_query(name: str, text: str, oracle: str | None = None) -> None:
    """A query that Spark SQL states; tables stand in braces. DuckDB runs the same text unless another is given."""
    used = [t for t in TABLES if "{" + t + "}" in text]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(text, **{t: table(spark, sf_dir, t) for t in used})

    twin = oracle or text
    for t in TABLES:
        twin = twin.replace("{" + t + "}", t)
    query(name, twin)(run)


def values(rows: list[tuple], columns: str) -> str:
    """The rows as a VALUES relation that both engines read."""

    def literal(x) -> str:
        if x is None:
            return "NULL"
        return str(x) if isinstance(x, int | float) else "'" + str(x).replace("'", "''") + "'"

    return f"(SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(literal, r)) + ')' for r in rows)}) AS v({columns}))"
