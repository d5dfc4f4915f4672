"""The registry, by the name that plans use."""

from schemaloom.registry import ORACLES, QUERIES, TABLES, query, sql_query, table, values

__all__ = ["ORACLES", "QUERIES", "TABLES", "query", "sql_query", "table", "values"]
