"""Bounded context for asks: distinct rows and values in the order of their hashes, and column profiles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def digest(*columns: str | Column, seed: str = "0") -> Column:
    """A hash that DuckDB computes alike; samples follow its order, so that they can be replayed."""
    return F.md5(F.concat_ws("|", F.lit(seed), *(F.col(c).cast("string") if isinstance(c, str) else c for c in columns)))


#: Hex digits of a hash that bounds are found by, and the share of rows that they are found on.
PREFIX, BOUNDING = 3, 1 / 16


def sample_rows(df: DataFrame, key: str, columns: list[str], k: int = 5, seed: str = "0") -> DataFrame:
    """k distinct rows of each key, with the smallest hashes. The k-th different beginning among some rows' hashes bounds
    the k-th hash of all; every row is held against its key's bound, so that few are left to rank. Equal rows share a rank
    and are told apart on what is left."""
    hashed = lambda rows: rows.select(key, *columns).withColumn("digest", digest(*columns, seed=seed))
    begins = F.conv(F.substring("digest", 1, PREFIX), 16, 10).cast("int")
    some = hashed(df.where(F.rand(1) < BOUNDING)).groupBy(key, begins.alias("_begin")).agg(F.lit(1))
    bound = some.groupBy(F.col(key).alias("_key")).agg(F.get(F.array_sort(F.collect_list("_begin")), F.lit(k - 1)).alias("_bound")).where("_bound IS NOT NULL")
    left = hashed(df).join(F.broadcast(bound), F.col(key).eqNullSafe(F.col("_key")), "left").where(F.col("_bound").isNull() | (begins <= F.col("_bound"))).drop("_key", "_bound")
    order = Window.partitionBy(key).orderBy("digest")
    return left.withColumn("_k", F.dense_rank().over(order)).where(F.col("_k") <= k).drop("_k").dropDuplicates([key, "digest"])


def sample_values(df: DataFrame, key: str, columns: list[str], k: int = 5, seed: str = "0") -> DataFrame:
    """(key, header, value): k distinct values of each column and key that aren't blank."""
    long = df.select(key, *(F.col(c).cast("string").alias(c) for c in columns)).unpivot(key, columns, "header", "value").where("trim(value) <> ''")
    order = Window.partitionBy(key, "header").orderBy(digest("value", seed=seed))
    return long.withColumn("_k", F.dense_rank().over(order)).where(F.col("_k") <= k).drop("_k").distinct()


def sample_tables(tables: DataFrame, key: str, item: str, k: int = 5, seed: str = "0") -> DataFrame:
    order = Window.partitionBy(key).orderBy(digest(item, seed=seed), item)
    return tables.withColumn("_k", F.row_number().over(order)).where(F.col("_k") <= k).drop("_k")


def profile(df: DataFrame, key: str, columns: list[str], exact: bool = True) -> DataFrame:
    """(key, header, cells, rho_null, rho_multi, rho_uniq, digits, dates, chars) of each column and key.

    One scan, turned to a row a cell; equal cells are counted below the first shuffle and meet by a hash, so that neither
    a long text nor a value that a third of all cells hold travels more than once a task. With exact=False distinct values
    are estimated and one shuffle of a row a column is all. rho_multi is over cells that hold something, the others over
    all; digits and dates are shares of cells that hold something.
    """
    long = df.select(key, *(F.col(c).cast("string").alias(c) for c in columns)).unpivot(key, columns, "header", "value")
    held = long.withColumn("digest", F.when(F.trim("value") != "", F.md5("value")))
    return profile_of(held, [key, "header"], exact)[1].drop("kind")


def cell_key(value: Column) -> Column:
    """What equal cells meet by: the text itself below 16 bytes, else the 16 bytes of its hash; null if it holds nothing."""
    held = F.when(F.octet_length(value) < 16, value.cast("binary")).otherwise(F.unhex(digest(value)))
    return F.when(F.trim(value) != "", held)


def profile_of(cells: DataFrame, keys: list[str], exact: bool = True, counted: bool = False, summed: bool = False) -> tuple[DataFrame, DataFrame]:
    """(distinct cells with their counts, the profile of each key) of cells (keys, value, digest); a digest is null for a
    cell that holds nothing, and equal for equal values. All sums are over fixed-width columns, which Spark aggregates by
    hash; what a value shows is one number, its length with a bit for each test. counted: cells are distinct, with a count n.
    summed: the sums that shares_of() takes, in place of the profile."""
    v = F.col("value")
    full = F.col("digest").isNotNull()
    tests = {"full": full, "multi": full & v.contains(";"), "digits": full & v.rlike(r"^-?[0-9]+(\.[0-9]+)?$"), "dates": full & v.rlike(r"^[0-9]{4}-[0-9]{2}-[0-9]{2}")}
    bits = [F.coalesce(x, F.lit(False)).cast("long") * 2**at for at, x in enumerate(tests.values())]
    shown = F.when(full, F.length(v)).otherwise(0).cast("long") * 2 ** len(tests) + sum(bits[1:], bits[0])
    flat = cells.select(*keys, "digest", shown.alias("shown"), *(["n"] if counted else []))
    if counted:
        held, distinct = flat, F.count("digest")
    elif exact:
        held = flat.groupBy(*keys, "digest").agg(F.count("*").alias("n"), F.max("shown").alias("shown"))
        distinct = F.count("digest")
    else:
        held, distinct = flat.withColumn("n", F.lit(1)), F.approx_count_distinct("digest")
    of = {c: F.getbit("shown", F.lit(at)).cast("long") for at, c in enumerate(tests)} | {"chars": F.shiftright("shown", len(tests))}
    sums = held.groupBy(*keys).agg(F.sum("n").alias("cells"), *(F.sum(F.col("n") * x).alias(c) for c, x in of.items()), distinct.alias("distinct"))
    return held, sums if summed else shares_of(sums, keys)


def shares_of(sums: DataFrame, keys: list[str]) -> DataFrame:
    """The profile of each key from its sums: cells, full, multi, digits, dates, chars, distinct."""
    share = lambda a, b: F.when(b > 0, F.round(a / b, 6))
    shares = sums.select(
        *keys, "cells", share(F.col("cells") - F.col("full"), F.col("cells")).alias("rho_null"), share(F.col("multi"), F.col("full")).alias("rho_multi"), share(F.col("distinct"), F.col("cells")).alias("rho_uniq"),
        share(F.col("digits"), F.col("full")).alias("digits"), share(F.col("dates"), F.col("full")).alias("dates"), share(F.col("chars"), F.col("full")).alias("chars"),
    )
    return shares.withColumn("kind", kind())


def kind() -> Column:
    """What a profiled column holds: a date, an identifier, a number, long text or names of entities."""
    return (
        F.when(F.col("dates") >= 0.95, "date").when((F.col("digits") >= 0.95) & (F.col("rho_uniq") >= 0.95), "identifier").when(F.col("digits") >= 0.95, "number")
        .when(F.col("chars") > 60, "text").otherwise("entity")
    )


def rule_cardinality(uniq: Column, multi: Column, null: Column) -> Column:
    """Source : target from the shares of distinct, listed and missing values: few distinct single values are shared by
    many sources; many distinct ones belong to one each; lists make the target side many."""
    listed = F.coalesce(multi, F.lit(0)) >= 0.5
    own = uniq >= 0.8
    return F.when(uniq.isNull() | null.isNull(), F.lit(None)).when(listed & own, "1:n").when(listed, "m:n").when(own, "1:1").otherwise("n:1")


def exact_cardinality(pairs: DataFrame, src: str, dst: str) -> Column | DataFrame:
    """One row: the cardinality that all pairs show."""
    distinct = pairs.select(src, dst).distinct()
    fan = lambda a, b: distinct.groupBy(a).agg(F.count("*").alias("n")).agg(F.max("n").alias("n"))
    out, back = fan(src, dst).withColumnRenamed("n", "out"), fan(dst, src).withColumnRenamed("n", "back")
    side = lambda c, many: F.when(F.col(c) > 1, many).otherwise("1")
    both = out.crossJoin(back)
    return both.select(F.when((F.col("out") > 1) & (F.col("back") > 1), "m:n").otherwise(F.concat(side("back", "n"), F.lit(":"), side("out", "n"))).alias("cardinality"))
