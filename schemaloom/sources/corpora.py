"""Table corpora that the given tables are cut into: narrow web-like ones, wide ones with entity values, ones without
subject columns, and a fine-grained large one. Each has true types, attributes and relationships.

A source is a query with a fragment key k; a fragment is the rows of one key, and variants of it keep, rename or drop
headers. Cells are read once for each source; variants differ in headers alone.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from schemaloom.operators import tallies
from schemaloom.registry import TABLES, table
from schemaloom.sources import fragments as fr


@dataclass(frozen=True)
class Source:
    """sql: rows with k, for both engines, tables in braces; columns: (column, header, type that it denotes or "");
    path: SQL over k for the true path; subject: the header of what a row is about, if any."""

    name: str
    sql: str
    columns: tuple[tuple[str, str, str], ...]
    path: str
    narrow: frozenset[str]
    subject: str = ""

    @property
    def top(self) -> str:
        return self.path.replace("concat(", "").strip("'").split(">")[0]

    def twin(self) -> str:
        return reduce(lambda text, t: text.replace("{" + t + "}", t), TABLES, self.sql)


def source_of(b: fr.Base) -> Source:
    """A base of the web-like repository."""
    sql = f"SELECT {', '.join(b.columns)}, {b.split} AS k FROM {{{b.name}}} {b.join.replace('JOIN nation', 'JOIN {nation}')}"
    kept = frozenset(b.columns) - frozenset(b.narrow())
    subject = next((b.header(c) for c in b.columns if b.header(c) == "name"), "")
    return Source(b.name, sql, tuple((c, b.header(c), "") for c in b.columns), b.path_sql(), kept, subject)


def wide(name: str, sql: str, columns: str, path: str, narrow: str, subject: str = "") -> Source:
    """columns: column, or column=header, or column=header>type."""
    parts = [(c, *(h.split(">") + [""])[:2]) for c, _, h in (x.partition("=") for x in columns.split())]
    return Source(name, sql, tuple((c, h or c, t) for c, h, t in parts), path, frozenset(narrow.split()), subject)


WEB = tuple(source_of(b) for b in fr.BASES)
WIDE = (
    wide("customer_wide", "SELECT c_custkey, c_name, c_acctbal, c_mktsegment, n_name, r_name, concat(c_mktsegment, '-', r_name) AS k FROM {customer} JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey",
         "c_custkey=custkey c_name=name c_acctbal=acctbal c_mktsegment=mktsegment n_name=country>Country r_name=region>Region", "'Agent>Customer'", "c_acctbal", "name"),
    wide("supplier_wide", "SELECT s_suppkey, s_name, s_acctbal, n_name, r_name, r_name AS k FROM {supplier} JOIN {nation} ON s_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey",
         "s_suppkey=suppkey s_name=name s_acctbal=acctbal n_name=country>Country r_name=region>Region", "'Agent>Supplier'", "s_acctbal", "name"),
    wide("nation_wide", "SELECT n_nationkey, n_name, r_name, r_name AS k FROM {nation} JOIN {region} ON n_regionkey = r_regionkey", "n_nationkey=nationkey n_name=name r_name=region>Region", "'Place>Country'", "", "name"),
    wide("region_wide", "SELECT r_regionkey, r_name, 'all' AS k FROM {region}", "r_regionkey=regionkey r_name=name", "'Place>Region'", "", "name"),
    wide("part_wide", "SELECT p_partkey, p_name, p_brand, p_size, p_retailprice, p_type AS k FROM {part}", "p_partkey=partkey p_name=name p_brand=brand p_size=size p_retailprice=retailprice", "'Product>Part'", "p_size", "name"),
    wide("orders_wide", "SELECT o_orderkey, c_name, o_orderstatus, o_totalprice, o_orderdate, o_orderpriority AS k FROM {orders} JOIN {customer} ON o_custkey = c_custkey",
         "o_orderkey=orderkey c_name=customer>Customer o_orderstatus=orderstatus o_totalprice=totalprice o_orderdate=orderdate", "'Transaction>Order'", "o_totalprice"),
    wide("lineitem_wide", "SELECT l_orderkey, l_linenumber, p_name, s_name, l_quantity, l_shipdate, concat(l_returnflag, '-', l_linestatus) AS k FROM {lineitem} JOIN {part} ON l_partkey = p_partkey JOIN {supplier} ON l_suppkey = s_suppkey",
         "l_orderkey=orderkey l_linenumber=linenumber p_name=part>Part s_name=supplier>Supplier l_quantity=quantity l_shipdate=shipdate", "'Transaction>OrderLine'", "l_quantity"),
)
MULTI = tuple(x for x in WEB if x.name in ("orders", "lineitem", "events", "labels"))
#: Finer keys, for the large corpus.
FINE_KEYS = {
    "orders": "substr(CAST(o_orderdate AS STRING), 1, 7)", "lineitem": "concat(substr(CAST(l_shipdate AS STRING), 1, 7), l_returnflag)", "part": "concat(p_brand, p_type)",
    "documents": "concat(lang, source)", "events": "concat(substr(CAST(ts AS STRING), 1, 10), event_type)", "pages": "regexp_extract(url, '://([^/]+)', 1)",
}
FINE = tuple(
    Source(b.name, f"SELECT {', '.join(b.columns)}, {FINE_KEYS.get(b.name, b.split)} AS k FROM {{{b.name}}} {b.join.replace('JOIN nation', 'JOIN {nation}')}", source_of(b).columns, "'" + ">".join(b.types) + "'", source_of(b).narrow, source_of(b).subject)
    for b in fr.BASES
)
CORPORA = {"web": WEB, "wide": WIDE, "multi": MULTI}


def variants(source: Source, name: str = "web") -> Iterator[tuple[str, list[tuple[str, str]]]]:
    """(variant, [(column, header)]); the large corpus drops one column more in each of four projections."""
    renamed = lambda h: fr.SYNONYMS.get(h, h)
    modes = {"full": [(c, h) for c, h, _ in source.columns], "renamed": [(c, renamed(h)) for c, h, _ in source.columns], "narrow": [(c, h) for c, h, _ in source.columns if c not in source.narrow]}
    for mode, columns in modes.items():
        if name != "large":
            yield mode, columns
            continue
        for k in range(4):
            yield f"{mode}{k}", [x for j, x in enumerate(columns) if k == 0 or len(columns) < 3 or j != len(columns) - k]


def rows(spark: SparkSession, sf_dir: str, source: Source) -> DataFrame:
    used = [t for t in TABLES if "{" + t + "}" in source.sql]
    return spark.sql(source.sql, **{t: spread(table(spark, sf_dir, t)) if t in LONG else table(spark, sf_dir, t) for t in used})


#: Tables of long texts, which take most of the time for each row.
LONG = ("documents", "pages", "conversations")


def spread(df: DataFrame) -> DataFrame:
    """The rows over all cores: a file of one row group is read by one task, which would also do all that follows."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(4 * cores) if df.rdd.getNumPartitions() < cores else df


def met(left: DataFrame, right: DataFrame, keys: list[str], how: str = "inner") -> DataFrame:
    """left with right's other columns by keys that may be null: rows without a fragment key are a fragment too."""
    other = right.select(*(F.col(c).alias(f"_{c}") if c in keys else F.col(c) for c in right.columns))
    same = reduce(Column.__and__, (F.col(c).eqNullSafe(F.col(f"_{c}")) for c in keys))
    return left.join(other, same, how).drop(*(f"_{c}" for c in keys))


def fragments(spark: SparkSession, sf_dir: str, sources: tuple[Source, ...]) -> DataFrame:
    """(base, k, n_rows, path): a count below the shuffle for each source."""
    every = [rows(spark, sf_dir, x).groupBy("k").agg(F.count("*").alias("n_rows")).select(F.lit(x.name).alias("base"), "k", "n_rows", F.expr(x.path).alias("path")) for x in sources]
    return reduce(DataFrame.unionByName, every)


def fragments_sql(sources: tuple[Source, ...]) -> str:
    return " UNION ALL ".join(f"SELECT '{x.name}' AS base, k, n AS n_rows, {x.path} AS path FROM (SELECT k, count(*) AS n FROM ({x.twin()}) GROUP BY k)" for x in sources)


def layout(sources: tuple[Source, ...], name: str = "web") -> list[tuple]:
    """(base, variant, pos, column, header, attribute, denotes): the columns of each source in each variant. Columns of
    one header below one top-level type are one true attribute."""
    return [(x.name, v, pos, c, h, f"{x.top}.{own[c][0]}", own[c][1]) for x in sources for own in [{c: (h, t) for c, h, t in x.columns}] for v, cs in variants(x, name) for pos, (c, h) in enumerate(cs)]


LAYOUT = "base string, variant string, pos int, column string, header string, attribute string, denotes string"


def layout_sql(sources: tuple[Source, ...], name: str = "web") -> str:
    return "(VALUES " + ", ".join("(" + ", ".join(str(x) if isinstance(x, int) else f"'{x}'" for x in row) + ")" for row in layout(sources, name)) + ") l(base, variant, pos, \"column\", header, attribute, denotes)"


def table_id() -> Column:
    return F.concat_ws("_", "base", "k", "variant")


def tables(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(table_id, base, k, variant, headers, path): every table of a corpus."""
    sources = FINE if name == "large" else CORPORA[name]
    wide_ = [(x.name, v, [h for _, h in cs]) for x in sources for v, cs in variants(x, name)]
    shapes = spark.createDataFrame(wide_, "base string, variant string, headers array<string>")
    return fragments(spark, sf_dir, sources).join(F.broadcast(shapes), "base").select(table_id().alias("table_id"), "base", "k", "variant", "headers", "path")


def sampled(spark: SparkSession, sf_dir: str, name: str, k: int = 5) -> DataFrame:
    """tables() with `rows`: k distinct rows each, in the order of their hashes, cut to the variant's columns. Long
    cells are cut at 80 characters for the prompt alone."""
    from schemaloom.operators import sampling as s

    sources = FINE if name == "large" else CORPORA[name]
    every = []
    for x in sources:
        names = [c for c, _, _ in x.columns]
        top = s.sample_rows(rows(spark, sf_dir, x), "k", names, k)
        cells = F.array(*(F.coalesce(F.substring(F.col(c).cast("string"), 1, 80), F.lit("")) for c in names))
        every.append(top.select(F.lit(x.name).alias("base"), "k", "digest", cells.alias("cells")))
    held = reduce(DataFrame.unionByName, every).groupBy("base", "k").agg(F.transform(F.sort_array(F.collect_list(F.struct("digest", "cells"))), lambda r: r["cells"]).alias("cells"))
    picks = [(x.name, v, [[c for c, _, _ in x.columns].index(c) for c, _ in cs], [h for _, h in cs]) for x in sources for v, cs in variants(x, name)]
    shapes = spark.createDataFrame(picks, "base string, variant string, places array<int>, headers array<string>")
    joined = met(fragments(spark, sf_dir, sources), held, ["base", "k"]).join(F.broadcast(shapes), "base")
    cut = F.transform("cells", lambda r: F.transform("places", lambda k: F.get(r, k)))
    return joined.select(table_id().alias("table_id"), "base", "k", "variant", "headers", "path", cut.alias("rows"))


def cells(spark: SparkSession, sf_dir: str, sources: tuple[Source, ...]) -> DataFrame:
    """(base, k, column, value): every cell as text, blank ones too."""
    def long(x: Source) -> DataFrame:
        names = [c for c, _, _ in x.columns]
        return rows(spark, sf_dir, x).select("k", *(F.col(c).cast("string").alias(c) for c in names)).unpivot("k", names, "column", "value").select(F.lit(x.name).alias("base"), "k", "column", "value")

    return reduce(DataFrame.unionByName, [long(x) for x in sources])


#: Types that are counted as they are stored, and as what.
STORED = {x: "long" for x in ("byte", "short", "integer", "long")} | {x: x for x in ("double", "float", "date", "timestamp", "timestamp_ntz", "boolean")}


#: Of those, the ones that are counted in blocks, and how.
NUMBERS = {"long": tallies.whole, "double": tallies.amount}


def counted(spark: SparkSession, sf_dir: str, sources: tuple[Source, ...], numbers: bool = True) -> DataFrame:
    """(base, k, column, value, n): distinct cells as text with how often they stand there, blank ones too. Numbers
    and times are counted as they are stored and turned to text once a distinct value. Without numbers, cells of numeric
    columns are left out but for those that tallies do not hold."""
    every = []
    for x in sources:
        df = rows(spark, sf_dir, x)
        kinds: dict[str, list[str]] = {}
        for c, _, _ in x.columns:
            name = df.schema[c].dataType.typeName()
            kinds.setdefault(STORED.get(name, "string"), []).append(c)
        for kind, names in kinds.items():
            some = df.select("k", *(F.col(c).cast(kind).alias(c) for c in names))
            if not numbers and kind in NUMBERS:
                left = {c: F.when(NUMBERS[kind](F.col(c)).isNull(), F.col(c)) for c in names}
                some = some.where(reduce(Column.__or__, (x.isNotNull() for x in left.values()))).select("k", *(x.alias(c) for c, x in left.items()))
            one = some.unpivot("k", names, "column", "value")
            if not numbers and kind in NUMBERS:
                one = one.where("value IS NOT NULL")
            # zero and negative zero are one key, but two texts
            zero = (F.when(F.col("value") == 0, F.col("value").cast("string")) if kind in ("double", "float") else F.lit(None).cast("string")).alias("zero")
            held = one.groupBy("k", "column", "value", zero).agg(F.count("*").alias("n"))
            every.append(held.select(F.lit(x.name).alias("base"), "k", "column", F.coalesce("zero", F.col("value").cast("string")).alias("value"), "n"))
    return reduce(DataFrame.unionByName, every)


def placed(spark: SparkSession, sf_dir: str, sources: tuple[Source, ...], spoken: set[tuple[str, str]]) -> tuple[list[tuple], dict[str, dict]]:
    """([(base, k, column, place, header, item, worded, rows)] of every fragment's columns, base -> k -> column -> place)."""
    by = {x.name: x for x in sources}
    shape, places = [], {x.name: {} for x in sources}
    for r in fragments(spark, sf_dir, sources).collect():  # a row a fragment
        own = places[r.base].setdefault(r.k, {})
        for c, header, _ in by[r.base].columns:
            own[c] = len(shape)
            shape.append((r.base, r.k, c, len(shape), header, ".".join(x for x in (r.base, r.k, header) if x is not None), (r.base, c) in spoken, r.n_rows))
    return shape, places


def in_blocks(spark: SparkSession, sf_dir: str, sources: tuple[Source, ...], places: dict[str, dict], words: bool = True) -> tuple[list[DataFrame], set[tuple[str, str]]]:
    """(blocks of the numbers of each source, the (base, column) that they count)."""
    blocks, numeric = [], set()
    for x in sources:
        df = rows(spark, sf_dir, x)
        kinds = {c: STORED.get(df.schema[c].dataType.typeName()) for c, _, _ in x.columns}
        held = {c: NUMBERS[k](F.col(c)) for c, k in kinds.items() if k in NUMBERS}
        if held and places[x.name]:
            numeric |= {(x.name, c) for c in held}
            blocks.append(tallies.number_blocks(df.select("k", *(v.alias(c) for c, v in held.items())), places[x.name], {c for c in held if kinds[c] == "double"}, words))
    return blocks, numeric


def sums_of(spark: SparkSession, shape: list[tuple], numeric: set[tuple[str, str]], found: DataFrame, texts: DataFrame) -> DataFrame:
    """The sums that shares_of() takes, of each fragment's columns: numbers from parts of their sums (at, n, full, chars),
    all else from distinct cells."""
    from schemaloom.operators.sampling import cell_key, profile_of

    keys, summed = ["base", "k", "column"], ["cells", "full", "multi", "digits", "dates", "chars", "distinct"]
    tally = {r.at: r for r in found.groupBy("at").agg(*(F.sum(c).alias(c) for c in ("n", "full", "chars"))).collect()}
    mine = []
    for base, k, c, place, *_, n_rows in shape:
        if (base, c) in numeric:
            full, chars, distinct = (tally[place].full, tally[place].chars, tally[place].n) if place in tally else (0, 0, 0)
            mine.append((base, k, c, n_rows, full, 0, full, 0, chars, distinct))
    own = spark.createDataFrame(mine, "base string, k string, column string, " + ", ".join(f"{c} long" for c in summed))
    other = profile_of(texts.withColumn("digest", cell_key(F.col("value"))), keys, counted=True, summed=True)[1]
    counts = F.broadcast(spark.createDataFrame(sorted(numeric), "base string, column string").withColumn("counted", F.lit(True)))
    other = other.join(counts, ["base", "column"], "left").withColumn("cells", F.when(F.col("counted"), 0).otherwise(F.col("cells"))).select(*keys, *summed)
    return own.union(other).groupBy(*keys).agg(*(F.sum(c).alias(c) for c in summed))


PLACED = "base string, k string, column string, at int, header string, item string, worded boolean, n_rows long"


def tallied(spark: SparkSession, sf_dir: str, sources: tuple[Source, ...], worded: tuple[Source, ...]) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(profiles() without samples, the words of worded sources' columns as lists of the items that hold them, the same
    without headers as hashed vectors (base, k, column, vector), rare words heavier): numbers are counted in blocks, and
    neither distinct cells nor words are written for them."""
    from schemaloom.operators import postings as po
    from schemaloom.operators.clustering import spread_vectors
    from schemaloom.operators.sampling import shares_of
    from schemaloom.sources.shared import cut

    keys = ["base", "k", "column"]
    shape, places = placed(spark, sf_dir, sources, {(x.name, c) for x in worded for c, _, _ in x.columns})
    at = spark.createDataFrame(shape, PLACED)
    texts = cut(counted(spark, sf_dir, sources, numbers=False))
    same = (F.col("base") == F.col("_base")) & F.col("k").eqNullSafe(F.col("_k")) & (F.col("column") == F.col("_column"))
    named = F.broadcast(at.where("worded").select(*(F.col(c).alias(f"_{c}") for c in keys), "at"))
    split = lambda c: F.split(F.lower(c), "[^a-z0-9]+")
    word = F.when(F.translate("value", "0123456789", "") == "", F.array("value")).otherwise(split("value"))
    said = texts.where("trim(value) <> ''").join(named, same).select("at", F.explode(word).alias("term"), "n").where("term <> ''")
    blocks, numeric = in_blocks(spark, sf_dir, sources, places)
    blocks.insert(0, tallies.word_blocks(said.where(tallies.held_word(F.col("term")))))
    found = cut(tallies.merged(reduce(DataFrame.union, blocks), [r[5] for r in shape], {r[3] for r in shape if r[6]}))
    sums = cut(sums_of(spark, shape, numeric, found.where("at IS NOT NULL"), texts))
    heads = sums.where("full > 0").join(F.broadcast(at.where("worded").select(*(F.col(c).alias(f"_{c}") for c in keys), "at", "header")), same).select("at", F.explode(split("header")).alias("term"), F.col("full").alias("n"))
    apart = said.where(~tallies.held_word(F.col("term"))).union(heads.where("term <> ''")).groupBy("at", "term").agg(F.sum("n").cast("double").alias("w"))
    terms = apart.join(F.broadcast(at.select("at", "item")), "at").select("item", "term", "w")
    lists = found.where("at IS NULL").select("held", "n").union(cut(po.postings(terms)))
    # logarithms of shares as differences: how many items there are is known at the end alone
    texts_ = said.where(~tallies.held_word(F.col("term"))).groupBy("at", "term").agg(F.sum("n").alias("n")).withColumn("items", F.count("*").over(Window.partitionBy("term")))
    place, sign = F.pmod(F.xxhash64("term"), F.lit(tallies.PLACES)).cast("int"), F.when(F.pmod(F.xxhash64("term", F.lit(1)), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    own_texts = texts_.select("at", place.alias("place"), (F.col("n") * sign).alias("w"), (F.col("n") * sign * F.log("items")).alias("less"))
    two = F.arrays_zip(F.slice("hashed", 1, tallies.PLACES).alias("w"), F.slice("hashed", tallies.PLACES + 1, tallies.PLACES).alias("less"))
    own_numbers = found.where("at IS NOT NULL").select("at", F.posexplode(two).alias("place", "x")).select("at", "place", "x.w", "x.less").where("w <> 0 OR less <> 0")
    hashed = cut(own_texts.union(own_numbers).groupBy("at", "place").agg(F.sum("w").alias("w"), F.sum("less").alias("less")))
    n_items = float(max(1, hashed.select("at").distinct().count()))
    vectors = spread_vectors(hashed.select(F.col("at").cast("string").alias("item"), "place", (F.col("w") * F.log(F.lit(n_items)) - F.col("less")).alias("w")).where("w <> 0"), tallies.PLACES)
    return shares_of(sums, keys), lists, cut(vectors.withColumnRenamed("item", "place").join(F.broadcast(at), F.col("place") == F.col("at").cast("string")).select(*keys, "vector"))


def dense_vectors(spark: SparkSession, sf_dir: str, sources: tuple[Source, ...], dense: tuple[str, ...]) -> DataFrame:
    """(base, k, column, vector) of the dense columns: the direction of their rows' sum, places beyond the words' size
    taken round. Summed before the shuffle."""
    from schemaloom.operators.clustering import spread_vectors

    every = [spark.createDataFrame([], "base string, k string, column string, vector array<float>")]
    for x in sources:
        for c in (c for c, _, _ in x.columns if c in dense):
            at = rows(spark, sf_dir, x).select(F.col("k").alias("item"), F.posexplode(c).alias("place", "w")).where("w IS NOT NULL AND NOT isnan(w)")
            held = at.groupBy("item", F.pmod("place", F.lit(tallies.PLACES)).alias("place")).agg(F.sum("w").alias("w")).where("w <> 0")
            every.append(spread_vectors(held, tallies.PLACES).select(F.lit(x.name).alias("base"), F.col("item").alias("k"), F.lit(c).alias("column"), "vector"))
    return reduce(DataFrame.unionByName, every)


def first_values(heads: DataFrame, samples: int) -> DataFrame:
    """(base, k, column, samples): the values with the smallest hashes. heads: (base, k, column, hash, head)."""
    keys = ["base", "k", "column"]
    first = heads.withColumn("_r", F.row_number().over(Window.partitionBy(*keys).orderBy("hash"))).where(F.col("_r") <= samples)
    return first.groupBy(*keys).agg(F.transform(F.sort_array(F.collect_list(F.struct("_r", "head"))), lambda x: x["head"]).alias("samples"))


def profiled(spark: SparkSession, sf_dir: str, sources: tuple[Source, ...], samples: int = 5) -> DataFrame:
    """profiles() with samples from numbers counted in blocks, of which neither cells nor words are written."""
    from schemaloom.operators.sampling import cell_key, digest, shares_of
    from schemaloom.sources.shared import cut

    keys = ["base", "k", "column"]
    shape, places = placed(spark, sf_dir, sources, set())
    texts = cut(counted(spark, sf_dir, sources, numbers=False))
    blocks, numeric = in_blocks(spark, sf_dir, sources, places, words=False)
    of = F.unhex(digest("value")).alias("hash")
    heads = texts.where(cell_key(F.col("value")).isNotNull()).select(*keys, of, F.substring("value", 1, 80).alias("head"))
    found = spark.createDataFrame([], tallies.SUMMED)
    if blocks:
        found = cut(tallies.summed(reduce(DataFrame.union, blocks), len(shape), samples))
        at = F.broadcast(spark.createDataFrame(shape, PLACED).select(*keys, "at"))
        heads = heads.union(found.join(at, "at").select(*keys, F.explode("heads").alias("value")).select(*keys, of, F.col("value").alias("head")))
    return met(shares_of(sums_of(spark, shape, numeric, found, texts), keys), first_values(heads, samples), keys, "left")


def profiles(spark: SparkSession, sf_dir: str, sources: tuple[Source, ...], samples: int = 5, cells: DataFrame | None = None) -> DataFrame:
    """(base, k, column, cells, rho_null, rho_multi, rho_uniq, kind, samples) of each column of each fragment, from the
    distinct cells with their counts; cells: those of counted(), if at hand. Samples are the values with the smallest
    hashes; a task sends the first few of each column."""
    from schemaloom.operators.sampling import cell_key, digest, profile_of

    held = (counted(spark, sf_dir, sources) if cells is None else cells).withColumn("digest", cell_key(F.col("value")))
    keys = ["base", "k", "column"]
    stats = profile_of(held, keys, counted=True)[1]
    if not samples:
        return stats
    heads = held.where("digest IS NOT NULL").select(*keys, F.unhex(digest("value")).alias("hash"), F.substring("value", 1, 80).alias("head"))
    return met(stats, first_values(heads, samples), keys, "left")


def profiles_sql(sources: tuple[Source, ...]) -> str:
    """base, k, column, cells, rho_null, rho_multi, rho_uniq, kind."""
    parts = []
    for x in sources:
        for c, _, _ in x.columns:
            v = f"CASE WHEN trim(CAST({c} AS VARCHAR)) <> '' THEN CAST({c} AS VARCHAR) END"
            parts.append(f"SELECT '{x.name}' AS base, k, '{c}' AS \"column\", {v} AS v FROM ({x.twin()})")
    return f"""
SELECT base, k, "column", cells, CASE WHEN cells > 0 THEN round((cells - f) / cells, 6) END AS rho_null, CASE WHEN f > 0 THEN round(multi / f, 6) END AS rho_multi, round(d / cells, 6) AS rho_uniq,
  CASE WHEN f > 0 AND dates / f >= 0.95 THEN 'date' WHEN f > 0 AND digits / f >= 0.95 AND d / cells >= 0.95 THEN 'identifier' WHEN f > 0 AND digits / f >= 0.95 THEN 'number' WHEN f > 0 AND chars / f > 60 THEN 'text' ELSE 'entity' END AS kind
FROM (SELECT base, k, "column", count(*) AS cells, count(v) AS f, count(DISTINCT v) AS d, count(*) FILTER (contains(v, ';')) AS multi, count(*) FILTER (regexp_matches(v, '^-?[0-9]+(\\.[0-9]+)?$')) AS digits,
  count(*) FILTER (regexp_matches(v, '^[0-9]{{4}}-[0-9]{{2}}-[0-9]{{2}}')) AS dates, sum(length(v)) AS chars FROM ({' UNION ALL '.join(parts)}) GROUP BY base, k, "column")"""


def columns(spark: SparkSession, sf_dir: str, name: str, samples: int = 5, cells: DataFrame | None = None, profile: DataFrame | None = None) -> DataFrame:
    """(col, table_id, base, k, variant, pos, column, header, attribute, denotes, path, and the profile): every column of
    every table of a corpus. Names, not cells, are multiplied by the variants."""
    sources = FINE if name == "large" else CORPORA[name]
    shape = spark.createDataFrame(layout(sources, name), LAYOUT)
    held = (profiles(spark, sf_dir, sources, samples, cells) if profile is None else profile).join(F.broadcast(shape), ["base", "column"])
    path = reduce(lambda a, x: F.when(F.col("base") == x.name, F.expr(x.path)).otherwise(a), sources, F.lit(None).cast("string"))
    return held.withColumn("table_id", table_id()).withColumn("path", path).withColumn("col", F.concat_ws(".", "table_id", "header"))


def columns_sql(name: str) -> str:
    sources = FINE if name == "large" else CORPORA[name]
    path = "CASE base " + " ".join(f"WHEN '{x.name}' THEN {x.path}" for x in sources) + " END"
    return f"""SELECT *, concat_ws('.', table_id, header) AS col FROM (SELECT p.*, l.variant, l.pos, l.header, l.attribute, l.denotes, concat_ws('_', p.base, k, variant) AS table_id, {path.replace('CASE base', 'CASE p.base')} AS path
FROM ({profiles_sql(sources)}) p JOIN {layout_sql(sources, name)} ON l.base = p.base AND l."column" = p."column")"""
