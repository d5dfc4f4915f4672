"""Runs of the methods over a corpus, each step written once for a session and read by the queries that need it."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from schemaloom.operators import asks, attributes
from schemaloom.operators.lexicon import Lexicon
from schemaloom.sources import corpora
from schemaloom.sources.shared import cut

#: Errors in a hundred asks, of each kind, and wrong verdicts.
NOISE, WRONG = 8, 4
#: Columns whose values are vectors already.
DENSE = ("embedding",)
_HELD: dict[tuple, object] = {}


def once(spark: SparkSession, key: tuple, make: Callable[[], object]):
    """What make() gives, written in the shared folder; made once for an application."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _HELD:
        _HELD[key] = make()
    return _HELD[key]


def lexicon() -> Lexicon:
    return Lexicon(NOISE, WRONG)


def together(spark: SparkSession, *steps: Callable[[], object]) -> list:
    """What steps that share none give, made at once: while one is planned or waits for its last tasks, another's run."""
    with ThreadPoolExecutor(len(steps)) as pool:
        return [x.result() for x in [pool.submit(inheritable_thread_target(spark)(step)) for step in steps]]


def ledgered(spark: SparkSession, key: tuple, make: Callable[[], object]) -> tuple[object, list]:
    """(what make() gives, the ledger of the asks that made it); made once for an application. What it is made from must be
    there before, so that no other step's asks are taken for its own."""
    def run():
        with asks.ledger() as held:
            return make(), held

    return once(spark, key, run)


def of_web(spark: SparkSession, step: str, sf_dir: str, corpus: str) -> bool:
    """Whether a step over the web corpus is there, of whose bases the smaller corpus has some."""
    return corpus == "multi" and (spark.sparkContext.applicationId, step, sf_dir, "web") in _HELD


def smaller(df: DataFrame) -> DataFrame:
    return df.where(F.col("base").isin(*(x.name for x in corpora.MULTI)))


def tables(spark, sf_dir: str, corpus: str) -> DataFrame:
    """(table_id, base, k, variant, headers, path, rows): path is the true one, which no method reads."""
    if of_web(spark, "tables", sf_dir, corpus):
        return smaller(tables(spark, sf_dir, "web"))
    return once(spark, ("tables", sf_dir, corpus), lambda: cut(corpora.sampled(spark, sf_dir, corpus)))


def tallied(spark, sf_dir: str, corpus: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(profiles without samples, words as lists of the columns that hold them, columns' hashed vectors) of a corpus; dense
    vectors have no words."""
    sources = corpora.FINE if corpus == "large" else corpora.CORPORA[corpus]
    worded = tuple(replace(x, columns=tuple(c for c in x.columns if c[0] not in DENSE)) for x in sources)
    return once(spark, ("tallied", sf_dir, corpus), lambda: corpora.tallied(spark, sf_dir, sources, worded))


def vectors(spark, sf_dir: str, corpus: str) -> DataFrame:
    """(base, k, column, vector): unit vectors of every column that holds something, of its words or of its dense vectors."""
    sources = corpora.FINE if corpus == "large" else corpora.CORPORA[corpus]
    return once(spark, ("vectors", sf_dir, corpus), lambda: tallied(spark, sf_dir, corpus)[2].union(cut(corpora.dense_vectors(spark, sf_dir, sources, DENSE))))


def stats(spark, sf_dir: str, corpus: str) -> DataFrame:
    """columns() without samples, which weights need not."""
    if (spark.sparkContext.applicationId, "columns", sf_dir, corpus) in _HELD:
        return columns(spark, sf_dir, corpus).drop("samples")
    return once(spark, ("stats", sf_dir, corpus), lambda: cut(corpora.columns(spark, sf_dir, corpus, 0, profile=tallied(spark, sf_dir, corpus)[0])))


def columns(spark, sf_dir: str, corpus: str) -> DataFrame:
    """Every column with its profile and samples."""
    if of_web(spark, "columns", sf_dir, corpus):
        return smaller(columns(spark, sf_dir, "web"))
    sources = corpora.FINE if corpus == "large" else corpora.CORPORA[corpus]
    return once(spark, ("columns", sf_dir, corpus), lambda: cut(corpora.columns(spark, sf_dir, corpus, profile=corpora.profiled(spark, sf_dir, sources))))


def asked_types(spark, sf_dir: str, corpus: str, constraint: str = "none", verify: bool = True) -> tuple[tuple[DataFrame, DataFrame, DataFrame], list]:
    held = tables(spark, sf_dir, corpus)
    return ledgered(spark, ("types", sf_dir, corpus, constraint, verify), lambda: asks.infer_types(held, lexicon(), constraint, verify))


def types(spark, sf_dir: str, corpus: str, constraint: str = "none", verify: bool = True) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(paths, hierarchy, rejects)."""
    return asked_types(spark, sf_dir, corpus, constraint, verify)[0]


def owners(spark, sf_dir: str, corpus: str) -> DataFrame:
    """(table_id, type_name): the most specific inferred type of each table."""
    return types(spark, sf_dir, corpus)[0].select("table_id", F.element_at("path", -1).alias("type_name"))


def asked_attributes(spark, sf_dir: str, corpus: str) -> tuple[dict[str, DataFrame], list]:
    held = attributes.column_context(columns(spark, sf_dir, corpus), tables(spark, sf_dir, corpus))
    of, edges = owners(spark, sf_dir, corpus), types(spark, sf_dir, corpus)[1]
    return ledgered(spark, ("attributes", sf_dir, corpus), lambda: attributes.infer_attributes(held, of, edges, lexicon()))


def attributes_of(spark, sf_dir: str, corpus: str) -> dict[str, DataFrame]:
    return asked_attributes(spark, sf_dir, corpus)[0]
