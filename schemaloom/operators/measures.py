"""Accuracy and cost measures."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from schemaloom.operators.hierarchy import ROOT, reach

#: Types whose closure a task may hold at once.
MOST_CLOSURE = 1_000_000


def pair_counts(items: DataFrame, predicted: str = "predicted", truth: str = "truth") -> DataFrame:
    """One row tp, fp, fn, tn: pairs of items put together by both, by the prediction, by the truth, by neither. From
    the sizes of the classes' overlaps: no pair is formed."""
    pairs = lambda: F.coalesce(F.sum(F.expr("n * (n - 1) div 2")), F.lit(0))
    cells = items.groupBy(predicted, truth).agg(F.count("*").alias("n"))
    both = cells.agg(pairs().alias("tp"))
    of = lambda c, name: cells.groupBy(c).agg(F.sum("n").alias("n")).agg(pairs().alias(name))
    every = cells.agg(F.sum("n").alias("n")).select(F.expr("coalesce(n * (n - 1) div 2, 0)").alias("every"))
    row = both.crossJoin(of(predicted, "p")).crossJoin(of(truth, "t")).crossJoin(every)
    return row.select("tp", (F.col("p") - F.col("tp")).alias("fp"), (F.col("t") - F.col("tp")).alias("fn"), (F.col("every") - F.col("p") - F.col("t") + F.col("tp")).alias("tn"))


def rand_index(items: DataFrame, predicted: str = "predicted", truth: str = "truth") -> DataFrame:
    total = F.col("tp") + F.col("fp") + F.col("fn") + F.col("tn")
    return pair_counts(items, predicted, truth).select(F.when(total > 0, F.round((F.col("tp") + F.col("tn")) / total, 6)).alias("value"))


def rand_index_overlap(items: DataFrame, predicted: DataFrame, truth: DataFrame) -> DataFrame:
    """For items with several clusters: a pair is together if it shares one. items: (item); predicted, truth: (item,
    cluster). Forms pairs within clusters, for repositories of moderate size."""
    n = items.distinct().count()
    pairs = lambda df: df.alias("a").join(df.alias("b"), F.expr("a.cluster = b.cluster AND a.item < b.item")).select(F.col("a.item").alias("x"), F.col("b.item").alias("y")).distinct()
    p, t = pairs(predicted), pairs(truth)
    differ = p.join(t, ["x", "y"], "left_anti").union(t.join(p, ["x", "y"], "left_anti")).agg(F.count("*").alias("d"))
    total = n * (n - 1) // 2
    return differ.select(F.round(1 - F.col("d") / F.lit(float(max(total, 1))), 6).alias("value"))


def purity(items: DataFrame, predicted: str = "predicted", truth: str = "truth", macro: bool = True) -> DataFrame:
    """Share of the commonest true class: the mean over predicted clusters, or over items."""
    cells = items.groupBy(predicted, truth).agg(F.count("*").alias("n"))
    clusters = cells.groupBy(predicted).agg(F.max("n").alias("most"), F.sum("n").alias("n"))
    value = F.avg(F.col("most") / F.col("n")) if macro else F.sum("most") / F.sum("n")
    return clusters.agg(F.round(value, 6).alias("value"))


def type_count(edges: DataFrame, root: str = ROOT) -> DataFrame:
    return edges.select(F.explode(F.array("child", "parent")).alias("t")).where(F.col("t") != root).agg(F.count_distinct("t").alias("value"))


def align_types(members: DataFrame, truth: DataFrame) -> DataFrame:
    """(type_name, gt_type): the commonest true type of a type's tables; ties by name. members: (type_name, table_id);
    truth: (table_id, gt_type)."""
    n = members.join(truth, "table_id").groupBy("type_name", "gt_type").agg(F.count("*").alias("n"))
    order = Window.partitionBy("type_name").orderBy(F.desc("n"), "gt_type")
    return n.withColumn("_k", F.row_number().over(order)).where("_k = 1").select("type_name", "gt_type")


def complete_paths(edges: DataFrame, root: str = ROOT, most_paths: int = 1_000_000) -> DataFrame:
    """(path_no, pos, type_name) of every way from a top-level type to a leaf. Refuses hierarchies with more ways than
    most_paths rather than drop some."""
    steps = edges.select("child", "parent").distinct()
    now = steps.where(F.col("parent") == root).select(F.array("child").alias("path"))
    inner, done = steps.select(F.col("parent").alias("p")).distinct(), None
    while not now.isEmpty():
        last = F.element_at("path", -1)
        ended = now.join(inner, last == F.col("p"), "left_anti")
        done = ended if done is None else done.union(ended)
        now = now.join(steps, last == F.col("parent")).select(F.concat("path", F.array("child")).alias("path"))
        if now.count() > most_paths:
            raise ValueError("too many paths")
    if done is None:
        return edges.sparkSession.createDataFrame([], "path_no string, pos int, type_name string")
    return done.select(F.array_join("path", ">").alias("path_no"), F.posexplode("path").alias("pos", "type_name"))


def tree_scores(aligned: DataFrame, truth: DataFrame, allow_equal: bool = True) -> DataFrame:
    """(path_no, score): the longest chain of a path's aligned types in which each is below the one before in the true
    hierarchy, over the path's length. aligned: (path_no, pos, gt_type); null types count in the length alone."""
    ways = reach(truth).select("descendant", "ancestor")
    if ways.count() > MOST_CLOSURE:
        raise ValueError("the true hierarchy is too large to broadcast")
    below = aligned.sparkSession.sparkContext.broadcast({(r.descendant, r.ancestor) for r in ways.collect()})

    def score(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for types in frame["types"]:
                best: list[int] = []
                for k, t in enumerate(types):
                    before = [best[j] for j in range(k) if types[j] is not None and ((t, types[j]) in below.value or allow_equal and t == types[j])]
                    best.append(0 if t is None else 1 + max(before, default=0))
                out.append(max(best, default=0) / max(1, len(types)))
            yield pd.DataFrame({"path_no": frame["path_no"].astype(str), "score": out})

    ordered = aligned.groupBy("path_no").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "gt_type"))), lambda x: x["gt_type"]).alias("types"))
    return ordered.mapInPandas(score, "path_no string, score double")


def precision_recall_f1(predicted: DataFrame, truth: DataFrame, on: list[str]) -> DataFrame:
    p, t = predicted.select(on).distinct(), truth.select(on).distinct()
    row = p.join(t, on, "left_semi").agg(F.count("*").alias("hit")).crossJoin(p.agg(F.count("*").alias("p"))).crossJoin(t.agg(F.count("*").alias("t")))
    precision, recall = F.col("hit") / F.col("p"), F.col("hit") / F.col("t")
    return row.select(F.round(precision, 6).alias("p"), F.round(recall, 6).alias("r"), F.round(2 * F.col("hit") / (F.col("p") + F.col("t")), 6).alias("f1"))


def cardinality_accuracy(predicted: DataFrame, truth: DataFrame, on: list[str]) -> DataFrame:
    """Over relationships that both have."""
    both = predicted.select(*on, F.col("cardinality").alias("_c")).join(truth, on)
    return both.agg(F.round(F.avg((F.col("_c") == F.col("cardinality")).cast("int")), 6).alias("value"))
