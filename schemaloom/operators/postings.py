"""Terms as lists of the items that hold them. Terms with equal lists are one weighted row, so that whatever is summed over
terms - norms, vectors of groups of items, dot products of pairs - is summed below the shuffle, with a row an item or pair.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: held: (item, w) of every item that holds a term, in the order of items; n: how many terms have this list.
POSTINGS = "held array<struct<item:string,w:double>>, n long"
#: Pairs that are formed at once, and items up to which a task keeps one matrix of sums.
PAIRS_AT_ONCE, MATRIX_ITEMS = 1 << 21, 3000


def postings(terms: DataFrame) -> DataFrame:
    """terms: (item, term, w), each item and term once."""
    held = terms.groupBy("term").agg(F.array_sort(F.collect_list(F.struct("item", "w"))).alias("held"))
    return held.groupBy("held").agg(F.count("*").alias("n"))


def items_of(lists: DataFrame) -> list[str]:
    return sorted(r.item for r in lists.select(F.explode("held").alias("h")).select("h.item").distinct().collect())


def rare(lists: DataFrame, items: int) -> DataFrame:
    """Weights lowered by how many of all items have a term; terms that all of them have go."""
    by = F.log(F.lit(float(items)) / F.size("held"))
    return lists.where(F.size("held") < items).select(F.transform("held", lambda x: F.struct(x["item"].alias("item"), (x["w"] * by).alias("w"))).alias("held"), "n")


def norms(lists: DataFrame) -> dict[str, float]:
    rows = lists.select(F.explode("held").alias("h"), "n").groupBy("h.item").agg(F.sqrt(F.sum(F.col("n") * F.col("h.w") * F.col("h.w"))).alias("norm")).collect()
    return {r.item: r.norm for r in rows if r.norm > 0}


def _flat(batch: pa.RecordBatch, at: pd.Index) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, place of its item in `at` or -1, w) of every entry of a batch."""
    lists = batch.column("held")
    flat = lists.flatten()
    row = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
    codes = flat.field("item").dictionary_encode()
    known = at.get_indexer(codes.dictionary.to_pandas())
    return row, (known[codes.indices.to_numpy()] if len(row) else np.zeros(0, int)), flat.field("w").to_numpy()


def grouped(lists: DataFrame, owner: dict[str, tuple[str, float]]) -> DataFrame:
    """The lists of groups in place of items: weights times the item's share, added up. owner: item -> (group, share);
    other items go."""
    at, groups = pd.Index(list(owner)), sorted({g for g, _ in owner.values()})
    place = {g: k for k, g in enumerate(groups)}
    of, share = np.array([place[g] for g, _ in owner.values()] + [0]), np.array([s for _, s in owner.values()] + [0.0])
    names = np.array(groups, object)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            row, code, w = _flat(batch, at)
            keep = code >= 0
            row, code, w = row[keep], code[keep], w[keep]
            keys, back = np.unique(row * len(groups) + of[code], return_inverse=True)
            sums = np.bincount(back, w * share[code], len(keys))
            rows, first = np.unique(keys // max(1, len(groups)), return_index=True)
            entries = pa.StructArray.from_arrays([pa.array(names[keys % max(1, len(groups))], pa.string()), pa.array(sums)], ["item", "w"])
            held = pa.ListArray.from_arrays(pa.array(np.append(first, len(keys)).astype(np.int32)), entries)
            yield pa.RecordBatch.from_arrays([held, batch.column("n").take(pa.array(rows))], ["held", "n"])

    return lists.mapInArrow(run, POSTINGS).groupBy("held").agg(F.sum("n").alias("n"))


def cosine_pairs(lists: DataFrame, lengths: dict[str, float]) -> DataFrame:
    """(a, b, sim), a < b, of items with sim > 0. lengths: norms() of the lists. Lists of one length are multiplied
    together; a task gives each pair once, or once for a block of PAIRS_AT_ONCE where items are very many."""
    names = sorted(lengths)
    at, by = pd.Index(names), np.array([1 / lengths[x] for x in names] + [0.0])
    size = len(names)
    label = np.array(names, object)

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(pairs, products)"""
        for batch in batches:
            row, code, w = _flat(batch, at)
            keep = code >= 0
            row, code, w = row[keep], code[keep], (w * by[code])[keep]
            order = np.lexsort((code, row))
            row, code, w = row[order], code[order], w[order]
            rows, first, count = np.unique(row, return_index=True, return_counts=True)
            n = batch.column("n").to_numpy()[rows]
            for length in np.unique(count).tolist():
                if length < 2:
                    continue
                mine = np.flatnonzero(count == length)
                step = max(1, 2 * PAIRS_AT_ONCE // (length * (length - 1)))
                i, j = np.triu_indices(length, 1)
                for k in range(0, len(mine), step):
                    some = mine[k : k + step]
                    cells = first[some][:, None] + np.arange(length)
                    c, x = code[cells], w[cells]
                    yield (c[:, i] * size + c[:, j]).ravel(), (x[:, i] * x[:, j] * n[some][:, None]).ravel()

    def frame(keys: np.ndarray, dots: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(label[keys // size], pa.string()), pa.array(label[keys % size], pa.string()), pa.array(dots)], ["a", "b", "dot"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if size > MATRIX_ITEMS:
            for keys, dots in blocks(batches):
                keys, back = np.unique(keys, return_inverse=True)
                yield frame(keys, np.bincount(back, dots, len(keys)))
            return
        sums, waiting, n = np.zeros(size * size), [], 0
        for block in blocks(batches):
            waiting.append(block)
            n += len(block[0])
            if n >= PAIRS_AT_ONCE:
                sums += np.bincount(np.concatenate([k for k, _ in waiting]), np.concatenate([d for _, d in waiting]), size * size)
                waiting, n = [], 0
        for keys, dots in waiting:
            sums += np.bincount(keys, dots, size * size)
        found = np.flatnonzero(sums > 0)
        if len(found):
            yield frame(found, sums[found])

    return lists.mapInArrow(run, "a string, b string, dot double").groupBy("a", "b").agg(F.sum("dot").alias("sim"))
