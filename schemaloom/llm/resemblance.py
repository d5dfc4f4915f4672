"""Exact Jaccard similarity of word shingles within groups of candidates, in comparisons of bounded size."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.llm.shared import byte_texts, slices

SLICE_BYTES = 1 << 20
#: Similarity of near copies, as a fraction of whole numbers.
LEAST = (4, 5)
#: Texts and shingles of one part of a group; two parts meet in one task.
PART_ROWS, PART_SHINGLES = 1024, 1 << 20
ODD = 0x9E3779B97F4A7C15


def shingles(text: bytes, words_each: int = 5) -> np.ndarray:
    """The sorted distinct 64-bit hashes of a text's word shingles; a shorter text is one, a text without words none."""
    words = text.lower().split()  # of bytes: A-Z, and ASCII white space
    if not words:
        return np.zeros(0, np.uint64)
    each = np.array(list(map(xxhash.xxh64_intdigest, words)), np.uint64)
    n = min(words_each, len(each))
    out = np.full(len(each) - n + 1, n, np.uint64)
    for k in range(n):
        out = out * np.uint64(ODD) + each[k : k + len(out)]
    return np.unique(out)


def mixed(x: np.ndarray) -> np.ndarray:
    """64-bit values with every bit spread over all others."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def near_pairs(sets: list[np.ndarray], least: tuple[int, int] = LEAST) -> tuple[list[int], list[int]]:
    """Places (a, b) of sets of the least similarity that join all such sets, directly or through others."""
    over, under = least
    order = sorted(range(len(sets)), key=lambda k: len(sets[k]))
    sizes = np.array([len(sets[k]) for k in order])
    _, flat = np.unique(np.concatenate([sets[k] for k in order]), return_inverse=True)
    starts = np.concatenate(([0], np.cumsum(sizes)))
    label, mark = np.arange(len(order)), np.zeros(flat.max() + 1, np.int32)
    left, right = [], []
    for i in range(len(order)):
        after = int(np.searchsorted(sizes * over, sizes[i] * under, "right"))
        if not (label[i + 1 : after] != label[i]).any():
            continue
        own = flat[starts[i] : starts[i + 1]]
        mark[own] = 1
        shared = np.add.reduceat(mark[flat[starts[i + 1] : starts[after]]], starts[i + 1 : after] - starts[i + 1])
        mark[own] = 0
        for j in (np.flatnonzero(under * shared >= over * (sizes[i] + sizes[i + 1 : after] - shared)) + i + 1).tolist():
            if label[j] != label[i]:
                label[label == label[j]] = label[i]
                left.append(order[i])
                right.append(order[j])
    return left, right


def linked(source: DataFrame, grouped: DataFrame, words_each: int = 5, least: tuple[int, int] = LEAST, part_rows: int = PART_ROWS) -> DataFrame:
    """Links (a, b) that join all texts of a group with at least the similarity `least`, and no others; source: (id,
    text), grouped: (id, group, size) with a shingle count. In a group every text is compared with every other that is
    not joined to it already; a group larger than a task is cut into parts, each two of which meet in one."""
    sizes = grouped.groupBy("group").agg(F.count("*").alias("n"), F.sum("size").alias("size")).where("n > 1")
    parts = sizes.select("group", F.greatest(F.ceil(F.col("n") / part_rows), F.ceil(F.col("size") / PART_SHINGLES)).alias("parts"))
    # by sorting at every size: the texts' shuffle grows with them alone
    held = source.join(grouped.select("id", "group").join(parts, "group").hint("merge"), "id").select("group", "parts", "id", "text")

    def sets_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", SLICE_BYTES):
            sets = [shingles(x, words_each).tobytes() for x in byte_texts(batch.column("text"))]
            kept = [batch.column(c) for c in ("group", "parts", "id")]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(sets, pa.binary())], ["group", "parts", "id", "found"])

    def compared(rows: pa.Table) -> pa.Table:
        ids, sets = rows.column("id").to_numpy(), [np.frombuffer(x, np.uint64) for x in rows.column("found").to_pylist()]
        left, right = near_pairs(sets, least)
        return pa.table({"a": pa.array(ids[left], pa.int64()), "b": pa.array(ids[right], pa.int64())})

    rows = held.mapInArrow(sets_of, "group long, parts long, id long, found binary").withColumn("own", F.pmod(F.xxhash64("id"), "parts"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).where("parts = 1 OR own <> other")
    return rows.groupBy("group", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q")).applyInArrow(compared, "a long, b long")
