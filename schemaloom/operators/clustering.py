"""Average linkage by nearest-neighbour chains, silhouettes along its merges, kept slices, spanning links of dense vectors.

Items may stand for several equal ones: a block's matrix is over distinct items, weights count them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Distinct items of one block that a task may cluster: one float32 matrix of 1.6 GB.
MOST_BLOCK = 20_000
#: Rows of one part of a block product; two parts meet in one task.
PART_ROWS = 2048


def merges_of(distance: np.ndarray, weights: np.ndarray | None = None) -> list[tuple[int, int, float]]:
    """Average-linkage merges (left, right, height), by rising height; a cluster is named by its smallest row.

    A chain of nearest neighbours ends in a pair that are each other's; average linkage lets such pairs be merged in any
    order. n squared steps in all, and one matrix.
    """
    n = len(distance)
    d = np.array(distance, np.float32 if n > 4096 else float)
    np.fill_diagonal(d, np.inf)
    size = np.ones(n) if weights is None else np.asarray(weights, float).copy()
    alive, chain, out = np.ones(n, bool), [], []
    for _ in range(n - 1):
        if not chain:
            chain = [int(np.argmax(alive))]
        while True:
            at = chain[-1]
            near = int(np.argmin(d[at]))
            if len(chain) > 1 and d[at, chain[-2]] <= d[at, near]:
                near = chain[-2]
                break
            chain.append(near)
        del chain[-2:]
        i, j = sorted((at, near))
        out.append((i, j, float(d[i, j])))
        row = (size[i] * d[i] + size[j] * d[j]) / (size[i] + size[j])
        row[~alive] = np.inf
        row[[i, j]] = np.inf
        d[i], d[:, i] = row, row
        d[j], d[:, j] = np.inf, np.inf
        size[i] += size[j]
        alive[j] = False
    # by height, a merge after those that made its sides; then names are the smallest rows
    name = np.arange(n)
    sorted_ = []
    for k in np.argsort(np.array([h for _, _, h in out]), kind="stable").tolist():
        i, j, height = out[k]
        a, b = sorted((int(name[i]), int(name[j])))
        while name[a] != a:
            a = int(name[a])
        while name[b] != b:
            b = int(name[b])
        a, b = sorted((a, b))
        name[b] = a
        sorted_.append((a, b, height))
    return sorted_


def scored_slices(distance: np.ndarray, merges: list[tuple[int, int, float]], weights: np.ndarray | None = None) -> Iterator[tuple[float, np.ndarray, float | None]]:
    """(height, labels, silhouette) of each slice; merges of equal height fall together. Sums of distances to each
    cluster are kept up merge by merge, so a slice costs its items times its clusters."""
    n = len(distance)
    w = np.ones(n) if weights is None else np.asarray(weights, float)
    sums, labels, live = np.asarray(distance, float) * w, np.arange(n), np.ones(n, bool)
    size = w.copy()
    for k, (i, j, height) in enumerate(merges):
        sums[:, i] += sums[:, j]
        size[i] += size[j]
        live[j] = False
        labels[labels == j] = i
        if k + 1 == len(merges) or merges[k + 1][2] > height + 1e-9:
            yield height, labels.copy(), _silhouette(sums, labels, np.flatnonzero(live), size, w)


def _silhouette(sums: np.ndarray, labels: np.ndarray, live: np.ndarray, size: np.ndarray, w: np.ndarray) -> float | None:
    if len(live) < 2 or len(live) >= w.sum():
        return None
    at = np.searchsorted(live, labels)
    own = size[labels]
    rows = np.arange(len(labels))
    a = np.where(own > 1, sums[rows, labels] / np.maximum(own - 1, 1), 0)
    other = sums[:, live] / size[live]
    other[rows, at] = np.inf
    b = other.min(axis=1)
    top = np.maximum(a, b)
    return float((np.where((own > 1) & (top > 0), (b - a) / np.where(top > 0, top, 1), 0) * w).sum() / w.sum())


def silhouette(distance: np.ndarray, labels: np.ndarray, weights: np.ndarray | None = None) -> float | None:
    """Mean silhouette; none for one cluster or only singletons. A singleton's is 0."""
    w = np.ones(len(labels)) if weights is None else np.asarray(weights, float)
    names, at = np.unique(labels, return_inverse=True)
    sums = np.zeros((len(labels), len(names)))
    for k in range(len(names)):
        sums[:, k] = (np.asarray(distance)[:, at == k] * w[at == k]).sum(axis=1)
    return _silhouette(sums, at, np.arange(len(names)), np.bincount(at, w), w)


def kept_nodes(distance: np.ndarray, delta: float = 0.15, weights: np.ndarray | None = None, heights: str = "merge", grid: int = 20) -> list[tuple[frozenset[int], frozenset[int] | None]]:
    """(members, parent's members or none) of the clusters of every slice that scores above the best less delta, from
    the top down; single items are no clusters. heights: the merges' own, or an even grid of them from 0 to the last."""
    w = np.ones(len(distance)) if weights is None else np.asarray(weights, float)
    scored = list(scored_slices(distance, merges_of(distance, w), w))
    if heights == "grid" and scored:
        marks, chosen = np.linspace(0, scored[-1][0], grid + 1)[1:], []
        for mark in marks:
            below = [x for x in scored if x[0] <= mark + 1e-9]
            if below and (not chosen or chosen[-1] is not below[-1]):
                chosen.append(below[-1])
        scored = chosen
    scores = [x for _, _, x in scored if x is not None]
    if not scores:
        return []
    nodes: list[tuple[frozenset[int], frozenset[int] | None]] = []
    seen: set[frozenset[int]] = set()
    for _, labels, value in reversed(scored):
        if value is None or value <= max(scores) - delta:
            continue
        for name in np.unique(labels):
            members = frozenset(np.flatnonzero(labels == name).tolist())
            if w[list(members)].sum() > 1 and members not in seen:
                above = [x for x, _ in nodes if members < x]
                nodes.append((members, min(above, key=len, default=None)))
                seen.add(members)
    return nodes


def set_distances(sets: list[list[str]]) -> np.ndarray:
    """One less the Jaccard similarity of each two sets; of two empty ones 0."""
    vocabulary = {e: k for k, e in enumerate(sorted({e for x in sets for e in x}))}
    x = np.zeros((len(sets), max(1, len(vocabulary))), np.float32)
    for row, elements in enumerate(sets):
        x[row, [vocabulary[e] for e in elements]] = 1
    common = x @ x.T
    size = x.sum(axis=1)
    union = size[:, None] + size[None, :] - common
    return (1 - np.where(union > 0, common / np.maximum(union, 1), 1)).round(9)


def distinct_sets(frame: pd.DataFrame) -> tuple[pd.DataFrame, list[list[str]], np.ndarray]:
    """The frame with the number of each row's set, the distinct sets, and how many rows have each."""
    keys = [tuple(sorted(set(x))) for x in frame["elements"]]
    first: dict[tuple, str] = {}
    for k, item in zip(keys, frame["item"], strict=True):
        first[k] = min(item, first.get(k, item))
    order = sorted(first, key=lambda k: (first[k], k))
    at = {k: n for n, k in enumerate(order)}
    frame = frame.assign(which=[at[k] for k in keys])
    return frame, [list(k) for k in order], np.bincount(frame["which"], minlength=len(order)).astype(float)


def dense_vectors(terms: DataFrame, size: int = 256) -> DataFrame:
    """(item, vector): sparse terms hashed into a unit vector of a fixed size, signs by hash, so that other terms' shares
    cancel out. A row for each item and place is summed before the shuffle."""
    place, sign = F.pmod(F.xxhash64("term"), F.lit(size)).cast("int"), F.when(F.pmod(F.xxhash64("term", F.lit(1)), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    return spread_vectors(terms.groupBy("item", place.alias("place")).agg(F.sum(F.col("w") * sign).alias("w")), size)


def spread_vectors(held: DataFrame, size: int = 256) -> DataFrame:
    """(item, vector) of unit length from (item, place, w)."""
    pairs = held.groupBy("item").agg(F.collect_list(F.struct("place", "w")).alias("at"))

    def spread(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = np.zeros((len(frame), size), np.float32)
            for row, cells in enumerate(frame["at"]):
                for cell in cells:
                    out[row, cell["place"]] = cell["w"]
            out /= np.maximum(1e-12, np.linalg.norm(out, axis=1, keepdims=True))
            yield pd.DataFrame({"item": frame["item"], "vector": list(out)})

    return pairs.mapInPandas(spread, "item string, vector array<float>")


def near_links(vectors: DataFrame, least: float, block: str | None = None, part_rows: int = PART_ROWS) -> DataFrame:
    """(a, b) of items with a cosine of at least `least` that span what is near, directly or through others, as blocked
    products: rows are dealt into parts of a stated size, and each two parts of a block meet in one task, which gives a
    link for each row at most. vectors: (item, vector) of unit length, and the column `block`, within which items meet."""
    by = F.coalesce(F.col(block), F.lit("")) if block else F.lit("")
    keyed = vectors.select(by.alias("block"), "item", "vector")
    parts = keyed.groupBy("block").agg(F.ceil(F.count("*") / part_rows).alias("parts"))
    dealt = keyed.join(parts, "block").withColumn("own", F.pmod(F.xxhash64("item"), "parts")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).where("parts = 1 OR own <> other")

    def links(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("item").reset_index(drop=True)
        x = np.stack(frame["vector"].to_numpy()).astype(np.float32)
        of, out = np.arange(len(x)), []
        for at in range(0, len(x), 512):
            near = x[at : at + 512] @ x.T >= least - 1e-6
            for row in range(len(near)):
                hits = np.flatnonzero(near[row])
                labels, first = np.unique(of[hits], return_index=True)
                for k in np.flatnonzero(labels != of[at + row]).tolist():
                    out.append((at + row, int(hits[first[k]])))
                of[np.isin(of, labels)] = labels.min() if len(labels) else of[at + row]
        names = frame["item"].tolist()
        return pd.DataFrame([(names[a], names[b]) for a, b in out], columns=["a", "b"])

    return dealt.groupBy("block", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q")).applyInPandas(links, "a string, b string")
