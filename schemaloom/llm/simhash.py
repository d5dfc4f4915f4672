"""SimHash near-dedup: fingerprints, a self-join over binary tries, connected components."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.llm import resemblance
from schemaloom.llm.graph import components
from schemaloom.llm.resemblance import mixed
from schemaloom.llm.shared import Scratch, byte_texts, documents, slices

SEED = 42
SLICE_BYTES = 4 << 20
#: For sets of shingles, whose bits are unpacked.
SET_SLICE_BYTES = 1 << 20
NO_ID = -(1 << 63)  # stands for a null doc_id, which is the smallest
BUCKET_ROWS = 256
BATCH_ROWS = 1 << 17
#: Rows of a bucket that meet in one task; a larger one is cut into parts that meet in pairs.
PART_ROWS = 1 << 18
FRONTIER = 1 << 17
SIGN = np.uint64(1 << 63)
#: near_copies: keys of a text, minimum hashes in each, and the trie's error budget for a similarity of 0.8. Two texts at
#: 0.8 share no key with a chance of 4e-5; their fingerprints differ in 10 bits of 64 on average, in over 20 with one
#: of 2e-4.
KEYS, KEY_HASHES, WIDE = 14, 3, 20


def fingerprint(text: bytes, words_each: int = 4) -> int:
    """64 majority bits over the hashes of a text's word shingles; 0 if it has no words."""
    words = text.lower().split()  # of bytes: A-Z, and ASCII white space
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = [0, *(ends[:-1] + 1).tolist()]
    get = xxhash.xxh64_intdigest
    hashes = [get(joined[a:b], SEED) for a, b in zip(starts, ends[words_each - 1 :].tolist())] or [get(joined, SEED)]  # noqa: B905
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = np.array(hashes[at : at + (1 << 16)], np.uint64)
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.uint64)[0])


def bands(errors: int, free: int) -> list[int]:
    """Bit offsets that cut 64 bits into errors + free bands; of any two values within the errors, at least `free`
    bands are equal."""
    n = errors + free
    return [64 * k // n for k in range(n + 1)]


def rotated(values: np.ndarray, cut: list[int], lead: tuple[int, ...]) -> tuple[np.ndarray, int]:
    """Values with the bands in lead put first, and the number of their bits."""
    out, width = np.zeros_like(values), 0
    order = [*lead, *(k for k in range(len(cut) - 1) if k not in lead)]
    for k in order:
        size = cut[k + 1] - cut[k]
        part = values >> np.uint64(cut[k]) & np.uint64((1 << size) - 1)
        out = (out << np.uint64(size) if size < 64 else out) | part
    for k in lead:
        width += cut[k + 1] - cut[k]
    return out, width


class Labels:
    """Smallest member of each set of joined rows."""

    def __init__(self, n: int):
        self.of = np.arange(n)

    def join(self, a: np.ndarray, b: np.ndarray) -> None:
        while True:
            x, y = self.of[a], self.of[b]
            open_ = x != y
            if not open_.any():
                return
            a, b, x, y = a[open_], b[open_], x[open_], y[open_]
            np.minimum.at(self.of, np.maximum(x, y), np.minimum(x, y))
            while (self.of != (up := self.of[self.of])).any():
                self.of = up


def range_extremes(values: np.ndarray):
    """Minimum and maximum over any row range, by a sparse table."""
    low, high = [values], [values]
    width = 1
    while 2 * width <= len(values):
        low.append(np.minimum(low[-1][:-width], low[-1][width:]))
        high.append(np.maximum(high[-1][:-width], high[-1][width:]))
        width *= 2

    def of(first: np.ndarray, after: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        level = np.frexp(after - first)[1] - 1
        a, b = np.zeros(len(first), values.dtype), np.zeros(len(first), values.dtype)
        for k in np.unique(level):
            m = level == k
            x, y = first[m], after[m] - (1 << k)
            a[m], b[m] = np.minimum(low[k][x], low[k][y]), np.maximum(high[k][x], high[k][y])
        return a, b

    return of


def trie_self_join(values: np.ndarray, roots: np.ndarray, skip: int, errors: int) -> np.ndarray:
    """Labels that join all rows of a root whose values differ in at most `errors` bits, directly or through others.

    values: sorted within each root, and equal there in their first `skip` bits; roots: first row of each, and the end.
    The trie is implicit: a node is a row range that shares its leading bits. Node pairs go down together, one bit a
    level, from each root paired with itself; a pair's differing bits add up, and it ends when they exceed the budget,
    when few rows are left (these are compared), or when all its rows are joined already.
    """
    labels = Labels(len(values))
    near = np.flatnonzero(np.bitwise_count(values[1:] ^ values[:-1]) <= errors)
    inside = np.zeros(len(values), np.int64)
    inside[roots[:-1]] = 1
    inside = np.cumsum(inside)
    near = near[inside[near] == inside[near + 1]]
    labels.join(near, near + 1)
    sums: dict[int, np.ndarray] = {}
    first = np.stack((roots[:-1], roots[1:], roots[:-1], roots[1:], np.zeros(len(roots) - 1, roots.dtype))).astype(np.int64)
    stack = [(skip, first)]
    while stack:
        depth, pairs = stack.pop()
        if pairs.shape[1] > FRONTIER:
            half = pairs.shape[1] // 2
            stack += [(depth, pairs[:, half:]), (depth, pairs[:, :half])]
            continue
        a0, a1, b0, b1, _ = pairs
        few = (a1 - a0) * (b1 - b0) <= 64
        if few.any():
            x0, x1, y0, y1, _ = pairs[:, few]
            each = (x1 - x0) * (y1 - y0)
            which = np.repeat(np.arange(len(each)), each)
            k = np.arange(each.sum()) - np.repeat(np.cumsum(each) - each, each)
            wide = (y1 - y0)[which]
            x, y = x0[which] + k // wide, y0[which] + k % wide
            hit = (x < y) & (np.bitwise_count(values[x] ^ values[y]) <= errors)
            labels.join(x[hit], y[hit])
            pairs = pairs[:, ~few]
        if pairs.shape[1] > 4096:
            of = range_extremes(labels.of)
            (al, ah), (bl, bh) = of(pairs[0], pairs[1]), of(pairs[2], pairs[3])
            pairs = pairs[:, (np.minimum(al, bl) != np.maximum(ah, bh))]
        if depth == 64 or not pairs.shape[1]:
            continue
        if depth not in sums:
            sums[depth] = np.concatenate(([0], np.cumsum(values >> np.uint64(63 - depth) & np.uint64(1)))).astype(np.int64)
        ones = sums[depth]
        a0, a1, b0, b1, e = pairs
        am, bm, same = a1 - (ones[a1] - ones[a0]), b1 - (ones[b1] - ones[b0]), a0 == b0
        down = np.concatenate((np.stack((a0, am, b0, bm, e)), np.stack((am, a1, bm, b1, e)), np.stack((a0, am, bm, b1, e + 1)), np.stack((am, a1, b0, bm, e + 1))[:, ~same]), axis=1)
        down = down[:, (down[0] < down[1]) & (down[2] < down[3]) & (down[4] <= errors)]
        if down.shape[1]:
            stack.append((depth + 1, down))
    return labels.of


def meet(rows: DataFrame, errors: int, skip: int, part_rows: int = PART_ROWS) -> DataFrame:
    """Links (a, b) that span, within each bucket, what is within the errors there, directly or through others; rows:
    (choice, bucket, moved, node), where a bucket's values are equal in their first `skip` bits.

    A bucket is a trie of its own and meets in one task as 28 bytes a row. One of more than part_rows rows is cut into
    parts by hash, each two of which meet in a task, so that no bucket has to fit in one; it comes back as one link for
    each row and task at most.
    """
    sizes = rows.groupBy("choice", "bucket").agg(F.ceil(F.count("*") / part_rows).alias("parts")).where("parts > 1")
    cut = rows.join(sizes, ["choice", "bucket"], "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    cut = cut.withColumn("own", F.pmod(F.xxhash64("moved"), "parts")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    cut = cut.where("parts = 1 OR own <> other").select("choice", "bucket", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"), "moved", "node")

    def links(key: list[np.ndarray], moved: np.ndarray, node: np.ndarray) -> pa.RecordBatch:
        edge = np.zeros(len(moved) - 1, bool)
        for x in key:
            edge |= x[1:] != x[:-1]
        roots = np.concatenate(([0], np.flatnonzero(edge) + 1, [len(moved)]))
        few = np.diff(roots)
        if (few == 1).any():  # a bucket of one has no links
            kept = np.repeat(few > 1, few)
            moved, node, roots = moved[kept], node[kept], np.concatenate(([0], np.cumsum(few[few > 1])))
        of = trie_self_join(moved, roots, skip, errors)
        least = np.full(len(of), np.iinfo(np.int64).max)
        np.minimum.at(least, of, node)
        other = least[of]
        keep = other != node
        return pa.RecordBatch.from_arrays([pa.array(node[keep]), pa.array(other[keep])], ["a", "b"])

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append([batch.column(c).to_numpy() for c in ("choice", "bucket", "p", "q", "moved", "node")])
            if sum(len(x[0]) for x in held) >= BATCH_ROWS:
                columns = [np.concatenate(x) for x in zip(*held, strict=True)]
                ends = np.flatnonzero(np.any([x[1:] != x[:-1] for x in columns[:4]], axis=0))
                n = int(ends[-1]) + 1 if len(ends) else 0
                if n:
                    yield links([x[:n] for x in columns[:4]], columns[4][:n].view(np.uint64) ^ SIGN, columns[5][:n])
                held = [[x[n:] for x in columns]]
        if held and sum(len(x[0]) for x in held):
            columns = [np.concatenate(x) for x in zip(*held, strict=True)]
            yield links(columns[:4], columns[4].view(np.uint64) ^ SIGN, columns[5])

    keys = ["choice", "bucket", "p", "q"]
    return cut.repartition(*keys).sortWithinPartitions(*keys, "moved").mapInArrow(joined, "a long, b long")


def link(nodes: DataFrame, errors: int, bucket_rows: int = BUCKET_ROWS, part_rows: int = PART_ROWS) -> DataFrame:
    """Links (a, b) that span what is near; nodes: (fp, node) with distinct fp.

    64 bits are cut into errors + free bands, and each choice of `free` bands gives every value a bucket by their bits:
    two near values share one at least. More values take more free bands, so that a bucket of unlike values stays
    small; like ones are at most the values within the errors of each other, and meet() splits them.
    """
    total, free = nodes.count(), 1
    while free < 8 and total >> (64 * free // (errors + free)) > bucket_rows:
        free += 1
    cut = bands(errors, free)
    choices = list(combinations(range(errors + free), free))

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values, ids = batch.column("fp").to_numpy().view(np.uint64), batch.column("node")
            for k, lead in enumerate(choices):
                moved, width = rotated(values, cut, lead)
                key = (moved >> np.uint64(64 - width)) if width else moved * 0
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(values), k, np.int32)), pa.array(key.view(np.int64)), pa.array((moved ^ SIGN).view(np.int64)), ids], ["choice", "bucket", "moved", "node"])

    shortest = min(sum(cut[x + 1] - cut[x] for x in lead) for lead in choices)
    return meet(nodes.mapInArrow(spread, "choice int, bucket long, moved long, node long"), errors, shortest, part_rows)


def near_groups(docs: DataFrame, id_col: str = "doc_id", text: str = "text", words_each: int = 4, errors: int = 4) -> DataFrame:
    """For each row: id, fingerprint (64-bit integer), component_id, the smallest id reachable through fingerprints
    that differ in at most `errors` bits.

    Null and empty texts have fingerprint 0, linked like any other. A null id counts as the smallest. Rows that repeat
    an id share its component if their texts are near, and tie otherwise. Equal fingerprints are one node, so copies
    cost nothing; other columns are left out. An empty table gives no rows.
    """
    scratch = Scratch(docs.sparkSession, "simhash")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text, SLICE_BYTES):
            values = np.array([fingerprint(x, words_each) for x in byte_texts(batch.column(text))], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(id_col).cast(pa.int64()), pa.array(values.view(np.int64))], [id_col, "fp"])

    prints = scratch.table("prints", docs.select(F.col(id_col).cast("long").alias(id_col), text).mapInArrow(run, f"`{id_col}` long, fp long"))
    nodes = scratch.table("nodes", prints.groupBy("fp").agg(F.min(F.coalesce(id_col, F.lit(NO_ID))).alias("node")))
    found = components(link(nodes, errors), scratch)
    named = nodes.join(found, "node", "left").select("fp", F.coalesce("component", "node").alias("component_id"))
    named = scratch.table("named", named)
    return prints.join(named, "fp").select(id_col, F.col("fp").alias("fingerprint"), "component_id")


def majority(hashes: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The 64 majority bits of each run of hashes."""
    ones = np.add.reduceat(np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"), starts, axis=0, dtype=np.int32)
    return np.packbits(2 * ones > sizes[:, None], axis=1, bitorder="little").view(np.uint64).reshape(-1)


def minimum_keys(hashes: np.ndarray, starts: np.ndarray, seed: int = SEED) -> np.ndarray:
    """KEYS keys of each run of hashes, a row each: KEY_HASHES minima under different permutations, hashed together."""
    rng = np.random.default_rng(seed)
    out = np.zeros((len(starts), KEYS), np.uint64)
    for k in range(KEYS):
        for _ in range(KEY_HASHES):
            turn, odd = rng.integers(0, 1 << 63, 2, dtype=np.uint64)
            out[:, k] = mixed(out[:, k] ^ np.minimum.reduceat((hashes ^ turn) * (odd * np.uint64(2) + np.uint64(1)), starts))
    return out


def near_copies(docs: DataFrame, id_col: str = "doc_id", text: str = "text", words_each: int = 5, least: tuple[int, int] = (4, 5), errors: int = WIDE, part_rows: int = PART_ROWS, group_rows: int = resemblance.PART_ROWS) -> DataFrame:
    """(node, component) of each id whose text is linked to another's; a component's name is its smallest id.

    Two texts are linked if the sets of their word shingles have a Jaccard similarity of at least `least`; a text of
    fewer words is one shingle, texts without words are copies of each other, a null id is the smallest, and rows that
    repeat an id count as one if their texts are copies. Equal sets are one node. Fingerprints over the distinct
    shingles meet in tries with a budget wide enough for that similarity, but only with those that share one of the
    text's minimum-hash keys: at so many errors no bands would keep unlike values apart. What the tries join directly
    or through others is then compared exactly, so that no link is wrong; KEYS, KEY_HASHES and WIDE above bound what
    may be missed. Groups larger than a task are cut into parts that meet in pairs.
    """
    scratch = Scratch(docs.sparkSession, "copies")
    source = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("id"), F.col(text).alias("text"))

    def prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", SET_SLICE_BYTES):
            sets = [resemblance.shingles(x, words_each) for x in byte_texts(batch.column("text"))]
            both = np.frombuffer(b"".join(xxhash.xxh3_128_digest(x.tobytes()) for x in sets), ">i8").reshape(-1, 2).astype(np.int64)
            sizes = np.array([len(x) for x in sets], np.int64)
            some = np.flatnonzero(sizes)
            fp, keys = np.zeros(len(sets), np.uint64), np.zeros((len(sets), KEYS), np.uint64)
            if len(some):
                starts = np.concatenate(([0], np.cumsum(sizes[some])[:-1]))
                flat = mixed(np.concatenate([sets[k] for k in some.tolist()]))
                fp[some], keys[some] = majority(flat, starts, sizes[some]), minimum_keys(flat, starts)
            columns = [batch.column("id"), pa.array(both[:, 0]), pa.array(both[:, 1]), pa.array(sizes), pa.array((fp ^ SIGN).view(np.int64))]
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, KEYS * len(sets) + 1, KEYS, dtype=np.int32)), pa.array(keys.view(np.int64).reshape(-1)))
            yield pa.RecordBatch.from_arrays([*columns, lists], ["id", "h1", "h2", "size", "moved", "keys"])

    seen = scratch.table("prints", source.mapInArrow(prints, "id long, h1 long, h2 long, size long, moved long, keys array<long>"))
    alike = seen.groupBy("h1", "h2").agg(F.min("id").alias("node"), *(F.first(c).alias(c) for c in ("size", "moved", "keys")))
    firsts = scratch.table("firsts", alike)
    copies = seen.join(firsts.select("h1", "h2", "node"), ["h1", "h2"]).where("id <> node").select(F.col("id").alias("a"), F.col("node").alias("b"))
    spread = firsts.where("size > 0").select(F.posexplode("keys").alias("choice", "bucket"), "moved", "node")
    groups = components(meet(spread, errors, 0, part_rows), scratch.inner("tries"))
    nodes = firsts.where("size > 0").groupBy(F.col("node").alias("id")).agg(F.sum("size").alias("size"))
    grouped = scratch.table("members", groups.select(F.col("node").alias("id"), F.col("component").alias("group")).join(nodes, "id"))
    links = resemblance.linked(source, grouped, words_each, least, group_rows)
    found = components(links.union(copies), scratch.inner("linked"))
    scratch.drop("prints", "firsts", "members", "tries")
    return found


def op6_simhash_tries(spark, sf_dir: str) -> DataFrame:
    found = near_groups(documents(spark, sf_dir))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fingerprint"), 16, "0")).alias("fingerprint"), "component_id")
