"""Substring dedup with enhanced suffix arrays.

Two equal strings of LENGTH bytes have equal smallest k-gram hashes, so every start of such a string belongs to the group
of its window's smallest hash, wherever it stands. Consecutive starts of one group make a context: the bytes that their
strings span. A context seen before goes whole. Contexts of one group that differ meet in a task, which builds an
enhanced suffix array of their starts and scans it with a stack: each interval of common prefixes whose left letters
differ is a maximal repeat with all its occurrences, and all but the first are cut.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.llm.shared import Scratch, byte_texts, documents, slices, unused

LENGTH = 100
GRAM = 32
MOST_STARTS = 128
SLICE_BYTES = 1 << 18  # its arrays stay in a core's cache
CUT_BYTES = 2 << 20
BATCH_BYTES = 1 << 19
NO_ID = -(1 << 63)  # stands for a null doc_id, which comes first
#: Distinct contexts of a group beyond which its strings are grouped each by itself.
HEAVY = 20_000
#: Bits of a Bloom filter: sixteen a key, up to a size that every task can hold.
FILTER_BITS = 1 << 28
MIX = (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(MIX[1])
    x = (x ^ (x >> np.uint64(27))) * np.uint64(MIX[2])
    return x ^ (x >> np.uint64(31))


def words(data: np.ndarray, kind: str = ">u8") -> np.ndarray:
    """The 8 bytes from each place as an integer; big-endian ones sort as the bytes do."""
    padded = np.concatenate((data, np.zeros(16, np.uint8)))
    out = np.empty(len(data), kind)
    for k in range(8):
        n = len(range(k, len(data), 8))
        out[k::8] = padded[k : k + 8 * n].view(kind)
    return out.astype(np.uint64, copy=False)


def gram_hashes(data: np.ndarray, gram: int = GRAM) -> np.ndarray:
    """A hash of the gram bytes (a multiple of 8) from each place."""
    w = words(data, "<u8")
    n = max(0, len(data) - gram + 1)
    out = np.zeros(n, np.uint64)
    for k in range(0, gram, 8):
        out = (out ^ w[k : k + n]) * np.uint64(MIX[0])
        out ^= out >> np.uint64(29)
    return mixed(out)


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each `width` neighbours, by doubling."""
    done = 1
    while done < width:
        step = min(done, width - done)
        x = np.minimum(x[:-step], x[step:])
        done += step
    return x


class Contexts:
    """The contexts of a slice of texts: group, text number, first start, number of starts, whether a string may recur
    within it."""

    def __init__(self, texts: list[bytes], length: int, heavy: Filter | None = None):
        sizes = np.array([len(x) for x in texts], np.int64)
        self.offsets = np.concatenate(([0], np.cumsum(sizes)))
        self.bytes = b"".join(texts)
        data = np.frombuffer(self.bytes, np.uint8)
        empty = np.zeros(0, np.int64)
        self.group, self.text, self.first, self.starts, self.recurs = empty.astype(np.uint64), empty, empty, empty, empty.astype(bool)
        self.alone = self.recurs  # whether a context is one string of a heavy group
        if len(data) < length:
            return
        h = gram_hashes(data)
        width = length - GRAM + 1
        least = sliding_min(h, width)
        n = len(least)
        room = np.zeros(n + 1, np.int64)  # starts whose string stays in its text
        some = sizes >= length
        np.add.at(room, self.offsets[:-1][some], 1)
        np.add.at(room, (self.offsets[1:] - length + 1)[some], -1)
        inside = np.cumsum(room[:-1]) > 0
        at = np.flatnonzero(inside)
        edge = np.concatenate(([True], (np.diff(at) > 1) | (np.diff(least[at].view(np.int64)) != 0)))
        begins = np.zeros(len(data) + 1, bool)
        begins[self.offsets[:-1]] = True
        edge |= begins[at]
        # long runs are cut every MOST_STARTS
        head = np.maximum.accumulate(np.where(edge, np.arange(len(at)), 0))
        edge |= (np.arange(len(at)) - head) % MOST_STARTS == 0
        if heavy is not None:
            alone = heavy.has(least[at])
            edge |= alone | np.concatenate(([False], alone[:-1]))
        begin = np.flatnonzero(edge)
        self.place = at[begin]
        self.starts = np.diff(np.concatenate((begin, [len(at)])))
        self.group = least[self.place]
        self.alone = np.zeros(len(begin), bool)
        if heavy is not None:
            self.alone = alone[begin]
            for k in np.flatnonzero(self.alone).tolist():
                p = int(self.place[k])
                self.group[k] = xxhash.xxh3_64_intdigest(self.bytes[p : p + length], 1)
        self.text = np.searchsorted(self.offsets, self.place, "right") - 1
        self.first = self.place - self.offsets[self.text]
        self.recurs = self.periodic(h, width, begin, at, n)
        self.length = length

    @staticmethod
    def periodic(h: np.ndarray, width: int, begin: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
        """Contexts near a gram that stands again within MOST_STARTS: of any string that recurs so soon, one gram in
        `width` neighbours lies at a multiple of the step."""
        step = max(1, width - 5)
        probed = h[::step].copy()
        again = np.zeros(len(probed), bool)
        padded = np.concatenate((h, np.zeros(MOST_STARTS + step, np.uint64)))
        for d in range(1, MOST_STARTS):
            again |= probed == padded[d::step][: len(probed)]
        mark = np.zeros(n + 1, np.int64)
        hits = np.flatnonzero(again) * step
        np.add.at(mark, np.minimum(np.maximum(hits - width + 1, 0), n), 1)
        np.add.at(mark, np.minimum(hits + 1, n), -1)
        near = np.cumsum(mark[:-1]) > 0
        return np.add.reduceat(near[at].astype(np.int64), begin) > 0

    def content(self, k: int) -> bytes:
        p = int(self.place[k])
        return self.bytes[p : p + int(self.starts[k]) + self.length - 1]


class Filter:
    """A Bloom filter in equal parts, each made apart; two bits a key."""

    def __init__(self, bits: int, parts: list[bytes]):
        self.bits, self.n, self.data = bits, len(parts), [np.frombuffer(x, np.uint8) for x in parts]

    @staticmethod
    def places(keys: np.ndarray, bits: int, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        each = bits // n
        x = mixed(keys ^ np.uint64(MIX[0]))
        return (x >> np.uint64(40)) % np.uint64(n), x % np.uint64(each), mixed(x + np.uint64(MIX[2])) % np.uint64(each)

    def has(self, keys: np.ndarray) -> np.ndarray:
        part, a, b = self.places(keys, self.bits, self.n)
        out = np.zeros(len(keys), bool)
        for k, data in enumerate(self.data):
            m = np.flatnonzero(part == np.uint64(k))
            both = [(data[(x[m] >> np.uint64(3)).astype(np.int64)] >> (x[m] & np.uint64(7)).astype(np.uint8) & 1).astype(bool) for x in (a, b)]
            out[m] = both[0] & both[1]
        return out


def filter_of(keys: DataFrame, most_bits: int, parts: int = 16):
    """A broadcast filter of the 64-bit keys (one column): sixteen bits each, at most most_bits in all. A full filter
    lets more through, never less. Parts are built in tasks of their own from keys that come in any number of batches."""
    count = keys.count()
    bits = max(parts * 64, min(most_bits, 1 << max(6, (16 * count).bit_length())))

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made: dict[int, np.ndarray] = {}
        for batch in batches:
            part, a, b = Filter.places(batch.column(0).to_numpy().view(np.uint64), bits, parts)
            for k in np.unique(part).tolist():
                data = made.setdefault(k, np.zeros(bits // parts // 8 + 1, np.uint8))
                m = part == np.uint64(k)
                for x in (a[m], b[m]):
                    np.bitwise_or.at(data, (x >> np.uint64(3)).astype(np.int64), np.uint8(1) << (x & np.uint64(7)).astype(np.uint8))
        for k, data in made.items():
            yield pa.RecordBatch.from_pydict({"part": pa.array([k], pa.int32()), "data": pa.array([data.tobytes()], pa.binary())})

    name = keys.columns[0]
    spark = keys.sparkSession

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            part = Filter.places(batch.column(0).to_numpy().view(np.uint64), bits, parts)[0]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(part.astype(np.int32))], [name, "part"])

    dealt = keys.mapInArrow(number, f"{name} long, part int").repartition(parts, "part").select(name)
    data = [np.zeros(bits // parts // 8 + 1, np.uint8) for _ in range(parts)]
    for row in dealt.mapInArrow(build, "part int, data binary").toLocalIterator():
        data[row.part] |= np.frombuffer(row.data, np.uint8)
    return spark.sparkContext.broadcast(Filter(bits, [x.tobytes() for x in data]))


def place_keys(doc: np.ndarray, first: np.ndarray) -> np.ndarray:
    return mixed(doc.view(np.uint64) * np.uint64(MIX[0]) + first.astype(np.uint64))


def dense(key: np.ndarray) -> np.ndarray:
    """Ranks of the keys, equal for equal ones."""
    order = np.argsort(key, kind="stable")
    out = np.empty(len(key), np.int64)
    out[order] = np.concatenate(([0], np.cumsum(np.diff(key[order].view(np.int64)) != 0)))[: len(key)]
    return out


class EnhancedSuffixArray:
    """Suffixes of some contexts, of those starts only whose LENGTH bytes stand more than once and not always after the
    same letter, with the common prefix of each and the one before."""

    def __init__(self, contexts: list[bytes], length: int):
        self.length = length
        sizes = np.array([len(x) + 1 for x in contexts], np.int64)
        offsets = np.concatenate(([0], np.cumsum(sizes)[:-1]))
        data = np.frombuffer(b"\xff".join(contexts) + b"\xff" + b"\0" * 512, np.uint8)
        ranks = {8: dense(words(data))}
        for k in (8, 16, 32, 64):
            r = ranks[k]
            ranks[2 * k] = dense((r * (len(r) + 1) + np.concatenate((r[k:], np.zeros(k, np.int64)))).view(np.uint64))
        starts = sizes - length
        which = np.repeat(np.arange(len(contexts)), starts)
        within = np.arange(starts.sum()) - np.repeat(np.cumsum(starts) - starts, starts)
        at = offsets[which] + within
        # the class of a start: its first `length` bytes
        cover = max(k for k in ranks if k <= length)
        r = ranks[cover]
        same = dense((r[at] * (len(r) + 1) + r[at + length - cover]).view(np.uint64))
        left = np.where(within > 0, data[at - 1].astype(np.int64), 256 + which)
        n = int(same.max()) + 1 if len(same) else 0
        low, high, count = np.full(n, 1 << 60), np.full(n, -1), np.bincount(same, minlength=n)
        np.minimum.at(low, same, left)
        np.maximum.at(high, same, left)
        keep = ((low < high) & (count > 1))[same]
        at, which, within, left, same = at[keep], which[keep], within[keep], left[keep], same[keep]
        order = np.lexsort((ranks[128][at + 128], ranks[128][at], same))
        self.which, self.within, self.left, same, at = which[order], within[order], left[order], same[order], at[order]
        self.segments = np.flatnonzero(np.concatenate(([True], np.diff(same) != 0, [True]))) if len(same) else np.zeros(1, np.int64)
        remaining = sizes[self.which] - 1 - self.within
        a, b = at[:-1], at[1:]
        common = np.zeros(len(a), np.int64)
        for k in (128, 64, 32, 16, 8):
            r = ranks[k]
            common += k * (r[a + common] == r[b + common])
        for _ in range(8):
            common += data[a + common] == data[b + common]
        # after two equal halves of 128 the descent may stop short: it starts again where it stands
        for k in (64, 32, 16, 8):
            r = ranks[k]
            common += k * (r[a + common] == r[b + common])
        for _ in range(8):
            common += data[a + common] == data[b + common]
        self.common = np.minimum(common, np.minimum(remaining[:-1], remaining[1:]))

    def maximal_repeats(self) -> Iterator[tuple[int, int, int]]:
        """(length, first row, row after the last) of each maximal repeat: an interval of the common-prefix tree whose
        rows stand after different letters."""
        left, common = self.left.tolist(), self.common.tolist()
        for a, b in zip(self.segments[:-1].tolist(), self.segments[1:].tolist(), strict=True):
            # a stack of open intervals: depth, first row, the one left letter or None
            stack: list[list] = []
            for row in range(a, b):
                depth = common[row] if row + 1 < b else self.length - 1  # with the next row
                letter, first = left[row], row
                while stack and stack[-1][0] > depth:
                    deep, first, seen = stack.pop()
                    if seen is None or seen != letter:
                        seen = None
                        yield deep, first, row + 1
                    letter = seen
                if depth < self.length:
                    continue
                if stack and stack[-1][0] == depth:
                    if stack[-1][2] != letter:
                        stack[-1][2] = None
                else:
                    stack.append([depth, first, letter])


def repeated_parts(contexts: list[bytes], order: np.ndarray, length: int) -> Iterator[tuple[int, int, int]]:
    """(context, first byte, bytes) of every occurrence of a maximal repeat but the first one; order: places of the
    contexts in the corpus, rising with them."""
    array = EnhancedSuffixArray(contexts, length)
    rank = order[array.which] * (1 << 20) + array.within
    longest: dict[int, int] = {}
    for deep, a, b in array.maximal_repeats():
        first = a + int(np.argmin(rank[a:b])) if b - a > 8 else min(range(a, b), key=rank.__getitem__)
        for row in range(a, b):
            if row != first and longest.get(row, 0) < deep:
                longest[row] = deep
    for row, deep in longest.items():
        yield int(array.which[row]), int(array.within[row]), deep


def duplicate_ranges(docs: DataFrame, scratch: Scratch, id_col: str, text: str, length: int, heavy_contexts: int = HEAVY, filter_bits: int = FILTER_BITS) -> DataFrame:
    """(doc, first, bytes): overlapping byte ranges that cover what stands earlier."""
    source = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc"), F.col(text).alias("text"))
    spark = docs.sparkSession

    def each(batches: Iterator[pa.RecordBatch], heavy=None, only=None) -> Iterator[tuple[np.ndarray, Contexts]]:
        for batch in slices(batches, "text", SLICE_BYTES):
            doc = batch.column("doc").to_numpy()
            if only:
                batch = batch.filter(pa.array(only.value.has(place_keys(doc, np.zeros(len(doc))))))
                doc = batch.column("doc").to_numpy()
            found = Contexts(byte_texts(batch.column("text")), length, heavy.value if heavy else None)
            if len(found.group):
                yield doc, found

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, found in each(batches):
            group, at = np.unique(found.group, return_inverse=True)
            n = np.bincount(at, 1 + found.recurs).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(group.view(np.int64)), pa.array(n)], ["g", "n"])

    counted = source.mapInArrow(count, "g long, n int").groupBy("g").agg(F.sum("n").alias("n"))
    groups = filter_of(scratch.table("groups", counted.where("n > 1").select("g")), filter_bits)

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = place_keys(batch.column(0).to_numpy(), batch.column(1).to_numpy())
            yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64))], ["k"])

    def seen(heavy=None, only=None) -> DataFrame:
        """Contexts of groups that stand more than once; with heavy, the single strings of those groups instead."""

        def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for docs_, found in each(batches, heavy, only):
                keep = np.flatnonzero(found.alone if heavy else groups.value.has(found.group))
                digests = np.array([xxhash.xxh3_64_intdigest(found.content(k)) for k in keep.tolist()], np.uint64)
                yield pa.RecordBatch.from_arrays([pa.array(found.group[keep].view(np.int64)), pa.array(digests.view(np.int64)), pa.array(docs_[found.text[keep]]), pa.array(found.first[keep].astype(np.int32)), pa.array(found.starts[keep].astype(np.int16)), pa.array(found.recurs[keep])], ["g", "c", "doc", "first", "starts", "recurs"])

        return source.mapInArrow(emit, "g long, c long, doc long, first int, starts short, recurs boolean")

    def grouped(rows: DataFrame, name: str) -> tuple[DataFrame, DataFrame]:
        """Distinct contexts with their first place, and the groups that have several or may repeat within one."""
        contexts = scratch.table(f"contexts-{name}", rows.groupBy("g", "c").agg(F.min(F.struct("doc", "first")).alias("place"), F.count("*").alias("n"), F.max("recurs").alias("recurs")))
        several = contexts.groupBy("g").agg(F.count("*").alias("kinds"), F.max("recurs").alias("recurs")).where("kinds > 1 or recurs")
        return contexts, scratch.table(f"groups-{name}", several)

    heavy = None
    rows = scratch.table("rows", seen())
    contexts, per_group = grouped(rows, "all")
    large = scratch.table("large", per_group.where(F.col("kinds") > heavy_contexts).select("g"))
    if not large.isEmpty():
        # a filter of them: what it lets through besides is split alike, wherever it stands
        heavy = filter_of(large, filter_bits)

        def split(batches: Iterator[pa.RecordBatch], inside: bool) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                yield batch.filter(pa.array(heavy.value.has(batch.column("g").to_numpy().view(np.uint64)) == inside))

        # only texts that hold such contexts are read again
        kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema)
        holders = rows.mapInArrow(lambda x: split(x, True), kinds).select("doc", F.lit(0).alias("first")).distinct()
        only = filter_of(scratch.table("holders", holders.mapInArrow(keyed, "k long")), filter_bits)
        single = scratch.table("single", seen(heavy, only))
        rows = rows.mapInArrow(lambda x: split(x, False), kinds).union(single)
        contexts, per_group = grouped(rows, "split")
    # contexts that stood before go whole
    again = contexts.where("n > 1").select("g", "c", "place")
    whole = rows.select("g", "c", "doc", "first", "starts").join(again, ["g", "c"]).where(F.struct("doc", "first") != F.col("place"))
    whole = whole.select("doc", "first", (F.col("starts") + F.lit(length - 1)).cast("int").alias("bytes"))
    # first ones of a group with several go through suffix arrays
    firsts = contexts.join(per_group.select("g"), "g", "left_semi").select(F.col("place.doc").alias("doc"), F.col("place.first").alias("first"))
    wanted = filter_of(scratch.table("wanted", firsts.mapInArrow(keyed, "k long")), filter_bits)

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for docs_, found in each(batches, heavy):
            doc = docs_[found.text]
            keep = np.flatnonzero(wanted.value.has(place_keys(doc, found.first)))
            yield pa.RecordBatch.from_arrays([pa.array(found.group[keep].view(np.int64)), pa.array(doc[keep]), pa.array(found.first[keep].astype(np.int32)), pa.array([found.content(k) for k in keep.tolist()], pa.binary())], ["g", "doc", "first", "content"])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def ranges(table: pa.Table) -> pa.RecordBatch:
            doc, first, contents = table.column("doc").to_numpy(), table.column("first").to_numpy(), table.column("content").to_pylist()
            order = np.empty(len(doc), np.int64)
            order[np.lexsort((first, doc))] = np.arange(len(doc))
            found = list(repeated_parts(contents, order, length))
            k = np.array([x[0] for x in found], np.int64)
            return pa.RecordBatch.from_arrays([pa.array(doc[k]), pa.array((first[k] + np.array([x[1] for x in found], np.int64)).astype(np.int32)), pa.array([x[2] for x in found], pa.int32())], ["doc", "first", "bytes"])

        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(batch)
            table = pa.Table.from_batches(held)
            g = table.column("g").to_numpy()
            size = np.cumsum([len(x) for x in table.column("content").to_pylist()])
            at = 0
            while size[-1] - (size[at - 1] if at else 0) > BATCH_BYTES:
                cut = int(np.searchsorted(size, (size[at - 1] if at else 0) + BATCH_BYTES))
                same = np.flatnonzero(np.diff(g[cut:]) != 0)  # a group stays together
                if not len(same):
                    break
                cut += int(same[0]) + 1
                yield ranges(table.slice(at, cut - at))
                at = cut
                if at >= len(g):
                    break
            held = table.slice(at).combine_chunks().to_batches() if at < len(g) else []
        if held:
            yield ranges(pa.Table.from_batches(held))

    sorted_ = source.mapInArrow(fetch, "g long, doc long, first int, content binary").repartition("g").sortWithinPartitions("g")
    parts = sorted_.mapInArrow(scan, "doc long, first int, bytes int")
    return whole.union(parts)


def cut_repeats(docs: DataFrame, id_col: str = "doc_id", text: str = "text", length: int = LENGTH, heavy_contexts: int = HEAVY) -> DataFrame:
    """For each row: id, n_bytes, n_removed, n_spans, kept (bytes): without each byte that is covered by a string of
    `length` bytes which also starts earlier, in a smaller id or before it in the same text.

    Null and short texts lose nothing. A null id comes first. Ids should not repeat: rows that share one share its
    ranges, clipped to their texts. Other columns are left out. length: at least GRAM bytes, at most 128.
    """
    if not GRAM <= length <= 128:
        raise ValueError("length must be from 32 to 128")
    scratch = Scratch(docs.sparkSession, "suffixes")
    ranges = duplicate_ranges(docs, scratch, id_col, text, length, heavy_contexts)
    source = docs.select(F.col(id_col), F.col(text))
    of, cuts = unused("_doc", source), unused("_ranges", source)
    per_doc = scratch.table("ranges", ranges.groupBy("doc").agg(F.sort_array(F.collect_set(F.struct("first", "bytes"))).alias(cuts)).withColumnRenamed("doc", of))
    scratch.drop("groups", "rows", "contexts-all", "groups-all", "large", "holders", "single", "contexts-split", "groups-split", "wanted")
    joined = source.join(per_doc, F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)) == F.col(of), "left").drop(of)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text, CUT_BYTES):
            rows = []
            for data, ranges_ in zip(byte_texts(batch.column(text)), batch.column(cuts).to_pylist(), strict=True):
                spans: list[list[int]] = []
                for r in ranges_ or ():
                    a, b = min(r["first"], len(data)), min(r["first"] + r["bytes"], len(data))
                    if spans and a <= spans[-1][1]:
                        spans[-1][1] = max(spans[-1][1], b)
                    elif a < b:
                        spans.append([a, b])
                kept, at = [], 0
                for a, b in spans:
                    kept.append(data[at:a])
                    at = b
                kept = b"".join([*kept, data[at:]])
                rows.append((len(data), len(data) - len(kept), len(spans), kept))
            n, gone, runs, kept = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([batch.column(id_col), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(runs, pa.int64()), pa.array(kept, pa.binary())], [id_col, "n_bytes", "n_removed", "n_spans", "kept"])

    kind = docs.schema[id_col].dataType.simpleString()
    return joined.mapInArrow(cut, f"`{id_col}` {kind}, n_bytes long, n_removed long, n_spans long, kept binary")


def op5_maximal_repeats(spark, sf_dir: str) -> DataFrame:
    return cut_repeats(documents(spark, sf_dir)).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))
