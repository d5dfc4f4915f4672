"""Numbers counted in sorted blocks: what a task has seen of whole numbers and amounts goes to the shuffle as distinct
(column, number, count) entries, delta coded, so that keys and prices of many rows take a byte or two each.

An entry's label is its column's place times eight plus a kind. A digit word is a number too: its value, and how many
zeros stand in front of it, so that it meets equal words of texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Kinds of entries: whole numbers by sign, amounts in hundredths by sign, words alone.
WHOLE, AMOUNT, WORD, KINDS = 0, 2, 4, 8
#: Digits of a number or word that is held so, and what a zero in front adds.
DIGITS, ZERO = 17, 10**17
#: Values that a task sorts at once, numbers that lie together, buckets, entries that are merged at once.
AT_ONCE, RUN_BITS, BUCKETS, MERGED = 8 << 20, 14, 256, 4 << 20
#: Numbers below this are sorted with their labels as one key.
SHORT_BITS = 40

BLOCKS = "bucket int, n int, block binary"
#: An item's list and how many terms have it, or an item's place with its distinct values, full cells and characters, and
#: its words hashed to PLACES sums, as they are and by the logarithm of how many items have each.
FOUND = "held array<struct<item:string,w:double>>, n long, at int, full long, chars long, hashed array<double>"
FIELDS = ["held", "n", "at", "full", "chars", "hashed"]
PLACES = 256
#: A column's place with its distinct values, full cells and characters, and texts among which are those with the smallest
#: hashes.
SUMMED = "at int, n long, full long, chars long, heads array<string>"
#: Hundredths as an amount's text has them.
HUNDREDTHS = [str(x // 10) if x % 10 == 0 else f"{x:02}" for x in range(100)]


def whole(c: Column) -> Column:
    """Whole numbers that are held here; null for others."""
    return F.when((c > -ZERO) & (c < ZERO), c.cast("long"))


def amount(c: Column) -> Column:
    """Hundredths of amounts whose text has one or two decimals; null for others."""
    cents = F.rint(c * 100)
    plain = (F.abs(c) < 1e7) & (cents / 100 == c) & ((c != 0) | (c.cast("string") == "0.0"))
    return F.when(plain, cents.cast("long"))


def _counted(label: np.ndarray, code: np.ndarray, n: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (label, code) with their counts, in order."""
    if not len(code):
        return label.astype(np.int64), code, np.zeros(0, np.int64)
    if n is None and code.max() < 1 << SHORT_BITS and label.max() < 1 << 62 - SHORT_BITS:
        keys, n = np.unique(label.astype(np.int64) << SHORT_BITS | code, return_counts=True)
        return keys >> SHORT_BITS, keys & (1 << SHORT_BITS) - 1, n
    order = np.lexsort((code, label))
    label, code = label[order], code[order]
    first = np.flatnonzero(np.append(True, (label[1:] != label[:-1]) | (code[1:] != code[:-1])))
    n = np.diff(np.append(first, len(code))) if n is None else np.add.reduceat(n[order], first)
    return label[first], code[first], n


def _planes(x: np.ndarray) -> bytes:
    return np.ascontiguousarray(x.view(np.uint8).reshape(len(x), -1).T).tobytes()


def _blocks(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
    label, code, n = (np.concatenate([p[k] for p in parts]) for k in range(3))
    bucket = ((code >> RUN_BITS) % BUCKETS).astype(np.uint16)
    order = np.argsort(bucket, kind="stable")
    label, code, n, bucket = label[order].astype(np.int32), code[order], n[order].astype(np.int64), bucket[order]
    ends = np.flatnonzero(np.append(bucket[1:] != bucket[:-1], True)) + 1 if len(bucket) else []
    out, at = [], 0
    for end in ends:
        some = slice(at, end)
        raw = _planes(np.diff(label[some], prepend=np.int32(0))) + _planes(np.diff(code[some], prepend=np.int64(0))) + _planes(n[some])
        out.append((int(bucket[at]), int(end - at), pa.compress(raw, codec="zstd", asbytes=True)))
        at = end
    if out:
        yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate((pa.int32(), pa.int32(), pa.binary()))], ["bucket", "n", "block"])


def _read(n: int, block: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    raw = np.frombuffer(pa.decompress(block, 20 * n, codec="zstd", asbytes=True), np.uint8)
    plane = lambda a, b, t: np.ascontiguousarray(raw[a * n : b * n].reshape(b - a, n).T).view(t).ravel()
    return np.cumsum(plane(0, 4, np.int32), dtype=np.int32).astype(np.int64), np.cumsum(plane(4, 12, np.int64)), plane(12, 20, np.int64)


def number_blocks(df: DataFrame, places: dict[str | None, dict[str, int]], amounts: set[str], words: bool = True) -> DataFrame:
    """Blocks of the rows' numbers. df: k and the columns of whole() and amount(); places: k -> column -> place;
    amounts: which columns are hundredths; words: whether amounts are also given as their two words."""
    names = [c for c in df.columns if c != "k"]
    keys = list(places)
    row_of = {k: i for i, k in enumerate(keys)}
    label_of = {c: np.array([places[k][c] * KINDS for k in keys], np.int64) for c in names}

    def entries(c: str, key: np.ndarray, v: np.ndarray) -> Iterator[tuple]:
        label, code, n = _counted(label_of[c][key] + (AMOUNT if c in amounts else WHOLE) + (v < 0), np.abs(v))
        yield label, code, n
        if c in amounts and words:
            word, cents = label // KINDS * KINDS + WORD, code % 100
            last = np.where(cents % 10 == 0, cents // 10, np.where(cents < 10, ZERO + cents, cents))
            yield _counted(word, code // 100, n)
            yield _counted(word, last, n)

    def flush(held: dict[str, list]) -> Iterator[pa.RecordBatch]:
        parts = [p for c, pairs in held.items() if pairs for p in entries(c, np.concatenate([k for k, _ in pairs]), np.concatenate([v for _, v in pairs]))]
        if parts:
            yield from _blocks(parts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = {c: [] for c in names}, 0
        for batch in batches:
            k = batch.column("k").dictionary_encode(null_encoding="encode")
            key = np.array([row_of[x] for x in k.dictionary.to_pylist()], np.int32)[k.indices.to_numpy(zero_copy_only=False)] if len(k) else np.zeros(0, np.int32)
            for c in names:
                v = batch.column(c)
                there = v.is_valid().to_numpy(zero_copy_only=False)
                held[c].append((key[there], v.drop_null().to_numpy()))
                size += len(held[c][-1][1])
            if size >= AT_ONCE:
                yield from flush(held)
                held, size = {c: [] for c in names}, 0
        yield from flush(held)

    return df.mapInArrow(run, BLOCKS)


def held_word(term: Column) -> Column:
    """Whether a word is held as a number here."""
    return term.rlike(f"^[0-9]{{1,{DIGITS}}}$")


def word_blocks(terms: DataFrame) -> DataFrame:
    """Blocks of digit words. terms: (at, term, n), at a place."""
    value = F.col("term").cast("long")
    coded = terms.select((F.col("at") * KINDS + WORD).cast("long").alias("label"), (value + (F.length("term") - F.length(value.cast("string"))).cast("long") * ZERO).alias("code"), F.col("n").cast("long").alias("n"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            held.append(tuple(batch.column(c).to_numpy() for c in ("label", "code", "n")))
            size += batch.num_rows
            if size >= AT_ONCE // 4:
                yield from _blocks([_counted(*(np.concatenate([h[k] for h in held]) for k in range(3)))])
                held, size = [], 0
        if size:
            yield from _blocks([_counted(*(np.concatenate([h[k] for h in held]) for k in range(3)))])

    return coded.mapInArrow(run, BLOCKS)


def _mixed(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = x.astype(np.uint64)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def _merges(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Distinct (code, label) with their counts, in order, of some whole buckets at a time."""
    counted = lambda: _counted(*(np.concatenate([h[k] for h in held]) for k in (1, 0, 2)))
    held, size, last = [], 0, None
    for batch in batches:
        for bucket, n, block in zip(*(batch.column(c).to_pylist() for c in ("bucket", "n", "block")), strict=True):
            if bucket != last and size >= MERGED:
                yield counted()
                held, size = [], 0
            last = bucket
            held.append(_read(n, block))
            size += n
    if held:
        yield counted()


def _add_cells(sums: np.ndarray, code: np.ndarray, label: np.ndarray, n: np.ndarray) -> None:
    """Adds each place's distinct values, cells and characters to its sums; words alone are no cells."""
    kind, at = label % KINDS, label // KINDS
    cell = kind < WORD
    kind, at, v, times = kind[cell], at[cell], code[cell], n[cell]
    whole_ = np.where(kind < AMOUNT, v, v // 100)
    width = np.searchsorted(10 ** np.arange(1, 18, dtype=np.int64), whole_, "right") + 1 + kind % 2 + np.where(kind < AMOUNT, 0, 2 + (v % 10 != 0))
    for k, w in enumerate((None, times, times * width)):
        sums[k] += np.bincount(at, w, sums.shape[1])


def merged(blocks: DataFrame, items: list[str], worded: set[int]) -> DataFrame:
    """FOUND of all blocks: lists of the words as postings() gives them, for places in worded alone, terms with equal
    lists together as far as they were merged at once; and parts of each place's sums. items: their names by place."""
    names, known = np.array([*items, ""], object), np.array([x in worded for x in range(len(items))] + [False])

    def lists(label: np.ndarray, code: np.ndarray, n: np.ndarray, hashed: np.ndarray) -> pa.RecordBatch | None:
        keep = (label % KINDS != AMOUNT) & (label % KINDS != AMOUNT + 1) & known[label // KINDS]
        code, at, n = _counted(code[keep], label[keep] // KINDS, n[keep])
        if not len(code):
            return None
        first = np.flatnonzero(np.append(True, code[1:] != code[:-1]))
        size = np.diff(np.append(first, len(code)))
        mark = _mixed(code)
        place, sign = at * PLACES + (mark % np.uint64(PLACES)).astype(np.int64), np.where(mark >> np.uint64(63), 1.0, -1.0)
        for part, w in enumerate((n * sign, n * sign * np.log(np.repeat(size, size)))):
            hashed[part] += np.bincount(place, w, len(items) * PLACES).reshape(len(items), PLACES)
        with np.errstate(over="ignore"):
            a = _mixed(_mixed(at.astype(np.uint64) + np.uint64(0x9E3779B97F4A7C15)) + n.astype(np.uint64))
            b = _mixed(_mixed(at.astype(np.uint64) ^ np.uint64(0xC2B2AE3D27D4EB4F)) * np.uint64(3) + n.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
            marks = np.stack([np.add.reduceat(a, first), np.add.reduceat(b, first), size.astype(np.uint64)], 1)
        order = np.lexsort(marks.T)
        new = np.append(True, (marks[order][1:] != marks[order][:-1]).any(1))
        chosen, times = order[new], np.diff(np.append(np.flatnonzero(new), len(order)))
        wide = size[chosen]
        ends = np.append(0, np.cumsum(wide))
        rows = np.repeat(first[chosen] - ends[:-1], wide) + np.arange(ends[-1])
        item = pa.DictionaryArray.from_arrays(pa.array(at[rows].astype(np.int32)), pa.array(names, pa.string())).cast(pa.string())
        held = pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.StructArray.from_arrays([item, pa.array(n[rows].astype(float))], ["item", "w"]))
        none = lambda t: pa.nulls(len(times), t)
        return pa.RecordBatch.from_arrays([held, pa.array(times.astype(np.int64)), none(pa.int32()), none(pa.int64()), none(pa.int64()), none(pa.list_(pa.float64()))], FIELDS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, hashed = np.zeros((3, len(items))), np.zeros((2, len(items), PLACES))
        for code, label, n in _merges(batches):
            _add_cells(sums, code, label, n)
            found = lists(label, code, n, hashed)
            if found is not None:
                yield from (found.slice(a, 20_000) for a in range(0, len(found), 20_000))
        at = np.flatnonzero((sums[0] > 0) | hashed.any((0, 2)))
        if len(at):
            cells = [pa.array(sums[k][at].astype(np.int64)) for k in range(3)]
            flat = pa.array(np.concatenate(list(hashed[:, at]), 1).ravel())
            words = pa.ListArray.from_arrays(pa.array(np.arange(len(at) + 1, dtype=np.int32) * (2 * PLACES)), flat)
            none = pa.nulls(len(at), pa.list_(pa.struct([("item", pa.string()), ("w", pa.float64())])))
            yield pa.RecordBatch.from_arrays([none, cells[0], pa.array(at.astype(np.int32)), *cells[1:], words], FIELDS)

    return blocks.repartition(64, "bucket").sortWithinPartitions("bucket").mapInArrow(run, FOUND)


def _texts(kind: int, v: np.ndarray) -> list[str]:
    """The numbers' texts, by the kind of their entries."""
    sign = "-" if kind % 2 else ""
    if kind < AMOUNT:
        return [f"{sign}{x}" for x in v.tolist()]
    return [f"{sign}{x}.{HUNDREDTHS[y]}" for x, y in zip((v // 100).tolist(), (v % 100).tolist(), strict=True)]


def _beginnings(kind: np.ndarray, v: np.ndarray) -> np.ndarray:
    """How digest() of each number's text begins: eight bytes of it as a number."""
    out = np.zeros(len(v), np.uint64)
    for k in np.unique(kind).tolist():
        mine = kind == k
        out[mine] = np.frombuffer(b"".join([md5(b"0|" + x.encode()).digest()[:8] for x in _texts(k, v[mine])]), ">u8")
    return out


def summed(blocks: DataFrame, n_places: int, samples: int) -> DataFrame:
    """SUMMED of all blocks, parts of each place's sums: no word is listed. A number is hashed once, whatever columns hold
    it; a part's texts are those with the smallest hashes in it."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, bound = np.zeros((3, n_places)), np.full(n_places, np.iinfo(np.uint64).max, np.uint64)
        best = (np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64))  # place, hash, number with its kind
        for code, label, n in _merges(batches):
            _add_cells(sums, code, label, n)
            kind = label % KINDS
            cell = kind < WORD
            keys, of = np.unique(code[cell] * WORD + kind[cell], return_inverse=True)
            mark, at = _beginnings(keys % WORD, keys // WORD)[of], label[cell] // KINDS
            near = mark <= bound[at]
            at, mark, key = (np.concatenate(x) for x in zip(best, (at[near], mark[near], keys[of[near]]), strict=True))
            order = np.lexsort((mark, at))
            at, mark, key = at[order], mark[order], key[order]
            first = np.flatnonzero(np.append(True, at[1:] != at[:-1])) if len(at) else np.zeros(0, np.int64)
            size = np.diff(np.append(first, len(at)))
            full = size >= samples
            bound[at[first[full]]] = mark[first[full] + samples - 1]
            keep = mark <= bound[at]
            best = (at[keep], mark[keep], key[keep])
        held = np.flatnonzero(sums[0] > 0)
        if len(held):
            heads: dict[int, list[str]] = {}
            for at, key in zip(best[0].tolist(), best[2].tolist(), strict=True):
                heads.setdefault(at, []).extend(_texts(key % WORD, np.array([key // WORD])))
            cells = [pa.array(sums[k][held].astype(np.int64)) for k in range(3)]
            yield pa.RecordBatch.from_arrays([pa.array(held.astype(np.int32)), *cells, pa.array([heads.get(x, []) for x in held.tolist()], pa.list_(pa.string()))], ["at", "n", "full", "chars", "heads"])

    return blocks.repartition(64, "bucket").sortWithinPartitions("bucket").mapInArrow(run, SUMMED)
