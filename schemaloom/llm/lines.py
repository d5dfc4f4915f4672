"""Line dedup: a sharded minimal perfect hash over distinct line hashes, probed by the documents."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.llm.shared import Scratch, byte_texts, documents, slices, unused

BLANK = b" \t\n\x0b\x0c\r"
CONTINUATION = bytes(range(0x80, 0xC0))
SLICE_BYTES = 8 << 20
SHARD_KEYS = 1 << 20
#: Bytes of all shards' arrays up to which every task gets them whole; beyond, line hashes travel to the shards.
BROADCAST_BYTES = 64 << 20
ROUTE_ROWS = 1 << 20
NO_ID = -(1 << 63)  # stands for a null doc_id, which sorts first
ADDED = ("n_lines", "n_dropped", "kept_text")


def key_of(line: bytes, least: int) -> bytes | None:
    """A line's key if it is long enough to be judged."""
    key = line.strip(BLANK)
    if len(key) < least or len(key.translate(None, CONTINUATION)) < least:
        return None
    return key.lower()  # of bytes: A-Z only


class PerfectHash:
    """Minimal perfect hash of distinct 64-bit keys: at each level the keys that have a bit of their own stay, the
    others go on; a key's index is the rank of its bit."""

    def __init__(self, levels: list[np.ndarray]):
        self.levels = levels
        self.ranks, total = [], 0
        for bits in levels:
            self.ranks.append(total + np.concatenate(([0], np.cumsum(np.bitwise_count(bits), dtype=np.int64))))
            total = int(self.ranks[-1][-1])
        self.size = total

    @staticmethod
    def place(keys: np.ndarray, level: int, words: int) -> np.ndarray:
        x = keys ^ np.uint64((level + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1)
        for shift, factor in ((33, 0xFF51AFD7ED558CCD), (33, 0xC4CEB9FE1A85EC53)):
            x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
        return (x ^ (x >> np.uint64(33))) % np.uint64(words * 64)

    @classmethod
    def build(cls, keys: np.ndarray, spare: float = 1.5) -> "PerfectHash":
        levels = []
        while len(keys):
            words = max(1, int(len(keys) * spare) // 64 + 1)
            at = cls.place(keys, len(levels), words)
            alone = np.bincount(at.astype(np.int64), minlength=words * 64) == 1
            levels.append(np.packbits(alone, bitorder="little").view(np.uint64))
            keys = keys[~alone[at.astype(np.int64)]]
        return cls(levels)

    def lookup(self, keys: np.ndarray) -> np.ndarray:
        """Index of each key; of a key that was not built in, -1 or any index."""
        out = np.full(len(keys), -1, np.int64)
        live = np.arange(len(keys))
        for level, (bits, ranks) in enumerate(zip(self.levels, self.ranks, strict=True)):
            at = self.place(keys[live], level, len(bits))
            word, bit = (at >> np.uint64(6)).astype(np.int64), at & np.uint64(63)
            found = (bits[word] >> bit & np.uint64(1)).astype(bool)
            below = bits[word] & ((np.uint64(1) << bit) - np.uint64(1))
            out[live[found]] = (ranks[word] + np.bitwise_count(below))[found]
            live = live[~found]
        return out


class Shard:
    """A perfect hash over first halves of 128-bit line hashes, with the second halves as fingerprints, the number of
    documents and the last document of each line. Of lines that share first halves one is in the hash; the others stand
    in a short list beside it, which is compared whole."""

    def __init__(self, levels, prints, counts, last, more=b""):
        self.more = np.frombuffer(more, np.int64).reshape(-1, 4)
        self.hash, self.prints, self.counts, self.last = PerfectHash([np.frombuffer(x, np.uint64) for x in levels]), np.frombuffer(prints, np.uint64), np.frombuffer(counts, np.uint32), np.frombuffer(last, np.int64)

    @staticmethod
    def arrays(first: np.ndarray, second: np.ndarray, counts: np.ndarray, last: np.ndarray) -> tuple:
        index = PerfectHash.build(first)
        at = index.lookup(first)
        put = lambda values, kind: values.astype(kind)[np.argsort(at)].tobytes()
        return [x.tobytes() for x in index.levels], put(second, np.uint64), put(np.minimum(counts, 0xFFFFFFFF), np.uint32), put(last, np.int64)

    @classmethod
    def pack(cls, first: np.ndarray, second: np.ndarray, counts: np.ndarray, last: np.ndarray) -> tuple:
        """What makes a shard of lines with any hashes."""
        once = np.unique(first, return_index=True)[1]
        rest = np.setdiff1d(np.arange(len(first)), once)
        more = np.stack((first[rest].view(np.int64), second[rest].view(np.int64), counts[rest].astype(np.int64), last[rest]), axis=1) if len(rest) else np.zeros((0, 4), np.int64)
        return *cls.arrays(first[once], second[once], counts[once], last[once]), more.tobytes()

    def others_hold(self, first: np.ndarray, second: np.ndarray, doc: np.ndarray, least_docs: int) -> np.ndarray:
        """Whether enough documents have the line and the last of them is another."""
        at = self.hash.lookup(first)
        found = np.zeros(len(first), bool)
        some = np.flatnonzero(at >= 0)
        found[some] = (self.prints[at[some]] == second[some]) & (self.counts[at[some]] >= least_docs) & (self.last[at[some]] != doc[some])
        for a, b, n, last in self.more.tolist():
            if n >= least_docs:
                found |= (first.view(np.int64) == a) & (second.view(np.int64) == b) & (doc != last)
        return found


def shard_of(first: np.ndarray, shards: int) -> np.ndarray:
    return (first >> np.uint64(32)) * np.uint64(shards) >> np.uint64(32)


def hashed(texts: list[bytes], least: int) -> tuple[list[list[bytes]], np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Each text's lines; then of the lines long enough: text number, line number and both hash halves."""
    split, owner, number, digests = [], [], [], []
    for k, text in enumerate(texts):
        split.append(lines := text.split(b"\n"))
        for j, line in enumerate(lines):
            if len(line) >= least and (key := key_of(line, least)) is not None:
                owner.append(k)
                number.append(j)
                digests.append(xxhash.xxh3_128_digest(key))
    both = np.frombuffer(b"".join(digests), ">u8").reshape(-1, 2).astype(np.uint64)
    return split, np.array(owner, np.int64), np.array(number, np.int64), both[:, 0], both[:, 1]


def doc_ids(column: pa.Array) -> np.ndarray:
    return column.cast(pa.int64()).fill_null(NO_ID).to_numpy(zero_copy_only=False)


def rewritten(batch: pa.RecordBatch, id_col: str, text: str, split: list[list[bytes]], owner, number, gone) -> pa.RecordBatch:
    dropped: dict[int, set[int]] = {}
    for k, j in zip(owner[gone].tolist(), number[gone].tolist(), strict=True):
        dropped.setdefault(k, set()).add(j)
    kept = [b"\n".join(x if k not in dropped else [y for j, y in enumerate(x) if j not in dropped[k]]) for k, x in enumerate(split)]
    names = [c for c in batch.schema.names if c not in ADDED]
    out = [batch.column(batch.schema.names.index(c)) for c in names]
    out += [pa.array([len(x) for x in split], pa.int64()), pa.array([len(dropped.get(k, ())) for k in range(len(split))], pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())]
    return pa.RecordBatch.from_arrays(out, [*names, *ADDED])


def drop_repeated_lines(docs: DataFrame, id_col: str = "doc_id", text: str = "text", least_chars: int = 20, least_docs: int = 3, broadcast_bytes: int = BROADCAST_BYTES, shard_keys: int = SHARD_KEYS) -> DataFrame:
    r"""docs with n_lines, n_dropped and kept_text.

    A text's lines are its parts between \n (null or empty: one empty line). Lines whose key - stripped of ASCII white
    space, A-Z lowered - has least_chars code points or more and stands in least_docs rows or more go, except in the
    largest id that holds it. A null id is the smallest. Rows that repeat an id count as documents of their own but
    share its decisions. Columns of docs with the three added names are replaced. Equal keys are found by 128-bit
    hashes.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "lines")
    docs = docs.drop(*ADDED)

    def distinct(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text, SLICE_BYTES):
            _, owner, _, first, second = hashed(byte_texts(batch.column(text)), least_chars)
            if not len(owner):
                continue
            ids = doc_ids(batch.column(id_col))[owner]
            order = np.lexsort((owner, second, first))
            same_line = np.concatenate(([False], (np.diff(first[order]) == 0) & (np.diff(second[order]) == 0)))
            once = order[~(same_line & np.concatenate(([False], np.diff(owner[order]) == 0)))]  # a line once for each row
            starts = np.flatnonzero(np.concatenate(([True], (np.diff(first[once]) != 0) | (np.diff(second[once]) != 0))))
            n = np.diff(np.concatenate((starts, [len(once)])))
            head = once[starts]
            yield pa.RecordBatch.from_arrays([pa.array(first[head].view(np.int64)), pa.array(second[head].view(np.int64)), pa.array(n), pa.array(np.maximum.reduceat(ids[once], starts))], ["first", "second", "n", "last"])

    counted = docs.select(id_col, text).mapInArrow(distinct, "first long, second long, n long, last long")
    repeated = scratch.table("repeated", counted.groupBy("first", "second").agg(F.sum("n").alias("n"), F.max("last").alias("last")).where(F.col("n") >= least_docs))
    keys = repeated.count()
    shards = max(1, -(-keys // shard_keys))

    def build(table: pa.Table) -> pa.Table:
        get = lambda c: table.column(c).to_numpy()
        first, second = get("first").view(np.uint64), get("second").view(np.uint64)
        levels, prints, counts, last, more = Shard.pack(first, second, get("n"), get("last"))
        return pa.table({"shard": pa.array([table.column("shard")[0].as_py()], pa.int64()), "levels": pa.array([levels], pa.list_(pa.binary())), "prints": pa.array([prints], pa.binary()), "counts": pa.array([counts], pa.binary()), "last": pa.array([last], pa.binary()), "more": pa.array([more], pa.binary())})

    number = F.shiftrightunsigned(F.shiftrightunsigned("first", 32) * shards, 32).alias("shard")
    kind = "shard long, levels array<binary>, prints binary, counts binary, last binary, more binary"
    arrays = scratch.table("arrays", repeated.select("*", number).groupBy("shard").applyInArrow(build, kind))
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema) + ", n_lines long, n_dropped long, kept_text string"

    if keys * 24 <= broadcast_bytes:
        held = spark.sparkContext.broadcast({r.shard: (r.levels, r.prints, r.counts, r.last, r.more) for r in arrays.toLocalIterator()})
        made: dict[int, Shard] = {}

        def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for k, x in held.value.items():
                made.setdefault(k, Shard(*x))
            for batch in slices(batches, text, SLICE_BYTES):
                split, owner, place, first, second = hashed(byte_texts(batch.column(text)), least_chars)
                ids, at = doc_ids(batch.column(id_col))[owner], shard_of(first, shards)
                gone = np.zeros(len(owner), bool)
                for k, shard in made.items():
                    mine = np.flatnonzero(at == np.uint64(k))
                    gone[mine] = shard.others_hold(first[mine], second[mine], ids[mine], least_docs)
                yield rewritten(batch, id_col, text, split, owner, place, gone)

        return docs.mapInArrow(probe, fields)
    return routed(docs, scratch, arrays, shards, fields, id_col, text, least_chars, least_docs)


def routed(docs: DataFrame, scratch: Scratch, arrays: DataFrame, shards: int, fields: str, id_col: str, text: str, least_chars: int, least_docs: int) -> DataFrame:
    """For arrays too large for every task: line hashes go to their shard, in as many groups as its rows ask for, and
    the hits return to their documents."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text, SLICE_BYTES):
            _, owner, _, first, second = hashed(byte_texts(batch.column(text)), least_chars)
            yield pa.RecordBatch.from_arrays([pa.array(shard_of(first, shards).astype(np.int64)), pa.array(doc_ids(batch.column(id_col))[owner]), pa.array(first.view(np.int64)), pa.array(second.view(np.int64))], ["shard", "doc", "first", "second"])

    lines = scratch.table("lines", docs.select(id_col, text).mapInArrow(emit, "shard long, doc long, first long, second long"))
    salts = scratch.table("salts", lines.groupBy("shard").agg(F.ceil(F.count("*") / ROUTE_ROWS).alias("salts")))
    lines = lines.join(F.broadcast(salts), "shard").withColumn("salt", F.pmod(F.xxhash64("doc"), F.col("salts")))
    other = salts.select(F.col("shard").alias("_shard"), F.col("salts").alias("_salts"))  # names of its own: both sides of the cogroup come from this table
    spread = arrays.join(F.broadcast(other), F.col("shard") == F.col("_shard")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("_salts") - 1))).drop("_shard", "_salts")

    def probe(left: pa.Table, right: pa.Table) -> pa.Table:
        if not right.num_rows or not left.num_rows:
            return left.select(["doc", "first", "second"]).slice(0, 0)
        row = right.slice(0, 1).to_pylist()[0]
        get = lambda c: left.column(c).to_numpy()
        gone = Shard(row["levels"], row["prints"], row["counts"], row["last"], row["more"]).others_hold(get("first").view(np.uint64), get("second").view(np.uint64), get("doc"), least_docs)
        return left.select(["doc", "first", "second"]).filter(pa.array(gone))

    hits = lines.groupBy("shard", "salt").cogroup(spread.groupBy("shard", "salt")).applyInArrow(probe, "doc long, first long, second long")
    of, dropped = unused("_doc", docs), unused("_gone", docs)
    per_doc = scratch.table("hits", hits.groupBy("doc").agg(F.collect_set(F.struct("first", "second")).alias(dropped)).withColumnRenamed("doc", of))
    joined = docs.join(per_doc, F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)) == F.col(of), "left").drop(of)

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text, SLICE_BYTES):
            split, owner, place, first, second = hashed(byte_texts(batch.column(text)), least_chars)
            sets = [{(g["first"], g["second"]) for g in x or ()} for x in batch.column(dropped).to_pylist()]
            gone = np.array([(a, b) in sets[k] for k, a, b in zip(owner.tolist(), first.view(np.int64).tolist(), second.view(np.int64).tolist(), strict=True)], bool)
            rest = batch.select([c for c in batch.schema.names if c != dropped])
            yield rewritten(rest, id_col, text, split, owner, place, gone)

    return joined.mapInArrow(apply, fields)


def op8_line_dedup(spark, sf_dir: str) -> DataFrame:
    kept = drop_repeated_lines(documents(spark, sf_dir).select("doc_id", "text"))
    return kept.select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


def line_sql(docs: str = "documents") -> str:
    return rf"""
WITH l AS (
  SELECT doc_id, unnest(range(1, len(ls) + 1)) AS k, unnest(ls) AS line
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM {docs})),
n AS (
  SELECT doc_id, k, line, translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
r AS (
  SELECT key, max(doc_id) AS last FROM n WHERE length(key) >= 20 GROUP BY key HAVING count(DISTINCT doc_id) >= 3),
g AS (SELECT n.doc_id, n.k, n.line, r.key IS NOT NULL AND r.last <> n.doc_id AS gone FROM n LEFT JOIN r ON n.key = r.key)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped,
  coalesce(string_agg(line, chr(10) ORDER BY k) FILTER (NOT gone), '') AS kept_text
FROM g GROUP BY doc_id
"""


OP8_SQL = f"SELECT doc_id, n_lines, n_dropped, sha256(kept_text) AS kept_sha256 FROM ({line_sql()})"
