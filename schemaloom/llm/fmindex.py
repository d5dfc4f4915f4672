"""Benchmark decontamination with an FM-index for each training shard.

A shard is a bounded slice of documents. All its words, numbered by the shard's own vocabulary, become a suffix array, a
Burrows-Wheeler transform in a wavelet matrix and sampled suffix positions. Windows of any benchmark are searched
backwards, all at once, and their occurrences located from the samples. An index can be written and searched again.
"""

from __future__ import annotations

import hashlib
import io
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.llm.shared import byte_texts, documents, filesystem, slices, write_whole

WINDOW = 13
SHARD_BYTES = 4 << 20
#: Bytes of benchmark text that are searched for, and broadcast, at once; a larger benchmark is taken in blocks.
BLOCK_BYTES = 32 << 20
#: Word characters are 0-9, A-Z, a-z and every byte of a non-ASCII character; A-Z are lowered, the rest separates.
TABLE = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))
SCHEMA = "n_words long, n_hit long, spans array<struct<first:long,after:long>>, items array<string>"


def words_of(text: bytes) -> list[bytes]:
    return text.translate(TABLE).split()


def suffix_order(seq: np.ndarray) -> np.ndarray:
    """Suffix array by doubling; a suffix that ends first sorts first. A rank is the first row of the suffixes that are
    still alike, and only those are sorted again."""
    n = len(seq)
    order = np.argsort(seq, kind="stable")
    rank = np.empty(n, np.int64)

    def settle(rows: np.ndarray, some: np.ndarray, edge: np.ndarray) -> np.ndarray:
        """Ranks of suffixes in their rows, where an edge starts a new group; rows of groups with more than one."""
        head = np.flatnonzero(edge)
        size = np.diff(np.append(head, len(some)))
        rank[some] = np.repeat(rows[head], size)
        return rows[np.repeat(size > 1, size)]

    open_ = settle(np.arange(n), order, np.concatenate(([True], np.diff(seq[order]) != 0))[:n])
    step = 1
    while len(open_):
        some = order[open_]
        after = np.where(some + step < n, rank[np.minimum(some + step, n - 1)] + 1, 0)
        key = rank[some] * (n + 1) + after
        by = np.argsort(key, kind="stable")
        some, key = some[by], key[by]
        order[open_] = some
        open_ = settle(open_, some, np.concatenate(([True], np.diff(key) != 0)))
        step *= 2
    return order


class WaveletMatrix:
    """Rank of any symbol of an integer sequence in one lookup for each bit of the alphabet."""

    def __init__(self, seq: np.ndarray, bits: int):
        self.bits, self.ranks, self.zeros = bits, [], []
        for level in reversed(range(bits)):
            one = (seq >> level & 1).astype(bool)
            self.ranks.append(np.concatenate(([0], np.cumsum(one))).astype(np.int32))
            self.zeros.append(len(seq) - int(self.ranks[-1][-1]))
            seq = np.concatenate((seq[~one], seq[one]))

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Occurrences of each symbol before each position."""
        low = np.zeros(len(at), np.int64)
        at = at.astype(np.int64)
        for k, level in enumerate(reversed(range(self.bits))):
            ranks, one = self.ranks[k], (symbol >> level & 1).astype(bool)
            low_ones, at_ones = ranks[low], ranks[at]
            low = np.where(one, self.zeros[k] + low_ones, low - low_ones)
            at = np.where(one, self.zeros[k] + at_ones, at - at_ones)
        return at - low


class FMIndex:
    def __init__(self, seq: np.ndarray, alphabet: int, sample: int = 8):
        """seq: ids from 1; 0 separates runs. alphabet: the largest id plus 1."""
        text = np.concatenate((seq.astype(np.int64) + 1, [0]))  # the end sorts first and is unique
        order = suffix_order(text)
        self.bwt = text[order - 1]
        self.tree = WaveletMatrix(self.bwt, max(1, int(alphabet).bit_length()))
        self.before = np.concatenate(([0], np.cumsum(np.bincount(text, minlength=alphabet + 1))))
        kept = order % sample == 0
        self.kept_before, self.kept, self.samples = np.concatenate(([0], np.cumsum(kept))), kept, order[kept]

    @classmethod
    def of(cls, bwt: np.ndarray, kept: np.ndarray, samples: np.ndarray, alphabet: int) -> "FMIndex":
        """From a transform and its samples, as they were written."""
        out = cls.__new__(cls)
        out.bwt, out.kept, out.samples = bwt, kept, samples
        out.tree = WaveletMatrix(bwt, max(1, int(alphabet).bit_length()))
        out.before = np.concatenate(([0], np.cumsum(np.bincount(bwt, minlength=alphabet + 1))))
        out.kept_before = np.concatenate(([0], np.cumsum(kept)))
        return out

    def search(self, patterns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Suffix-array intervals [low, high) of equally long patterns, one a row, by backward steps."""
        low, high = np.zeros(len(patterns), np.int64), np.full(len(patterns), len(self.bwt), np.int64)
        live = np.arange(len(patterns))
        for column in reversed(range(patterns.shape[1])):
            symbol = patterns[live, column].astype(np.int64) + 1
            start = self.before[symbol]
            low[live], high[live] = start + self.tree.rank(symbol, low[live]), start + self.tree.rank(symbol, high[live])
            live = live[low[live] < high[live]]
            if not len(live):
                break
        dead = np.ones(len(patterns), bool)
        dead[live] = False
        low[dead] = high[dead] = 0
        return low, high

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Text positions of suffix-array rows: steps back until a sampled row."""
        rows, steps, at = rows.astype(np.int64), np.zeros(len(rows), np.int64), np.zeros(len(rows), np.int64)
        live = np.arange(len(rows))
        while len(live):
            done = self.kept[rows[live]]
            ended = live[done]
            at[ended] = self.samples[self.kept_before[rows[ended]]] + steps[ended]
            live = live[~done]
            symbol = self.bwt[rows[live]]
            rows[live] = self.before[symbol] + self.tree.rank(symbol, rows[live])
            steps[live] += 1
        return at


class Phrases:
    """The distinct windows of a block of benchmark items, grouped by length, as vocabulary ids."""

    def __init__(self, items: list[tuple[str, bytes]], window: int = WINDOW):
        vocabulary: dict[bytes, int] = {}
        found: dict[tuple[int, ...], set[str]] = {}
        for item_id, text in items:
            ids = [vocabulary.setdefault(w, len(vocabulary)) for w in words_of(text)]
            for k in range(max(1, len(ids) - window + 1) if ids else 0):
                found.setdefault(tuple(ids[k : k + window]), set()).add(item_id)
        self.words = list(vocabulary)
        self.by_length = {}
        for n in sorted({len(x) for x in found}):
            some = [x for x in found if len(x) == n]
            self.by_length[n] = (np.array(some, np.int64), [sorted(found[x]) for x in some])


class ShardIndex:
    """The FM-index of a shard's texts: their words one after another, with a separator behind each text."""

    def __init__(self, texts: list[bytes]):
        clean = pa.array([x.translate(TABLE) for x in texts], pa.binary()).cast(pa.string())
        cut = pc.split_pattern(clean, " ")
        parts = cut.flatten().dictionary_encode()
        names, which = parts.dictionary.to_pylist(), parts.indices.to_numpy().astype(np.int64)
        empty = names.index("") if "" in names else -1
        there = np.concatenate(([0], np.cumsum(which != empty)))
        self.counts = np.diff(there[np.asarray(cut.offsets) - cut.offsets[0].as_py()])
        # ids from 1; 0 separates texts
        number = np.arange(1, len(names) + 1)
        if empty >= 0:
            number[empty + 1 :] -= 1
        words = number[which[which != empty]] if len(which) else which
        self.offsets = np.concatenate(([0], np.cumsum(self.counts + 1)))
        seq = np.zeros(int(self.offsets[-1]), np.int64)
        inside = np.ones(len(seq), bool)
        inside[self.offsets[1:] - 1] = False
        seq[inside] = words
        self.names = [x.encode() for k, x in enumerate(names) if k != empty]
        self.index = FMIndex(seq, len(self.names) + 1)
        self.vocabulary = {x: k for k, x in enumerate(self.names, 1)}

    def to_bytes(self) -> bytes:
        """A compressed archive of its arrays; the wavelet matrix is made again from the transform."""
        out = io.BytesIO()
        index = self.index
        np.savez_compressed(out, counts=self.counts, names=np.frombuffer(b"\n".join(self.names), np.uint8), bwt=index.bwt.astype(np.uint32), kept=np.packbits(index.kept), samples=index.samples.astype(np.uint32))
        return out.getvalue()

    @classmethod
    def from_bytes(cls, data: bytes) -> "ShardIndex":
        held = np.load(io.BytesIO(data))
        out = cls.__new__(cls)
        out.counts = held["counts"]
        out.offsets = np.concatenate(([0], np.cumsum(out.counts + 1)))
        joined = held["names"].tobytes()
        out.names = joined.split(b"\n") if joined else []
        out.vocabulary = {x: k for k, x in enumerate(out.names, 1)}
        bwt = held["bwt"].astype(np.int64)
        out.index = FMIndex.of(bwt, np.unpackbits(held["kept"], count=len(bwt)).astype(bool), held["samples"].astype(np.int64), len(out.names) + 1)
        return out

    def find(self, phrases: Phrases) -> list[tuple[int, int, list, list]]:
        """For each text: words, hit words, merged spans of hit words [first, after), sorted items found."""
        results = [(int(n), 0, [], []) for n in self.counts]
        here = np.array([self.vocabulary.get(w, 0) for w in phrases.words], np.int64)
        covered = np.zeros(int(self.offsets[-1]) + 1, np.int64)
        items: dict[int, set[str]] = {}
        for length, (patterns, owners) in phrases.by_length.items():
            mine = here[patterns]
            known = np.flatnonzero((mine > 0).all(axis=1))  # a window with a word that the shard lacks isn't there
            if not len(known):
                continue
            low, high = self.index.search(mine[known])
            hit = np.flatnonzero(high > low)
            if not len(hit):
                continue
            sizes = (high - low)[hit]
            rows = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes) + np.repeat(low[hit], sizes)
            first = self.index.locate(rows)
            np.add.at(covered, first, 1)
            np.add.at(covered, first + length, -1)
            docs = np.searchsorted(self.offsets, first, "right") - 1
            for doc, k in set(zip(docs.tolist(), np.repeat(known[hit], sizes).tolist(), strict=True)):
                items.setdefault(doc, set()).update(owners[k])
        inside = np.cumsum(covered)[:-1] > 0
        edges = np.diff(np.concatenate(([0], inside.astype(np.int8), [0])))
        firsts, afters = np.flatnonzero(edges == 1), np.flatnonzero(edges == -1)
        owner = np.searchsorted(self.offsets, firsts, "right") - 1
        for doc in np.unique(owner).tolist():
            mine = owner == doc
            spans = [(int(a - self.offsets[doc]), int(b - self.offsets[doc])) for a, b in zip(firsts[mine], afters[mine], strict=True)]
            results[doc] = (int(self.counts[doc]), sum(b - a for a, b in spans), spans, sorted(items.get(doc, ())))
        return results


def search_shard(texts: list[bytes], phrases: Phrases) -> list[tuple[int, int, list, list]]:
    return ShardIndex(texts).find(phrases) if texts else []


def write_index(docs: DataFrame, folder: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Writes an index file for each shard of the documents and gives the manifest: file, docs (ids in the index's order).
    The file's name is its content's hash, so that a task that runs again writes the same one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = filesystem(folder)
        for batch in slices(batches, "text", SHARD_BYTES):
            data = ShardIndex(byte_texts(batch.column("text"))).to_bytes()
            name = f"{hashlib.sha256(data + repr(batch.column('id').to_pylist()).encode()).hexdigest()[:32]}.fm"
            write_whole(fs, f"{root}/{name}", [data])
            yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([batch.column("id").to_pylist()], pa.list_(pa.int64()))], ["file", "docs"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).alias("text")).mapInArrow(run, "file string, docs array<long>")


def search_index(manifest: DataFrame, folder: str, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """(doc_id, n_words, n_hit, spans, items) of written indexes: texts are not read again. The benchmark is one block."""
    phrases = manifest.sparkSession.sparkContext.broadcast(Phrases(items_of(benchmark), window))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = filesystem(folder)
        for batch in batches:
            for row in batch.to_pylist():
                with fs.open_input_stream(f"{root}/{row['file']}", compression=None) as source:
                    found = ShardIndex.from_bytes(source.read()).find(phrases.value)
                yield pa.RecordBatch.from_arrays([pa.array(row["docs"], pa.int64()), *found_arrays(found)], ["doc_id", "n_words", "n_hit", "spans", "items"])

    return manifest.repartitionByRange(max(1, manifest.count()), "file").mapInArrow(run, f"doc_id long, {SCHEMA}")


def items_of(benchmark: DataFrame) -> list[tuple[str, bytes]]:
    """A block of items; a null id is an empty one."""
    small = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("i"), F.coalesce(F.col("text"), F.lit("")).alias("t"))
    return [(r.i, r.t.encode()) for r in small.toLocalIterator()]


def found_arrays(found: list[tuple[int, int, list, list]]) -> list[pa.Array]:
    kind = pa.list_(pa.struct([("first", pa.int64()), ("after", pa.int64())]))
    spans = [[{"first": a, "after": b} for a, b in x[2]] for x in found]
    return [pa.array([x[0] for x in found], pa.int64()), pa.array([x[1] for x in found], pa.int64()), pa.array(spans, kind), pa.array([x[3] for x in found], pa.list_(pa.string()))]


def find_benchmark(docs: DataFrame, benchmark: DataFrame, text: str = "text", window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """docs with n_words, n_hit, spans (merged removal spans, in words) and items (ids found, sorted as strings).

    Null texts and texts without words have no words; items without words are never found; item texts may repeat; a null
    item id is an empty one. A
    benchmark of more than block_bytes is searched for block by block, each broadcast on its own. Columns of docs that
    bear one of the four names are replaced. No shuffle unless there are several blocks.
    """
    key = F.coalesce(F.col("item_id").cast("string"), F.lit(""))
    total = benchmark.agg(F.sum(F.octet_length(F.coalesce("text", F.lit(""))) + F.octet_length(key))).first()[0] or 0
    blocks = max(1, -(-total // block_bytes))
    docs = docs.drop("n_words", "n_hit", "spans", "items")
    spark, out = docs.sparkSession, None
    for k in range(blocks):
        mine = benchmark if blocks == 1 else benchmark.where(F.pmod(F.xxhash64(key), F.lit(blocks)) == k)
        phrases = spark.sparkContext.broadcast(Phrases(items_of(mine), window))
        source = docs if out is None else out

        def scan(batches: Iterator[pa.RecordBatch], phrases=phrases) -> Iterator[pa.RecordBatch]:
            for batch in slices(batches, text, SHARD_BYTES):
                found = search_shard(byte_texts(batch.column(text)), phrases.value)
                arrays = [batch.column(c) for c in range(batch.num_columns) if batch.schema.names[c] not in ("n_words", "n_hit", "spans", "items")]
                names = [c for c in batch.schema.names if c not in ("n_words", "n_hit", "spans", "items")]
                if "spans" in batch.schema.names:
                    before = zip(batch.column("spans").to_pylist(), batch.column("items").to_pylist(), strict=True)
                    found = [merged(new, *old) for new, old in zip(found, before, strict=True)]
                arrays += found_arrays(found)
                yield pa.RecordBatch.from_arrays(arrays, [*names, "n_words", "n_hit", "spans", "items"])

        fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
        out = source.mapInArrow(scan, f"{fields}, {SCHEMA}")
    return out


def merged(new: tuple, spans: list[dict], items: list[str]) -> tuple:
    """Results of one more block joined with those of the blocks before."""
    words, _, more, found = new
    out: list[list[int]] = []
    for a, b in sorted([*((s["first"], s["after"]) for s in spans), *more]):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return words, sum(b - a for a, b in out), [tuple(x) for x in out], sorted({*items, *found})


def contaminated() -> "F.Column":
    return (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))


def op9_fm_decontamination(spark, sf_dir: str) -> DataFrame:
    found = find_benchmark(documents(spark, sf_dir).select("doc_id", "text"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), contaminated().alias("contaminated"),
    )


OP9_SQL = r"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
b AS (
  SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
bw AS (
  SELECT DISTINCT item_id, least(13, len(ws)) AS n, array_to_string(list_slice(ws, k, k + 12), ' ') AS win
  FROM (SELECT item_id, ws, unnest(range(1, greatest(1, len(ws) - 12) + 1)) AS k FROM b WHERE len(ws) > 0)),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (
  SELECT doc_id, n, k, array_to_string(list_slice(ws, k, k + n - 1), ' ') AS win
  FROM (SELECT doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) AS k FROM w, sizes WHERE len(ws) >= n)),
hits AS (SELECT DISTINCT dw.doc_id, dw.k, dw.n, bw.item_id FROM dw JOIN bw USING (win)),
hit_words AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + n)) AS p FROM hits) GROUP BY doc_id),
hit_items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(i, ',' ORDER BY i) AS items
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS i FROM hits) GROUP BY doc_id)
SELECT w.doc_id, coalesce(len(ws), 0)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= coalesce(len(ws), 0) AS contaminated
FROM w LEFT JOIN hit_words USING (doc_id) LEFT JOIN hit_items USING (doc_id)
"""
