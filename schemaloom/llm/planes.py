"""Token ids in bit or byte planes: fixed-size blocks, each plane a zstandard frame, with a chunk index.

A file: eight magic bytes; for each block its planes' frames; a footer of frames - the chunk index (byte offset, ids and
plane lengths of each block) and the document table (ids' bytes and counts, also in byte planes); the footer's length
and the magic bytes again. A plane of zeros has length 0 and no frame.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.llm.shared import Scratch, documents, filesystem, slices, write_whole

MAGIC = b"IDPLANE1"
BLOCK_IDS = 1 << 16
SLICE_BYTES = 4 << 20
CACHE_ENTRIES = 1_000_000
#: Bytes of a tokenizer file that is broadcast.
MODEL_BYTES = 64 << 20
#: Parts that go through the library in one text.
JOINED_PARTS = 64
#: White space on both sides of a space, or before one that ends the text: the tokenizer's own pass takes such texts.
ANY_SPACE = r"[\t-\r\x1c-\x20\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}]"


def to_planes(values: np.ndarray, bits: bool = False) -> list[bytes]:
    """Planes of an unsigned array, lowest first: the k-th byte, or the k-th bit, of every value."""
    data = np.ascontiguousarray(values).view(np.uint8).reshape(len(values), values.itemsize)
    planes = np.unpackbits(data, axis=1, bitorder="little").T if bits else data.T
    return [(np.packbits(p, bitorder="little") if bits else np.ascontiguousarray(p)).tobytes() if p.any() else b"" for p in planes]


def from_planes(planes: list[bytes], n: int, kind: np.dtype, bits: bool = False) -> np.ndarray:
    width = np.dtype(kind).itemsize * (8 if bits else 1)
    data = np.zeros((width, n), np.uint8)
    for k, plane in enumerate(planes):
        if plane:
            row = np.frombuffer(plane, np.uint8)
            data[k] = np.unpackbits(row, count=n, bitorder="little") if bits else row
    flat = np.packbits(np.ascontiguousarray(data.T), axis=1, bitorder="little") if bits else np.ascontiguousarray(data.T)
    return np.ascontiguousarray(flat).view(kind).reshape(n)


class PlaneWriter:
    """Takes ids in any portions and gives a file's bytes; holds one block."""

    def __init__(self, bits: bool = False, block_ids: int = BLOCK_IDS, level: int = 3):
        self.bits, self.block_ids, self.zip = bits, block_ids, zstandard.ZstdCompressor(level=level)
        self.held: list[np.ndarray] = []
        self.n_held, self.offset, self.index, self.docs, self.total = 0, len(MAGIC), [], [], 0

    def put(self, doc_id: int, ids: np.ndarray) -> None:
        self.docs.append((doc_id, len(ids)))
        self.held.append(ids)
        self.n_held += len(ids)
        self.total += len(ids)

    def blocks(self, end: bool = False) -> Iterator[bytes]:
        if self.n_held < self.block_ids and not (end and self.n_held):
            return
        flat = np.concatenate(self.held).astype("<u4")
        cut = len(flat) if end else len(flat) - len(flat) % self.block_ids
        for at in range(0, cut, self.block_ids):
            part = flat[at : min(cut, at + self.block_ids)]
            frames = [self.zip.compress(p) if p else b"" for p in to_planes(part, self.bits)]
            self.index.append((self.offset, len(part), *map(len, frames)))
            yield b"".join(frames)
            self.offset += sum(map(len, frames))
        self.held, self.n_held = [flat[cut:]], len(flat) - cut

    def footer(self) -> bytes:
        width = 32 if self.bits else 4
        index = np.array(self.index, "<u8").reshape(-1, 2 + width)
        docs = np.array(self.docs, "<i8").reshape(-1, 2)
        out = struct.pack("<IIQ", int(self.bits), len(index), len(docs))
        for column in (index.T.reshape(-1), docs.T.reshape(-1).view("<u8")):
            for plane in to_planes(column):
                frame = self.zip.compress(plane) if plane else b""
                out += struct.pack("<I", len(frame)) + frame
        return out + struct.pack("<Q", len(out)) + MAGIC


class PlaneFile:
    """Reads a file's footer, then any block by its index entry."""

    def __init__(self, source):
        self.source, self.unzip = source, zstandard.ZstdDecompressor()
        source.seek(0, 2)
        end = source.tell()
        source.seek(end - 16)
        size, magic = struct.unpack("<Q8s", source.read(16))
        if magic != MAGIC:
            raise ValueError("not a plane file")
        source.seek(end - 16 - size)
        data, at = source.read(size), 16
        bits, blocks, docs = struct.unpack("<IIQ", data[:16])
        self.bits = bool(bits)
        columns = []
        for n, rows in ((blocks, 2 + (32 if bits else 4)), (docs, 2)):
            planes = []
            for _ in range(8):
                (length,) = struct.unpack("<I", data[at : at + 4])
                planes.append(self._open(data[at + 4 : at + 4 + length]))
                at += 4 + length
            columns.append(from_planes(planes, n * rows, np.dtype("<u8")).reshape(rows, n))
        self.index, (ids, counts) = columns[0].T.astype(np.int64), columns[1]
        self.doc_ids, self.counts = ids.view("<i8"), counts.astype(np.int64)

    def _open(self, frame: bytes) -> bytes:
        return self.unzip.decompress(frame) if frame else b""

    def block(self, k: int) -> np.ndarray:
        offset, n, *lengths = self.index[k].tolist()
        self.source.seek(offset)
        data, planes, at = self.source.read(sum(lengths)), [], 0
        for length in lengths:
            planes.append(self._open(data[at : at + length]))
            at += length
        return from_planes(planes, n, np.dtype("<u4"), self.bits)

    def documents(self) -> Iterator[tuple[int, int, np.ndarray]]:
        """(id, first id's place in the file, ids) of each document; holds its blocks only."""
        block, held, first = 0, np.zeros(0, "<u4"), 0  # held starts at id number first
        start = 0
        for doc_id, n in zip(self.doc_ids.tolist(), self.counts.tolist(), strict=True):
            if first + len(held) < start + n:
                parts = [held[start - first :]]
                have = len(parts[0])
                while have < n:
                    parts.append(self.block(block))
                    have += len(parts[-1])
                    block += 1
                held, first = np.concatenate(parts), start
            yield doc_id, start, held[start - first : start - first + n]
            start += n


class ByteLevelEncoder:
    """Ids as the tokenizers library gives them, through a cache of bounded size.

    The byte-level pattern never joins a letter, digit or mark with the space after it, so a text falls apart before
    its single spaces, and each part's ids can be kept. Texts are cut and their parts numbered as Arrow columns; the
    distinct parts of a slice alone are looked up, and those that are not in the cache go through the library, many in
    one call. Texts with a special token, a zero or tangled white space go through it whole.
    """

    def __init__(self, spec: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(spec)
        special = [re.escape(x.content) for x in self.tokenizer.get_added_tokens_decoder().values()]
        self.whole = "|".join([*special, r"\x00", f"{ANY_SPACE} (?:{ANY_SPACE}|$)", r"^ $"])
        # as many bytes as letters: each letter of a byte-level token stands for one byte
        self.lengths = np.zeros(self.tokenizer.get_vocab_size(), np.int64)
        for name, k in self.tokenizer.get_vocab().items():
            self.lengths[k] = len(name)
        self.cache: dict[str, bytes] = {"": b""}

    def library(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(x.ids, "<u4") for x in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def learn(self, parts: list[str]) -> None:
        """Takes parts into the cache. Parts that begin with a space and a letter can follow one another in one text."""
        if len(self.cache) + len(parts) > CACHE_ENTRIES:
            self.cache = {"": b""}
        joined: list[str] = []
        alone: list[str] = []
        for x in parts:
            (joined if x[0] == " " and x[1:2].isalpha() else alone).append(x)
        for at in range(0, len(joined), JOINED_PARTS):
            some = joined[at : at + JOINED_PARTS]
            text = "".join(some)
            ids = self.library([text])[0]
            sizes = list(map(len, some)) if text.isascii() else [len(x.encode()) for x in some]
            cuts = (4 * (np.searchsorted(np.cumsum(self.lengths[ids]), np.cumsum(sizes)) + 1)).tolist()
            data = ids.tobytes()
            self.cache.update(zip(some, [data[a:b] for a, b in zip([0, *cuts[:-1]], cuts, strict=True)], strict=True))
        self.cache.update(zip(alone, [x.tobytes() for x in self.library(alone)], strict=True))

    def parted(self, texts: pa.Array) -> list[np.ndarray]:
        """Ids of texts that may be cut before their spaces."""
        cut = pc.split_pattern(pc.replace_substring(texts, " ", "\0 "), "\0")
        parts = cut.flatten().dictionary_encode()
        names, which = parts.dictionary.to_pylist(), parts.indices.to_numpy()
        found = list(map(self.cache.get, names))
        if missing := [x for x, y in zip(names, found, strict=True) if y is None]:
            self.learn(missing)
            get = self.cache.get
            found = [get(x) if y is None else y for x, y in zip(names, found, strict=True)]
        each = np.fromiter(map(len, found), np.int64, len(found)) // 4
        flat = np.frombuffer(b"".join(found), "<u4")
        sizes, first = each[which], (np.cumsum(each) - each)[which]
        ends = np.cumsum(sizes)
        ids = flat[np.arange(ends[-1] if len(ends) else 0) + np.repeat(first - ends + sizes, sizes)]
        rows = np.concatenate(([0], ends))[np.asarray(cut.offsets) - cut.offsets[0].as_py()]
        return np.split(ids, rows[1:-1])

    def encode(self, texts: list[str] | pa.Array) -> list[np.ndarray]:
        texts = texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string())
        if not len(texts):
            return []
        # blanks that end a text would be parted from what they belong to
        whole = pc.or_(pc.match_substring_regex(texts, self.whole), pc.ends_with(texts, " "))
        some = np.flatnonzero(whole.to_numpy(zero_copy_only=False))
        if not len(some):
            return self.parted(texts)
        at = np.flatnonzero(~whole.to_numpy(zero_copy_only=False))
        out: list[np.ndarray] = [np.zeros(0, "<u4")] * len(texts)
        for k, ids in zip(some.tolist(), self.library(texts.take(pa.array(some)).to_pylist()), strict=True):
            out[k] = ids
        if len(at):
            for k, ids in zip(at.tolist(), self.parted(texts.take(pa.array(at))), strict=True):
                out[k] = ids
        return out


_ENCODERS: dict[str, ByteLevelEncoder] = {}


def encoder_of(spec: str) -> ByteLevelEncoder:
    """One encoder for each tokenizer file and process."""
    if spec not in _ENCODERS:
        _ENCODERS[spec] = ByteLevelEncoder(spec)
    return _ENCODERS[spec]


def write_planes(docs: DataFrame, folder: str, spec: str, id_col: str = "doc_id", text: str = "text", end_id: int = 2, bits: bool = False) -> DataFrame:
    """Writes the documents' ids in ascending id order, a file for each range of ids, and gives the manifest: shard,
    file, n_docs, n_tokens. A null text is empty and gives the end id alone; a null id sorts first and reads back as the
    smallest 64-bit integer; rows that repeat an id follow one another by their texts' hashes. An empty table has no
    files. A retried task writes its file anew under the same name."""
    held = docs.sparkSession.sparkContext.broadcast(spec)
    ordered = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text).alias("text")).repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        writer, shard = PlaneWriter(bits), TaskContext.get().partitionId()
        encoder = encoder_of(held.value)
        fs, root = filesystem(folder)
        name = f"ids-{shard:06d}.planes"

        def content() -> Iterator[bytes]:
            yield MAGIC
            for batch in slices(batches, "text", SLICE_BYTES):
                texts = batch.column("text").cast(pa.string()).fill_null("")
                ids = batch.column("doc_id").fill_null(-(1 << 63)).to_pylist()
                for doc_id, found in zip(ids, encoder.encode(texts), strict=True):
                    writer.put(doc_id, np.append(found, np.uint32(end_id)))
                yield from writer.blocks()
            yield from writer.blocks(True)
            yield writer.footer()

        write_whole(fs, f"{root}/{name}", content())
        if writer.docs:
            yield pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int64()), "file": [name], "n_docs": pa.array([len(writer.docs)], pa.int64()), "n_tokens": pa.array([writer.total], pa.int64())})

    return ordered.mapInArrow(run, "shard long, file string, n_docs long, n_tokens long")


def read_planes(manifest: DataFrame, folder: str) -> DataFrame:
    """For each document of the manifest's files: doc_id, start over all files, n_tokens, ids_crc32. Files are read
    apart; only the manifest, a row for each file, is summed in one place."""
    from pyspark.sql import Window

    before = F.coalesce(F.sum("n_tokens").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    files = manifest.select("file", before.alias("before"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = filesystem(folder)
        for batch in batches:
            for row in batch.to_pylist():
                with fs.open_input_file(f"{root}/{row['file']}") as source:
                    rows = ((d, row["before"] + s, len(x), zlib.crc32(x.tobytes())) for d, s, x in PlaneFile(source).documents())
                    while some := list(islice(rows, 10_000)):
                        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*some, strict=True)], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return files.repartitionByRange(max(1, manifest.count()), "file").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op4_token_planes(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    with open(public_tokenizers.path("byte_bpe_50k.json"), encoding="utf-8") as f:
        spec = f.read(MODEL_BYTES + 1)
    if len(spec) > MODEL_BYTES:
        raise ValueError("the tokenizer file is too large to broadcast")
    scratch = Scratch(spark, "planes")
    manifest = scratch.table("manifest", write_planes(documents(spark, sf_dir), scratch.path("files"), spec))
    return read_planes(manifest, scratch.path("files"))
