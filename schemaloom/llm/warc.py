"""WARC archives: writing with revisit records, a normaliser of monolithic gzip files, reading through its index."""

from __future__ import annotations

import base64
import hashlib
import json
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.llm.shared import Scratch, byte_texts, filesystem, slices, write_whole

CHUNK = 1 << 20
FILE_BYTES = 256 << 20
NO_ID = -(1 << 63)  # stands for a null page_id, which is the smallest
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
CONTROL = re.compile(r"[\x00-\x20\x7f]")


def digest_of(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_name(page_id: int) -> str:
    return f"<urn:page:{page_id}>"


def head(fields: list[tuple[str, str]], length: int) -> bytes:
    lines = ["WARC/1.1", *(f"{k}: {v}" for k, v in fields), f"Content-Length: {length}"]
    return ("\r\n".join(lines) + "\r\n\r\n").encode()


def page_record(page_id: int, url: str | None, payload: bytes, refers_to: int | None, refers_url: str | None, date: str) -> bytes:
    """A response with its payload, or a revisit that keeps the HTTP header alone."""
    uri = CONTROL.sub(lambda m: f"%{ord(m[0]):02X}", url or "about:blank")
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    fields = [("WARC-Type", "response" if refers_to is None else "revisit"), ("WARC-Record-ID", record_name(page_id)), ("WARC-Date", date), ("WARC-Target-URI", uri), ("WARC-Payload-Digest", f"sha1:{digest_of(payload)}"), ("Content-Type", "application/http; msgtype=response")]
    if refers_to is not None:
        fields += [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_name(refers_to)), ("WARC-Refers-To-Target-URI", CONTROL.sub(lambda m: f"%{ord(m[0]):02X}", refers_url or "about:blank"))]
    block = http + (payload if refers_to is None else b"")
    return head(fields, len(block)) + block + b"\r\n\r\n"


def info_record(name: str, date: str) -> bytes:
    block = b"format: WARC File Format 1.1\r\n"
    return head([("WARC-Type", "warcinfo"), ("WARC-Record-ID", f"<urn:file:{name}>"), ("WARC-Date", date), ("WARC-Filename", name), ("Content-Type", "application/warc-fields")], len(block)) + block + b"\r\n\r\n"


def fields_of(header: bytes) -> dict[str, str]:
    first, *lines = header.decode("utf-8", "replace").split("\r\n")
    if not first.startswith("WARC/"):
        raise ValueError(f"no WARC record: {first[:40]!r}")
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines if x)}


def inflated(source, wbits: int = 31) -> Iterator[bytes]:
    """A gzip file's content in bounded chunks; members may follow one another."""
    inflate = zlib.decompressobj(wbits)
    while data := source.read(CHUNK):
        while data:
            yield inflate.decompress(data, CHUNK)
            data = inflate.unconsumed_tail
            if inflate.eof:
                data, inflate = inflate.unused_data, zlib.decompressobj(wbits)
    tail = inflate.flush()
    if tail:
        yield tail


def stream_records(chunks: Iterator[bytes]) -> Iterator[tuple[bytes, Iterator[bytes]]]:
    """(header, block in chunks) of each record; the block must be read before the next record."""
    held = bytearray()

    def fill() -> bool:
        for x in chunks:
            if x:
                held.extend(x)
                return True
        return False

    while True:
        while held[:2] == b"\r\n":
            del held[:2]
        if not held and not fill():
            return
        while (end := held.find(b"\r\n\r\n")) < 0:
            if not fill():
                if held.strip():
                    raise ValueError("the archive ends inside a header")
                return
        header = bytes(held[: end + 4])
        if not header.strip():
            del held[: end + 4]
            continue
        del held[: end + 4]
        left = int(fields_of(header)["content-length"])

        def block() -> Iterator[bytes]:
            nonlocal left
            while left:
                if not held and not fill():
                    raise ValueError("the archive ends inside a block")
                part = bytes(held[:left])
                del held[: len(part)]
                left -= len(part)
                yield part

        yield header, (reader := block())
        for _ in reader:
            pass
        while len(held) < 4 and fill():
            pass
        if held[:4] != b"\r\n\r\n":
            raise ValueError("a record isn't closed")
        del held[:4]


def normalised(chunks: Iterator[bytes], index: list[dict]) -> Iterator[bytes]:
    """The same records, each as a gzip member of its own; index gets a line for each."""
    offset = 0
    for header, block in stream_records(chunks):
        fields, deflate, size = fields_of(header), zlib.compressobj(6, zlib.DEFLATED, 31), 0
        for part in (header,):
            size += len(out := deflate.compress(part))
            yield out
        for part in block:
            size += len(out := deflate.compress(part))
            yield out
        out = deflate.compress(b"\r\n\r\n") + deflate.flush()
        yield out
        size += len(out)
        index.append({"offset": offset, "length": size, "type": fields["warc-type"], "id": fields["warc-record-id"], "uri": fields.get("warc-target-uri"), "digest": fields.get("warc-payload-digest")})
        offset += size


def with_revisits(pages: DataFrame, scratch: Scratch, least_bytes: int = 0) -> DataFrame:
    """page_id, url, html and, for revisits, the response's page_id and url. Equal payloads are found by SHA-1; the
    table of responses is written, so that its join with the pages can split a payload that a third of them share."""
    pages = pages.select(F.coalesce(F.col("page_id").cast("long"), F.lit(NO_ID)).alias("page_id"), "url", F.coalesce("html", F.lit("")).alias("html")).withColumn("sha1", F.sha1(F.encode("html", "UTF-8")))
    last = pages.groupBy("sha1").agg(F.max(F.struct("page_id", "url")).alias("last"), F.count("*").alias("n"), F.max(F.octet_length("html")).alias("size"))
    shared = scratch.table("responses", last.where((F.col("n") > 1) & (F.col("size") >= least_bytes)).select("sha1", F.col("last.page_id").alias("to"), F.col("last.url").alias("to_url")))
    joined = pages.join(shared, "sha1", "left")
    revisit = F.col("to") != F.col("page_id")
    return joined.select("page_id", "url", "html", F.when(revisit, F.col("to")).alias("refers_to"), F.when(revisit, F.col("to_url")).alias("refers_url"))


def write_archives(pages: DataFrame, folder: str, date: str = "1970-01-01T00:00:00Z", file_bytes: int = FILE_BYTES) -> DataFrame:
    """Writes with_revisits' rows as monolithic gzip files, each one stream; gives a row for each file."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = filesystem(folder)
        rows = ((batch.column("page_id").to_pylist(), batch.column("url").to_pylist(), byte_texts(batch.column("html")), batch.column("refers_to").to_pylist(), batch.column("refers_url").to_pylist()) for batch in slices(batches, "html", 8 << 20))
        records = (page_record(*row, date) for columns in rows for row in zip(*columns, strict=True))
        part, names, ended = TaskContext.get().partitionId(), [], False

        def stream(name: str, first: bytes) -> Iterator[bytes]:
            nonlocal ended
            deflate, size, record = zlib.compressobj(6, zlib.DEFLATED, 31), 0, info_record(name, date) + first
            while True:
                yield deflate.compress(record)
                size += len(record)
                if size >= file_bytes or (record := next(records, None)) is None:
                    ended = size < file_bytes
                    yield deflate.flush()
                    return

        while not ended and (first := next(records, None)) is not None:
            names.append(f"part-{part:06d}-{len(names):04d}.warc.gz")
            write_whole(fs, f"{root}/{names[-1]}", stream(names[-1], first))
        if names:
            yield pa.RecordBatch.from_pydict({"file": names})

    return pages.mapInArrow(run, "file string")


def dealt(files: DataFrame) -> DataFrame:
    """About a file for each task: ranged, so that no two names need share one, and with a stated number, which adaptive
    plans leave alone. files is a written table with a row for each file."""
    return files.repartitionByRange(max(1, files.count()), "file")


def normalise_archives(files: DataFrame, folder: str, to: str) -> DataFrame:
    """Each monolithic file, inflated once: records as members of their own in `to`, with a sidecar index in JSON
    lines. A retried task writes both anew. Gives a row for each file: file, records."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = filesystem(folder)
        out = filesystem(to)[1]
        for batch in batches:
            for name in batch.column("file").to_pylist():
                index: list[dict] = []
                with fs.open_input_stream(f"{root}/{name}", compression=None) as source:
                    write_whole(fs, f"{out}/{name}", normalised(inflated(source), index))
                write_whole(fs, f"{out}/{name}.index.jsonl", (json.dumps(x).encode() + b"\n" for x in index))
                yield pa.RecordBatch.from_pydict({"file": [name], "records": pa.array([len(index)], pa.int64())})

    return dealt(files).mapInArrow(run, "file string, records long")


def parsed(member: bytes) -> dict:
    """A page record's contents, checked against its own digest where the payload is there."""
    text = zlib.decompress(member, 31)
    header, _, block = text.partition(b"\r\n\r\n")
    fields = fields_of(header)
    block = block[: int(fields["content-length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    size = int(next(x.split(b":")[1] for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:")))
    digest, kind = fields["warc-payload-digest"].removeprefix("sha1:"), fields["warc-type"]
    if kind == "response" and (digest_of(payload) != digest or len(payload) != size):
        raise ValueError(f"{fields['warc-record-id']} doesn't match its digest")
    number = lambda name: int(name[len("<urn:page:") : -1])
    return {"page_id": number(fields["warc-record-id"]), "url": fields["warc-target-uri"], "payload": payload if kind == "response" else None, "payload_bytes": size, "payload_digest": digest, "record_type": kind, "refers_to": number(fields["warc-refers-to"]) if "warc-refers-to" in fields else None}


READ = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload", pa.binary()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())])


def read_archives(files: DataFrame, folder: str, payloads: bool = True) -> DataFrame:
    """The page records of normalised files, each member found by its index entry."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = filesystem(folder)
        for batch in batches:
            for name in batch.column("file").to_pylist():
                with fs.open_input_stream(f"{root}/{name}.index.jsonl", compression=None) as source:
                    index = [json.loads(x) for x in source.read().splitlines()]
                rows, held = [], 0
                with fs.open_input_file(f"{root}/{name}") as source:
                    for entry in index:
                        if entry["type"] == "warcinfo":
                            continue
                        source.seek(entry["offset"])
                        rows.append(parsed(source.read(entry["length"])))
                        held += rows[-1]["payload_bytes"]
                        if not payloads:
                            rows[-1]["payload"] = None
                        if held > 8 << 20 or len(rows) == 10_000:
                            yield pa.RecordBatch.from_pylist(rows, READ)
                            rows, held = [], 0
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, READ)

    kinds = "page_id long, url string, payload binary, payload_bytes long, payload_digest string, record_type string, refers_to long"
    return files.select("file").mapInArrow(run, kinds)


def archived(pages: DataFrame, least_bytes: int = 0, payloads: bool = True) -> DataFrame:
    """Writes pages as WARC, normalises the files and reads them back.

    A null html is an empty payload, a null url about:blank, a null page_id the smallest 64-bit integer. Rows that tie
    for the largest page_id of a payload are all responses. An empty table gives no files and no rows. Other columns are
    left out.
    """
    scratch = Scratch(pages.sparkSession, "warc")
    written = scratch.table("written", write_archives(with_revisits(pages, scratch, least_bytes), scratch.path("monolithic")))
    normal = scratch.table("normal", normalise_archives(written, scratch.path("monolithic"), scratch.path("members")))
    scratch.drop("monolithic")
    return read_archives(dealt(normal), scratch.path("members"), payloads)


def op3_warc_normaliser(spark, sf_dir: str) -> DataFrame:
    back = archived(spark.read.parquet(f"{sf_dir}/pages.parquet"), payloads=False)
    return back.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP3_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h, sha1(coalesce(html, '')) AS x FROM pages),
m AS (SELECT h, max(page_id) AS last FROM p GROUP BY h)
SELECT page_id, strlen(p.h)::BIGINT AS payload_bytes,
  array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((CAST('0x' || substr(x, CAST(5 * (i // 4) + 1 AS BIGINT), 5) AS INTEGER) >> CAST(15 - 5 * (i % 4) AS INTEGER)) & 31), 1)), '') AS payload_digest,
  CASE WHEN last = page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN last <> page_id THEN last END AS refers_to
FROM p JOIN m USING (h)
"""
