"""Substring dedup by sliding spans of sentences."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.llm.shared import Scratch, byte_texts, documents, slices, unused

SLICE_BYTES = 4 << 20
NO_ID = -(1 << 63)  # stands for a null doc_id, which comes first
#: Words that a span holds at least.
SPAN_WORDS = 24
#: A sentence ends with its closing marks and the blanks after them, or with a line.
SENTENCE = re.compile(rb"[.!?]+[\t-\r ]+|\n[\t-\r ]*")
ADDED = ("n_sentences", "n_removed", "kept_text")


def sentences(text: bytes) -> list[bytes]:
    """The text in parts that join to the whole; an empty text has one."""
    ends = [m.end() for m in SENTENCE.finditer(text)]
    cuts = [0, *ends, len(text)]
    return [text[a:b] for a, b in zip(cuts, cuts[1:], strict=False)] if ends else [text]


def spans_of(parts: list[bytes], least_words: int) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
    """(first sentence, number of sentences, key) of every run that is looked for: from each sentence with words, and up
    to each, the shortest one of two such sentences at least that holds least_words words; the whole text if there is
    none. A key is the run's words, A-Z lowered, with single spaces."""
    words = [x.lower().split() for x in parts]
    place = np.flatnonzero([len(x) > 0 for x in words])
    if not len(place):
        return place, place, []
    joined = [b" ".join(words[k]) for k in place.tolist()]
    ends = np.cumsum([len(words[k]) for k in place.tolist()])
    before = np.concatenate(([0], ends[:-1]))
    n = np.arange(len(place))
    last = np.maximum(np.searchsorted(ends, before + least_words), n + 1)
    head = np.minimum(np.searchsorted(before, ends - least_words, "right") - 1, n - 1)
    forth, back = last < len(place), head >= 0
    runs = np.unique(np.concatenate((np.stack((n[forth], last[forth]), axis=1), np.stack((head[back], n[back]), axis=1))), axis=0)
    if not len(runs):
        runs = np.array([[0, len(place) - 1]])
    keys = [b" ".join(joined[a : b + 1]) for a, b in runs.tolist()]
    first = place[runs[:, 0]]
    return first, place[runs[:, 1]] - first + 1, keys


def drop_repeated_spans(docs: DataFrame, id_col: str = "doc_id", text: str = "text", least_words: int = SPAN_WORDS) -> DataFrame:
    """docs with n_sentences, n_removed and kept_text.

    Every sentence begins a run and ends one: the shortest of two sentences at least that holds least_words words; a
    text without such runs is one itself. All are hashed; of equal runs the first stays, by id and place, and the
    sentences under any other go. Null and empty texts are one empty sentence and have no run. A null id comes first. Rows that repeat an id share its places: their runs are taken
    together, and a first place stands for each of them. Columns with the added names are replaced. Runs meet by
    128-bit hash, counted before the shuffle; the table of repeated ones is written, so that Spark can split the join
    for a passage that very many documents share.
    """
    scratch = Scratch(docs.sparkSession, "spans")
    docs = docs.drop(*ADDED)
    source = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc"), F.col(text).alias("text"))

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", SLICE_BYTES):
            owner, starts, sizes, digests = [], [], [], []
            for k, x in enumerate(byte_texts(batch.column("text"))):
                first, size, keys = spans_of(sentences(x), least_words)
                owner.append(np.full(len(first), k))
                starts.append(first)
                sizes.append(size)
                digests += map(xxhash.xxh3_128_digest, keys)
            both = np.frombuffer(b"".join(digests), ">i8").reshape(-1, 2).astype(np.int64)
            doc = batch.column("doc").to_numpy()[np.concatenate(owner)]
            yield pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1]), pa.array(doc), pa.array(np.concatenate(starts).astype(np.int32)), pa.array(np.concatenate(sizes).astype(np.int32))], ["h1", "h2", "doc", "first", "size"])

    runs = source.mapInArrow(emit, "h1 long, h2 long, doc long, first int, size int")
    counted = runs.groupBy("h1", "h2").agg(F.min(F.struct("doc", "first")).alias("place"), F.count("*").alias("n"))
    repeated = scratch.table("repeated", counted.where("n > 1").select("h1", "h2", "place"))
    later = runs.join(repeated, ["h1", "h2"]).where(F.struct("doc", "first") != F.col("place"))
    of, found_runs = unused("_doc", docs), unused("_runs", docs)
    per_doc = scratch.table("later", later.groupBy("doc").agg(F.collect_set(F.struct("first", "size")).alias(found_runs)).withColumnRenamed("doc", of))
    scratch.drop("repeated")
    joined = docs.join(per_doc, F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)) == F.col(of), "left").drop(of)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text, SLICE_BYTES):
            total, removed, kept = [], [], []
            for x, found in zip(byte_texts(batch.column(text)), batch.column(found_runs).to_pylist(), strict=True):
                parts = sentences(x)
                gone = {k for r in found or () for k in range(r["first"], r["first"] + r["size"])}
                total.append(len(parts))
                removed.append(sum(k < len(parts) for k in gone))
                kept.append(b"".join([y for k, y in enumerate(parts) if k not in gone]) if gone else x)
            names = [c for c in batch.schema.names if c != found_runs]
            arrays = [batch.column(batch.schema.names.index(c)) for c in names]
            yield pa.RecordBatch.from_arrays([*arrays, pa.array(total, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())], [*names, *ADDED])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return joined.mapInArrow(cut, f"{fields}, n_sentences long, n_removed long, kept_text string")


def op1_sentence_spans(spark, sf_dir: str) -> DataFrame:
    kept = drop_repeated_spans(documents(spark, sf_dir).select("doc_id", "text"))
    return kept.select("doc_id", "n_sentences", "n_removed", F.col("kept_text").alias("text"))


OP1_SQL = r"""
WITH s AS (
  SELECT doc_id, unnest(range(1, len(ps) + 1)) AS k, unnest(ps) AS part
  FROM (SELECT doc_id, string_split(regexp_replace(coalesce(text, ''), '([.!?]+[\x09-\x0D ]+|\n[\x09-\x0D ]*)', '\1' || chr(1), 'g'), chr(1)) AS ps FROM documents)),
w AS (
  SELECT *, list_filter(regexp_split_to_array(translate(part, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x09-\x0D ]+'), lambda x: x <> '') AS ws FROM s),
c AS (SELECT doc_id, k, part, array_to_string(ws, ' ') AS words, len(ws) AS n FROM w),
v AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY k) AS r, sum(n) OVER (PARTITION BY doc_id ORDER BY k) AS upto, count(*) OVER (PARTITION BY doc_id) AS m FROM c WHERE n > 0),
ends AS (
  SELECT a.doc_id, a.r, greatest(min(b.r), a.r + 1) AS last FROM v a JOIN v b ON a.doc_id = b.doc_id AND b.r >= a.r AND b.upto - (a.upto - a.n) >= 24
  GROUP BY a.doc_id, a.r, a.m HAVING greatest(min(b.r), a.r + 1) <= a.m
  UNION SELECT b.doc_id, least(max(a.r), b.r - 1), b.r FROM v a JOIN v b ON a.doc_id = b.doc_id AND a.r <= b.r AND b.upto - (a.upto - a.n) >= 24
  GROUP BY b.doc_id, b.r HAVING least(max(a.r), b.r - 1) >= 1),
every AS (SELECT * FROM ends UNION ALL SELECT DISTINCT doc_id, 1, m FROM v WHERE doc_id NOT IN (SELECT doc_id FROM ends)),
runs AS (
  SELECT e.doc_id, min(v.k) AS k, max(v.k) AS last, string_agg(v.words, ' ' ORDER BY v.r) AS key
  FROM every e JOIN v ON v.doc_id = e.doc_id AND v.r BETWEEN e.r AND e.last GROUP BY e.doc_id, e.r, e.last),
later AS (
  SELECT doc_id, unnest(range(k, last + 1)) AS k
  FROM (SELECT *, row_number() OVER (PARTITION BY key ORDER BY doc_id, k) AS nth FROM runs) WHERE nth > 1),
gone AS (SELECT DISTINCT doc_id, k FROM later)
SELECT c.doc_id, count(*) AS n_sentences, count(g.k) AS n_removed, coalesce(string_agg(c.part, '' ORDER BY c.k) FILTER (g.k IS NULL), '') AS text
FROM c LEFT JOIN gone g ON g.doc_id = c.doc_id AND g.k = c.k GROUP BY c.doc_id
"""
