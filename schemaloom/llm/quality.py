"""Quality classifier: similarity-weighted votes of the nearest labelled latent-semantic vectors."""

from __future__ import annotations

from collections.abc import Iterator
from operator import eq
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.llm.shared import byte_texts, documents, slices

SLICE_BYTES = 4 << 20
#: Most labelled documents that a model keeps: those whose ids have the smallest hashes.
SAMPLE = 6000
FOLDS, HELD = 5, 0
ACCEPT = 0.3
WINDOW = 50
#: Classes of a byte: letters, digits, blanks, parts of non-ASCII characters, and marks that set kinds of text apart.
CLASSES = np.full(256, 14, np.int64)
for _code, _bytes in enumerate((b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b" ", b"\r\n", bytes(range(128, 256)), b".?", b",", b"!", b"|", b"$%&*#", b":;", b"-'\""), 1):
    CLASSES[list(_bytes)] = _code
TRIGRAMS = 16**3
SHAPES = TRIGRAMS + 3
#: Places that lower-cased words are hashed to, and how long their part of a vector is beside that of the shapes.
WORDS = 1024
WORD_SHARE = 0.5
TERMS = SHAPES + WORDS
#: The three repetition terms count as much as so many trigrams each.
REPETITION_WEIGHT = 5


def term_rates(text: bytes) -> np.ndarray:
    """A whole text's terms per thousand: trigrams of byte classes, words like the one before, words met within the
    last WINDOW, lines met before; and its lower-cased words, by hash."""
    out = np.zeros(TERMS)
    if not text:
        return out
    a = CLASSES[np.frombuffer(text, np.uint8)]
    if len(a) > 2:
        out[:TRIGRAMS] = np.bincount(a[:-2] * 256 + a[1:-1] * 16 + a[2:], minlength=TRIGRAMS) * (1000 / len(a))
    words = text.split()
    if words:
        out[TRIGRAMS] = 1000 * sum(map(eq, words, words[1:])) / len(words)
        parts = [words[k : k + WINDOW] for k in range(0, len(words), WINDOW)]
        out[TRIGRAMS + 1] = 1000 * (1 - sum(len(set(x)) / len(x) for x in parts) / len(parts))
        places = np.fromiter(map(crc32, text.lower().split()), np.int64, len(words)) % WORDS
        out[SHAPES:] = np.bincount(places, minlength=WORDS) * (1000 / len(words))
    lines = text.split(b"\n")
    out[TRIGRAMS + 2] = 1000 * (1 - len(set(lines)) / len(lines))
    return out


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(1e-12, np.linalg.norm(x, axis=1, keepdims=True))


def balanced(x: np.ndarray, shapes: int) -> np.ndarray:
    """x made into unit vectors, in place, in which the terms from `shapes` on, the words, have a fixed share."""
    length = lambda y: np.maximum(1e-12, np.linalg.norm(y, axis=1, keepdims=True)).astype(x.dtype)
    x[:, :shapes] /= length(x[:, :shapes])
    x[:, shapes:] /= length(x[:, shapes:]) / x.dtype.type(WORD_SHARE)
    x /= length(x)
    return x


class Model:
    """Latent axes of a labelled sample, its vectors on them, and its labels."""

    def __init__(self, rates: np.ndarray, labels: np.ndarray, axes: int = 24, neighbours: int = 5, power: float = 4.0, seed: int = 7):
        self.neighbours, self.power, self.labels = neighbours, power, labels.astype(float)
        self.prior = float(labels.mean()) if len(labels) else 0.5
        seen = (rates > 0).sum(axis=0) if len(rates) else np.zeros(TERMS)
        self.weights = np.where(seen >= 3, np.log((1 + len(rates)) / (1 + seen)) + 0.2, 0.0)
        self.weights[TRIGRAMS:SHAPES] *= REPETITION_WEIGHT**0.5
        # float32, and the terms that count alone: the sample's matrix is the driver's largest object
        some = np.flatnonzero(self.weights)
        x = np.log1p(rates[:, some].astype(np.float32, copy=False))
        x *= self.weights[some].astype(np.float32)
        x = balanced(x, int(np.searchsorted(some, SHAPES)))
        basis = np.random.default_rng(seed).standard_normal((TERMS, axes + 8))[some].astype(np.float32)
        self.axes = np.zeros((TERMS, axes))
        if len(some) and len(x):
            for _ in range(6):  # subspace iteration to the leading right singular vectors
                basis = np.linalg.qr(x.T @ (x @ basis))[0]
            turn = np.linalg.svd(x @ basis, full_matrices=False)[2][:axes]
            found = basis @ turn.T
            self.axes[some, : found.shape[1]] = found
        self.vectors = unit(np.asarray(x @ self.axes[some].astype(np.float32), float))

    def weighted(self, rates: np.ndarray) -> np.ndarray:
        return balanced(np.log1p(rates) * self.weights, SHAPES)

    def scores(self, rates: np.ndarray, block: int = 256) -> np.ndarray:
        """Exact cosines with every labelled vector, a block of documents at a time; the nearest ones' labels, weighted
        by a power of the cosine. Of equally near ones the first in the sample, by id. The prior where no cosine is above zero."""
        out = np.full(len(rates), self.prior)
        n = min(self.neighbours, len(self.labels))
        later = 1e-12 * np.arange(len(self.labels))
        if not n:
            return out
        for at in range(0, len(rates), block):
            cosine = unit(self.weighted(rates[at : at + block]) @ self.axes) @ self.vectors.T - later
            near = np.argpartition(-cosine, n - 1, axis=1)[:, :n]
            weight = np.maximum(0, np.take_along_axis(cosine, near, 1)) ** self.power
            total = weight.sum(axis=1)
            some = total > 1e-12
            out[at : at + block][some] = (weight * self.labels[near]).sum(axis=1)[some] / total[some]
        return np.clip(out, 0, 1)


def held_out(id_col) -> "F.Column":
    """Whether a row belongs to the fold that nothing is learnt from; a null id doesn't."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(FOLDS)) == HELD, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "quality", sample: int = SAMPLE) -> Model:
    """A model of at most `sample` labelled documents outside the held-out fold. Of an id's repeated labels the largest
    counts; null ids and labels are left out. What reaches the driver is the sample's terms."""
    known = labels.where(F.col(id_col).isNotNull() & F.col(label).isNotNull() & ~held_out(id_col))
    known = known.groupBy(F.col(id_col).alias("_id")).agg(F.max(label).cast("double").alias("_label"))
    chosen = known.orderBy(F.xxhash64("_id"), "_id").limit(sample)
    texts = docs.select(F.col(id_col).alias("_id"), F.col(text).alias("_text")).join(F.broadcast(chosen), "_id")

    def terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "_text", SLICE_BYTES):
            found = [term_rates(x) for x in byte_texts(batch.column("_text"))]
            at = [np.flatnonzero(x) for x in found]
            yield pa.RecordBatch.from_arrays([batch.column("_id").cast(pa.int64()), batch.column("_label"), pa.array([k.astype(np.int16) for k in at], pa.list_(pa.int16())), pa.array([x[k].astype(np.float32) for x, k in zip(found, at, strict=True)], pa.list_(pa.float32()))], ["id", "label", "at", "rate"])

    # of texts that share an id the one with the smallest hash, so that no more than the sample is collected
    once = texts.groupBy("_id", "_label").agg(F.min_by("_text", F.xxhash64("_text")).alias("_text"))
    rows = once.select(F.col("_id").cast("long").alias("_id"), "_label", "_text").mapInArrow(terms, "id long, label double, at array<short>, rate array<float>").toArrow()
    order = np.argsort(rows.column("id").to_numpy(), kind="stable")
    at, rate = (rows.column(c).combine_chunks() for c in ("at", "rate"))
    ends = np.cumsum([0, *(len(x) for x in at)]) if len(at) else np.zeros(1, np.int64)
    values, places = rate.flatten().to_numpy(), at.flatten().to_numpy()
    rates = np.zeros((len(order), TERMS), np.float32)
    for row, k in enumerate(order.tolist()):
        rates[row, places[ends[k] : ends[k + 1]]] = values[ends[k] : ends[k + 1]]
    return Model(rates, rows.column("label").to_numpy()[order])


def score(docs: DataFrame, model: Model, text: str = "text", accept: float = ACCEPT) -> DataFrame:
    """docs with score (0 to 1) and predicted. Whole texts alone decide; a null or empty text gets the prior. Columns
    of these names are replaced."""
    docs = docs.drop("score", "predicted")
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text, SLICE_BYTES):
            texts = byte_texts(batch.column(text))
            found = np.concatenate([held.value.scores(np.array([term_rates(x) for x in texts[k : k + 256]])) for k in range(0, len(texts), 256)])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found), pa.array((found >= accept).astype(np.int32))], [*batch.schema.names, "score", "predicted"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return docs.mapInArrow(run, f"{fields}, score double, predicted int")


def op2_neighbour_quality(spark, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score(docs.select("doc_id", "text"), model).select("doc_id", held_out("doc_id").alias("held_out"), "score", "predicted")
