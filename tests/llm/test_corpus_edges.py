"""Nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns, for each operator and stage."""

import hashlib

import corpus_pipeline
import pytest
from schemaloom.llm import bpe, fmindex, lines, planes, quality, simhash, sketch, spans, suffixes, warc
from schemaloom.llm.shared import Scratch

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
LONG = "word " * 30_000
ROWS = [
    (1, "A plain text of a few words.", "en", "s", 28),
    (2, None, None, None, None),
    (3, "", "en", "s", 0),
    (4, LONG, "en", "s", len(LONG)),
    (5, "é ß 日本 " * 40, "x", "s", 1),
    (5, "é ß 日本 " * 40, "x", "s", 1),
    (None, "A plain text of a few words.", "en", "s", 28),
    (7, "\n\n \t \n", "en", "s", 1),
    (8, "A plain text of a few words.\nA plain text of a few words.", "en", "s", 1),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("tables"))
    spark.createDataFrame([(1, 1, 0), (4, 0, 0), (None, 1, 0), (8, None, 0), (1, 0, 0), (3, 1, 1)], "doc_id long, quality int, toxic int").write.mode("overwrite").parquet(f"{path}/labels.parquet")
    spark.createDataFrame([(1, "a plain text of a few words"), (2, None), (3, ""), (1, "x y")], "item_id long, text string").write.mode("overwrite").parquet(f"{path}/benchmark.parquet")
    return path


def clashing(df, *names):
    from pyspark.sql import functions as F

    return df.select("*", *(F.lit("clash").alias(n) for n in names))


def apply(name, docs, spark, folder):
    import public_tokenizers

    if name == "spans":
        return spans.drop_repeated_spans(clashing(docs, "n_removed", "h1", "doc", "place", "_x"))
    if name == "quality":
        model = quality.fit(docs, spark.read.parquet(f"{folder}/labels.parquet"))
        return quality.score(clashing(docs, "score", "label"), model)
    if name == "planes":
        scratch = Scratch(spark, "t")
        with open(public_tokenizers.path("byte_bpe_50k.json")) as f:
            spec = f.read()
        manifest = scratch.table("m", planes.write_planes(clashing(docs, "file", "shard"), scratch.path("f"), spec))
        return planes.read_planes(manifest, scratch.path("f"))
    if name == "suffixes":
        return suffixes.cut_repeats(clashing(docs, "first", "doc", "g"))
    if name == "simhash":
        return simhash.near_groups(clashing(docs, "fp", "node", "component"))
    if name == "bpe":
        return bpe.encode_words(clashing(docs, "n_tokens"), public_tokenizers.path("word_bpe_49k.json"), with_ids=True)
    if name == "lines":
        return lines.drop_repeated_lines(clashing(docs, "n_lines", "first", "last"))
    if name == "lines routed":
        return lines.drop_repeated_lines(clashing(docs, "n_lines", "shard", "salt"), broadcast_bytes=-1)
    if name == "fmindex":
        return fmindex.find_benchmark(clashing(docs, "items", "n_hit"), spark.read.parquet(f"{folder}/benchmark.parquet"))
    if name == "fmindex blocks":
        return fmindex.find_benchmark(docs, spark.read.parquet(f"{folder}/benchmark.parquet"), block_bytes=10)
    return sketch.edited_fingerprints(clashing(docs, "sketch", "_bucket"))


NAMES = ["spans", "quality", "planes", "suffixes", "simhash", "bpe", "lines", "lines routed", "fmindex", "fmindex blocks", "sketch"]


@pytest.mark.parametrize("name", NAMES)
def test_each_row_has_a_result(name, docs, spark, folder):
    assert len(apply(name, docs, spark, folder).collect()) == len(ROWS)


@pytest.mark.parametrize("name", NAMES)
def test_an_empty_table_has_none(name, none, spark, folder):
    assert apply(name, none, spark, folder).collect() == []


def test_stages_take_edge_rows_and_keep_the_columns(docs, none, spark, folder):
    for given in (docs, none):
        at = given
        for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
            out = stage(spark, at, folder)
            if k < len(corpus_pipeline.STAGES) - 1:
                assert out.columns == given.columns
            at = spark.createDataFrame(out.collect(), out.schema)


def test_pages(spark):
    kind = "page_id long, url string, html string, payload string"
    pages = spark.createDataFrame([(1, "http://a/\n b", "<p>é</p>", "x"), (2, None, "<p>é</p>", "x"), (2, "u", "<p>é</p>", "x"), (3, "u", None, "x"), (4, "u", "", "x"), (None, "u", "z" * 300_000, "x")], kind)
    got = {(r.page_id, r.record_type, r.refers_to, r.payload_bytes) for r in warc.archived(pages).collect()}
    assert got == {(1, "revisit", 2, 9), (2, "response", None, 9), (3, "revisit", 4, 0), (4, "response", None, 0), (warc.NO_ID, "response", None, 300_000)}
    assert warc.archived(spark.createDataFrame([], kind)).collect() == []


def test_defined_results(docs, spark, folder):
    by = {r.doc_id: r for r in apply("lines", docs, spark, folder).collect()}
    assert by[2].n_lines == by[3].n_lines == 1 and by[2].kept_text == ""
    assert by[1].n_dropped == 1 and by[8].n_dropped == 0  # the largest id keeps its lines
    found = {r.doc_id: r for r in apply("fmindex", docs, spark, folder).collect()}
    assert found[1].n_hit == 7 and found[1].items == ["1"] and found[2].n_words == 0 and found[8].n_hit == 14
    near = {r.doc_id: r for r in apply("simhash", docs, spark, folder).collect()}
    assert near[2].fingerprint == near[3].fingerprint == near[7].fingerprint == 0 and near[7].component_id == 2
    assert near[1].component_id == simhash.NO_ID  # a null id is the smallest
    cut = {r.doc_id: r for r in apply("suffixes", docs, spark, folder).collect()}
    assert cut[4].n_removed == len(LONG) - 5 and cut[2].n_bytes == 0
    tokens = {r.doc_id: r for r in apply("bpe", docs, spark, folder).collect()}
    assert tokens[2].n_tokens == 0 and tokens[2].ids_sha256 == hashlib.sha256(b"").hexdigest()
