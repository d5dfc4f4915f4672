"""Whole corpora and whole tables in the result tables."""

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from schemaloom.operators import asks, attributes
from schemaloom.plans import QUERIES, runs, workloads
from schemaloom.sources import corpora

SMALL = "/root/testdata/sf0.001"


def test_top_types_of_every_corpus_and_constraint(spark, monkeypatch):
    tables = spark.createDataFrame([("a", "Agent>Customer"), ("b", "Agent>Supplier"), ("c", "Place>Region")], "table_id string, path string")
    paths = spark.createDataFrame([(x, 1, [t]) for x, t in (("a", "Agent"), ("b", "Agent"), ("c", "Place"))], "table_id string, path_no int, path array<string>")
    edges = spark.createDataFrame([("Agent", "Thing", 2), ("Place", "Thing", 1)], "child string, parent string, weight long")
    types = spark.createDataFrame([("a", "Agent"), ("b", "Agent"), ("c", "Place")], "table_id string, type_name string")
    monkeypatch.setattr(runs, "tables", lambda spark, sf_dir, corpus: tables)
    monkeypatch.setattr(runs, "types", lambda spark, sf_dir, corpus, constraint="none", verify=True: (paths, edges, None))
    monkeypatch.setattr(workloads, "affinity_types", lambda spark, sf_dir, corpus, weighted=True: types.withColumnRenamed("type_name", "cluster"))
    monkeypatch.setattr(workloads, "taxonomy", lambda spark, sf_dir, corpus: (types, edges))
    found = QUERIES["w_top_types"](spark, "nowhere").collect()
    methods = [("path-first", c) for c in asks.CONSTRAINTS] + [("affinity", "weighted"), ("affinity", "flat"), ("type-then-taxonomy", "bfs")]
    assert sorted((r.corpus, r.method, r.config) for r in found) == sorted((c, *m) for c in ("web", "wide", "multi", "large") for m in methods)
    assert all((r.ri, r.purity) == (1.0, 1.0) for r in found)


def test_columns_of_dense_vectors_have_vectors(spark, monkeypatch):
    none = spark.createDataFrame([], "base string, k string, column string, vector array<float>")
    monkeypatch.setattr(runs, "tallied", lambda spark, sf_dir, corpus: (None, None, none))
    found = {r.k: np.array(r.vector) for r in workloads.value_vectors(spark, SMALL, "web").collect()}
    given = pd.read_parquet(f"{SMALL}/embeddings.parquet")
    assert set(found) == {str(x) for x in given["label"].unique()}
    for label, rows in given.groupby("label"):
        total = np.sum(np.stack(rows["embedding"].to_numpy()).astype(float), axis=0)
        assert np.allclose(found[str(label)][: len(total)], total / np.linalg.norm(total), atol=1e-5) and not found[str(label)][len(total) :].any()


def test_rows_without_a_fragment_key_are_a_fragment(spark, monkeypatch, tmp_path):
    rows = [(1, "Customer#1", 3, 1.5, "AUTO"), (2, "Customer#2", 4, 2.5, None), (3, "Customer#3", 4, 3.5, None)]
    spark.createDataFrame(rows, "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string").write.parquet(str(tmp_path / "customer.parquet"))
    own = tuple(x for x in corpora.WEB if x.name == "customer")
    monkeypatch.setitem(corpora.CORPORA, "web", own)
    tables = {r.table_id: r.rows for r in corpora.sampled(spark, str(tmp_path), "web").collect()}
    assert set(tables) == {f"customer{k}_{v}" for k in ("", "_AUTO") for v in ("full", "renamed", "narrow")} and len(tables["customer_full"]) == 2
    samples = {r.column: r.samples for r in corpora.profiled(spark, str(tmp_path), own).where("k IS NULL").collect()}
    assert sorted(samples["c_custkey"]) == ["2", "3"] and sorted(samples["c_name"]) == ["Customer#2", "Customer#3"]
    columns = spark.createDataFrame([("t", "customer", None, "c_name", "x", 1.0)], "table_id string, base string, k string, column string, header string, weight double")
    plain, held = (workloads.table_vectors(columns, v).first().vector for v in (spark.createDataFrame([("customer", k, "c_name", [1.0] * 256)], "base string, k string, column string, vector array<float>") for k in ("AUTO", None)))
    assert np.count_nonzero(plain) == 1 and np.count_nonzero(held) > 1


def test_asks_about_columns_show_the_rows_around(spark, monkeypatch):
    class Shown:
        def complete(self, prompts):
            return ["rows" if '"around":[["v","w"]]' in x else "none" for x in prompts]

    columns = spark.createDataFrame([("t.h", "t", "h", "entity", ["v"])], "col string, table_id string, header string, kind string, samples array<string>")
    tables = spark.createDataFrame([("t", [["v", "w"]])], "table_id string, rows array<array<string>>")
    monkeypatch.setattr(runs, "columns", lambda spark, sf_dir, corpus: columns)
    monkeypatch.setattr(runs, "tables", lambda spark, sf_dir, corpus: tables)
    monkeypatch.setattr(runs, "types", lambda spark, sf_dir, corpus: (spark.createDataFrame([("t", ["A"])], "table_id string, path array<string>"), None, None))
    monkeypatch.setattr(attributes, "infer_attributes", lambda held, of, edges, completer: held)
    held = runs.asked_attributes(spark, "rows around", "web")[0]
    groups = columns.select(F.lit("A").alias("type_name"), F.lit("S").alias("sem_type"), "col")
    assert attributes.name_attributes(groups, held, Shown()).first().name == "rows"
