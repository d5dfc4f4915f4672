"""The methods' steps on small inputs with known answers, and clustering against its definitions."""

import json

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F
from schemaloom.operators import affinity, asks, attributes, baselines, clustering, relations
from schemaloom.operators import hierarchy as h
from schemaloom.operators.lexicon import Lexicon


def naive_merges(distance, weights):
    d, size, live, out = distance.astype(float).copy(), weights.astype(float).copy(), list(range(len(distance))), []
    np.fill_diagonal(d, np.inf)
    while len(live) > 1:
        sub = d[np.ix_(live, live)]
        k = int(np.argmin(sub))
        i, j = sorted((live[k // len(live)], live[k % len(live)]))
        out.append((i, j, float(d[i, j])))
        rest = [x for x in live if x not in (i, j)]
        d[i, rest] = d[rest, i] = (size[i] * d[i, rest] + size[j] * d[j, rest]) / (size[i] + size[j])
        size[i] += size[j]
        live.remove(j)
    return out


@pytest.mark.parametrize("seed", range(6))
def test_chains_merge_as_the_definition_does(seed):
    rng = np.random.default_rng(seed)
    x = rng.random((24, 3))
    d = np.linalg.norm(x[:, None] - x[None], axis=2)
    w = rng.integers(1, 4, 24).astype(float)
    got, want = clustering.merges_of(d, w), naive_merges(d, w)
    assert [(i, j) for i, j, _ in got] == [(i, j) for i, j, _ in want]
    assert np.allclose([x[2] for x in got], [x[2] for x in want])


def test_weights_stand_for_equal_items():
    rng = np.random.default_rng(1)
    sets = [sorted(rng.choice(list("abcdefgh"), rng.integers(2, 6), replace=False)) for _ in range(7)]
    sets = [list(x) for x in sorted({tuple(x) for x in sets})]
    weights = np.array([1, 3, 2, 1, 2, 1, 1][: len(sets)], float)
    many = [x for x, n in zip(sets, weights, strict=True) for _ in range(int(n))]
    of = np.repeat(np.arange(len(sets)), weights.astype(int))
    one, all_ = clustering.set_distances(sets), clustering.set_distances(many)
    small = [(round(hh, 6), round(v, 6)) for hh, _, v in clustering.scored_slices(one, clustering.merges_of(one, weights), weights) if v is not None]
    large = [(round(hh, 6), round(v, 6)) for hh, _, v in clustering.scored_slices(all_, clustering.merges_of(all_)) if v is not None and hh > 1e-9]
    assert small == large
    for labels in (np.arange(len(sets)) % 3, np.arange(len(sets)) % 2):
        assert abs(clustering.silhouette(one, labels, weights) - clustering.silhouette(all_, labels[of])) < 1e-9


def test_block_products_join_what_all_pairs_join(spark):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((60, 8))
    x[30:] = x[:30] + 0.2 * rng.standard_normal((30, 8))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    names = [f"i{k:02d}" for k in range(60)]
    df = spark.createDataFrame(pd.DataFrame({"item": names, "vector": [list(map(float, r)) for r in x], "block": ["a" if k % 2 else "b" for k in range(60)]}), "item string, vector array<float>, block string")
    sims = x.astype(np.float32) @ x.astype(np.float32).T

    def classes(links, keep):
        of = dict(zip(names, names, strict=True))
        for a, b in links:
            low, high = sorted((of[a], of[b]))
            of = {k: low if v == high else v for k, v in of.items()}
        return of

    for block in (None, "block"):
        want = [(names[a], names[b]) for a in range(60) for b in range(a) if sims[a, b] >= 0.8 and (block is None or a % 2 == b % 2)]
        for rows in (2048, 7):
            got = [tuple(r) for r in clustering.near_links(df, 0.8, block, rows).collect()]
            assert set(got) <= {(a, b) for a, b in want} | {(b, a) for a, b in want} and classes(got, 0) == classes(want, 0)


def test_cycles_of_several_components_break_alike(spark):
    rng = np.random.default_rng(3)
    rows = {(f"t{a}", f"t{b}"): int(w) for a, b, w in zip(rng.integers(0, 12, 30), rng.integers(0, 12, 30), rng.integers(1, 5, 30), strict=True) if a != b}
    edges = spark.createDataFrame([(a, b, w) for (a, b), w in rows.items()], "child string, parent string, weight long")
    assert {tuple(r) for r in h.break_cycles(edges, bound=0).collect()} == {tuple(r) for r in h.break_cycles(edges).collect()}


def test_asks_are_repeated_until_they_are_valid(spark):
    def stubborn(prompt, temperature):  # repeats a type at the first n attempts
        x = json.loads(prompt.rsplit("\n", 1)[1])
        return "Thing -> A -> A" if x["attempt"] < x["n"] else "Thing -> A -> B"

    rows = spark.createDataFrame([("x", 0), ("y", 2), ("z", 9)], "ask string, n int")
    good, bad = asks.ask_until_valid(rows, "type_path", ["n"], asks.EndpointCompleter(stubborn), h.extract_path(F.col("text")), ~h.malformed(F.col("parsed")))
    assert {(r.ask, tuple(r.parsed)) for r in good.collect()} == {("x", ("A", "B")), ("y", ("A", "B"))}
    assert {(r.ask, r.text) for r in bad.collect()} == {("z", "Thing -> A -> A")}


def test_ledger_counts_calls(spark):
    rows = spark.createDataFrame([("x", "title"), ("y", "name")], "ask string, header string")
    with asks.ledger() as held:
        asks.answers(rows, "attr_name", ["header"], Lexicon())
    assert [(stage, df.count()) for stage, df in held] == [("attr_name", 2)]


def test_every_path_of_an_answer_is_found(spark):
    row = spark.createDataFrame([("Thing -> A -> B. Or else Thing -> A -> C_d. No -> No",)], "t string").select(attributes.extract_paths(F.col("t")).alias("p")).first()
    assert [list(x) for x in row.p] == [["A", "B"], ["A", "C_d"]]


def columns(spark):
    rows = [
        ("t1.name", "t1", "name", "entity", ["Ann"], 0.0, 0.0, 1.0), ("t1.country", "t1", "country", "entity", ["X", "Y"], 0.0, 0.0, 0.1),
        ("t2.title", "t2", "title", "entity", ["Bob"], 0.0, 0.0, 1.0), ("t2.country", "t2", "country", "entity", ["X", "Z"], 0.0, 0.0, 0.2),
        ("c.name", "c", "name", "entity", ["X"], 0.0, 0.0, 1.0), ("c.size", "c", "size", "number", ["1"], 0.0, 0.0, 0.9),
    ]
    return spark.createDataFrame(rows, "col string, table_id string, header string, kind string, samples array<string>, rho_null double, rho_multi double, rho_uniq double")


EDGES = [("Agent", "Thing", 2), ("Customer", "Agent", 2), ("Place", "Thing", 1), ("Country", "Place", 1)]


def test_attributes_and_relationships_end_to_end(spark):
    edges = spark.createDataFrame(EDGES, "child string, parent string, weight long")
    owners = spark.createDataFrame([("t1", "Customer"), ("t2", "Customer"), ("c", "Country")], "table_id string, type_name string")
    found = attributes.infer_attributes(columns(spark), owners, edges, Lexicon())
    clusters = {(r.col, r.attr_name, r.owner) for r in found["clusters"].collect()}
    assert ("t2.title", "name", "Agent") in clusters and ("c.size", "size", "Place") in clusters  # only children share all
    assert {r.sem_type for r in found["semantic"].where("col LIKE '%.title'").collect()} == {"Name"}
    rel = relations.infer_relationships(found["clusters"], columns(spark), edges, Lexicon())
    assert {(r.src, r.attr_name, r.dst) for r in rel.collect()} == {("Agent", "country", "Country")}
    stats = relations.evidence(rel, found["clusters"], columns(spark))
    assert [(r.tables, r.uniq) for r in stats.collect()] == [(2, 0.15)]
    for shown, want in (("both", "n:1"), ("stats", "n:1"), ("rows", "1:1")):
        rows = relations.evidence_rows(rel, found["clusters"], columns(spark).where("table_id <> 't2'") if shown == "rows" else columns(spark))
        assert [r.cardinality for r in relations.infer_cardinality(rel, stats, rows, Lexicon(), shown).collect()] == [want]


def test_refinements_are_checked(spark):
    with pytest.raises(ValueError):
        relations.select_type(columns(spark), columns(spark), Lexicon(), "neither")
    with pytest.raises(ValueError):
        baselines.direct_group(columns(spark), Lexicon(), context=10)


def test_taxonomies_of_both_kinds_agree_without_errors(spark):
    types = spark.createDataFrame([("a", "Customer"), ("b", "AutomobileCustomer"), ("c", "Agent"), ("d", "Place")], "table_id string, type_name string")
    want = {("AutomobileCustomer", "Customer", 1), ("Customer", "Agent", 1), ("Agent", "Thing", 1), ("Place", "Thing", 1)}
    assert {tuple(r) for r in baselines.type_taxonomy(types, Lexicon()).collect()} == want
    assert {tuple(r) for r in baselines.pairwise_taxonomy(types, Lexicon()).collect()} == want


def test_link_thresholds_on_one_pass(spark):
    cols = spark.createDataFrame([("s", "Country", "name", True), ("x", "Customer", "c", False), ("y", "Customer", "c", False)], "col string, type_name string, attr_id string, is_subject boolean")
    sims = spark.createDataFrame([("s", "x", 0.9), ("s", "y", 0.4)], "a string, b string, sim double")
    truth = spark.createDataFrame([("Customer", "Country")], "src_type string, dst_type string")
    got = {(r.d1, r.d2): r.f1 for r in affinity.tune_links(cols, sims, truth, [0.3, 0.5, 0.95], [0.0, 0.5]).collect()}
    assert got == {(0.3, 0.0): 1.0, (0.3, 0.5): 1.0, (0.5, 0.0): 1.0, (0.5, 0.5): 0.0, (0.95, 0.0): 0.0, (0.95, 0.5): 0.0}


def test_folders_are_swept(spark, monkeypatch):
    from pathlib import Path

    from schemaloom.sources import shared

    monkeypatch.setattr(shared, "_MADE", [])  # other tests' tables stay
    path = Path(shared.cut(spark.range(3)).inputFiles()[0].removeprefix("file://")).parent
    assert path.exists()
    shared.sweep()
    assert not path.exists()
