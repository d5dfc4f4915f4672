"""Worked examples, invariants and twins of the methods' operators."""

from decimal import Decimal

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F
from schemaloom.operators import affinity, asks, hierarchy, measures, sampling
from schemaloom.plans import ORACLES, QUERIES
from schemaloom.plans.registry import TABLES
from schemaloom.sources import fixtures as fx

SMALL = "/root/testdata/sf0.001"
#: Queries over numbers that DuckDB and Spark sum in other orders are compared to so many digits.
DIGITS = 5


def test_every_query_is_named_once_and_oracles_belong_to_queries():
    assert set(ORACLES) <= set(QUERIES) and len(QUERIES) > 100


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_queries_against_duckdb(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SMALL}/{t}.parquet'")
    df = QUERIES[name](spark, SMALL)
    cols = sorted(df.columns)
    want = con.sql(f"SELECT {', '.join(f'{chr(34)}{c}{chr(34)}' for c in cols)} FROM ({ORACLES[name]})").fetchall()
    norm = lambda r: tuple(f"{x:.{DIGITS}f}" if isinstance(x, float | Decimal) else str(x) for x in r)
    assert sorted(map(norm, df.select(cols).collect())) == sorted(map(norm, want))


def test_cycles_go_and_orphans_hang_under_the_root(spark):
    edges = spark.createDataFrame([("A", "B", 3), ("B", "C", 2), ("C", "A", 1), ("D", "A", 1)], "child string, parent string, weight long")
    for bound in (hierarchy.SMALL_EDGES, 0):
        left = hierarchy.break_cycles(edges, bound=bound)
        assert {r.child + r.parent for r in left.collect()} == {"AB", "BC", "DA"}
        assert hierarchy.reach(left, bound=bound).where("descendant = ancestor").isEmpty()
    rooted = hierarchy.attach_orphans(left)
    assert {r.child for r in rooted.where("parent = 'Thing'").collect()} == {"C"}
    by_join = {tuple(r) for r in hierarchy.reach(rooted, bound=0).collect()}
    assert by_join == {tuple(r) for r in hierarchy.reach(rooted).collect()}
    assert {tuple(r) for r in hierarchy.levels(rooted, bound=0).collect()} == {tuple(r) for r in hierarchy.levels(rooted).collect()}


def test_verification_takes_the_wrong_edge_alone(spark):
    before = hierarchy.prune_inverse(hierarchy.prune_self_loops(hierarchy.merge_edges(hierarchy.path_edges(fx.paths(spark)))))
    after = hierarchy.verify_edges(before, fx.relation(spark, fx.VERDICTS))
    gone = {(r.child, r.parent) for r in before.join(after, ["child", "parent"], "left_anti").collect()}
    assert gone == {("CreativeWork", "Event")} and after.where("child = 'CreativeWork' AND parent = 'Thing'").count() == 1


def test_rand_index_and_purity_of_the_worked_example(spark):
    rows = fx.relation(spark, fx.CLUSTERS)
    assert round(measures.rand_index(rows).first().value, 4) == 0.3333
    assert measures.purity(rows).first().value == 0.75 and round(measures.purity(rows, macro=False).first().value, 4) == 0.6667


def test_equal_types_count_only_when_allowed(spark):
    rows, truth = fx.relation(spark, fx.TREE), fx.relation(spark, fx.TREE_TRUTH)
    strict = {r.path_no: r.score for r in measures.tree_scores(rows, truth, allow_equal=False).collect()}
    assert strict["3"] == 0.5 and round(strict["1"], 4) == 0.6667


def test_asks_go_on_from_the_cache(spark, tmp_path):
    rows = spark.createDataFrame([(k, f"prompt {k % 3}") for k in range(6)], "ask_id long, prompt string")
    cache = f"file://{tmp_path}/cache"
    first = asks.ask(rows, asks.ReplayCompleter({f"prompt {k}": str(k) for k in range(3)}), cache)
    assert {(r.ask_id, r.text) for r in first.collect()} == {(k, str(k % 3)) for k in range(6)}
    again = asks.ask(rows, asks.EndpointCompleter(lambda prompt, t: "asked again"), cache)
    assert {r.text for r in again.collect()} == {"0", "1", "2"}


def test_prompts_name_their_parts(spark):
    row = spark.range(1).select(asks.render_prompt("type_path", F.lit("{}"), "full").alias("p")).first()
    assert "leaf types" in row.p and "Thing" in row.p and row.p.endswith("{}")


def test_samples_ignore_order_and_repeats(spark):
    df = spark.createDataFrame([("k", str(x)) for x in range(50)], "k string, v string")
    one = {r.digest for r in sampling.sample_rows(df, "k", ["v"]).collect()}
    two = {r.digest for r in sampling.sample_rows(df.union(df).repartition(3), "k", ["v"]).collect()}
    assert one == two and len(one) == 5


def test_sampling_limits_below_the_shuffle(spark, capsys):
    sampling.sample_rows(spark.createDataFrame([("k", "v")], "k string, v string"), "k", ["v"]).explain()
    assert "WindowGroupLimit" in capsys.readouterr().out


def naive_merges(d):
    groups, out = [{k} for k in range(len(d))], []
    while len(groups) > 1:
        h, i, j = min((np.mean([d[a, b] for a in x for b in y]), i, j) for i, x in enumerate(groups) for j, y in enumerate(groups) if i < j)
        out.append(h)
        groups[i] |= groups.pop(j)
    return out


def test_agglomeration_against_the_naive_one():
    x = np.random.default_rng(1).random((25, 3))
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(-1))
    heights = [h for _, _, h in affinity.merges_of(d)]
    assert np.allclose(heights, naive_merges(d)) and heights == sorted(heights)


def test_silhouette_against_the_definition():
    rng = np.random.default_rng(2)
    x, labels = rng.random((30, 2)), rng.integers(0, 4, 30)
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(-1))
    want = []
    for i in range(30):
        own = [j for j in range(30) if labels[j] == labels[i] and j != i]
        a = np.mean(d[i, own]) if own else 0
        b = min(np.mean(d[i, labels == c]) for c in set(labels) if c != labels[i])
        want.append((b - a) / max(a, b) if own else 0)
    assert abs(affinity.silhouette(d, labels) - np.mean(want)) < 1e-12


def test_kept_slices_nest_and_shrink():
    d = 1 - np.kron(np.eye(3), np.ones((4, 4)) * 0.9) - 0.05
    np.fill_diagonal(d, 0)
    wide, narrow = affinity.kept_nodes(d, 0.5), affinity.kept_nodes(d, 0.01)
    assert {m for m, _ in narrow} <= {m for m, _ in wide}
    assert all(p is None or m < p for m, p in wide) and {frozenset(range(4))} <= {m for m, _ in narrow}


def test_signature_pairs_find_near_sets(spark):
    rows = [(f"i{k}", [f"t{j}" for j in range(k, k + 20)]) for k in range(0, 12)]
    sets = spark.createDataFrame(rows, "item string, terms array<string>")
    got = {(r.a, r.b) for r in affinity.signature_pairs(sets, least=0.8).collect()}
    exact = {(min(a, b), max(a, b)) for a, x in rows for b, y in rows if a < b and len({*x} & {*y}) / len({*x} | {*y}) >= 0.8}
    assert len(got & exact) >= 0.9 * len(exact) and got <= exact


def test_links_shrink_as_thresholds_grow(spark):
    cols = spark.createDataFrame([("s", "A", "x", True), ("c", "B", "y", False), ("d", "B", "y", False)], "col string, type_name string, attr_id string, is_subject boolean")
    sims = spark.createDataFrame([("s", "c", 0.8), ("d", "s", 0.4)], "a string, b string, sim double")
    n = [affinity.subject_links(cols, sims, d1, d2).count() for d1, d2 in ((0.3, 0.9), (0.5, 0.4), (0.5, 0.5), (0.9, 0.0))]
    assert n == [1, 1, 0, 0]


def test_sketches_stay_within_their_error(spark):
    got = {r.event_type: r for r in QUERIES["s_agg_sketch"](spark, SMALL).collect()}
    exact = spark.read.parquet(f"{SMALL}/events.parquet").groupBy("event_type").agg(F.count_distinct("user_id").alias("n"))
    assert all(abs(got[r.event_type].users - r.n) <= 0.1 * r.n + 2 for r in exact.collect())
