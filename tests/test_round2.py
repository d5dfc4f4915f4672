"""Findings of the second round."""

from __future__ import annotations

from pyspark.sql import functions as F


def test_profiles_count_past_any_sketch(spark):
    from schemaloom.streaming import arrivals as st

    rows = spark.range(12_000).select(F.lit("a").alias("kind"), (F.col("id") % 9000).alias("user"), F.when(F.col("id") % 3 == 0, "x").alias("props")).repartition(3)
    found = st.drained(st.profiles(st.arriving(spark, rows, "many"), "kind", "user", "props"), "many")
    last = found.groupBy("kind", "part").agg(*(F.max(c).alias(c) for c in ("cells", "missing", "users")))
    assert last.agg(F.sum("cells"), F.sum("missing"), F.sum("users")).collect() == [(12_000, 8_000, 9_000)]


def test_postings_give_what_pairwise_joins_give(spark):
    import random

    from schemaloom.operators import affinity as a
    from schemaloom.operators import postings as po

    rng = random.Random(5)
    rows = [(f"i{i}", f"t{t}", float(rng.randint(1, 3))) for i in range(12) for t in range(60) if rng.random() < 0.4] + [(f"i{i}", "all", 1.0) for i in range(12)]
    terms = spark.createDataFrame(rows, "item string, term string, w double")
    lists = po.postings(terms)
    rounded = lambda df: {(r.a, r.b): round(r.sim, 6) for r in df.collect()}
    assert rounded(po.cosine_pairs(lists, po.norms(lists))) == rounded(a.cosine_pairs(terms, digits=None))
    rare = po.rare(lists, len(po.items_of(lists)))
    lengths = po.norms(rare)
    owner = {f"i{i}": (f"g{i % 3}", 0.1 * (i + 1)) for i in range(11)}
    held = po.grouped(rare, {i: (g, w / lengths[i]) for i, (g, w) in owner.items()})
    got = {r.item: (r.n, round(r.w, 6)) for r in held.select(F.explode("held").alias("h"), "n").groupBy("h.item").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("h.w")).alias("w")).collect()}
    owned = spark.createDataFrame([(i, g, w) for i, (g, w) in owner.items()], "item string, table_id string, weight double")
    want = a.table_vectors(a.unit(a.idf(terms)), owned).groupBy("item").agg(F.count("*").alias("n"), F.sum("w").alias("w"))
    assert got == {r.item: (r.n, round(r.w, 6)) for r in want.collect()}


def test_cells_meet_by_short_texts_and_long_hashes(spark):
    from schemaloom.operators.sampling import cell_key

    df = spark.createDataFrame([("short",), ("x" * 15,), ("x" * 16,), ("\u00e9" * 8,), ("y" * 90,), (" ",), (None,)], "value string")
    keys = [r.key for r in df.select(cell_key(F.col("value")).alias("key")).collect()]
    assert len({bytes(k) for k in keys[:5]}) == 5 and max(len(k) for k in keys[:5]) == 16 and keys[5:] == [None, None]


def test_counted_cells_are_the_cells(spark, tmp_path):
    from schemaloom.sources import corpora

    src = corpora.Source("events", "SELECT event_id, value, ts, props, 'a' AS k FROM {events}", tuple((c, c, "") for c in ("event_id", "value", "ts", "props")), "'x'", frozenset())
    spark.sql("SELECT * FROM VALUES (1L, 0.0D, TIMESTAMP_NTZ '2024-01-01 00:00:01.5', 'p'), (1L, -0.0D, NULL, ' '), (NULL, double('NaN'), NULL, NULL), (-7L, 1.0E7D, NULL, 'p') AS t(event_id, value, ts, props)").write.parquet(f"{tmp_path}/events.parquet")
    want = corpora.cells(spark, str(tmp_path), (src,)).groupBy("base", "k", "column", "value").agg(F.count("*").alias("n"))
    key = lambda df: sorted(map(str, df.select("base", "k", "column", "value", "n").collect()))
    assert key(corpora.counted(spark, str(tmp_path), (src,))) == key(want)


def test_queries_read_given_tables(spark):
    from schemaloom.plans import QUERIES

    for name in ("g_extract_paths", "g_malformed", "g_runs_mean"):
        assert QUERIES[name](spark, "/root/testdata/sf0.001").inputFiles(), name


def test_links_of_the_worked_example(spark):
    from schemaloom.operators import affinity as a

    cols = spark.createDataFrame([("c1", "Country", "name", True), ("c2", "Country", "name", True), ("c3", "Customer", "nation", False), ("c4", "Customer", "nation", False), ("c5", "Customer", "city", False), ("c6", "Country", "size", False)], "col string, type_name string, attr_id string, is_subject boolean")
    sims = spark.createDataFrame([("c1", "c3", 0.9), ("c2", "c4", 0.5), ("c2", "c5", 0.8), ("c1", "c6", 0.99)], "a string, b string, sim double")
    found = lambda d1, d2: sorted(tuple(r) for r in a.subject_links(cols, sims, d1, d2).collect())
    assert found(0.75, 0.15) == [("Customer", "city", "Country", 1, 1), ("Customer", "nation", "Country", 1, 2)]
    assert found(0.75, 0.5) == [("Customer", "city", "Country", 1, 1)]
    assert found(0.45, 0.0) == [("Customer", "city", "Country", 1, 1), ("Customer", "nation", "Country", 2, 2)]


def test_links_and_replay_read_given_tables(spark, tmp_path):
    from schemaloom.plans import QUERIES

    for name in ("a_links_con", "a_links_gen", "a_links_join", "a_links_swap"):
        assert QUERIES[name](spark, "/root/testdata/sf0.001").count(), name
    rows = [(1, 0, "user", "a"), (1, 1, "assistant", "x"), (2, 0, "user", "a"), (2, 1, "assistant", "y"), (2, 2, "user", "b"), (3, 0, "user", None), (3, 1, "assistant", "z")]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    assert sorted(tuple(r) for r in QUERIES["g_replay"](spark, str(tmp_path)).collect()) == [("1.0", "x"), ("2.0", "x")]


def test_numbers_in_blocks_give_what_cells_give(spark, tmp_path):
    from schemaloom.operators import affinity as a
    from schemaloom.operators import postings as po
    from schemaloom.sources import corpora

    columns = ("event_id", "user_id", "value", "ts", "props")
    src = corpora.Source("events", "SELECT event_id, user_id, value, ts, props, event_type AS k FROM {events}", tuple((c, c, "") for c in columns), "'x'", frozenset())
    rows = """(5L, 7, 0.0D, TIMESTAMP_NTZ '2024-01-01 00:00:01.072425', 'p 5 007 07', 'a'), (5L, -7, -0.0D, NULL, ' ', 'a'), (-5L, NULL, double('NaN'), NULL, NULL, 'b'), (9223372036854775807L, 0, 1.0E7D, NULL, 'p', 'b'),
    (100000000000000000L, 12, 12.05D, NULL, '100000000000000000 99999999999999999 00', NULL), (99999999999999999L, 12, -1234.5D, NULL, '0', NULL), (3L, 3, 0.001D, NULL, '12.05', 'b'), (-9223372036854775808L, 3, 84197.04D, NULL, 'x;y', 'a')"""
    spark.sql(f"SELECT * FROM VALUES {rows} AS t(event_id, user_id, value, ts, props, event_type)").repartition(3).write.parquet(f"{tmp_path}/events.parquet")
    profiles, lists, vectors = corpora.tallied(spark, str(tmp_path), (src,), (src,))
    key = lambda df, *names: sorted(map(str, df.select(*names).collect()))
    names = ("base", "k", "column", "cells", "rho_null", "rho_multi", "rho_uniq", "digits", "dates", "chars", "kind")
    assert key(profiles, *names) == key(corpora.profiles(spark, str(tmp_path), (src,), 0), *names)
    cells = corpora.counted(spark, str(tmp_path), (src,)).where("trim(value) <> ''").select(F.concat_ws(".", "base", "k", "column").alias("item"), F.col("column").alias("header"), "value", "n")
    total = lambda df: key(df.groupBy("held").agg(F.sum("n").alias("n")), "held", "n")
    assert total(lists.withColumn("held", F.array_sort("held"))) == total(po.postings(a.word_terms(cells)))
    hashed = [r.vector for r in vectors.orderBy("k", "column").collect()]
    terms = a.word_terms(cells.withColumn("header", F.lit("")))
    exact = {(r.a, r.b): r.sim for r in a.cosine_pairs(a.idf(terms), digits=None).collect()}
    names = [(r.k, r.column) for r in vectors.orderBy("k", "column").collect()]
    assert len(names) == a.idf(terms).select("item").distinct().count()
    assert all(abs(sum(x * x for x in v) - 1) < 1e-5 for v in hashed)
    at = {".".join(x for x in ("events", *n) if x is not None): v for n, v in zip(names, hashed, strict=True)}
    # few words seldom share a place of 256
    assert sum(abs(sum(x * y for x, y in zip(at[i], at[j], strict=True)) - sim) < 1e-4 for (i, j), sim in exact.items()) >= 0.8 * len(exact)


def test_samples_have_the_smallest_hashes(spark):
    from schemaloom.operators import sampling as s

    df = spark.range(4000).select(F.when(F.col("id") % 7 > 0, F.concat(F.lit("k"), F.col("id") % 3)).alias("k"), (F.col("id") % 900).alias("v")).union(spark.sql("SELECT 'few', 1L UNION ALL SELECT 'few', 1L"))
    found = sorted((str(r.k), r.digest) for r in s.sample_rows(df, "k", ["v"], 5).collect())
    every = {(str(r.k), r.digest) for r in df.withColumn("digest", s.digest("v")).collect()}
    assert found == sorted(x for k in {k for k, _ in every} for x in sorted(y for y in every if y[0] == k)[:5])


def test_value_sims_need_no_distinct_cells(spark):
    from schemaloom.plans import affinities, runs

    sf_dir = "/root/testdata/sf0.001/."  # a name that no other test has used
    assert affinities.wide_sims(spark, sf_dir).count()
    assert not any("counted" in key and sf_dir in key for key in runs._HELD)


def test_sampled_profiles_in_blocks_are_the_profiles(spark, tmp_path, monkeypatch):
    from schemaloom.operators import tallies
    from schemaloom.sources import corpora

    src = corpora.Source("events", "SELECT event_id, value, n, props, k FROM {events}", tuple((c, c, "") for c in ("event_id", "value", "n", "props")), "'x'", frozenset())
    odd = [(1, 0.0), (1, -0.0), (None, float("nan")), (-7, 1.0e7), (10**17, 0.125), (5, 2.5), (-5, -2.5), (0, -0.05), (12, 12.0), (120, 9999999.99), (-(2**63), None)]
    rows = [(a, v, None, f"{a}", "a") for a, v in odd] + [(i * 37 % 4001, i / 100, i % 3, " " if i % 2 else "7", "ab"[i % 2]) for i in range(3000)] + [(None, None, None, None, None)]
    spark.createDataFrame(rows, "event_id long, value double, n int, props string, k string").repartition(3).write.parquet(f"{tmp_path}/events.parquet")
    key = lambda df: sorted(str(r) for r in df.select("base", "k", "column", "cells", "rho_null", "rho_multi", "rho_uniq", "digits", "dates", "chars", "kind", "samples").collect())
    want = key(corpora.profiles(spark, str(tmp_path), (src,)))
    assert key(corpora.profiled(spark, str(tmp_path), (src,))) == want
    monkeypatch.setattr(tallies, "BUCKETS", 3)
    assert key(corpora.profiled(spark, str(tmp_path), (src,))) == want


def test_failures_and_columns_write_no_distinct_cells(spark, tmp_path):
    from schemaloom.operators import affinity as a
    from schemaloom.plans import QUERIES, affinities, runs

    sf_dir = f"{tmp_path}/sf"
    (tmp_path / "sf").symlink_to("/root/testdata/sf0.001")
    found = {r.case: r.n for r in QUERIES["w_failures"](spark, sf_dir).collect()}
    assert not any(sf_dir in key and key[1] in ("cells", "counted") for key in runs._HELD)
    like = "a LIKE 'events.%user_id' AND b LIKE 'customer.%'"
    assert found["joins by values alone"] == affinities.enc_join(spark, sf_dir).where(like).count()
    own, other = affinities.cells_of(spark, sf_dir, "events", ("user_id",)), affinities.cells_of(spark, sf_dir, "customer")
    pairs = a.containments(affinities.cells(spark, sf_dir).select("item", "value"), 0.05).where(like)
    assert sorted(a.containments_of(own, other, 0.05).collect()) == sorted(pairs.collect()) != []


def test_costs_count_each_ask_once(spark, tmp_path):
    from schemaloom.plans import QUERIES, runs

    (tmp_path / "sf").symlink_to("/root/testdata/sf0.001")
    sf_dir = f"{tmp_path}/sf"
    found = {(r.corpus, r.stage): r.calls for r in QUERIES["w_cost"](spark, sf_dir).collect()}
    for corpus in ("web", "wide", "multi"):
        assert found[corpus, "column_path"] == runs.columns(spark, sf_dir, corpus).count()
        assert found[corpus, "type_path"] >= runs.tables(spark, sf_dir, corpus).count()
        assert found[corpus, "type_path"] < 2 * runs.tables(spark, sf_dir, corpus).count()
    assert {(r.corpus, r.stage): r.calls for r in QUERIES["w_cost"](spark, sf_dir).collect()} == found
    assert not any(sf_dir in key and "multi" in key and key[1] in ("tables", "columns") for key in runs._HELD)


def test_steps_made_at_once_keep_ledgers_apart(spark):
    from schemaloom.operators import asks
    from schemaloom.plans import runs

    def asked(stage, n):
        rows = spark.range(n).select(F.concat(F.lit(stage), F.col("id")).alias("ask"), F.lit("Place").alias("child"), F.lit("Thing").alias("parent"))
        with asks.ledger() as held:
            for _ in range(2):
                asks.answers(rows, stage, ["child", "parent"], asks.ReplayCompleter({}))
        return [(s, df.count()) for s, df in held]

    with asks.ledger() as outer:
        assert runs.together(spark, lambda: asked("verify", 3), lambda: asked("is_a", 5)) == [[("verify", 3)] * 2, [("is_a", 5)] * 2]
    assert outer == []
