"""The operators against brute force, libraries and round trips on small fixtures."""

import hashlib
import random
import zlib
from collections import defaultdict

import corpus_pipeline
import numpy as np
import public_tokenizers
import pytest
import xxhash
from schemaloom.llm import bpe, fmindex, lines, planes, quality, simhash, sketch, suffixes
from schemaloom.llm.shared import documents
from tokenizers import Tokenizer

SMALL = "/root/testdata/sf0.001"


def sha(x):
    return hashlib.sha256(x if isinstance(x, bytes) else x.encode()).hexdigest()


@pytest.fixture(scope="module")
def texts(spark):
    return {r.doc_id: r.text for r in documents(spark, SMALL).select("doc_id", "text").collect()}


def odd_texts(seed, n, alphabet="abcdethinganos é ñ'’sßΣσİǅ́\t\n\x1c\x85　日本語🙂12٣!?._-"):
    rng = random.Random(seed)
    made = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 60))) for _ in range(n)]
    return made + ["a" * 2000, "ha" * 700, "x<|endoftext|>y <|startoftext|>", " ", "", "a ", "  a", "a\n b", "a\n ", "a   b"]


def word_encoder():
    with open(public_tokenizers.path("word_bpe_49k.json")) as f:
        return bpe.WordEncoder(f.read())


def test_bpe_is_the_library(texts):
    encoder, library = word_encoder(), Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    for x in [*odd_texts(1, 400), *list(texts.values())[:60]]:
        ids = library.encode(x, add_special_tokens=False).ids
        assert encoder.encode(x) == ids
        assert encoder.decode(ids) == library.decode(ids, skip_special_tokens=False)
        assert encoder.digest(ids) == (sha(" ".join(map(str, ids))), sha(library.decode(ids, skip_special_tokens=False)))


def test_transducer_emits_early_and_holds_little():
    encoder = word_encoder()
    transducer, rng, got, most = encoder.transducer, random.Random(2), [], 0
    symbols = [rng.choice("thean") for _ in range(5000)]
    for x in symbols:
        got += transducer.feed(x)
        most = max(most, len(transducer.last))
    early = len(got)
    got += transducer.finish()
    assert got == encoder.merges.short(symbols) and early > 1000 and most <= 6 * encoder.merges.reach


def test_bytewise_decoder_waits_for_whole_characters():
    codes = {k: bpe.LETTERS[b] for k, b in enumerate("é日".encode())}
    decoder = bpe.Decoder(codes, {9: "<s>"}, True)
    assert [decoder.feed(k) for k in (0, 1, 2, 3, 4)] == ["", "é", "", "", "日"] and decoder.feed(0) + decoder.finish() == "�"


def test_plane_ids_are_the_librarys(texts):
    with open(public_tokenizers.path("byte_bpe_50k.json")) as f:
        spec = f.read()
    encoder, library = planes.ByteLevelEncoder(spec), Tokenizer.from_str(spec)
    every = [*odd_texts(3, 400), *list(texts.values())[:60]]
    assert [x.tolist() for x in encoder.encode(every)] == [library.encode(x, add_special_tokens=False).ids for x in every]


@pytest.mark.parametrize("bits", [False, True])
def test_plane_files_come_back(bits):
    import io

    rng = np.random.default_rng(4)
    writer, docs, out = planes.PlaneWriter(bits, block_ids=100), [], planes.MAGIC
    for k in range(150):
        docs.append(rng.integers(0, 70_000, rng.choice([0, 1, 5, 250, 100]), dtype=np.uint32))
        writer.put(k - 5, docs[-1])
        out += b"".join(writer.blocks())
    out += b"".join(writer.blocks(True)) + writer.footer()
    start = 0
    for (doc, at, ids), (k, want) in zip(planes.PlaneFile(io.BytesIO(out)).documents(), enumerate(docs), strict=True):
        assert doc == k - 5 and at == start and (ids == want).all()
        start += len(want)


def test_op4_rows(spark, texts):
    library, start = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json")), 0
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in planes.op4_token_planes(spark, SMALL).collect()}
    for doc in sorted(texts):
        ids = np.array([*library.encode(texts[doc], add_special_tokens=False).ids, 2], "<u4")
        assert got[doc] == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)


def removed(docs, length):
    seen, out = set(), {}
    for k in sorted(docs):
        data = docs[k].encode()
        cover = bytearray(len(data))
        for a in range(len(data) - length + 1):
            if data[a : a + length] in seen:
                cover[a : a + length] = b"\1" * length
            else:
                seen.add(data[a : a + length])
        kept = bytes(x for x, c in zip(data, cover, strict=True) if not c)
        out[k] = (len(data), len(data) - len(kept), sum(1 for a in range(len(data)) if cover[a] and not (a and cover[a - 1])), sha(kept))
    return out


def repeated_docs(seed):
    rng, docs, k = random.Random(seed), {}, 0
    text = lambda n, alphabet="abcdefgh é.": "".join(rng.choice(alphabet) for _ in range(n))
    base = [text(rng.randint(80, 400)) for _ in range(6)]
    for _ in range(50):
        parts = []
        for _ in range(rng.randint(0, 4)):
            b, r = rng.choice(base), rng.random()
            at = rng.randrange(len(b))
            parts.append(text(rng.randint(0, 150)) if r < 0.3 else b if r < 0.6 else b[at:] if r < 0.75 else b[:at] + "Z" + b[at + 1 :] if r < 0.87 else text(rng.randint(1, 6), "xyz") * rng.randint(20, 90))
        docs[k] = "".join(parts)
        k += rng.randint(1, 3)
    return docs


@pytest.mark.parametrize("heavy", [20_000, 3])
def test_suffixes_against_brute_force(spark, heavy):
    docs = repeated_docs(5)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string").repartition(3)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, sha(bytes(r.kept))) for r in suffixes.cut_repeats(df, heavy_contexts=heavy).collect()}
    assert got == removed(docs, 100)


def test_maximal_repeats_have_all_occurrences():
    a, b = "x" + "abcdefghij" * 11 + "1", "y" + "abcdefghij" * 11 + "2"
    array = suffixes.EnhancedSuffixArray([a.encode(), b.encode()], 100)
    found = {(deep, frozenset(zip(array.which[p:q].tolist(), array.within[p:q].tolist(), strict=True))) for deep, p, q in array.maximal_repeats()}
    assert (110, frozenset({(0, 1), (1, 1)})) in found
    assert (100, frozenset({(0, 1), (1, 1), (0, 11), (1, 11)})) in found


def slow_fingerprint(text):
    words = "".join(c.lower() if "A" <= c <= "Z" else c for c in text).encode().split()
    hashes = [xxhash.xxh64_intdigest(b" ".join(words[k : k + 4]), 42) for k in range(max(1, len(words) - 3))] if words else []
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in hashes) > len(hashes))


def components(values, errors):
    labels = simhash.Labels(len(values))
    a, b = np.nonzero(np.triu(np.bitwise_count(values[:, None] ^ values[None, :]) <= errors, 1))
    labels.join(a, b)
    return labels.of


def test_op6_rows(spark, texts):
    ids = sorted(texts)
    values = np.array([slow_fingerprint(texts[k]) for k in ids], np.uint64)
    want = {(k, f"{int(v):016x}", ids[c]) for k, v, c in zip(ids, values, components(values, 4), strict=True)}
    assert {tuple(r) for r in simhash.op6_simhash_tries(spark, SMALL).collect()} == want


def test_tries_against_all_pairs():
    rng = np.random.default_rng(6)
    values = {0}
    for x in rng.integers(0, 1 << 63, 25).tolist():
        for _ in range(int(rng.integers(1, 50))):
            y = x
            for bit in rng.integers(0, 64, int(rng.integers(0, 7))).tolist():
                y ^= 1 << bit
            values.add(y)
    values = np.array(sorted(values), np.uint64)
    assert (simhash.trie_self_join(values, np.array([0, len(values)]), 0, 4) == components(values, 4)).all()


@pytest.mark.parametrize("rows", [256, 1])
def test_links_for_few_and_many_bands(spark, rows):
    rng = np.random.default_rng(7)
    base = rng.integers(0, 1 << 62, 20)
    values = np.unique(np.array([int(x) ^ sum(1 << int(b) for b in rng.choice(62, rng.integers(0, 6), replace=False)) for x in base for _ in range(12)], np.int64))
    nodes = spark.createDataFrame([(int(v), k) for k, v in enumerate(values)], "fp long, node long")
    labels = simhash.Labels(len(values))
    for r in simhash.link(nodes, 4, bucket_rows=rows).collect():
        labels.join(np.array([r.a]), np.array([r.b]))
    assert (labels.of == components(values.view(np.uint64), 4)).all()


def test_perfect_hash_is_minimal():
    keys = np.unique(np.random.default_rng(8).integers(0, 1 << 63, 5000, dtype=np.uint64))
    index = lines.PerfectHash.build(keys)
    assert sorted(index.lookup(keys).tolist()) == list(range(len(keys)))


def test_line_probes_agree_by_either_way(spark):
    rng = random.Random(9)
    pool = [f"this is shared line number {k} of the pool" for k in range(12)]
    rows = [(k, "\n".join(rng.choice(pool) if rng.random() < 0.4 else f"own line {rng.random()} of this document" for _ in range(rng.randint(0, 8)))) for k in range(80)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    one = {tuple(r) for r in lines.drop_repeated_lines(df).collect()}
    two = {tuple(r) for r in lines.drop_repeated_lines(df, broadcast_bytes=-1, shard_keys=3).collect()}
    assert one == two and any(r[3] for r in one)


def shingles(text):
    words = "".join(c.lower() if "A" <= c <= "Z" else c for c in text).encode().split()
    return {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))} if words else set()


def test_op10_rows(spark, texts):
    ids = sorted(texts)
    got = {r.doc_id: r for r in sketch.op10_scaled_sketch(spark, SMALL).collect()}
    off = []
    for k, after in zip(ids, ids[1:] + ids[:1], strict=True):
        x, n = texts[k], len(texts[k])
        edited = x[: n - n // 4] + texts[after][: n // 4]
        assert (got[k].n_chars, got[k].edited_sha256) == (n, sha(edited))
        a, b = shingles(x), shingles(edited)
        off.append(abs(len(a & b) / len(a | b) - got[k].near_edited))
        assert 0 <= got[k].near_next <= 1
    assert np.mean(off) < 0.08
    same = defaultdict(set)
    for k in ids:
        same[texts[k]].add(got[k].fingerprint)
    assert all(len(x) == 1 for x in same.values())


def test_sketches_merge(spark):
    from pyspark.sql import functions as F

    row = spark.createDataFrame([("a b c d e f g h " * 20, "q r s t u v w x y z " * 30)], "a string, b string").select(sketch.merged(sketch.sketch(F.col("a")), sketch.sketch(F.col("b"))).alias("m"), sketch.sketch(F.col("a")).alias("x"), sketch.sketch(F.col("b")).alias("y"))
    got = row.select("*", sketch.containment(F.col("x"), F.col("m")).alias("c")).first()
    assert set(got.x) | set(got.y) >= set(got.m) and (got.c == 1 or len(got.x) == 1)


def test_quality_on_held_out_labels(spark):
    labels = {r.doc_id: r.quality for r in spark.read.parquet("/root/testdata/sf0.01/labels.parquet").collect()}
    rows = quality.op2_neighbour_quality(spark, "/root/testdata/sf0.01").collect()
    assert all(0 <= r.score <= 1 and r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and r.predicted == int(r.score >= 0.3) for r in rows)
    held = [r.predicted == labels[r.doc_id] for r in rows if r.held_out and r.doc_id in labels]
    assert np.mean(held) > 0.95


def test_quality_votes_are_exact():
    rng = np.random.default_rng(10)
    rates = rng.poisson(0.2, (60, quality.TERMS)).astype(float)
    model = quality.Model(rates, rng.integers(0, 2, 60))
    got = model.scores(rates[:20], block=7)
    for k in range(20):
        v = quality.unit(model.weighted(rates[k : k + 1]) @ model.axes)[0]
        cosine = model.vectors @ v
        near = np.argsort(-cosine, kind="stable")[: model.neighbours]
        weight = np.maximum(0, cosine[near]) ** model.power
        assert abs(got[k] - (weight * model.labels[near]).sum() / weight.sum()) < 1e-9


def test_pipeline_against_brute_force(spark, texts, tmp_path):
    """Each stage's rule in plain Python on what the stage before kept; the vote's scores come from its own model."""
    docs = documents(spark, SMALL)
    model = quality.fit(docs, spark.read.parquet(f"{SMALL}/labels.parquet"))
    left = {k: x for k, x in texts.items() if model.scores(np.array([quality.term_rates(x.encode())]))[0] >= 0.3}
    holders = defaultdict(set)
    key = lambda line: "".join(c.lower() if "A" <= c <= "Z" else c for c in line.strip(" \t\n\v\f\r"))
    for k, x in left.items():
        for line in x.split("\n"):
            if len(key(line)) >= 20:
                holders[key(line)].add(k)
    gone = lambda k, line: len(holders[key(line)]) >= 3 and max(holders[key(line)]) != k if len(key(line)) >= 20 else False
    left = {k: "\n".join(line for line in x.split("\n") if not gone(k, line)) for k, x in left.items()}
    ids = sorted(left)
    labels, sets = simhash.Labels(len(ids)), [shingles(left[k]) for k in ids]
    near = [(a, b) for b in range(len(ids)) for a in range(b) if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b])]
    for a, b in near:
        labels.join(np.array([a]), np.array([b]))
    left = {k: left[k] for k, c in zip(ids, labels.of, strict=True) if ids[c] == k}
    split = lambda x: x.encode().translate(__import__("schemaloom.llm.fmindex", fromlist=["x"]).TABLE).split()
    windows = set()
    for r in spark.read.parquet(f"{SMALL}/benchmark.parquet").collect():
        words = split(r.text)
        windows |= {tuple(words[k : k + 13]) for k in range(max(1, len(words) - 12))} if words else set()
    clean = {}
    for k, x in left.items():
        words = split(x)
        hit = {p for n in {len(w) for w in windows} for a in range(len(words) - n + 1) if tuple(words[a : a + n]) in windows for p in range(a, a + n)}
        if not hit or 20 * len(hit) < len(words):
            clean[k] = x
    library = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = {(k, len(e.ids), sha(" ".join(map(str, e.ids)))) for k, x in clean.items() for e in [library.encode(x, add_special_tokens=False)]}
    assert {tuple(r)[:3] for r in corpus_pipeline.run(spark, SMALL).collect()} == want


def naive_merge(merges, text):
    rank, s = {p: k for k, p in enumerate(merges)}, list(text)
    while found := [rank[p] for p in zip(s, s[1:]) if p in rank]:  # noqa: B905
        first, out, k = min(found), [], 0
        while k < len(s):
            if k + 1 < len(s) and rank.get((s[k], s[k + 1])) == first:
                out.append(s[k] + s[k + 1])
                k += 2
            else:
                out.append(s[k])
                k += 1
        s = out
    return s


def random_lists(n):
    rng = random.Random(12)
    for _ in range(n):
        letters = "abcd"[: rng.randint(1, 4)]
        tokens, merges = list(letters), []
        for _ in range(rng.randint(1, 9)):
            a, b = rng.choice(tokens), rng.choice(tokens)
            if a + b not in tokens:
                merges.append((a, b))
                tokens.append(a + b)
        yield letters, tokens, merges, rng


def test_lookahead_bounds_what_is_held_and_other_lists_are_refused():
    kept = 0
    for letters, tokens, merges, rng in random_lists(600):
        merge_list = bpe.MergeList({t: k for k, t in enumerate(tokens)}, merges, "")
        proper = all(naive_merge(merges, t) == [t] for t in tokens)
        if not proper:
            with pytest.raises(ValueError):
                merge_list.check()
            continue
        merge_list.check()
        transducer, text, out, held = bpe.Transducer(merge_list), "".join(rng.choice(letters) for _ in range(300)), [], 0
        for x in text:
            out += transducer.feed(x)
            held = max(held, len(transducer.last))
        out += transducer.finish()
        assert [merge_list.names[k] for k in out] == naive_merge(merges, text) and held <= 4 * merge_list.reach + merge_list.lookahead
        kept += 1
    assert kept > 200


def test_perfect_hash_keeps_lines_whose_hashes_share_halves():
    first = np.array([7, 7, 9], np.uint64)
    second, counts, last = np.array([1, 2, 3], np.uint64), np.array([3, 5, 2]), np.array([10, 20, 30])
    shard = lines.Shard(*lines.Shard.pack(first, second, counts, last))
    ask = lambda a, b, doc: bool(shard.others_hold(np.array([a], np.uint64), np.array([b], np.uint64), np.array([doc]), 3)[0])
    assert ask(7, 1, 1) and ask(7, 2, 1) and not ask(7, 1, 10) and not ask(7, 2, 20) and not ask(9, 3, 1) and not ask(7, 3, 1)


@pytest.mark.parametrize("length", [32, 33, 36, 37, 64, 128])
def test_suffixes_of_other_lengths(spark, length):
    docs = repeated_docs(length)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string").repartition(2)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, sha(bytes(r.kept))) for r in suffixes.cut_repeats(df, length=length).collect()}
    assert got == removed(docs, length)


def test_suffix_arrays_sort_suffixes():
    rng = np.random.default_rng(13)
    for n in [*range(8), 40, 90]:
        seq = rng.integers(0, 3, n)
        assert fmindex.suffix_order(seq).tolist() == sorted(range(n), key=lambda k: seq[k:].tolist())


def test_written_indexes_find_what_the_texts_hold(spark, tmp_path):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text")
    benchmark = spark.read.parquet(f"{SMALL}/benchmark.parquet")
    folder = f"file://{tmp_path}/index"
    manifest = fmindex.write_index(docs, folder)
    manifest = spark.createDataFrame(manifest.collect(), manifest.schema)
    norm = lambda df: {(r.doc_id, r.n_words, r.n_hit, tuple(map(tuple, r.spans)), tuple(r["items"])) for r in df.collect()}
    found = norm(fmindex.search_index(manifest, folder, benchmark))
    assert found == norm(fmindex.find_benchmark(docs, benchmark)) and any(x[2] for x in found)
    # another benchmark, of passages of the documents themselves
    other = docs.where("doc_id % 7 = 0").selectExpr("doc_id AS item_id", "substr(text, 1, 200) AS text")
    assert norm(fmindex.search_index(manifest, folder, other)) == norm(fmindex.find_benchmark(docs, other))


def test_hot_buckets_are_cut_into_parts(spark):
    rng = np.random.default_rng(14)
    base = int(rng.integers(0, 1 << 62))
    values = np.unique([base ^ sum(1 << int(b) for b in rng.choice(40, rng.integers(1, 8), replace=False)) for _ in range(300)])
    nodes = spark.createDataFrame([(int(v), k) for k, v in enumerate(values)], "fp long, node long")
    want = components(values.astype(np.int64).view(np.uint64), 4)
    labels = simhash.Labels(len(values))
    for r in simhash.link(nodes, 4, part_rows=16).collect():
        labels.join(np.array([r.a]), np.array([r.b]))
    assert (labels.of == want).all()


def test_near_copies_recall_at_the_least_similarity(spark):
    """Pairs of a similarity of just 0.8: nearly all must be found, and nothing below."""
    rng = random.Random(15)
    rows, pairs = [], []
    for k in range(400):
        n = rng.randint(30, 200)
        text = [f"w{rng.randrange(10**6)}" for _ in range(n)]
        cut = max(1, round(0.2 * (n - 4)))
        rows.append((2 * k, " ".join(text)))
        rows.append((2 * k + 1, " ".join(text[cut:])))  # shares n - 4 - cut of n - 4 shingles
        pairs.append(5 * (n - 4 - cut) >= 4 * (n - 4))
    found = simhash.near_copies(spark.createDataFrame(rows, "doc_id long, text string"))
    got = {r.node for r in found.collect() if r.node % 2}
    assert got <= {2 * k + 1 for k, near in enumerate(pairs) if near}
    assert len(got) >= 0.99 * sum(pairs) and sum(pairs) > 150


def test_votes_prefer_the_first_of_equal_neighbours():
    rates = np.tile(np.random.default_rng(16).poisson(2.0, quality.TERMS).astype(float), (12, 1))
    model = quality.Model(rates, np.array([1, 1, 1, 1, 1, *[0] * 7]), neighbours=5)
    assert model.scores(rates[:1])[0] > 0.999


def test_sentence_runs_cover_exact_copies_whole(spark):
    from schemaloom.llm import spans

    texts = ["Short. One more long sentence that has rather many words in it so that it alone would be enough for a run of words here. End.", "Tiny.", "", None, "two words", "A b c. D e f."]
    rows = [(k, x) for k, x in enumerate(texts * 2)]
    kept = {r.doc_id: r.kept_text for r in spans.drop_repeated_spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(kept[k] == (x or "") for k, x in enumerate(texts)) and all(kept[k + len(texts)] == "" for k in range(len(texts)))
