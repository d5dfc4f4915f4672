"""The pipeline's near-duplicate stage against all pairs' exact similarity."""

import random
from functools import partial

import corpus_pipeline
import pytest
from schemaloom.llm import simhash


def near(a, b):
    cut = lambda x: {tuple(w[k : k + 5]) for w in [x.lower().split()] for k in range(max(1, len(w) - 4)) if w}
    x, y = cut(a), cut(b)
    return 5 * len(x & y) >= 4 * len(x | y)


def edited_texts():
    rng, out = random.Random(4), []
    words = [f"w{k}" for k in range(400)]
    for k in range(12):
        text = [rng.choice(words) for _ in range(rng.randint(1, 240))]
        for edits in (0, 0, 1, 2, 3, 4, 6):
            copy = list(text)
            for _ in range(edits):
                copy[rng.randrange(len(copy))] = rng.choice(words)
            out.append(" ".join(copy) + (" shared words at each text's end" if k % 2 else ""))
    return [*out, "", " ", "One two", "one TWO", "one"]


@pytest.mark.parametrize("small", [False, True])
def test_near_dedup_keeps_one_of_all_near_copies(spark, monkeypatch, small):
    if small:  # buckets and groups cut into parts
        monkeypatch.setattr(simhash, "near_copies", partial(simhash.near_copies, part_rows=3, group_rows=3))
    texts = edited_texts()
    of = list(range(len(texts)))
    for i, a in enumerate(texts):
        for j in range(i):
            if of[i] != of[j] and near(a, texts[j]):
                old, new = max(of[i], of[j]), min(of[i], of[j])
                of = [new if k == old else k for k in of]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id for r in corpus_pipeline.one_of_each_group(spark, docs, "").collect()}
    assert got == {k for k, c in enumerate(of) if c == k}
