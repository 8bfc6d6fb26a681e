"""The near-duplicate stage against all pairs of texts."""

import random

import corpus_pipeline
import pytest
from cellstream.llm import jaccard


def five(text):
    w = (text or "").encode().lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def brute(texts):
    sets, parent = {d: five(t) for d, t in texts.items()}, {d: d for d in texts}

    def root(v):
        while parent[v] != v:
            v = parent[v]
        return v

    order = sorted(sets)
    for i, a in enumerate(order):
        for b in order[i + 1 :]:
            both = len(sets[a] & sets[b])
            if sets[a] == sets[b] or both and 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
                ra, rb = root(a), root(b)
                parent[max(ra, rb)] = min(ra, rb)
    return {d: root(d) for d in sets}


@pytest.fixture(scope="module")
def near():
    """Copies with words changed in a few places, chains of copies of copies, and a line that all texts share."""
    rng = random.Random(4)
    vocabulary, line, texts = [f"w{i}" for i in range(3000)], "the one line that very many of the documents share among them", {}
    for _ in range(12):
        base = rng.choices(vocabulary, k=rng.randint(30, 400))
        for _ in range(9):
            copy = list(base)
            for _ in range(rng.randint(0, max(1, len(copy) // 40))):
                copy[rng.randrange(len(copy))] = rng.choice(vocabulary)
            texts[len(texts)] = " ".join(copy) + "\n" + line
            base = copy if rng.random() < 0.4 else base
    return texts


def test_near_duplicates_of_five_words(spark, near):
    df = spark.createDataFrame(list(near.items()), "doc_id long, text string").repartition(4)
    want = brute(near)
    assert {r["doc_id"]: r["component_id"] for r in jaccard.classes(df).collect()} == want
    assert {r["doc_id"] for r in corpus_pipeline.near_duplicates(spark, df, "").collect()} == set(want.values()) and len(set(want.values())) < 60


def test_small_documents(docs, rows):
    assert {r["doc_id"]: r["component_id"] for r in jaccard.classes(docs).collect()} == brute(rows)


@pytest.mark.parametrize("mask,block", [(63, 1024), ((1 << 64) - 1, 3)])
def test_shared_digests_and_small_blocks(spark, near, mask, block):
    """Texts that share a digest are told apart, and cutting postings into blocks changes nothing."""
    df = spark.createDataFrame(list(near.items()), "doc_id long, text string").repartition(3)
    assert {r["doc_id"]: r["component_id"] for r in jaccard.classes(df, mask=mask, block=block).collect()} == brute(near)


def test_edge_rows(spark, empty):
    long = "all of these words are said once by many people in very many different places of the world "
    df = spark.createDataFrame([(None, long), (None, None), (1, long + "a"), (1, long + "a"), (1, "another text"), (2, long), (3, ""), (4, None), (5, "w " * 30000)], "doc_id long, text string")
    df = df.selectExpr("*", "1 AS node", "2 AS row", "3 AS n")
    assert sorted((r["doc_id"] or 0, r["text"] or "", r["node"]) for r in jaccard.first_of_each(df).collect()) == sorted([(0, long, 1), (0, "", 1), (1, long + "a", 1), (1, long + "a", 1), (1, "another text", 1), (3, "", 1), (5, "w " * 30000, 1)])
    assert jaccard.first_of_each(empty).count() == 0 and jaccard.first_of_each(empty).columns == empty.columns


def test_sketches_never_rule_a_link_out():
    import numpy as np

    rng = np.random.default_rng(0)
    for _ in range(300):
        size = int(rng.integers(1, 4000))
        a = rng.integers(0, 1 << 63, size, dtype=np.uint64)
        b = np.unique(np.concatenate([a[: size - int(rng.integers(0, size // 9 + 1))], rng.integers(0, 1 << 63, int(rng.integers(0, size // 9 + 1)), dtype=np.uint64)]))
        a = np.unique(a)
        x, y = (np.frombuffer(jaccard._sketch(v), "<u8") for v in (a, b))
        apart = len(np.setxor1d(a, b))
        assert max(jaccard.differing(x, y[None, :])[0], jaccard.differing(y, x[None, :])[0]) <= apart
