"""The join with shingles that most documents hold, in many buckets and small chunks."""

import random

import pytest

from placeminer.llm import components, jaccard

from .test_operators import components_of


def corpus(n, seed):
    """Documents that all hold one passage, some of them near copies of one another, some copies."""
    rng = random.Random(seed)
    word = lambda: f"w{rng.randrange(5000)}"
    common = " ".join(f"c{i}" for i in range(12))
    rows, texts = [], []
    for i in range(n):
        if texts and rng.random() < 0.5:
            words = rng.choice(texts[-20:]).split()
            for _ in range(rng.choice([0, 1, 1, 3])):
                words[rng.randrange(len(words))] = word()
            text = " ".join(words)
        else:
            text = " ".join(word() for _ in range(rng.randint(3, 60))) + " " + common + (" " + " ".join(word() for _ in range(10)) if rng.random() < 0.5 else "")
        texts.append(text)
        rows.append((i, text))
    return rows


@pytest.mark.parametrize("heavy, chunk, buckets", [(2, 500, 37), (8, 3000, 5), (64, 300_000, 8), (1 << 30, 1000, 16)])
def test_a_shingle_that_all_documents_hold(spark, monkeypatch, heavy, chunk, buckets):
    rows = corpus(260, heavy)
    for name, value in (("HEAVY", heavy), ("CHUNK", chunk), ("DEAL", 1), ("SEEN", 40)):
        monkeypatch.setattr(jaccard, name, value)
    monkeypatch.setattr(jaccard, "bucketed", lambda df: buckets)
    got = {tuple(r) for r in jaccard.groups(spark.createDataFrame(rows, "doc_id long, text string").repartition(6)).collect()}
    assert got == components_of(rows)


def test_hot_keys_are_joined_in_place(spark, monkeypatch):
    rng = random.Random(2)
    edges = [(0, i) for i in range(1, 900)] + [(i, 5000 + rng.randrange(40)) for i in range(2000, 2600)] + [(7, 7), (None, 3), (1, 2), (1, 2)]
    df = spark.createDataFrame(edges, "u long, v long").repartition(12)
    want = None
    for hot in (10, 1_000_000):
        monkeypatch.setattr(components, "HOT", hot)
        monkeypatch.setattr(components, "HELD", 50)
        got = {tuple(r) for r in components.connected(df).collect()}
        want = want or got
        assert got == want and {r for _, r in got} >= {0} and sum(r == 0 for _, r in got) == 900
        big = spark.createDataFrame([(k % 3, k) for k in range(600)] + [(k, k) for k in range(3, 50)], "k long, x long")
        out = components.spread_join(big, big.groupBy("k").agg({"x": "count"}).withColumnRenamed("count(x)", "n"), "k", "n")
        assert sorted(r["x"] for r in out.collect()) == sorted(r["x"] for r in big.collect())


def test_plans_tell_the_size_of_their_input(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert 100_000 < jaccard.input_bytes(docs.where("doc_id > 3")) < 10_000_000
    assert jaccard.bucketed(spark.createDataFrame([(1, "a")], "doc_id long, text string").union(docs.select("doc_id", "text"))) == 8
