import random

import pytest
from pyspark.sql import functions as F

from placeminer.functions import places as pl
from placeminer.functions.replay import token_replay, token_series, trace_state
from placeminer.operators.kernel import Block
from placeminer.operators.tree import Tree

from .brute import E, S, all_places, counts, random_log, replay


def arr(*xs):
    return F.array(*[F.lit(x) for x in xs]) if xs else F.array().cast("array<string>")


def one(spark, col):
    return spark.range(1).select(col.alias("x")).first()["x"]


def test_expansions_selfloops_and_effect(spark):
    a, b, c = arr("a"), arr("b"), arr("b", "c")
    assert one(spark, pl.is_post_expansion(a, c, a, b, direct=True))
    assert one(spark, pl.is_post_expansion(a, c, a, arr()))
    assert not one(spark, pl.is_post_expansion(a, c, a, arr(), direct=True))
    assert not one(spark, pl.is_pre_expansion(a, c, a, b))
    assert one(spark, pl.is_through(a, b)) and not one(spark, pl.is_through(a, arr()))
    assert one(spark, pl.selfloops(arr("a", "b"), c)) == ["b"]
    e = one(spark, pl.effect(arr("a", "b"), c))
    assert (e["gain"], e["loss"]) == (["a"], ["c"])
    assert one(spark, pl.support_size(arr("a", "b"), c)) == 3
    assert one(spark, pl.place_id(arr("b", "a", "a"), c)) == "a,b>b,c"
    assert {(w["a"], w["b"]) for w in one(spark, pl.wires(arr("a", "b"), c))} == {("a", "b"), ("a", "c"), ("b", "b"), ("b", "c")}
    made = one(spark, pl.make(arr("b", "a"), c))
    assert made["pre"] == ["a", "b"] and made["depth"] == 4


@pytest.mark.parametrize(
    "seq, pre, post, want",
    [
        ("S a b a b E", "a", "b", (True, False, False, False)),
        ("S b E", "a", "b", (False, True, False, True)),
        ("S b E", "a", "b c", (False, True, False, True)),
        ("S b E", "a S", "b", (True, False, False, False)),
        ("S E", "S", "E", (True, False, False, False)),
        ("S a a E", "S", "a", (False, True, False, True)),
        ("S a a E", "S a", "a E", (True, False, False, False)),
        ("S c E", "c", "c", (False, True, False, False)),
    ],
)
def test_examples(spark, seq, pre, post, want):
    seq, pre, post = seq.split(), pre.split(), post.split()
    s = one(spark, trace_state(arr(*seq), arr(*pre), arr(*post)))
    assert (s["fit"], s["under"], s["over"], s["unbalanced"]) == want == replay(seq, pre, post)


def test_tokens(spark):
    assert one(spark, token_series(arr("S", "a", "b", "E"), arr("S", "a"), arr("b", "E"))) == [1, 2, 1, 0]
    t = one(spark, token_replay(arr("S", "b", "b", "E"), arr("S"), arr("b")))
    assert tuple(t) == (1, 2, 1, 0)


def test_kernel_agrees_with_brute_force_and_is_monotone():
    rng = random.Random(4)
    labels = [S, "a", "b", "c", E]
    at = {a: i for i, a in enumerate(labels)}
    literal_breaks = 0
    for _ in range(25):
        log = random_log(rng)
        block = Block([[at[a] for a in s] for s, _ in log], [f for _, f in log], 5)
        places = all_places((S, "a", "b", "c"), ("a", "b", "c", E), 8)
        got = block.counts([(tuple(at[a] for a in i), tuple(at[a] for a in o)) for i, o in places])
        want = {p: counts(log, *p) for p in places}
        assert [tuple(x) for x in got.tolist()] == [want[p] for p in places]
        for (i, o), c in want.items():
            assert c[0] <= block.total - c[1] and c[0] <= block.total - c[2]
            for a in ("a", "b", "c", E):
                if a not in o and (i, tuple(sorted((*o, a), key=labels.index))) in want:
                    assert want[i, tuple(sorted((*o, a), key=labels.index))][1] >= c[1]
            for a in (S, "a", "b", "c"):
                key = (tuple(sorted((*i, a), key=labels.index)), o)
                if a not in i and key in want:
                    assert want[key][2] >= c[2]
                    literal_breaks += want[key][3] < c[3]
    assert literal_breaks  # being out of balance is not monotone, being overfed is


def test_tree_counts_parents_and_paths():
    t = Tree((S, "a", "b", "c"), ("a", "b", "c", E), 8)
    every = t.subtree()
    assert len(every) == len(set(every)) == 1 + 4 + 225
    through = [n for n in every if n[0] and n[1]]
    assert len(through) == 225
    for prefer in ("post", "pre"):
        m = Tree(t.pre, t.post, 8, prefer)
        assert set(m.subtree()) >= set(through)
        for n in m.subtree():
            for c in m.children(n):
                assert m.parent(c) == n
    assert {d: sum(len(i) + len(o) == d for i, o in through) for d in range(2, 9)} == t.space()
    below = t.subtree(((0,), (0,)))
    assert len(below) == 64 and {len(i) + len(o) for i, o in below} == set(range(2, 9))
    assert sorted(below, key=lambda n: (len(n[0]) + len(n[1]), t.path(n))) == below
    for n in below:
        for rule in ("post", "pre"):
            cut = {"cut_post": rule == "post", "cut_pre": rule == "pre"}
            kept = {x for c in t.children(n, **cut) for x in t.subtree(c)}
            assert len(t.subtree(n)) - 1 - len(kept) == t.cut_mass(n, rule)


def test_space_of_the_wide_tree():
    t = Tree(tuple(map(str, range(25))), tuple(map(str, range(25))), 6)
    n = 0
    totals = [n := n + k for k in t.space().values()]
    assert totals == [625, 15625, 220625, 2233125, 17769625]


def test_spread_equals_children(spark):
    for prefer in ("post", "pre"):
        t = Tree((S, "a", "b"), ("a", "b", E), 5, prefer)
        f = t.seeds(spark).withColumn("cut_post", F.lit(False)).withColumn("cut_pre", F.lit(False))
        seen = []
        while rows := f.collect():
            seen += [((tuple(r["pre"]), tuple(r["post"])), tuple(r["path"])) for r in rows]
            f = t.spread(f).withColumn("cut_post", F.lit(False)).withColumn("cut_pre", F.lit(False))
        want = [n for n in t.subtree() if n[0] and n[1]]
        assert sorted(n for n, _ in seen) == sorted(want)
        assert all(len(p) == len(n[0]) + len(n[1]) for n, p in seen)
        assert sorted(seen, key=lambda x: x[1]) == sorted(seen, key=lambda x: [(v >> 20, v & 0xFFFFF) for v in x[1]])
