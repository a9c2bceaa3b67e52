import random

import pytest
from pyspark.sql import functions as F

from placeminer.operators import log as logs
from placeminer.operators.baselines import alpha, brute, cuts, region
from placeminer.operators.compose import Budget, Candidate, Collect, Delta, Greedy, Implicit, Postponing, Threshold, Uniwired, cuts as node_cuts
from placeminer.operators.constraints import is_monotone_sequence, is_strengthening, max_depth, max_post, not_anywhere, not_in_pre, not_selfloop
from placeminer.operators.evaluate import SparkLog, decide, fitness, sampled_fitness
from placeminer.operators.implicit import dominance_fold, log_language_kept, remainder
from placeminer.operators.kernel import Block
from placeminer.operators.lp import feasible, lp_implicit, universal_place
from placeminer.operators.model import Net, closed_world, deadlocks, diff, from_json, from_pnml, to_dot, to_json, to_net, to_pnml
from placeminer.operators.post import Pipeline, drop_implicit_lp, merge_selfloop_places, merge_siblings
from placeminer.operators.tree import tree_of
from placeminer.plans.config import PRESETS, Config, Context
from placeminer.plans.propose import Stepper, _with_ids, discover, regrid, restart, walk
from placeminer.plans.run import prepare, run
from placeminer.plans.supervise import Supervisor
from placeminer.sources.logs import events
from placeminer.workloads import ready

from .brute import E, S, counts, random_log

LABELS = [S, "a", "b", "c", E]
AT = {a: i for i, a in enumerate(LABELS)}
TREE = tree_of(["a", "b", "c"], 8)


def block(log):
    return Block([[AT[a] for a in s] for s, _ in log], [f for _, f in log], 5)


def ids(i, o):
    return tuple(sorted(AT[a] for a in i)), tuple(sorted(AT[a] for a in o))


def test_worked_example_cut():
    log = [((S, "a", "b", E), 4), ((S, "a", "a", E), 6)]
    assert counts(log, (S,), ("a",))[:3] == (4, 6, 0)
    assert node_cuts(6, 0, 10, 0.5, 2, True, True) == (True, False)
    assert counts(log, (S, "a"), ("a", E))[0] == 10


@pytest.mark.parametrize("mode", ["paper", "both", "under", "over", "none"])
def test_pruned_walk_finds_exactly_the_passing_places(mode):
    rng = random.Random(7)
    for _ in range(12):
        b = block(random_log(rng))
        for tau in (1.0, 0.7, 0.5):
            every, n = brute.brute(b, LABELS, TREE, tau)
            for prefer in ("post", "pre"):
                t = tree_of(["a", "b", "c"], 8, prefer=prefer)
                found = walk(b, LABELS, t, tau, cut_mode=mode)
                assert len(found.places) == len(set(found.places)) and set(found.places) == set(every)
                assert found.proposed <= n and found.complete
            dfs = walk(b, LABELS, TREE, tau, cut_mode=mode, strategy="dfs", batch=3)
            best = walk(b, LABELS, TREE, tau, cut_mode=mode, strategy="best", heuristic=lambda p: len(set(p[0]) | set(p[1])), batch=1)
            assert set(dfs.places) == set(best.places) == set(every)
            assert dfs.proposed == best.proposed == walk(b, LABELS, TREE, tau, cut_mode=mode).proposed


def test_engines_agree_and_levels_equal_steps(spark, sf):
    p = prepare(events(spark, sf, "events_day"))
    t = tree_of(p.labels[1:-1], 3)
    table = _with_ids(t.seeds(spark), t, p.labels)
    cols = ["place_id", "n_fit", "n_under", "n_over", "n_unbalanced", "n_total"]
    got = {e: sorted(map(tuple, fitness(p.log, table, e, chunk=10).select(cols).collect())) for e in ("sql", "window", "arrow", "frontier")}
    assert got["sql"] == got["window"] == got["arrow"] == got["frontier"]
    big = SparkLog(p.log.variants, p.labels)
    big._total, big._cells = p.log.total, 10**12  # as if it were too large to broadcast
    a, b = discover(big, t, 0.6), walk(p.log, p.labels, t, 0.6)
    assert a.places == b.places and a.by_depth == b.by_depth
    pre = tree_of(p.labels[1:-1], 3, prefer="pre")
    assert set(discover(p.log, pre, 0.6).places) == set(b.places)
    assert big.support(b.places) == p.log.support(b.places) and big.first_unfit(b.places) == p.log.first_unfit(b.places)
    assert (big.dominance(b.places[:6]) == p.log.dominance(b.places[:6])).all()
    early = decide(p.log, b.places[:5] + [((1,), (2,))], 0.6)
    assert [early[q][0] for q in b.places[:5]] == [True] * 5
    assert all(0 <= e <= 1 for e, _ in sampled_fitness(p.log, b.places[:3], 0.5))


def test_log_language_equals_the_loop():
    rng = random.Random(3)
    for _ in range(20):
        b = block(random_log(rng))
        found = walk(b, LABELS, TREE, 0.6).places
        kept, now = [], b.total
        for i, p in enumerate(found):
            if b.support([*[found[k] for k in kept], p]) < now:
                kept.append(i)
                now = b.support([found[k] for k in kept])
        assert log_language_kept(b, found, 0.6) == kept
    with pytest.raises(ValueError):
        log_language_kept(b, found, 1.0)


def test_dominance_and_lp_keep_what_the_net_allows():
    rng = random.Random(5)
    universal = universal_place(5, 0, 4)
    other = block(random_log(rng, n=60))
    for _ in range(8):
        b = block(random_log(rng))
        found = walk(b, LABELS, tree_of(["a", "b", "c"], 4), 1.0).places

        class Log:
            def dominance(self, ps, scope="all"):
                return b.dominance(ps, scope)

            def misfits(self, p, given):
                return b.support(given) - b.support([*given, p])

        kept = [p for p, v, _ in dominance_fold(Log(), found) if v == "kept"]
        assert b.support(kept) == b.support(found)
        lp = drop_implicit_lp(found, universal=universal)
        assert (b.fits(lp).all(axis=1) == b.fits(found).all(axis=1)).all()
        assert (other.fits(lp).all(axis=1) == other.fits(found).all(axis=1)).all()
        merged = merge_selfloop_places(lp)
        assert (other.fits(merged).all(axis=1) == other.fits(lp).all(axis=1)).all()


def test_lp_edges():
    assert feasible([[1, 1]], ["="], [2]) is not None and feasible([[1, 1]], ["<="], [-1]) is None
    a, b, ac = ids("a", "b"), ids("b", "c"), ids(("a",), ("c",))
    assert lp_implicit(ac, [a, b]).implicit
    p, q = ids(("a", "c"), ("b",)), ids("a", "b")
    assert not lp_implicit(p, [q], "fit").implicit and lp_implicit(p, [q], "enabling").implicit
    u = universal_place(5, 0, 4)
    assert lp_implicit(ids((S, "a"), ("a", E)), [], universal=u).implicit
    assert remainder(ids("a", "b"), ids("c", "b")) == ids("a", "c")
    assert remainder(ids(("a",), ("b",)), ids(("c",), ("a",))) is None


def test_composers(spark, sf):
    p = ready(spark, sf, "conv")
    t = tree_of(p.labels[1:-1], 4)

    def go(c, tau=0.5):
        return walk(p.log, p.labels, t, tau, Threshold(c, tau))

    base = go(Collect())
    uni = go(Uniwired(Collect()))
    wires = [(a, b) for i, o in uni.places for a in i for b in o]
    assert len(wires) == len(set(wires)) and set(uni.places) <= set(base.places) and uni.complete
    spark_uni = discover(p.log, t, 0.5, Threshold(Uniwired(Collect()), 0.5))
    assert spark_uni.places == uni.places
    delta = go(Delta(Collect(), p.log, 0.2, 0.3))
    assert p.log.support(delta.places) >= 0.3 * p.log.total and not delta.complete
    late = go(Postponing(Collect(), lambda c: -c.fit, "end"))
    assert set(late.places) == set(base.places)
    for oracle in ("lp", "token_dominance", "log_language"):
        got = go(Implicit(Collect(), p.log, oracle, remove_existing=True, universal=p.universal))
        assert set(got.places) <= set(base.places)
        if oracle != "lp":
            assert p.log.support(got.places) == p.log.support(base.places)

    def bigger_wins(c: Candidate, members):
        smaller = [m for m in members if set(m[0]) <= set(c.place[0]) and set(m[1]) <= set(c.place[1])]
        return ("replace", smaller) if smaller else ("accept", [])

    greedy = go(Greedy(Collect(), bigger_wins))
    assert not any(x != y and set(x[0]) <= set(y[0]) and set(x[1]) <= set(y[1]) for x in greedy.places for y in greedy.places[greedy.places.index(x) + 1 :])
    assert set(restart(p.log, p.labels, t, 0.5, lambda: Threshold(Uniwired(Collect(), release=True), 0.5), 2).places) <= set(base.places)


def test_budget_constraints_and_roots(spark, sf):
    p = ready(spark, sf, "events_day")
    t = tree_of(p.labels[1:-1], 4)
    a = walk(p.log, p.labels, t, 0.5, budget=Budget(max_candidates=50), batch=7, strategy="dfs")
    assert a.proposed == 50 and a.stopped == "candidates" and not a.complete
    assert a.places == walk(p.log, p.labels, t, 0.5, budget=Budget(max_candidates=50), batch=7, strategy="dfs").places
    free = walk(p.log, p.labels, t, 0.5, constraints=[not_anywhere("click"), max_post(2)])
    assert all("click" not in (*i, *o) and len(o) <= 2 for i, o in free.names())
    on_spark = discover(p.log, t, 0.5, initial=[not_anywhere("click"), max_post(2)])
    assert set(on_spark.places) == set(free.places)
    roots = [((i,), (o,)) for i in range(len(t.pre)) for o in range(len(t.post))]
    halves = [walk(p.log, p.labels, t, 0.5, roots=r) for r in (roots[::2], roots[1::2])]
    whole = walk(p.log, p.labels, t, 0.5)
    assert sorted(halves[0].places + halves[1].places) == sorted(whole.places)
    universe = _with_ids(t.seeds(spark), t, p.labels).select("pre", "post").withColumns({s: F.transform(s, lambda x: x.cast("string")) for s in ("pre", "post")})
    assert is_strengthening(not_in_pre("1"), not_anywhere("1"), universe) and not is_strengthening(not_anywhere("1"), not_in_pre("1"), universe)
    assert is_monotone_sequence([not_selfloop("1"), not_anywhere("1")], universe) and max_depth(3).holds((("a",), ("b", "c")))
    s = Stepper(t, "bfs")
    first = s.next(1)[0]
    s.visit(first, cut_post=True, cut_pre=True)
    assert not any(n != first and t.parent(n) == first for _, n in s.heap)


def test_grid_sharing_rebuilds_every_walk():
    rng = random.Random(11)
    for _ in range(6):
        b = block(random_log(rng))
        rows = []
        walk(b, LABELS, TREE, 0.5, cut_mode="both", observe=lambda c: rows.append({"place": c.place, "n_fit": c.counts[0], "n_under": c.counts[1], "n_over": c.counts[2], "depth": c.depth}))
        for r in rows:
            r["pre"] = tuple(sorted(TREE.pre.index(LABELS[i]) for i in r["place"][0]))
            r["post"] = tuple(sorted(TREE.post.index(LABELS[i]) for i in r["place"][1]))
        for tau in (0.5, 0.7, 1.0):
            for d in (2, 4, 6):
                t = tree_of(["a", "b", "c"], d)
                assert len(regrid(rows, TREE, b.total, tau, d)) == walk(b, LABELS, t, tau, cut_mode="both").proposed


def test_models_and_files(tmp_path):
    places = [(("o",), ("i",)), (("vo",), ("vi",)), ((S,), ("o", "vo")), (("i", "vi"), (E,)), (("d", "o", "vo"), ("d", "i", "vi"))]
    net = to_net(places, ["x"])
    assert isinstance(net, Net) and "x" in net.transitions
    assert from_pnml(to_pnml(net)) == [(tuple(sorted(i)), tuple(sorted(o))) for i, o in places]
    assert from_json(to_json(net, {"tau": 1}))[0] == places
    assert "digraph" in to_dot(net)
    assert deadlocks(net, 500) == []
    assert deadlocks(to_net([(("a",), (E,)), (("b",), ("a",))]), 500, bound=1) is not None
    assert diff(places, places[1:])["first"] == [places[0]]
    assert len(closed_world(net, ["y"]).places) == len(places) + 1
    assert Pipeline([("none", lambda p: p)]).run(places) == places


def test_merge_siblings():
    b = block([((S, "a", "c", E), 3), ((S, "b", "c", E), 2)])
    out = merge_siblings([ids("a", "c"), ids("b", "c")], b, 1.0)
    assert out == [ids(("a", "b"), ("c",))]


def test_config_presets_and_context(spark, sf):
    for c in PRESETS.values():
        assert Config.from_json(c.to_json()) == c
    ctx = Context()
    ctx.offer("x", lambda c: [1])
    assert ctx.get("x") is ctx.get("x")
    with pytest.raises(KeyError):
        ctx.get("y")
    p = ready(spark, sf, "conv")
    out = run(Config(log="conv", tau=0.8, max_depth=3), p)
    assert out.finished and 0 <= out.fitness <= 1 and 0 <= out.precision <= 1
    with pytest.raises(ValueError):
        run(Config(oracle="log_language", tau=1.0), p)


def test_supervision(spark, sf):
    p = ready(spark, sf, "conv")
    sup = Supervisor(level="full")
    found = walk(p.log, p.labels, tree_of(p.labels[1:-1], 3), 0.5, supervisor=sup)
    assert sup.progress()["visited"] <= 1 and len(sup.curve) == len(found.places)
    assert sup.event_table(spark).count() and sup.timing_table(spark).where("n > 0").count()


def test_baselines_on_the_two_trace_log(spark, sf):
    named = logs.variants(spark.createDataFrame([([S, "o", "d", "d", "i", E], 1), ([S, "vo", "d", "d", "d", "vi", E], 1)], "seq array<string>, freq long"))
    places = alpha.alpha(named)
    assert (("o",), ("i",)) not in places
    tree = cuts.cuts(named)
    assert tree.kind == "sequence" and cuts.accepts(tree, ("o", "d", "vi"))  # the block model loses the dependency
    assert region.region(named)
    p = ready(spark, sf, "longterm")
    found = run(Config(tau=1.0, max_depth=6, oracle="lp"), p, quality=False).names()
    assert (("o",), ("i",)) in found and (("vo",), ("vi",)) in found
    every = walk(p.log, p.labels, tree_of(p.labels[1:-1], 6), 1.0).names()
    assert (tuple(sorted(("d", "o", "vo"))), tuple(sorted(("d", "i", "vi")))) in every


def test_edge_cases(spark):
    schema = "case_id string, ord struct<o0:int>, activity string"
    with pytest.raises(Exception):
        prepare(spark.createDataFrame([], schema)).log.total
    p = prepare(spark.createDataFrame([("c", (0,), "a")], schema))
    assert walk(p.log, p.labels, tree_of(["a"], 1), 1.0).places == []
    assert walk(p.log, p.labels, tree_of(["a"], 4), 0.0).complete
    cases = spark.createDataFrame([("c",), ("empty",)], "case_id string")
    t = logs.traces(spark.createDataFrame([("c", (0,), "a")], schema), cases)
    assert sorted(len(r["seq"]) for r in t.collect()) == [2, 3]
    wide = spark.createDataFrame([("c", (i,), f"a{i:02d}") for i in range(70)], schema)
    q = prepare(wide)
    assert discover(q.log, tree_of(q.labels[1:-1], 2), 1.0).proposed == 71 * 71
    long = spark.createDataFrame([(["__START__", *["a", "b"] * 50_000, "__END__"], 1)], "seq array<string>, freq long").selectExpr("xxhash64(seq) variant_id", "seq", "freq")
    log = SparkLog(logs.encode(long, [S, "a", "b", E]), [S, "a", "b", E])
    assert log.counts([((1,), (2,))]).tolist() == [[1, 0, 0, 0]]


def test_suite_projection_cancel_and_extra_cuts(spark, sf):
    import threading

    from placeminer.operators.baselines.dfg import footprint_matrix
    from placeminer.operators.compose import CutWhere, explain, redundancy_cut
    from placeminer.operators.evaluate import counts_projected
    from placeminer.operators.suite import EvaluatorSuite, adds_something, at_most_arcs, reaches_threshold
    from placeminer.workloads import names_log

    p = ready(spark, sf, "events_day")
    t = tree_of(p.labels[1:-1], 3)
    places = [t.ids(n, p.labels) for n in t.subtree() if n[0] and n[1]]
    assert (counts_projected(p.log, places, 4) == p.log.counts(places)).all()
    suite = EvaluatorSuite([adds_something(), reaches_threshold(0.5), at_most_arcs(2)])
    left = suite.passing(p.log, places)
    assert suite.asked["arcs<=2"] == len(places) >= suite.asked["fit>=0.5"] >= suite.asked["adds_something"] >= len(left)
    stop = threading.Event()
    stop.set()
    assert walk(p.log, p.labels, t, 0.5, budget=Budget(cancel=stop), strategy="dfs", batch=5).stopped == "cancelled"
    cut = walk(p.log, p.labels, t, 0.5, CutWhere(Threshold(Collect(), 0.5), lambda c, m: redundancy_cut(p.log, c.place, m)))
    assert not cut.complete and cut.proposed <= walk(p.log, p.labels, t, 0.5).proposed
    node = ((0,), (0,))
    assert explain(t, node, 9, 0, 10, 0.5) == [("underfed", t.cut_mass(node, "post"))]
    assert footprint_matrix(names_log(spark, sf, "conv"), p.labels[:2]).count()
    assert abs(logs.estimated_variants(names_log(spark, sf, "events_day")) / names_log(spark, sf, "events_day").count() - 1) < 0.1
    silent = prepare(events(spark, sf, "conv"), pre=[lambda e: e.where("activity <> 'system'")])
    assert "system" not in silent.labels


def test_planted_dependency_is_found(spark, sf):
    p = ready(spark, sf, "lifecycle_planted")
    found = run(Config(log="lifecycle_planted", tau=1.0, max_depth=2, oracle="lp"), p, quality=False).names()
    assert all(((f"place:{x}",), (f"close:{x}",)) in found for x in ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"))


def test_a_constraint_that_arrives_on_the_way_prunes_its_branches():
    steps = Stepper(TREE, "dfs")
    seen, late = [], None
    while nodes := steps.next(1):
        seen.append(nodes[0])
        steps.visit(nodes[0])
        if len(seen) == 10:
            steps.constraints.append(not_anywhere("a"))
            late = len(seen)
    names = [TREE.names(n) for n in seen]
    assert all("a" not in (*i, *o) for i, o in names[late:])
    free = tree_of(["b", "c"], 8)
    assert {n for n in names[late:]} | {n for n in names[:late] if "a" not in (*n[0], *n[1])} == {free.names(n) for n in free.subtree() if n[0] and n[1]}
    assert len(names) == len(set(names))


def test_constraints_filter_like_the_tree():
    """Generating under a monotone constraint gives what filtering the whole tree gives."""
    for c in (not_in_pre("a"), not_selfloop("b"), not_anywhere("c"), max_post(2), max_depth(4)):
        steps = Stepper(TREE, "bfs", constraints=[c])
        got = []
        while nodes := steps.next(5):
            got += nodes
            for n in nodes:
                steps.visit(n)
        assert sorted(got) == sorted(n for n in TREE.subtree() if n[0] and n[1] and c.holds(TREE.names(n)))
