"""The driver's walk and the distributed one agree in every option."""

import pytest

from placeminer.operators.compose import Budget, Collect, CutWhere, Delta, Greedy, Implicit, Postponing, Threshold, Uniwired
from placeminer.operators.constraints import heuristic_below, max_post, not_anywhere
from placeminer.operators.heuristics import place_size
from placeminer.plans.config import Config
from placeminer.plans.propose import discover, walk
from placeminer.plans.run import search
from placeminer.plans.supervise import Supervisor
from placeminer.operators.tree import tree_of
from placeminer.workloads import ready

CASES = {
    "base": (lambda p: Collect(), {}, []),
    "pre_first": (lambda p: Collect(), {"prefer": "pre"}, []),
    "every_cut": (lambda p: Collect(), {"cut_mode": "both"}, []),
    "uniwired": (lambda p: Uniwired(Collect()), {}, []),
    "postponing": (lambda p: Postponing(Uniwired(Collect()), lambda c: -c.depth), {}, []),
    "delta": (lambda p: Delta(Collect(), p.log, 0.2, 0.3), {}, []),
    "implicit": (lambda p: Implicit(Collect(), p.log, "log_language"), {}, []),
    "greedy": (lambda p: Greedy(Collect(), lambda c, m: ("replace", m[:1]) if len(m) > 3 else ("accept", [])), {}, []),
    "extra_cuts": (lambda p: CutWhere(Collect(), lambda c, m: len(c.place[0]) + c.place[1][0] > 3), {}, []),
    "candidates": (lambda p: Collect(), {"budget": {"max_candidates": 40}}, []),
    "candidates_and_wires": (lambda p: Uniwired(Collect()), {"budget": {"max_candidates": 45}}, []),
    "places": (lambda p: Collect(), {"budget": {"max_places": 3}}, []),
    "stagnation": (lambda p: Uniwired(Collect()), {"budget": {"stagnation": 1}}, []),
    "constraints": (lambda p: Collect(), {}, [not_anywhere("click"), max_post(1)]),
    "heuristic": (lambda p: Collect(), {}, [not_anywhere("click"), heuristic_below("size", place_size, 2.0, True)]),
    "not_monotone": (lambda p: Collect(), {}, [heuristic_below("odd", lambda x: float(len(x[0])), 1.0, False)]),
}


@pytest.mark.parametrize("name", CASES)
def test_both_walks_agree(spark, sf, name):
    make, options, constraints = CASES[name]
    p = _prepared(spark, sf)
    options = dict(options)
    limits = options.pop("budget", {})
    t = tree_of(p.labels[1:-1], 4, prefer=options.pop("prefer", "post"))
    a, b = Supervisor(), Supervisor()
    here = walk(p.log, p.labels, t, 0.5, Threshold(make(p), 0.5), budget=Budget(**limits), constraints=constraints, supervisor=a, **options)
    there = discover(p.log, t, 0.5, Threshold(make(p), 0.5), budget=Budget(**limits), initial=constraints, supervisor=b, **options)
    assert here.places == there.places
    assert (here.proposed, here.stopped, here.complete, here.by_depth) == (there.proposed, there.stopped, there.complete, there.by_depth)
    assert a.events == b.events and a.considered == b.considered and a.depth == b.depth


def test_options_change_what_is_found(spark, sf):
    """The cases above are not all the same run."""
    p = _prepared(spark, sf)
    t = tree_of(p.labels[1:-1], 4)
    runs = {n: walk(p.log, p.labels, t, 0.5, Threshold(make(p), 0.5), budget=Budget(**o.get("budget", {})), constraints=c) for n, (make, o, c) in CASES.items()}
    assert len({(r.proposed, tuple(r.places)) for r in runs.values()}) >= 10


def test_a_distributed_search_refuses_other_orders(spark, sf):
    with pytest.raises(ValueError):
        search(Config(strategy="dfs", max_depth=2), _prepared(spark, sf), distributed=True)


_KNOWN: dict = {}


def _prepared(spark, sf):
    if "p" not in _KNOWN:
        _KNOWN["p"] = ready(spark, sf, "events_day")
    return _KNOWN["p"]


def test_no_plan_stays_cached(spark, sf):
    from placeminer.workloads import queries

    held = lambda: spark.sparkContext._jsc.getPersistentRDDs().size()
    before = held()
    ready(spark, sf, "conv")
    for name in ("ordering_ablation", "passing_by_tau", "uniwired_compose_conv"):
        queries()[name](spark, sf).collect()
    assert held() == before
