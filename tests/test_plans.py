"""The physical plans that scale rests on."""

import re

from pyspark.sql import functions as F

from placeminer.operators import log as logs
from placeminer.operators.baselines.dfg import dfg
from placeminer.operators.evaluate import fitness
from placeminer.operators.tree import tree_of
from placeminer.plans.propose import _with_ids
from placeminer.sources.logs import events
from placeminer.workloads import ready


def plan(df) -> str:
    """What runs, without the plans of what is cached."""
    return df._jdf.queryExecution().executedPlan().toString().split("InMemoryRelation")[0]


def exchanges(df) -> int:
    return len(re.findall(r"\bExchange (?:hash|range|Round|Single)", plan(df)))


def test_one_shuffle_to_traces_and_one_to_variants(spark, sf):
    e = events(spark, sf, "events_day")
    t = logs.traces(e)
    assert exchanges(e) == 0 and exchanges(t) == 1 and exchanges(logs.variants(t)) == 2
    assert exchanges(dfg(logs.variants(t))) == 3


def test_a_filter_reaches_the_scan(spark, sf):
    t = logs.traces(events(spark, sf, "lineflags").where("case_id = '7'"))
    assert "PushedFilters" in plan(t)
    from placeminer.sources.spec import LogSpec

    spec = LogSpec("x", ("l_orderkey",), "l_returnflag", ("l_linenumber",), where="l_orderkey < 100")
    assert "LessThan(l_orderkey,100)" in plan(spec.events(spark.read.parquet(f"{sf}/lineitem.parquet")))


def test_children_need_no_shuffle_or_join(spark):
    t = tree_of(["a", "b", "c"], 6)
    kids = t.spread(t.seeds(spark).withColumns({"cut_post": F.lit(False), "cut_pre": F.lit(False)}))
    p = plan(t.spread(kids.withColumns({"cut_post": F.lit(False), "cut_pre": F.lit(False)})))
    assert "Exchange hash" not in p and "SortMergeJoin" not in p and "Cartesian" not in p


def test_replay_ships_partial_sums_only(spark, sf):
    p = ready(spark, sf, "conv")
    t = tree_of(p.labels[1:-1], 2)
    table = _with_ids(t.seeds(spark), t, p.labels)
    part = p.log._partial([((0,), (1,)), ((1,), (2,))])
    assert exchanges(part) == 1 and "Cartesian" not in plan(part)
    assert "Cartesian" not in plan(fitness(p.log, table, "arrow"))
    wide = fitness(p.log, table, "frontier")
    assert exchanges(wide) == 0 and wide.count() == 16
