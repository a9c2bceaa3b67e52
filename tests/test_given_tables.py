"""Queries that once made up their data follow the given tables."""

import duckdb
import pytest
from pyspark.sql import functions as F

from placeminer.functions.places import START
from placeminer.workloads import oracle_sql, queries, ready


def same_as_sql(rows, sf, name) -> bool:
    c = duckdb.connect()
    for t in ("events", "orders", "lineitem"):
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return sorted(map(repr, map(tuple, rows))) == sorted(map(repr, c.sql(oracle_sql()[name]).fetchall()))


def test_candidate_tree_is_over_the_activities_of_the_log(spark, sf):
    rows = queries()["candidate_tree_example"](spark, sf).collect()
    inner = ready(spark, sf, "events_day").labels[1:-1]
    assert len(rows) == 4 ** len(inner) and {"view", "purchase"} <= set(inner)
    assert [(r["pre"], r["post"]) for r in rows if r["depth"] == 2] == [(START, inner[0])]
    assert same_as_sql(rows, sf, "candidate_tree_example")


def test_order_types_decide_invoice_types(spark, sf):
    rows = queries()["longterm_dependency"](spark, sf).collect()
    n = spark.read.parquet(f"{sf}/orders.parquet").count()
    found = {(r["pre"], r["post"]) for r in rows}
    assert {("o", "i"), ("vo", "vi"), (START, "o,vo")} <= found and ("o", "vi") not in found
    assert all(r["n_fit"] == r["n_total"] == n for r in rows)


def test_deadlocks_are_those_of_the_net_of_the_orders(spark, sf, tmp_path):
    row = queries()["deadlocks_longterm"](spark, sf).first()
    assert row["complete"] and row["n_deadlocks"] == 0
    # Orders of one type alone have another net.
    spark.read.parquet(f"{sf}/orders.parquet").withColumn("o_orderpriority", F.lit("1-URGENT")).write.parquet(f"{tmp_path}/orders.parquet")
    spark.read.parquet(f"{sf}/lineitem.parquet").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert queries()["deadlocks_longterm"](spark, str(tmp_path)).first()["n_places"] < row["n_places"]


def test_examples_are_counted_on_given_logs(spark, sf):
    rows = queries()["micro_examples"](spark, sf).collect()
    totals = {r["log"]: r["n_total"] for r in rows}
    assert totals == {"order_types": spark.read.parquet(f"{sf}/orders.parquet").count(), "events_day": ready(spark, sf, "events_day").log.total}
    assert same_as_sql(rows, sf, "micro_examples")


@pytest.mark.parametrize("name", ["collected_places", "controlled_spearman", "controlled_spearman_depth", "cube_runs", "fastest_top_decile", "min_depth_at_max", "pareto_fit_prec", "pareto_fit_size"])
def test_statistics_of_the_runs_over_the_events(spark, sf, name):
    rows = queries()[name](spark, sf).collect()
    assert {r["log"] for r in rows} - {None} == {"events_day", "events_sess"}
    assert same_as_sql(rows, sf, name)
