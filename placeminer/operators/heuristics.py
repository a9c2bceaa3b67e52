"""Scores that order candidates."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Names = tuple[tuple[str, ...], tuple[str, ...]]


def place_size(p: Names) -> float:
    """Number of activities on either side (C11)."""
    return float(len(set(p[0]) | set(p[1])))


def interest(log: DataFrame, kind: str = "eventually") -> DataFrame:
    """pre_act, post_act, score, n (C12, C13): traces in which some ``pre_act`` is followed by some later (or the next) ``post_act``,
    over the larger of their trace counts. ``log`` holds labels (seq, freq)."""
    rows = log.select(F.xxhash64("seq").alias("v"), "freq", "seq")
    occ = rows.select("freq", F.explode(F.array_distinct("seq")).alias("a")).groupBy("a").agg(F.sum("freq").alias("occ"))
    if kind == "eventually":
        ends = rows.select("v", "freq", F.posexplode("seq").alias("pos", "a")).groupBy("v", "a").agg(F.first("freq").alias("freq"), F.min("pos").alias("lo"), F.max("pos").alias("hi"))
        pairs = ends.alias("x").join(ends.alias("y"), (F.col("x.v") == F.col("y.v")) & (F.col("x.lo") < F.col("y.hi"))).select(F.col("x.a").alias("pre_act"), F.col("y.a").alias("post_act"), F.col("x.freq").alias("freq"))
    else:
        steps = F.array_distinct(F.zip_with(F.slice("seq", F.lit(1), F.size("seq") - 1), F.slice("seq", F.lit(2), F.size("seq") - 1), lambda a, b: F.struct(a.alias("a"), b.alias("b"))))
        pairs = rows.select("freq", F.explode(steps).alias("s")).select(F.col("s.a").alias("pre_act"), F.col("s.b").alias("post_act"), "freq")
    counted = pairs.groupBy("pre_act", "post_act").agg(F.sum("freq").alias("n"))
    o = F.broadcast(occ)
    joined = counted.join(o.withColumnRenamed("a", "pre_act").withColumnRenamed("occ", "op"), "pre_act").join(o.withColumnRenamed("a", "post_act").withColumnRenamed("occ", "oq"), "post_act")
    return joined.select("pre_act", "post_act", (F.col("n") / F.greatest("op", "oq")).alias("score"), "n")


def interest_heuristic(log: DataFrame, kind: str = "eventually") -> Callable[[Names], float]:
    """Less is better: minus the mean score over the place's pairs (the matrix is alphabet x alphabet)."""
    table = {(r["pre_act"], r["post_act"]): r["score"] for r in interest(log, kind).collect()}
    return lambda p: -sum(table.get((a, b), 0.0) for a in p[0] for b in p[1]) / max(1, len(p[0]) * len(p[1]))


def by_gain(nodes: list, gain: Callable) -> list:
    """Children with high expected gain first."""
    return sorted(nodes, key=lambda n: -gain(n))
