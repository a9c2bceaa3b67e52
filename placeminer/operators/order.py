"""Orders of activities."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.places import END, START

STRATEGIES = ("first_index", "lexicographic", "random", "frequency", "trace_frequency", "mean_occurrences", "explicit")


def scores(log: DataFrame) -> DataFrame:
    """activity, mean_first, n_cases, n_events; positions count from 1 with the start marker, means weigh variants by frequency."""
    rows = log.select(F.xxhash64("seq").alias("v"), "freq", F.posexplode("seq").alias("pos", "activity"))
    each = rows.groupBy("v", "activity").agg(F.first("freq").alias("freq"), F.min(F.col("pos") + 1).alias("first"), F.count(F.lit(1)).alias("k"))
    return each.groupBy("activity").agg((F.sum(F.col("first") * F.col("freq")) / F.sum("freq")).alias("mean_first"), F.sum("freq").alias("n_cases"), F.sum(F.col("k") * F.col("freq")).alias("n_events"))


def rank(log: DataFrame, strategy: str = "first_index", descending: bool = False, seed: int = 0, explicit: list[str] | None = None) -> DataFrame:
    """activity, score, rank (from 0); ties go by label."""
    s = scores(log)
    score = {
        "first_index": F.col("mean_first"), "lexicographic": F.lit(0.0), "random": F.pmod(F.xxhash64(F.lit(seed), "activity"), F.lit(1 << 40)).cast("double"),
        "frequency": F.col("n_events").cast("double"), "trace_frequency": F.col("n_cases").cast("double"), "mean_occurrences": F.col("n_events") / F.col("n_cases"),
        "explicit": F.coalesce(*[F.when(F.col("activity") == a, F.lit(float(i))) for i, a in enumerate(explicit or [])], F.lit(float("inf"))),
    }[strategy]
    scored = s.select("activity", score.alias("score"))
    # One row per activity: the window is over the alphabet.
    w = W.orderBy(F.desc("score") if descending else F.asc("score"), "activity")
    return scored.withColumn("rank", F.row_number().over(w) - 1)


def ordered(log: DataFrame, strategy: str = "first_index", **options) -> list[str]:
    """Inner activities in order (driver)."""
    return [r["activity"] for r in rank(log, strategy, **options).orderBy("rank").collect() if r["activity"] not in (START, END)]
