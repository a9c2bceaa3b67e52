"""Statistics over runs. ``runs`` has one row per log, tau, depth, oracle."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def runtimes(runs: DataFrame) -> DataFrame:
    """Per log: shares of timeouts and 10th percentile, mean, 90th percentile, deviation of search, post and total seconds."""
    r = runs.withColumn("t_total", F.col("t_search") + F.col("t_post"))
    cols = [f(c).alias(f"{c[2:]}_{n}") for c in ("t_search", "t_post", "t_total") for n, f in (("p10", lambda c: F.percentile(c, 0.1)), ("mean", F.avg), ("p90", lambda c: F.percentile(c, 0.9)), ("std", F.stddev_samp))]
    share = lambda c, n: (100 * F.avg(F.col(c).cast("double"))).alias(n)
    return r.groupBy("log").agg(F.count(F.lit(1)).alias("runs"), share("stopped_search", "search_timeouts"), share("dnf", "total_timeouts"), *cols)


def place_medians(runs: DataFrame) -> DataFrame:
    """Per log: median of collected places, of those in runs that did not finish, and after post-processing."""
    m = lambda c: F.percentile(c, 0.5)
    return runs.groupBy("log").agg(m(F.col("collected")).alias("collected"), m(F.when(F.col("dnf"), F.col("collected"))).alias("collected_dnf"), m(F.when(~F.col("dnf"), F.col("after_post"))).alias("after_post"))


def pareto(runs: DataFrame, x: str, y: str, top: float = 0.25, less_y: bool = False, less_x: bool = False) -> DataFrame:
    """Runs in the best ``top`` share by F1 of their log that no other such run beats on both measures (A10)."""
    w = W.partitionBy("log").orderBy(F.desc("f1"))
    best = runs.where(F.col("f1").isNotNull()).withColumn("__r", F.percent_rank().over(w)).where(F.col("__r") <= top).drop("__r")
    sx, sy = (-1 if less_x else 1), (-1 if less_y else 1)
    points = best.select("log", (sx * F.col(x)).alias("x"), (sy * F.col(y)).alias("y")).distinct()
    a, b = points.alias("a"), points.alias("b")
    beaten = (F.col("a.log") == F.col("b.log")) & (F.col("b.x") >= F.col("a.x")) & (F.col("b.y") >= F.col("a.y")) & ((F.col("b.x") > F.col("a.x")) | (F.col("b.y") > F.col("a.y")))
    front = a.join(b, beaten, "left_anti")
    return front.select("log", (sx * F.col("x")).alias(x), (sy * F.col("y")).alias(y))


def fastest_top(runs: DataFrame, metric: str, top: float = 0.10) -> DataFrame:
    """Per log: percentile rank (by total time) of the fastest run among the best ``top`` share by the metric."""
    r = runs.where(F.col(metric).isNotNull()).withColumn("t_total", F.col("t_search") + F.col("t_post"))
    ranked = r.withColumn("q", F.percent_rank().over(W.partitionBy("log").orderBy(F.desc(metric)))).withColumn("speed", F.percent_rank().over(W.partitionBy("log").orderBy("t_total")))
    return ranked.where(F.col("q") <= top).groupBy("log").agg((100 * F.min("speed")).alias("percentile"))


def min_depth(runs: DataFrame, metric: str) -> DataFrame:
    """Per log and oracle: mean over tau of the least depth at which the metric is already at its maximum."""
    w = W.partitionBy("log", "oracle", "tau")
    at = runs.where(F.col(metric).isNotNull()).withColumn("m", F.max(metric).over(w)).where(F.col(metric) == F.col("m"))
    return at.groupBy("log", "oracle", "tau").agg(F.min("depth").alias("d")).groupBy("log", "oracle").agg(F.avg("d").alias("mean_depth"))


def controlled_spearman(runs: DataFrame, x: str, y: str, control: list[str]) -> DataFrame:
    """Per log: mean over the groups of the control columns of the rank correlation of x and y; constant groups have none and are counted."""
    keys = ["log", *control]

    def ranked(df: DataFrame, c: str) -> DataFrame:
        """Average ranks over ties."""
        return df.withColumn(f"r_{c}", F.rank().over(W.partitionBy(*keys).orderBy(c)) + (F.count(F.lit(1)).over(W.partitionBy(*keys, c)) - 1) / 2)

    both = ranked(ranked(runs.where(F.col(x).isNotNull() & F.col(y).isNotNull()), x), y)
    w = W.partitionBy(*keys)
    varies = (F.min(f"r_{x}").over(w) < F.max(f"r_{x}").over(w)) & (F.min(f"r_{y}").over(w) < F.max(f"r_{y}").over(w))
    each = both.withColumn("__x", F.when(varies, F.col(f"r_{x}"))).groupBy(*keys).agg(F.corr("__x", f"r_{y}").alias("rho"))
    return each.groupBy("log").agg(F.avg("rho").alias("rho"), F.count("rho").alias("groups"), F.count_if(F.col("rho").isNull()).alias("constant"))


def stagnation(curve: DataFrame) -> DataFrame:
    """Per run: when the last place was accepted, against the end of the walk (A14). ``curve``: run_id, seconds, evaluated, size, end_seconds."""
    return curve.groupBy("run_id").agg(F.max("seconds").alias("last_change"), F.max("evaluated").alias("evaluated_then"), F.max("size").alias("size"), F.max("end_seconds").alias("end"))


def cube(runs: DataFrame) -> DataFrame:
    """Totals over all groupings of log, tau and depth."""
    return runs.cube("log", "tau", "depth").agg(F.count(F.lit(1)).alias("n"), F.sum("collected").alias("collected"))
