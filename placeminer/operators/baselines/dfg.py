"""Directly-follows graph and footprint."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dfg(log: DataFrame, min_share: float = 0.0) -> DataFrame:
    """src, dst, n of a log (seq, freq), markers included; edges below ``min_share`` of the most frequent one are left out."""
    steps = F.zip_with(F.slice("seq", F.lit(1), F.size("seq") - 1), F.slice("seq", F.lit(2), F.size("seq") - 1), lambda a, b: F.struct(a.alias("src"), b.alias("dst")))
    out = log.select("freq", F.explode(steps).alias("s")).groupBy("s.src", "s.dst").agg(F.sum("freq").alias("n"))
    if min_share > 0:
        top = out.agg(F.max("n").alias("top"))
        out = out.crossJoin(F.broadcast(top)).where(F.col("n") >= min_share * F.col("top")).drop("top")
    return out


def footprint(log: DataFrame) -> DataFrame:
    """src, dst, relation for all pairs of activities: ``->``, ``<-``, ``||`` or ``#``."""
    g = dfg(log).select("src", "dst", F.lit(True).alias("there"))
    acts = log.select(F.explode("seq").alias("a")).distinct()
    pairs = acts.withColumnRenamed("a", "src").join(F.broadcast(acts.withColumnRenamed("a", "dst")))  # alphabet x alphabet
    back = g.select(F.col("src").alias("dst"), F.col("dst").alias("src"), F.lit(True).alias("back"))
    both = pairs.join(F.broadcast(g), ["src", "dst"], "left").join(F.broadcast(back), ["src", "dst"], "left")
    there, back_ = F.col("there").isNotNull(), F.col("back").isNotNull()
    return both.select("src", "dst", F.when(there & back_, "||").when(there, "->").when(back_, "<-").otherwise("#").alias("relation"))


def footprint_matrix(log: DataFrame, labels: list[str]) -> DataFrame:
    """The footprint with one column per activity."""
    return footprint(log).groupBy("src").pivot("dst", labels).agg(F.first("relation"))
