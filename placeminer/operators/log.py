"""Behaviors, variants and dictionaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.places import END, START


def traces(events: DataFrame, cases: DataFrame | None = None) -> DataFrame:
    """case_id, seq (labels between the markers).

    One shuffle by case. ``cases`` (case_id) adds cases without events as behaviors of length two.
    """
    body = F.transform(F.array_sort(F.collect_list(F.struct("ord", "activity"))), lambda x: x["activity"])
    out = events.groupBy("case_id").agg(body.alias("body"))
    if cases is not None:
        out = cases.select("case_id").distinct().join(out, "case_id", "left")
    empty = F.array().cast("array<string>")
    return out.select("case_id", F.concat(F.array(F.lit(START)), F.coalesce("body", empty), F.array(F.lit(END))).alias("seq"))


def variants(behaviors: DataFrame, check: bool = False) -> DataFrame:
    """variant_id, seq, freq: the log as a multiset (P2). ``check`` refuses colliding ids."""
    weight = F.sum("freq") if "freq" in behaviors.columns else F.count(F.lit(1))
    out = behaviors.groupBy("seq").agg(weight.alias("freq")).select(F.xxhash64("seq").alias("variant_id"), "seq", "freq")
    if check and out.groupBy("variant_id").count().where("count > 1").limit(1).count():
        raise ValueError("two variants share an id")
    return out


def alphabet(log: DataFrame) -> list[str]:
    """Labels of a log without the markers, sorted (driver; alphabets are small)."""
    rows = log.select(F.explode("seq").alias("a")).where(~F.col("a").isin(START, END)).distinct().collect()
    return sorted(r["a"] for r in rows)


def encode(log: DataFrame, labels: list[str]) -> DataFrame:
    """Sequences as positions in ``labels``, which must hold the markers."""
    table = F.create_map(*[x for i, a in enumerate(labels) for x in (F.lit(a), F.lit(i))])
    return log.withColumn("seq", F.transform("seq", lambda a: table[a]))


def sides(labels: list[str], pre: list[str] | None = None, post: list[str] | None = None, blacklist: tuple[str, ...] = ()) -> tuple[list[str], list[str]]:
    """Activities of presets (never the end marker) and of postsets (never the start marker), in the order of ``labels``."""
    banned = set(blacklist)
    a = [x for x in ([START, *labels] if pre is None else pre) if x != END and x not in banned]
    b = [x for x in ([*labels, END] if post is None else post) if x != START and x not in banned]
    return list(dict.fromkeys(a)), list(dict.fromkeys(b))


def stats(log: DataFrame) -> DataFrame:
    """n_traces, n_variants, n_activities, n_events, max_len, unique_share; markers do not count.

    Labels are counted from exploded events, so that no set of sequences meets in one task.
    """
    labels = log.select(F.explode(F.array_distinct("seq")).alias("a")).where(~F.col("a").isin(START, END)).agg(F.count_distinct("a").alias("n_activities"))
    rest = log.agg(F.sum("freq").alias("n_traces"), F.count(F.lit(1)).alias("n_variants"), F.sum(F.col("freq") * (F.size("seq") - 2)).alias("n_events"), F.max(F.size("seq") - 2).alias("max_len"))
    # One row beside one row.
    return rest.crossJoin(F.broadcast(labels)).select("n_traces", "n_variants", "n_activities", "n_events", "max_len", (F.col("n_variants") / F.col("n_traces")).alias("unique_share"))


def overview(log: DataFrame) -> DataFrame:
    """The four counts of the log table."""
    return stats(log).select(F.col("n_traces").alias("n_cases"), "n_variants", "n_activities", "n_events")


def project(log: DataFrame, keep: list) -> DataFrame:
    """The log restricted to some activities, compressed again (P8); markers must be named to stay."""
    wanted = F.array(*map(F.lit, keep))
    return variants(log.select(F.filter("seq", lambda a: F.array_contains(wanted, a)).alias("seq"), "freq"))


def subset(log: DataFrame, top_mass: float | None = None, where: Column | None = None, fraction: float | None = None, seed: int = 0) -> DataFrame:
    """Some of the variants: the most frequent ones that make up ``top_mass``, those that pass, or a sample."""
    out = log.where(where) if where is not None else log
    if fraction is not None:
        out = out.where(F.pmod(F.xxhash64(F.lit(seed), "seq"), F.lit(1 << 20)) < int(fraction * (1 << 20)))
    if top_mass is not None:
        # Frequencies, not variants, are ordered: their number is far smaller.
        mass = out.groupBy("freq").agg(F.sum("freq").alias("m"))
        total = F.sum("m").over(W.partitionBy(F.lit(1)))
        before = F.sum("m").over(W.partitionBy(F.lit(1)).orderBy(F.desc("freq")).rowsBetween(W.unboundedPreceding, -1))
        keep = mass.where("freq IS NOT NULL").select("freq", (F.coalesce(before, F.lit(0)) < top_mass * total).alias("keep")).where("keep").select("freq")
        out = out.join(F.broadcast(keep), "freq", "left_semi").select(*log.columns)
    return out


def by_segment(events: DataFrame, segment: Column | str) -> DataFrame:
    """segment, seq, freq: one log per segment (P11); events must carry the segment, constant per case."""
    s = F.col(segment) if isinstance(segment, str) else segment
    body = F.transform(F.array_sort(F.collect_list(F.struct("ord", "activity"))), lambda x: x["activity"])
    seqs = events.groupBy(s.alias("segment"), "case_id").agg(F.concat(F.array(F.lit(START)), body, F.array(F.lit(END))).alias("seq"))
    return seqs.groupBy("segment", "seq").agg(F.count(F.lit(1)).alias("freq"))


def preview(log: DataFrame, n: int = 20) -> DataFrame:
    """The most frequent variants as text."""
    return log.select(F.concat_ws(">", "seq").alias("variant"), "freq").orderBy(F.desc("freq"), "variant").limit(n)


def estimated_variants(behaviors: DataFrame, error: float = 0.02) -> int:
    """About how many variants there are, before they are grouped: tells whether compression pays."""
    return behaviors.agg(F.approx_count_distinct(F.xxhash64("seq"), error)).first()[0]
