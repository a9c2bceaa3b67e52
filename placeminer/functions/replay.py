"""Replay of a place over a trace as one column expression."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .places import _col


def _has(activities: Column, a: Column) -> Column:
    return F.array_contains(activities, a).cast("int")


def trace_state(seq: Column | str, pre: Column | str, post: Column | str) -> Column:
    """struct(fit, under, over, unbalanced, min_slack, final).

    An event first consumes (if it is in the postset) and must not drive the tokens below zero, then produces (if it is
    in the preset); so a self-loop needs a token from before. Underfed: some consumption was not covered.
    Overfed: tokens are left at the end. Unbalanced: tokens are left or missing at the end.
    """
    seq, pre, post = _col(seq), _col(pre), _col(post)
    zero = F.struct(F.lit(0).alias("tokens"), F.lit(0).alias("slack"))

    def step(s: Column, a: Column) -> Column:
        left = s["tokens"] - _has(post, a)
        return F.struct((left + _has(pre, a)).alias("tokens"), F.least(s["slack"], left).alias("slack"))

    def verdict(s: Column) -> Column:
        return F.struct(
            ((s["slack"] >= 0) & (s["tokens"] == 0)).alias("fit"), (s["slack"] < 0).alias("under"), (s["tokens"] > 0).alias("over"),
            (s["tokens"] != 0).alias("unbalanced"), s["slack"].alias("min_slack"), s["tokens"].alias("final"),
        )

    return F.aggregate(seq, zero, step, verdict)


def place_fits(seq: Column | str, pre: Column | str, post: Column | str) -> Column:
    return trace_state(seq, pre, post)["fit"]


def token_series(seq: Column | str, pre: Column | str, post: Column | str) -> Column:
    """Tokens after each event (V7)."""
    seq, pre, post = _col(seq), _col(pre), _col(post)
    last = lambda s: F.coalesce(F.element_at(s, -1), F.lit(0))
    start = F.array().cast("array<int>")
    return F.aggregate(seq, start, lambda s, a: F.concat(s, F.array(F.when(F.size(s) > 0, last(s)).otherwise(0) - _has(post, a) + _has(pre, a))))


def token_replay(seq: Column | str, pre: Column | str, post: Column | str) -> Column:
    """struct(produced, consumed, missing, remaining) with missing tokens added when they are needed."""
    seq, pre, post = _col(seq), _col(pre), _col(post)
    zero = F.struct(*[F.lit(0).alias(n) for n in ("tokens", "produced", "consumed", "missing")])

    def step(s: Column, a: Column) -> Column:
        need = _has(post, a)
        lack = F.greatest(need - s["tokens"], F.lit(0))
        return F.struct(
            (s["tokens"] + lack - need + _has(pre, a)).alias("tokens"), (s["produced"] + _has(pre, a)).alias("produced"),
            (s["consumed"] + need).alias("consumed"), (s["missing"] + lack).alias("missing"),
        )

    return F.aggregate(seq, zero, step, lambda s: F.struct(s["produced"].alias("produced"), s["consumed"].alias("consumed"), s["missing"].alias("missing"), s["tokens"].alias("remaining")))
