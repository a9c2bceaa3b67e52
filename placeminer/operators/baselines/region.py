"""A region miner: one linear program a causal pair over the log's prefixes."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lp import feasible
from .dfg import footprint

Names = tuple[tuple[str, ...], tuple[str, ...]]


def prefix_counts(log: DataFrame, acts: list[str]) -> tuple[list[tuple[tuple[int, ...], int]], list[tuple[int, ...]]]:
    """Distinct (activity counts of a prefix, next activity) and activity counts of whole traces; few beside the log."""
    at = {a: i for i, a in enumerate(acts)}
    pos = log.select("seq", F.explode(F.sequence(F.lit(1), F.size("seq"))).alias("k"))
    def times(seq, a: str):
        return F.size(F.filter(seq, lambda x: x == a))

    count = F.array(*[times(F.slice("seq", F.lit(1), F.col("k") - 1), a) for a in acts])
    rows = pos.select(count.alias("c"), F.get("seq", F.col("k") - 1).alias("a")).distinct().collect()
    full = log.select(F.array(*[times("seq", a) for a in acts]).alias("c")).distinct().collect()
    return [(tuple(r["c"]), at[r["a"]]) for r in rows], [tuple(r["c"]) for r in full]


def region(log: DataFrame, max_weight: int = 1) -> list[Names]:
    """For each causal pair (a, b) a place from a to b that every trace of the log fits, found by linear programs.

    Unknowns are the arcs into the place from each activity and out of it to each, at most one each; every prefix must
    leave enough tokens for its next activity, every trace must end without. Arcs beyond the pair are dropped one by one while a
    solution remains, which gives small places; solutions with fractions are skipped.
    """
    acts = sorted({r["a"] for r in log.select(F.explode("seq").alias("a")).distinct().collect()})
    prefixes, full = prefix_counts(log, acts)
    n = len(acts)
    causal = sorted((r["src"], r["dst"]) for r in footprint(log).where("relation = '->'").collect())
    out: list[Names] = []
    for a, b in causal:
        banned: set[int] = set()
        solution = _solve(n, prefixes, full, acts.index(a), n + acts.index(b), banned)
        if solution is None:
            continue
        for k in range(2 * n):
            if k not in (acts.index(a), n + acts.index(b)) and solution[k]:
                again = _solve(n, prefixes, full, acts.index(a), n + acts.index(b), banned | {k})
                if again is not None:
                    banned.add(k)
                    solution = again
        if all(x in (0, 1) for x in solution):
            place = tuple(acts[i] for i in range(n) if solution[i]), tuple(acts[i] for i in range(n) if solution[n + i])
            if place not in out:
                out.append(place)
    return out


def _solve(n: int, prefixes, full, must_in: int, must_out: int, banned: set[int]) -> list[Fraction] | None:
    rows, kinds, rhs = [], [], []
    for c, a in prefixes:
        used = list(c)
        used[a] += 1
        rows.append([*c, *[-x for x in used]])
        kinds.append(">=")
        rhs.append(0)
    for c in full:
        rows.append([*c, *[-x for x in c]])
        kinds.append("=")
        rhs.append(0)
    for k in range(2 * n):
        unit = [int(j == k) for j in range(2 * n)]
        rows.append(unit)
        kinds.append("=" if k in banned or k in (must_in, must_out) else "<=")
        rhs.append(0 if k in banned else 1)
    return feasible(rows, kinds, rhs)
