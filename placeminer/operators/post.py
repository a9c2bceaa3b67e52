"""Clean-up of a found set of places."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .compose import reaches
from .implicit import dominance_fold, log_language_kept
from .kernel import Place
from .lp import lp_implicit, screen

Step = Callable[[list[Place]], list[Place]]


class OutOfTime(Exception):
    """A hard limit of post-processing was reached; what was done until then is kept."""


@dataclass
class Pipeline:
    """Steps with one hard time limit (Q1). Any callable from places to places is a step, a model repair too (Q10)."""

    steps: list[tuple[str, Step]]
    seconds: float | None = None
    finished: bool = True
    sizes: list[tuple[str, int]] = field(default_factory=list)

    def run(self, places: list[Place]) -> list[Place]:
        began = time.time()
        for name, step in self.steps:
            if self.seconds is not None and time.time() - began > self.seconds:
                self.finished = False
                break
            try:
                places = step(places)
            except OutOfTime:
                self.finished = False
                break
            self.sizes.append((name, len(places)))
        return places


def _deepest(places: list[Place]) -> list[Place]:
    return sorted(places, key=lambda p: (-len(p[0]) - len(p[1]), p))


def drop_implicit_lp(places: list[Place], mode: str = "fit", universal: Place | None = None, spark=None, seconds: float | None = None) -> list[Place]:
    """Without the places that the rest makes redundant, one after another, deepest first (Q2).

    With a session the places are first screened in parallel against all others: one that is not redundant beside
    all of them is not beside fewer, so only the others need the ordered sweep.
    """
    began, left = time.time(), list(places)
    suspects = set(places)
    if spark is not None and len(places) > 32:
        flagged = screen(spark, places, places, mode, universal).where("implicit").collect()
        suspects = {places[r["place"]] for r in flagged}
    for p in _deepest(places):
        if p not in suspects:
            continue
        if seconds is not None and time.time() - began > seconds:
            raise OutOfTime
        rest = [q for q in left if q != p]
        if lp_implicit(p, rest, mode, universal).implicit:
            left = rest
    return left


def drop_implicit_log(places: list[Place], log, tau: float | None = None) -> list[Place]:
    """Only the places that are some variant's first misfit (Q5); at a threshold of one all would go, so none does."""
    if tau is not None and tau >= 1:
        return list(places)
    return [places[i] for i in log_language_kept(log, places)]


def drop_dominated(places: list[Place], log, rule: str = "remainder") -> list[Place]:
    return [p for p, verdict, _ in dominance_fold(log, places, rule) if verdict == "kept"]


def merge_selfloops(places: DataFrame) -> DataFrame:
    """Places (pre, post) of one net effect joined into one with all their self-loops (Q3).

    They always hold equal tokens, so one that asks for a token wherever any did allows exactly what all allowed.
    """
    gain = F.array_sort(F.array_except("pre", "post"))
    loss = F.array_sort(F.array_except("post", "pre"))
    grouped = places.select(gain.alias("gain"), loss.alias("loss"), F.array_intersect("pre", "post").alias("loops")).groupBy("gain", "loss").agg(
        F.array_sort(F.array_distinct(F.flatten(F.collect_list("loops")))).alias("loops"), F.count(F.lit(1)).alias("merged")
    )
    return grouped.select(F.array_sort(F.array_union("gain", "loops")).alias("pre"), F.array_sort(F.array_union("loss", "loops")).alias("post"), "merged")


def merge_selfloop_places(places: list[Place]) -> list[Place]:
    """The same for a list; first appearance orders the result."""
    out: dict[tuple, set] = {}
    for i, o in places:
        i, o = set(i), set(o)
        out.setdefault((tuple(sorted(i - o)), tuple(sorted(o - i))), set()).update(i & o)
    return [(tuple(sorted({*g, *loops})), tuple(sorted({*l, *loops}))) for (g, l), loops in out.items()]


def merge_siblings(places: list[Place], log, tau: float, max_size: int | None = None) -> list[Place]:
    """Pairs with one side in common become one place if that reaches the threshold (Q4); changes what the net allows."""
    left = list(places)
    changed = True
    while changed:
        changed = False
        pairs = []
        for x, p in enumerate(left):
            for q in left[x + 1 :]:
                if p[1] == q[1]:
                    pairs.append((p, q, (tuple(sorted({*p[0], *q[0]})), p[1])))
                elif p[0] == q[0]:
                    pairs.append((p, q, (p[0], tuple(sorted({*p[1], *q[1]})))))
        pairs = [t for t in pairs if t[2] not in left and (max_size is None or len(t[2][0]) + len(t[2][1]) <= max_size)]
        for (p, q, r), c in zip(pairs, log.counts([t[2] for t in pairs]) if pairs else []):
            if reaches(int(c[0]), log.total, tau) and p in left and q in left:
                left = [x for x in left if x not in (p, q)] + [r]
                changed = True
                break
    return left


def standard(universal: Place | None = None, mode: str = "fit", spark=None, seconds: float | None = None) -> Pipeline:
    """Linear-program removal, then self-loop merging."""
    return Pipeline([("drop_implicit_lp", lambda p: drop_implicit_lp(p, mode, universal, spark, seconds)), ("merge_selfloops", merge_selfloop_places)], seconds)
