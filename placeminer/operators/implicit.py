"""Redundant places: by the log's language, by dominance of token counts, by linear programs."""

from __future__ import annotations

import numpy as np

from .kernel import Place
from .lp import lp_implicit

ORACLES = ("log_language", "token_dominance", "lp")


def log_language_kept(log, ordered: list[Place], tau: float | None = None, allow_degenerate: bool = False) -> list[int]:
    """Positions of the places that a one-by-one filter keeps, where a place goes if the log's traces that fit all kept ones also fit it.

    A place is kept exactly if it is the first misfit of some variant, so one aggregation replaces the loop. At a threshold
    of one every place fits all traces and none would be kept.
    """
    if tau is not None and tau >= 1 and not allow_degenerate:
        raise ValueError("at a threshold of 1 the log language oracle rejects every place; pass allow_degenerate to have that")
    return sorted(log.first_unfit(ordered))


def remainder(p: Place, q: Place) -> Place | None:
    """The place that with q makes up p, or None if it would need an arc of weight two."""
    ip, op, iq, oq = map(set, (*p, *q))
    if (ip - iq) & (oq - op) or (op - oq) & (iq - ip):
        return None
    return tuple(sorted((ip - iq) | (oq - op))), tuple(sorted((op - oq) | (iq - ip)))


def dominates(log, p: Place, q: Place, rule: str = "remainder") -> bool:
    """Given that q never holds more tokens than p: whether p is redundant beside q under the rule."""
    if rule == "counts":
        return True
    r = remainder(p, q)
    if r is None:
        return False
    if not r[0] and not r[1]:
        return True
    return log.misfits(r, [q]) == 0


def dominance_fold(log, ordered: list[Place], rule: str = "remainder", scope: str = "all", remove_existing: bool = True) -> list[tuple[Place, str, Place | None]]:
    """(place, verdict, by) in order: ``kept``, ``rejected`` beside a kept place, or ``replaced`` by a later one."""
    if not ordered:
        return []
    below = log.dominance(ordered, scope)
    at = {p: i for i, p in enumerate(ordered)}
    kept: list[Place] = []
    out: dict[Place, tuple[str, Place | None]] = {}
    for p in ordered:
        by = next((q for q in kept if below[at[p], at[q]] and dominates(log, p, q, rule)), None)
        if by is not None:
            out[p] = ("rejected", by)
            continue
        if remove_existing:
            for q in [q for q in kept if below[at[q], at[p]] and dominates(log, q, p, rule)]:
                kept.remove(q)
                out[q] = ("replaced", p)
        kept.append(p)
        out[p] = ("kept", None)
    return [(p, *out[p]) for p in ordered]


def lp_fold(ordered: list[Place], mode: str = "fit", universal: Place | None = None, remove_existing: bool = False) -> list[tuple[Place, str, Place | None]]:
    """The one-by-one filter with linear programs."""
    kept: list[Place] = []
    out: dict[Place, tuple[str, Place | None]] = {}
    for p in ordered:
        if lp_implicit(p, kept, mode, universal).implicit:
            out[p] = ("rejected", None)
            continue
        kept.append(p)
        out[p] = ("kept", None)
        if remove_existing:
            for q in list(kept[:-1]):
                if lp_implicit(q, [k for k in kept if k != q], mode, universal).implicit:
                    kept.remove(q)
                    out[q] = ("replaced", p)
    return [(p, *out[p]) for p in ordered]


def agreement(log, ordered: list[Place], tau: float, universal: Place | None = None) -> dict[tuple[bool, bool, bool], int]:
    """How often the three oracles call a place redundant, as counts of (log language, dominance, lp)."""
    kept = set(log_language_kept(log, ordered, tau, allow_degenerate=True))
    dominance = {p: v != "kept" for p, v, _ in dominance_fold(log, ordered)}
    lp = {p: v != "kept" for p, v, _ in lp_fold(ordered, universal=universal)}
    out: dict[tuple[bool, bool, bool], int] = {}
    for i, p in enumerate(ordered):
        k = (i not in kept, bool(np.bool_(dominance[p])), lp[p])
        out[k] = out.get(k, 0) + 1
    return out
