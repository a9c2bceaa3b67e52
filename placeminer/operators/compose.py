"""Composers: what becomes of evaluated candidates, and what they cut.

A composer consumes candidates in order and says for each: accepted, rejected (why), replaced, postponed. Composers
nest; the innermost collects. Cuts of the walk that depend on one candidate alone are made by :func:`cuts`.
"""

from __future__ import annotations

import threading
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from .implicit import dominates
from .kernel import Place
from .lp import lp_implicit

MICRO = 1_000_000


@dataclass(frozen=True)
class Candidate:
    """An evaluated place; ``order`` sorts candidates as they were proposed."""

    place: Place
    counts: tuple[int, int, int, int]
    total: int
    order: tuple = ()

    @property
    def depth(self) -> int:
        return len(self.place[0]) + len(self.place[1])

    @property
    def fit(self) -> float:
        return self.counts[0] / self.total


def reaches(n_fit: int, total: int, tau: float) -> bool:
    """n_fit / total >= tau, exactly for thresholds of up to six digits."""
    return n_fit * MICRO >= round(tau * MICRO) * total


def exceeds(n: int, total: int, tau: float) -> bool:
    """n / total > 1 - tau, exactly."""
    return n * MICRO > (MICRO - round(tau * MICRO)) * total


def cuts(n_under: int, n_over: int, total: int, tau: float, depth: int, can_post: bool, can_pre: bool, mode: str = "paper") -> tuple[bool, bool]:
    """(cut_post, cut_pre) of a node (M4, M5).

    Too many underfed traces stay underfed under larger postsets; too many overfed ones stay so under larger presets, which
    may only be used where no postset extension would restore the balance. ``paper`` tries the second only if the first did not
    apply, ``both`` makes every valid cut, ``under``, ``over`` and ``none`` are for ablations.
    """
    under = depth >= 2 and exceeds(n_under, total, tau)
    over = not can_post and exceeds(n_over, total, tau)
    if mode == "none":
        return False, False
    if mode == "under":
        return under, False
    if mode == "over":
        return False, over
    if mode == "both":
        return under, over
    return under, over and not under


def explain(tree, node, n_under: int, n_over: int, total: int, tau: float, mode: str = "paper") -> list[tuple[str, int]]:
    """Which rules cut a node of a tree, and how many candidates each removes."""
    can_post, can_pre = bool(tree.extensions(node, "post")), bool(tree.extensions(node, "pre"))
    post, pre = cuts(n_under, n_over, total, tau, len(node[0]) + len(node[1]), can_post, can_pre, mode)
    return [(rule, tree.cut_mass(node, side)) for rule, side, on in (("underfed", "post", post), ("overfed", "pre", pre)) if on]


def cut_columns(total: int, tau: float, last_post: Column, mode: str = "paper", n_under: str = "n_under", n_over: str = "n_over") -> tuple[Column, Column]:
    """:func:`cuts` over a frontier with counts; ``last_post``: no postset extension is left."""
    most = F.lit((MICRO - round(tau * MICRO)) * total).cast("long")
    under = (F.col("depth") >= 2) & (F.col(n_under) * F.lit(MICRO).cast("long") > most)
    over = last_post & (F.col(n_over) * F.lit(MICRO).cast("long") > most)
    no = F.lit(False)
    return {"none": (no, no), "under": (under, no), "over": (no, over), "both": (under, over)}.get(mode, (under, over & ~under))


class Composer:
    """Protocol (M1). ``consume`` returns the verdict of one candidate; ``accepted`` is the result so far."""

    complete = True

    def consume(self, c: Candidate) -> str:
        raise NotImplementedError

    def end_of_level(self) -> None:
        """After each batch of candidates."""

    def finish(self) -> None:
        """After the last one."""

    @property
    def accepted(self) -> list[Place]:
        raise NotImplementedError

    def remove(self, p: Place) -> None:
        raise NotImplementedError

    @property
    def wired_pairs(self) -> set[tuple[int, int]]:
        """Pairs that no further candidate may connect."""
        return set()

    def extra_cuts(self, c: Candidate) -> tuple[bool, bool]:
        """(cut_post, cut_pre) beyond those of fitness (M17), asked of candidates that reach the threshold once they are consumed; void completeness."""
        return False, False


class Collect(Composer):
    """The innermost composer: accepts all."""

    def __init__(self):
        self.places: dict[Place, Candidate] = {}

    def consume(self, c: Candidate) -> str:
        self.places[c.place] = c
        return "accepted"

    @property
    def accepted(self) -> list[Place]:
        return list(self.places)

    def remove(self, p: Place) -> None:
        self.places.pop(p, None)


class Wrapper(Composer):
    def __init__(self, inner: Composer):
        self.inner = inner

    @property
    def complete(self) -> bool:
        return self.inner.complete

    def consume(self, c: Candidate) -> str:
        return self.inner.consume(c)

    def end_of_level(self) -> None:
        self.inner.end_of_level()

    def finish(self) -> None:
        self.inner.finish()

    @property
    def accepted(self) -> list[Place]:
        return self.inner.accepted

    def remove(self, p: Place) -> None:
        self.inner.remove(p)

    @property
    def wired_pairs(self) -> set[tuple[int, int]]:
        return self.inner.wired_pairs

    def extra_cuts(self, c: Candidate) -> tuple[bool, bool]:
        return self.inner.extra_cuts(c)


class CutWhere(Wrapper):
    """Cuts both subtrees of candidates that a predicate names (M16, M17), such as :func:`redundancy_cut`."""

    complete = False

    def __init__(self, inner: Composer, where):
        super().__init__(inner)
        self.where = where

    def extra_cuts(self, c: Candidate) -> tuple[bool, bool]:
        cut = bool(self.where(c, self.inner.accepted))
        return cut, cut


class Threshold(Wrapper):
    """Lets candidates pass that fit a share ``tau`` of the traces (M3)."""

    def __init__(self, inner: Composer, tau: float):
        super().__init__(inner)
        self.tau = tau

    def consume(self, c: Candidate) -> str:
        return self.inner.consume(c) if reaches(c.counts[0], c.total, self.tau) else "unfit"


class Uniwired(Wrapper):
    """After a place is accepted, none may share a preset and a postset activity with it (M6); ``release`` frees the
    pairs of places that leave again, which makes the result depend on what was skipped (M7)."""

    def __init__(self, inner: Composer, release: bool = False):
        super().__init__(inner)
        self.release = release
        self.owner: dict[tuple[int, int], Place] = {}

    @property
    def complete(self) -> bool:
        return self.inner.complete and not self.release

    def consume(self, c: Candidate) -> str:
        pairs = [(a, b) for a in c.place[0] for b in c.place[1]]
        if any(p in self.owner for p in pairs):
            return "wired"
        verdict = self.inner.consume(c)
        if verdict == "accepted":
            self.owner |= dict.fromkeys(pairs, c.place)
            self._sweep()
        return verdict

    def _sweep(self) -> None:
        if self.release:
            alive = set(self.inner.accepted)
            self.owner = {k: p for k, p in self.owner.items() if p in alive}

    @property
    def wired_pairs(self) -> set[tuple[int, int]]:
        return set(self.owner) | self.inner.wired_pairs


class Implicit(Wrapper):
    """Rejects redundant candidates, and with ``remove_existing`` members that a candidate makes redundant (M8).
    Composers over one log may share ``known``, the answers about pairs of places."""

    def __init__(self, inner: Composer, log, oracle: str = "lp", remove_existing: bool = False, universal: Place | None = None, rule: str = "remainder", mode: str = "fit", known: dict | None = None):
        super().__init__(inner)
        self.log, self.oracle, self.remove_existing, self.universal, self.rule, self.mode = log, oracle, remove_existing, universal, rule, mode
        self.known: dict[tuple, bool] = {} if known is None else known

    def _beside(self, p: Place, others: list[Place]) -> bool:
        if self.oracle == "lp":
            return lp_implicit(p, others, self.mode, self.universal).implicit
        if self.oracle == "log_language":
            return self.log.misfits(p, others) == 0
        fresh = [q for q in others if (p, q) not in self.known]
        if fresh:
            for q, less, more in zip(fresh, *self.log.beside(p, fresh)):
                self.known[p, q], self.known[q, p] = bool(less), bool(more)
        return any(self.known[p, q] and self._dominated(p, q) for q in others)

    def _dominated(self, p: Place, q: Place) -> bool:
        key = (p, q, self.rule)
        if key not in self.known:
            self.known[key] = dominates(self.log, p, q, self.rule)
        return self.known[key]

    def consume(self, c: Candidate) -> str:
        members = self.inner.accepted
        if self._beside(c.place, members):
            return "implicit"
        verdict = self.inner.consume(c)
        if verdict == "accepted" and self.remove_existing:
            for q in members:
                if self._beside(q, [r for r in self.inner.accepted if r != q]):
                    self.inner.remove(q)
        return verdict


class Delta(Wrapper):
    """Accepts a place if the traces that fit all places stay above ``floor`` and fall by at most ``delta`` of all (M9, M12);
    with ``schedule="linear"`` the allowance grows with depth."""

    complete = False

    def __init__(self, inner: Composer, log, delta: float, floor: float = 0.0, schedule: str = "constant", max_depth: int = 6):
        super().__init__(inner)
        self.log, self.delta, self.floor, self.schedule, self.max_depth = log, delta, floor, schedule, max_depth
        self.now = None

    def consume(self, c: Candidate) -> str:
        members = self.inner.accepted
        before = self.log.support(members) if self.now is None else self.now
        after = self.log.support([*members, c.place])
        allowed = self.delta * (c.depth / self.max_depth if self.schedule == "linear" else 1.0)
        if not reaches(after, c.total, self.floor):
            return "below floor"
        if (before - after) * MICRO > round(allowed * MICRO) * c.total:
            return "too much loss"
        verdict = self.inner.consume(c)
        self.now = after if verdict == "accepted" else before
        return verdict


class Greedy(Wrapper):
    """Accept, replace or reject by a decision over the candidate and the members (M2).

    ``decide(candidate, members)`` gives ``("accept", [])``, ``("replace", members to go)`` or ``("reject", [])``.
    """

    def __init__(self, inner: Composer, decide):
        super().__init__(inner)
        self.decide = decide

    def consume(self, c: Candidate) -> str:
        what, leaving = self.decide(c, self.inner.accepted)
        if what == "reject":
            return "rejected"
        for p in leaving:
            self.inner.remove(p)
        return self.inner.consume(c)


class Postponing(Wrapper):
    """Puts candidates aside and gives them to the inner composer by score, after each level or at the end."""

    def __init__(self, inner: Composer, score, retry: str = "level"):
        super().__init__(inner)
        self.score, self.retry = score, retry
        self.queue: list[Candidate] = []

    def consume(self, c: Candidate) -> str:
        self.queue.append(c)
        return "postponed"

    def _drain(self) -> None:
        again = []
        for c in sorted(self.queue, key=lambda c: (self.score(c), c.order)):
            if self.inner.consume(c) not in ("accepted", "unfit"):
                again.append(c)
        self.queue = again if self.retry == "level" else []

    def end_of_level(self) -> None:
        if self.retry == "level":
            self._drain()
        self.inner.end_of_level()

    def finish(self) -> None:
        self._drain()
        self.inner.finish()


@dataclass
class Budget:
    """Limits of a run (M13, M14); candidate budgets give the same result every time, seconds do not."""

    seconds: float | None = None
    max_candidates: int | None = None
    max_places: int | None = None
    stagnation: int | None = None
    #: Set from another thread to end the search after the batch at hand.
    cancel: threading.Event | None = None
    _quiet: int = field(default=0, repr=False)

    def spent(self, elapsed: float, candidates: int, places: int, changed: bool) -> str | None:
        self._quiet = 0 if changed else self._quiet + 1
        if self.cancel is not None and self.cancel.is_set():
            return "cancelled"
        if self.seconds is not None and elapsed > self.seconds:
            return "seconds"
        if self.max_candidates is not None and candidates >= self.max_candidates:
            return "candidates"
        if self.max_places is not None and places >= self.max_places:
            return "places"
        if self.stagnation is not None and self._quiet >= self.stagnation:
            return "stagnation"
        return None


def beam(log, candidates: list[Candidate], width: int, score) -> list[Place]:
    """Several place sets side by side: each candidate is added to or left out of each, the best ``width`` stay."""
    sets: list[tuple[Place, ...]] = [()]
    for c in candidates:
        grown = [*sets, *[(*s, c.place) for s in sets]]
        sets = sorted(grown, key=lambda s: (-score(log, s), len(s), s))[:width]
    return list(sets[0])


def support_score(alpha: float = 0.02):
    """Share of traces that fit the set, plus ``alpha`` a place."""
    return lambda log, s: log.support(list(s)) / log.total + alpha * len(s)


def redundancy_cut(log, p: Place, members: list[Place]) -> bool:
    """Experimental (M16): whether a place and so probably its subtree only repeats members; voids completeness."""
    return bool(members) and log.misfits(p, members) == 0 and bool(np.any([set(p[0]) & set(q[0]) and set(p[1]) & set(q[1]) for q in members]))
