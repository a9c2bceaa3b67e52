"""Constraints on places: predicates for nodes and as columns, with their kind.

``monotone``: once violated, violated by every descendant, so a violating node's subtree may go. ``cost``: ``local``
ones are decided at the node, ``summary`` ones against a set kept beside the walk.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Names = tuple[tuple[str, ...], tuple[str, ...]]


@dataclass(frozen=True)
class Constraint:
    """``holds`` on a place of labels, ``column`` on label arrays ``pre`` and ``post``."""

    name: str
    holds: Callable[[Names], bool]
    make: Callable[[], Column] | None = None
    monotone: bool = True
    cost: str = "local"

    @property
    def column(self) -> Column | None:
        """Made on demand, so that constraints need no running session."""
        return None if self.make is None else self.make()


def not_in_pre(a: str) -> Constraint:
    return Constraint(f"not_in_pre({a})", lambda p: a not in p[0], lambda: ~F.array_contains("pre", a))


def not_in_post(a: str) -> Constraint:
    return Constraint(f"not_in_post({a})", lambda p: a not in p[1], lambda: ~F.array_contains("post", a))


def not_selfloop(a: str) -> Constraint:
    return Constraint(f"not_selfloop({a})", lambda p: not (a in p[0] and a in p[1]), lambda: ~(F.array_contains("pre", a) & F.array_contains("post", a)))


def not_anywhere(a: str) -> Constraint:
    return Constraint(f"not_anywhere({a})", lambda p: a not in p[0] and a not in p[1], lambda: ~(F.array_contains("pre", a) | F.array_contains("post", a)))


def max_depth(d: int) -> Constraint:
    return Constraint(f"max_depth({d})", lambda p: len(p[0]) + len(p[1]) <= d, lambda: F.size("pre") + F.size("post") <= d)


def max_pre(n: int) -> Constraint:
    return Constraint(f"max_pre({n})", lambda p: len(p[0]) <= n, lambda: F.size("pre") <= n)


def max_post(n: int) -> Constraint:
    return Constraint(f"max_post({n})", lambda p: len(p[1]) <= n, lambda: F.size("post") <= n)


def heuristic_below(name: str, h: Callable[[Names], float], limit: float, monotone: bool) -> Constraint:
    """Keep places whose heuristic is at most ``limit``; not complete unless the heuristic never falls along the tree."""
    return Constraint(f"{name}<={limit}", lambda p: h(p) <= limit, None, monotone)


def wired(pairs: set[tuple[str, str]]) -> Constraint:
    """No place may connect a pair that an accepted one connects; the set is kept beside the walk."""
    return Constraint("wired", lambda p: not any((a, b) in pairs for a in p[0] for b in p[1]), None, True, "summary")


def every(constraints: list[Constraint]) -> Constraint:
    """Conjunction (C20)."""
    make = (lambda: reduce(and_, (c.column for c in constraints))) if constraints and all(c.make for c in constraints) else None
    return Constraint(" & ".join(c.name for c in constraints) or "true", lambda p: all(c.holds(p) for c in constraints), make, all(c.monotone for c in constraints), "local" if all(c.cost == "local" for c in constraints) else "summary")


def is_strengthening(old: Constraint, new: Constraint, universe: DataFrame) -> bool:
    """Whether everything that ``new`` lets pass, ``old`` lets pass too, on places (pre, post)."""
    return universe.where(new.column).exceptAll(universe.where(new.column & old.column)).isEmpty()


def is_monotone_sequence(constraints: list[Constraint], universe: DataFrame) -> bool:
    """Whether each constraint strengthens the one before it."""
    return all(is_strengthening(a, b, universe) for a, b in zip(constraints, constraints[1:]))
