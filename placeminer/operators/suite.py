"""User evaluators and short-circuit suites.

An evaluator takes places and gives each a result; an individual one looks at the log alone, a relative one also at
the accepted places. A suite runs evaluators from cheap to dear, each only on the places that all earlier ones let pass.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from .kernel import Place

Verdicts = list[bool]


@dataclass(frozen=True)
class IndividualEvaluator:
    """``judge(log, places)`` says for each place whether it passes; ``cost`` orders evaluators."""

    name: str
    judge: Callable[[object, list[Place]], Verdicts]
    cost: float = 1.0

    def run(self, log, places: list[Place], accepted: list[Place]) -> Verdicts:
        return self.judge(log, places)


@dataclass(frozen=True)
class RelativeEvaluator:
    """``judge(log, places, accepted)`` also sees what was accepted."""

    name: str
    judge: Callable[[object, list[Place], list[Place]], Verdicts]
    cost: float = 10.0

    def run(self, log, places: list[Place], accepted: list[Place]) -> Verdicts:
        return self.judge(log, places, accepted)


def reaches_threshold(tau: float) -> IndividualEvaluator:
    from .compose import reaches

    return IndividualEvaluator(f"fit>={tau}", lambda log, ps: [reaches(int(c[0]), log.total, tau) for c in log.counts(ps)] if ps else [], 5.0)


def at_most_arcs(n: int) -> IndividualEvaluator:
    return IndividualEvaluator(f"arcs<={n}", lambda log, ps: [len(i) + len(o) <= n for i, o in ps], 0.1)


def adds_something() -> RelativeEvaluator:
    """Passes places that some trace which fits all accepted ones does not fit."""
    return RelativeEvaluator("adds_something", lambda log, ps, acc: [log.misfits(p, acc) > 0 for p in ps], 20.0)


@dataclass
class EvaluatorSuite:
    """Evaluators in order of cost; ``asked`` counts how many places each had to judge."""

    evaluators: list
    asked: dict[str, int] = field(default_factory=dict)

    def passing(self, log, places: list[Place], accepted: list[Place] = ()) -> list[Place]:
        left = list(places)
        for e in sorted(self.evaluators, key=lambda e: e.cost):
            self.asked[e.name] = self.asked.get(e.name, 0) + len(left)
            left = [p for p, ok in zip(left, e.run(log, left, list(accepted))) if ok]
        return left
