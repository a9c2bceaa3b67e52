"""Exhaustive searches and extreme nets."""

from __future__ import annotations

from itertools import combinations

from ..compose import reaches
from ..kernel import Place
from ..tree import Tree


def brute(log, labels: list[str], tree: Tree, tau: float) -> tuple[list[Place], int]:
    """All through places of the tree that reach ``tau``, without any cut, and how many were evaluated (B1)."""
    nodes = sorted((x for x in tree.subtree() if x[0] and x[1]), key=lambda x: (len(x[0]) + len(x[1]), tree.path(x)))
    places = [tree.ids(x, labels) for x in nodes]
    counts = log.counts(places)
    return [p for p, c in zip(places, counts) if reaches(int(c[0]), log.total, tau)], len(places)


def brute_sets(log, places: list[Place], score, most: int = 3) -> tuple[tuple[Place, ...], float]:
    """The best set of at most ``most`` places by any score of a set (B2; doubly exponential, tiny alphabets only)."""
    options = [s for k in range(most + 1) for s in combinations(places, k)]
    return max(((s, score(log, s)) for s in options), key=lambda x: (x[1], -len(x[0])))


def flower() -> list[Place]:
    """No place at all: everything between the markers is allowed."""
    return []


def single_trace(seq: list[int]) -> list[Place]:
    """A chain of places for a trace whose activities differ (B10): only that trace is allowed."""
    if len(set(seq)) != len(seq):
        raise ValueError("a chain needs activities that differ")
    return [((a,), (b,)) for a, b in zip(seq, seq[1:])]
