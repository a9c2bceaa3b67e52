"""A footprint miner: maximal pairs of mutually unrelated activity sets in causal relation."""

from __future__ import annotations

from pyspark.sql import DataFrame

from .dfg import footprint


def alpha(log: DataFrame) -> list[tuple[tuple[str, ...], tuple[str, ...]]]:
    """Places of the classic footprint miner (driver; the footprint is alphabet x alphabet)."""
    rel = {(r["src"], r["dst"]): r["relation"] for r in footprint(log).collect()}
    acts = sorted({a for a, _ in rel})
    causal = {(a, b) for (a, b), r in rel.items() if r == "->"}
    free = lambda s: all(rel[x, y] == "#" for x in s for y in s)
    found = {(frozenset([a]), frozenset([b])) for a, b in causal if rel[a, a] == "#" and rel[b, b] == "#"}
    level = set(found)
    while level:
        grown = set()
        for i, o in level:
            for a in acts:
                if a not in i and all((a, b) in causal for b in o) and free(i | {a}):
                    grown.add((i | {a}, o))
                if a not in o and all((b, a) in causal for b in i) and free(o | {a}):
                    grown.add((i, o | {a}))
        found |= grown
        level = grown
    top = [(i, o) for i, o in found if not any((i, o) != (x, y) and i <= x and o <= y for x, y in found)]
    return sorted((tuple(sorted(i)), tuple(sorted(o))) for i, o in top)
