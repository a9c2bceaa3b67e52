"""Parameter grids."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame

from ..operators.compose import Candidate, Collect, Implicit, Threshold, reaches
from .config import Config
from .propose import Discovery, regrid, walk
from .run import RUNS, Outcome, Prepared, measure, pipeline, run, tree
from .supervise import Supervisor

TAUS = (1.0, 0.9, 0.8, 0.7, 0.6, 0.5)
DEPTHS = (2, 3, 4, 5, 6)
ORACLES = ("token_dominance", "lp")
MEASURED_AT_ONCE = 4


def evaluated(p: Prepared, config: Config) -> list[dict]:
    """Counts of every candidate of one walk that makes every valid cut, at the lowest threshold and largest depth of a grid."""
    rows: list[dict] = []
    t = tree(config, p)

    walk(p.log, p.labels, t, config.tau, Collect(), cut_mode="both", observe=lambda c: rows.append({"place": c.place, "order": c.order, "counts": c.counts, "depth": c.depth}))
    at_pre, at_post = {p.labels.index(a): i for i, a in enumerate(t.pre)}, {p.labels.index(a): i for i, a in enumerate(t.post)}
    for r in rows:
        r["pre"], r["post"] = tuple(sorted(at_pre[a] for a in r["place"][0])), tuple(sorted(at_post[a] for a in r["place"][1]))
        r["n_fit"], r["n_under"], r["n_over"], r["n_unbalanced"] = r["counts"]
    return rows


def grid(p: Prepared, base: Config, taus=TAUS, depths=DEPTHS, oracles=ORACLES, quality: bool = True, shared: bool = True) -> DataFrame:
    """One runs row per setting. ``shared`` evaluates candidates once, at the lowest threshold and largest depth, and rebuilds every
    setting's walk from their counts; its search times then leave evaluation out, which is reported under the oracle ``shared``.
    Candidates come by depth, so that one composer a threshold and oracle meets those of every depth in turn; the search time of a
    setting is that of all candidates down to its depth. Composers share what they learn about pairs of places."""
    rows, measures, outs = [], {}, []

    def score(places: list) -> tuple:
        key = tuple(sorted(places))
        if key not in measures:
            measures[key] = measure(p, places)
        return measures[key]

    if not shared:
        for tau in taus:
            for d in depths:
                for o in oracles:
                    out = run(replace(base, tau=tau, max_depth=d, oracle=o), p, quality=False)
                    if quality and out.finished:
                        out.fitness, out.precision = score(out.places)
                    rows.append(out.row())
        return p.spark.createDataFrame([tuple(r.values()) for r in rows], RUNS)
    began = time.time()
    top = replace(base, tau=min(taus), max_depth=max(depths))
    table = evaluated(p, top)
    spent = time.time() - began
    t, total, known = tree(top, p), p.log.total, {}
    for tau in taus:
        part = sorted(regrid(table, t, total, tau, max(depths)), key=lambda r: r["order"])
        passing = [Candidate(r["place"], r["counts"], total, r["order"]) for r in part if reaches(r["n_fit"], total, tau)]
        searched = {}
        for o in oracles:
            inner = Implicit(Collect(), p.log, o, base.remove_existing, p.universal if base.with_universal else None, mode=base.lp_mode, known=known)
            c, at, t_search = Threshold(inner, tau), 0, 0.0
            for d in sorted(depths):
                began = time.time()
                while at < len(passing) and passing[at].depth <= d:
                    c.consume(passing[at])
                    at += 1
                t_search += time.time() - began
                searched[d, o] = Discovery(p.labels, list(c.accepted), sum(r["depth"] <= d for r in part), None, True, Supervisor(level="off"), t_search)
        for d in depths:
            for o in oracles:
                config, found, began = replace(base, tau=tau, max_depth=d, oracle=o), searched[d, o], time.time()
                post = pipeline(config, p)
                out = Outcome(config, found, post.run(found.places), post.finished, found.seconds, time.time() - began)
                outs.append(out)
    if quality:
        # Few distinct sets of places, each some small jobs that would leave most cores idle one after another.
        sets = dict.fromkeys(tuple(sorted(out.places)) for out in outs if out.finished)
        with ThreadPoolExecutor(MEASURED_AT_ONCE) as pool:
            measures |= zip(sets, pool.map(inheritable_thread_target(p.spark)(lambda key: measure(p, list(key))), sets))
        for out in outs:
            if out.finished:
                out.fitness, out.precision = score(out.places)
    rows += [out.row() for out in outs]
    rows.append({"log": base.log, "tau": min(taus), "depth": max(depths), "oracle": "shared", "proposed": len(table), "collected": 0, "after_post": 0, "fitness": None, "precision": None, "f1": None, "t_search": spent, "t_post": 0.0, "stopped_search": False, "dnf": False})
    return p.spark.createDataFrame([tuple(r.values()) for r in rows], RUNS)
