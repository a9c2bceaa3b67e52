"""A whole run from events to a net and its quality."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..checkpoints import checkpointed
from ..functions.places import END, START
from ..operators import conformance, heuristics, log as logs, order
from ..operators.compose import Budget, Collect, Composer, Delta, Implicit, Postponing, Threshold, Uniwired
from ..operators.evaluate import SparkLog
from ..operators.lp import universal_place
from ..operators.post import Pipeline, drop_dominated, drop_implicit_log, drop_implicit_lp, merge_selfloop_places
from ..operators.tree import Tree, tree_of
from .config import Config, Context
from .propose import Discovery, discover, walk
from .supervise import Supervisor


@dataclass
class Prepared:
    """A log made ready: labels (markers first and last), encoded variants, and the context with everything that derives from them."""

    spark: SparkSession
    named: DataFrame
    log: SparkLog
    labels: list[str]
    context: Context

    @property
    def start(self) -> int:
        return self.labels.index(START)

    @property
    def end(self) -> int:
        return self.labels.index(END)

    @property
    def universal(self):
        return universal_place(len(self.labels), self.start, self.end)


def prepare(events: DataFrame, how: str = "first_index", seed: int = 0, explicit: list[str] | None = None, pre: list = ()) -> Prepared:
    """``pre``: functions from events to events that run first (P10), such as relabelling for duplicate or silent steps."""
    for step in pre:
        events = step(events)
    named = checkpointed(logs.variants(logs.traces(events)))
    inner = order.ordered(named, how, seed=seed, explicit=explicit)
    labels = [START, *inner, END]
    encoded = logs.encode(named, labels)
    context = Context()
    context.offer("variants", lambda _: encoded)
    context.offer("named", lambda _: named)
    context.offer("dictionary", lambda _: labels)
    context.offer("eventually", lambda _: heuristics.interest_heuristic(named, "eventually"))
    context.offer("directly", lambda _: heuristics.interest_heuristic(named, "directly"))
    context.offer("size", lambda _: heuristics.place_size)
    return Prepared(events.sparkSession, named, SparkLog(encoded, labels), labels, context)


def composer(config: Config, p: Prepared) -> Composer:
    """The nested composer that a configuration names."""
    inner: Composer = Collect()
    if config.oracle:
        if config.oracle == "log_language" and config.tau >= 1:
            raise ValueError("the log language oracle needs a threshold below 1")
        inner = Implicit(inner, p.log, config.oracle, config.remove_existing, p.universal if config.with_universal else None, mode=config.lp_mode)
    if config.composer == "uniwired":
        inner = Uniwired(inner, release=config.remove_existing)
    elif config.composer == "delta":
        inner = Delta(inner, p.log, config.delta, config.net_floor, config.schedule, config.max_depth)
    elif config.composer == "postponing":
        h = p.context.get(config.heuristic or "size")
        labels = p.labels
        inner = Postponing(inner, lambda c: h((tuple(labels[i] for i in c.place[0]), tuple(labels[i] for i in c.place[1]))))
    return Threshold(inner, config.tau)


def pipeline(config: Config, p: Prepared) -> Pipeline:
    free = p.universal if config.with_universal else None
    steps = {
        "lp": ("drop_implicit_lp", lambda x: drop_implicit_lp(x, config.lp_mode, free, p.spark, config.post_seconds)),
        "selfloops": ("merge_selfloops", merge_selfloop_places),
        "log_language": ("drop_implicit_log", lambda x: drop_implicit_log(x, p.log, config.tau)),
        "dominance": ("drop_dominated", lambda x: drop_dominated(x, p.log)),
    }
    return Pipeline([steps[s] for s in config.post], config.post_seconds)


def tree(config: Config, p: Prepared) -> Tree:
    return tree_of([a for a in p.labels if a not in (START, END)], config.max_depth, blacklist=config.blacklist, prefer=config.prefer)


def search(config: Config, p: Prepared, distributed: bool | None = None, supervisor: Supervisor | None = None) -> Discovery:
    """The search of a configuration: by levels on Spark, or by a stepper where the order of steps matters or the log is small."""
    sup = supervisor or Supervisor(level=config.supervision)
    budget = Budget(config.seconds, config.max_candidates, stagnation=config.stagnation)
    if distributed is None:
        distributed = config.strategy == "bfs" and not p.log.small
    if distributed:
        if config.strategy != "bfs":
            raise ValueError(f"a distributed search goes breadth first, not {config.strategy}")
        return discover(p.log, tree(config, p), config.tau, composer(config, p), cut_mode=config.cut_mode, budget=budget, supervisor=sup)
    h = p.context.get(config.heuristic or "size") if config.strategy == "best" else None
    return walk(p.log, p.labels, tree(config, p), config.tau, composer(config, p), strategy=config.strategy, heuristic=h, batch=config.batch, cut_mode=config.cut_mode, budget=budget, supervisor=sup)


@dataclass
class Outcome:
    config: Config
    discovery: Discovery
    places: list
    finished: bool
    t_search: float
    t_post: float
    fitness: float | None = None
    precision: float | None = None

    @property
    def f1(self) -> float | None:
        return conformance.f1(self.fitness, self.precision)

    def names(self) -> list:
        labels = self.discovery.labels
        return [(tuple(sorted(labels[i] for i in a)), tuple(sorted(labels[i] for i in b))) for a, b in self.places]

    def row(self) -> dict:
        """One row of the runs table."""
        c, d = self.config, self.discovery
        return {
            "log": c.log, "tau": c.tau, "depth": c.max_depth, "oracle": c.oracle or "none", "proposed": d.proposed, "collected": len(d.places), "after_post": len(self.places),
            "fitness": self.fitness, "precision": self.precision, "f1": self.f1, "t_search": self.t_search, "t_post": self.t_post, "stopped_search": d.stopped == "seconds", "dnf": not self.finished,
        }


RUNS = "log string, tau double, depth int, oracle string, proposed long, collected long, after_post long, fitness double, precision double, f1 double, t_search double, t_post double, stopped_search boolean, dnf boolean"


def run(config: Config, p: Prepared, quality: bool = True, **options) -> Outcome:
    t = time.time()
    found = search(config, p, **options)
    t_search, t = time.time() - t, time.time()
    post = pipeline(config, p)
    places = post.run(found.places)
    out = Outcome(config, found, places, post.finished, t_search, time.time() - t)
    if quality and post.finished:
        out.fitness, out.precision = measure(p, places)
    return out


def measure(p: Prepared, places: list, states: int = 50_000) -> tuple[float | None, float | None]:
    fit = conformance.alignment_fitness(p.log, places, p.start, p.end, states=states)
    return fit, conformance.etc_precision(p.log, places, p.start, p.end).first()["precision"]
