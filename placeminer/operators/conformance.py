"""Quality of a net on a log."""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .evaluate import SparkLog
from .kernel import Place

#: Cap of states of one alignment; beyond it the cost is null, on every machine alike.
STATES = 200_000
#: Results that a task keeps at once.
KNOWN = 100_000


def chained(state: int, a: int) -> int:
    """Signed 64-bit hash of a prefix from that of the shorter one and the next activity."""
    x = (state + (a + 1) * 0x9E3779B97F4A7C15) & (2**64 - 1)
    x = ((x ^ (x >> 30)) * 0xBF58476D1CE4E5B9) & (2**64 - 1)
    x = ((x ^ (x >> 27)) * 0x94D049BB133111EB) & (2**64 - 1)
    x ^= x >> 31
    return x - 2**64 if x >> 63 else x


class Machine:
    """Token game of a place set over activity ids; activities outside of all places are always enabled."""

    def __init__(self, places: list[Place], n_acts: int, start: int, end: int):
        self.need = [tuple(j for j, p in enumerate(places) if a in p[1]) for a in range(n_acts)]
        self.give = [tuple(j for j, p in enumerate(places) if a in p[0]) for a in range(n_acts)]
        self.start, self.end, self.n = start, end, n_acts
        self.zero = (0,) * len(places)

    def fire(self, marking: tuple[int, ...], a: int) -> tuple[int, ...] | None:
        m = list(marking)
        for j in self.need[a]:
            m[j] -= 1
            if m[j] < 0:
                return None
        for j in self.give[a]:
            m[j] += 1
        return tuple(m)

    def align(self, seq: list[int], states: int = STATES) -> tuple[int, list[int]] | None:
        """(cost, model trace) of a cheapest alignment, or None if there is none or the cap was reached.

        Moves on both sides are free, on one side cost one. The model runs from the start to the end marker and ends without tokens.
        The search is guided by what is still to come: each token of the fullest place takes a move of its own, and only
        as many of those are free as events are left.
        """
        done = {}
        still = lambda pos, m: max(0, max(m, default=0) - (len(seq) - pos))
        heap = [(0, 0, self.zero, 0, None, None, 0)]  # cost with what must come, -position, marking, phase, parent, act, cost
        # phase 0: before the start marker, 1: running, 2: ended
        while heap:
            _, back, marking, phase, parent, act, cost = heapq.heappop(heap)
            pos = -back
            key = (pos, marking, phase)
            if key in done:
                continue
            done[key] = (parent, act)
            if pos == len(seq) and phase == 2 and marking == self.zero:
                trace, k = [], key
                while k is not None:
                    up, a = done[k]
                    if a is not None and a >= 0:
                        trace.append(a)
                    k = up
                return cost, trace[::-1]
            if len(done) > states:
                return None
            allowed = (self.start,) if phase == 0 else () if phase == 2 else tuple(a for a in range(self.n) if a != self.start)
            here = seq[pos] if pos < len(seq) else None
            if here is not None:
                heapq.heappush(heap, (cost + 1 + still(pos + 1, marking), back - 1, marking, phase, key, -1, cost + 1))
            for a in allowed:
                m = self.fire(marking, a)
                if m is None:
                    continue
                p = 1 if a == self.start else 2 if a == self.end else 1
                if a == here:
                    heapq.heappush(heap, (cost + still(pos + 1, m), back - 1, m, p, key, a, cost))
                heapq.heappush(heap, (cost + 1 + still(pos, m), back, m, p, key, a, cost + 1))
        return None

    def shortest(self) -> int | None:
        """Length of a shortest complete model trace."""
        found = self.align([])
        return None if found is None else found[0]


def alignment(log: SparkLog, places: list[Place], start: int, end: int, states: int = STATES) -> DataFrame:
    """variant_id, freq, cost, trace_len, model_len, fitness = 1 - cost / (trace + shortest model trace); null where a cap was reached (A3).

    Between the markers, an activity outside of all places costs nothing on both sides and changes no token, so that variants are aligned without
    such events; those that then are equal meet in one task and are aligned once.
    """
    n = len(log.labels)
    shared = log.variants.sparkSession.sparkContext.broadcast(places)
    model_len = Machine(places, n, start, end).shortest()
    bound = F.array(*map(F.lit, sorted({start, end, *(a for p in places for side in p for a in side)})))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine, known = Machine(shared.value, n, start, end), {}
        for batch in batches:
            cost = []
            for s in map(tuple, batch.column("seq").to_pylist()):
                if s not in known:
                    if len(known) >= KNOWN:
                        known.clear()
                    found = machine.align(s, states)
                    known[s] = None if found is None else found[0]
                cost.append(known[s])
            length = batch.column("length").to_pylist()
            fit = [None if c is None or model_len is None else 1 - c / (k + model_len) for c, k in zip(cost, length)]
            yield pa.RecordBatch.from_arrays([batch.column("variant_id"), batch.column("freq"), pa.array(cost, pa.int64()), pa.array(length, pa.int64()), pa.array([model_len] * len(cost), pa.int64()), pa.array(fit, pa.float64())], names=["variant_id", "freq", "cost", "trace_len", "model_len", "fitness"])

    short = F.filter("seq", lambda a: F.array_contains(bound, a))
    rows = log.variants.select("variant_id", "freq", F.size("seq").alias("length"), short.alias("seq"))
    return rows.repartition(rows.sparkSession.sparkContext.defaultParallelism, "seq").mapInArrow(run, "variant_id long, freq long, cost long, trace_len long, model_len long, fitness double")


def alignment_fitness(log: SparkLog, places: list[Place], start: int, end: int, **caps) -> float | None:
    """Mean over traces; None if some alignment reached a cap."""
    # Distinct values are few, as lengths and costs are; their exact sum does not depend on the order of tasks.
    rows = alignment(log, places, start, end, **caps).groupBy("fitness").agg(F.sum("freq").alias("n")).collect()
    return None if not rows or any(r["fitness"] is None for r in rows) else math.fsum(r["fitness"] * r["n"] for r in rows) / sum(r["n"] for r in rows)


def etc_precision(log: SparkLog, places: list[Place], start: int, end: int, mode: str = "prefix") -> DataFrame:
    """enabled, escaping, precision = 1 - escaping / enabled over the log's prefixes (A4).

    Each prefix (up to a trace's first misfit, or of the aligned model trace with ``mode="align"``) is a state, weighted by the traces that
    reach it; enabled are the activities whose places all hold a token, escaping those that never follow the prefix in the log.
    """
    n = len(log.labels)
    shared = log.variants.sparkSession.sparkContext.broadcast(places)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine, may = Machine(shared.value, n, start, end), {}
        for batch in batches:
            steps: dict[tuple, int] = {}
            for seq, freq in zip(batch.column("seq").to_pylist(), batch.column("freq").to_pylist()):
                if mode == "align":
                    found = machine.align(seq)
                    seq = found[1] if found else seq
                m, state = machine.zero, 0
                for k, a in enumerate(seq[:-1]):
                    m = machine.fire(m, a)
                    if m is None:
                        break
                    state = chained(state, a)
                    if m not in may:
                        if len(may) >= KNOWN:
                            may.clear()
                        may[m] = tuple(b for b in range(n) if b != start and machine.fire(m, b) is not None)
                    step = (state, seq[k + 1], may[m])
                    steps[step] = steps.get(step, 0) + freq
            prefix, after, enabled = zip(*steps) if steps else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(prefix, pa.int64()), pa.array(after, pa.int32()), pa.array(enabled, pa.list_(pa.int32())), pa.array(list(steps.values()), pa.int64())], names=["prefix", "next", "enabled", "freq"])

    # Tasks by variant: those that made the variants may be fewer than there are cores.
    rows = log.variants.select("seq", "freq").repartition(log.variants.sparkSession.sparkContext.defaultParallelism, "seq")
    states = rows.mapInArrow(run, "prefix long, next int, enabled array<int>, freq long")
    # A prefix travels as one number; the enabled set is a function of the prefix, observed nexts are few a prefix.
    each = states.groupBy("prefix", "next", "enabled").agg(F.sum("freq").alias("freq")).groupBy("prefix", "enabled").agg(F.collect_set("next").alias("seen"), F.sum("freq").alias("freq"))
    sums = each.select((F.size("enabled") * F.col("freq")).alias("e"), (F.size(F.array_except("enabled", "seen")) * F.col("freq")).alias("x")).agg(F.coalesce(F.sum("e"), F.lit(0)).alias("enabled"), F.coalesce(F.sum("x"), F.lit(0)).alias("escaping"))
    return sums.select("enabled", "escaping", F.when(F.col("enabled") > 0, 1 - F.col("escaping") / F.col("enabled")).otherwise(1.0).alias("precision"))


def f1(fitness: float | None, precision: float | None) -> float | None:
    """Harmonic mean (A5)."""
    if fitness is None or precision is None:
        return None
    return 0.0 if fitness + precision == 0 else 2 * fitness * precision / (fitness + precision)


def size(places: list[Place]) -> dict[str, float]:
    """Places, arcs and mean depth."""
    arcs = [len(i) + len(o) for i, o in places]
    return {"places": len(places), "arcs": sum(arcs), "mean_depth": float(np.mean(arcs)) if arcs else 0.0}


def replay_fitness(log: SparkLog, places: list[Place]) -> DataFrame:
    """produced, consumed, missing, remaining tokens over all traces and places, and the classic replay fitness."""
    n = len(log.labels)
    shared = log.variants.sparkSession.sparkContext.broadcast(places)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(4, np.int64)
        ins = [{j for j, p in enumerate(shared.value) if a in p[0]} for a in range(n)]
        outs = [{j for j, p in enumerate(shared.value) if a in p[1]} for a in range(n)]
        for batch in batches:
            for seq, freq in zip(batch.column("seq").to_pylist(), batch.column("freq").to_pylist()):
                tokens, made, used, missing = [0] * len(shared.value), 0, 0, 0
                for a in seq:
                    for j in outs[a]:
                        used += 1
                        if tokens[j]:
                            tokens[j] -= 1
                        else:
                            missing += 1
                    for j in ins[a]:
                        made += 1
                        tokens[j] += 1
                total += freq * np.array([made, used, missing, sum(tokens)], np.int64)
        yield pa.RecordBatch.from_arrays([pa.array([int(x)]) for x in total], names=["produced", "consumed", "missing", "remaining"])

    sums = log.variants.select("seq", "freq").mapInArrow(run, "produced long, consumed long, missing long, remaining long").agg(*[F.sum(c).alias(c) for c in ("produced", "consumed", "missing", "remaining")])
    ratio = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(0.0)
    return sums.withColumn("fitness", 0.5 * (1 - ratio("missing", "consumed")) + 0.5 * (1 - ratio("remaining", "produced")))


def dead_activities(log: SparkLog, places: list[Place], start: int, end: int, limit: int = 20_000) -> list[str]:
    """Activities that no model trace can contain, as far as that is certain."""
    return [a for a, s in activity_status(log, places, start, end, limit).items() if s == "dead"]


def activity_status(log: SparkLog, places: list[Place], start: int, end: int, limit: int = 20_000) -> dict[str, str]:
    """``live`` (some model trace goes as far as it), ``dead`` (none does), or ``unknown`` where ``limit`` markings did not tell."""
    machine = Machine(places, len(log.labels), start, end)
    first = machine.fire(machine.zero, start)
    if first is None:
        return {a: "dead" for i, a in enumerate(log.labels) if i not in (start, end)}
    # Fewer tokens first: a net whose tokens can grow without end then still shows most of what it can do.
    seen, queue, fired = {first}, [(sum(first), first)], set()
    while queue and len(seen) < limit:
        m = heapq.heappop(queue)[1]
        for a in range(machine.n):
            if a in (start, end):
                continue
            nxt = machine.fire(m, a)
            if nxt is not None:
                fired.add(a)
                if nxt not in seen:
                    seen.add(nxt)
                    heapq.heappush(queue, (sum(nxt), nxt))
    rest = "unknown" if queue else "dead"
    return {a: "live" if i in fired else rest for i, a in enumerate(log.labels) if i not in (start, end)}
