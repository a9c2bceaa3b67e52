"""Fitness of places over a log: engines, early decision, support, token series.

Engines
- ``sql``: variants joined to broadcast places, higher-order functions; the reference.
- ``window``: exploded events with running sums; for giant traces, spills.
- ``arrow``: variants stay distributed, places are broadcast in chunks, tasks send partial sums.
- ``frontier``: places stay distributed, a log of at most ``BROADCAST_CELLS`` events is broadcast.
- ``auto``: ``frontier`` if the log is that small, else ``arrow``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.replay import token_series as _token_series
from ..functions.replay import trace_state
from .kernel import Block, Place

CHUNK = 4096
BROADCAST_CELLS = 4_000_000
COUNTS = ("n_fit", "n_under", "n_over", "n_unbalanced")
_SCHEMA = "place long, n_fit long, n_under long, n_over long, n_unbalanced long"


def _block(batch: pa.RecordBatch, n_acts: int) -> Block:
    return Block(batch.column("seq").to_pylist(), batch.column("freq").to_pylist(), n_acts)


@dataclass
class SparkLog:
    """A log of encoded variants (variant_id, seq array<int>, freq)."""

    variants: DataFrame
    labels: list[str]
    _total: int | None = field(default=None, repr=False)
    _cells: int | None = field(default=None, repr=False)
    _local: Block | None = field(default=None, repr=False)

    def _measure(self) -> None:
        row = self.variants.agg(F.sum("freq"), F.sum(F.size("seq"))).first()
        if not row[0]:
            raise ValueError("the log is empty")
        self._total, self._cells = int(row[0]), int(row[1])

    @property
    def total(self) -> int:
        if self._total is None:
            self._measure()
        return self._total

    @property
    def small(self) -> bool:
        """Whether the log may be broadcast."""
        if self._cells is None:
            self._measure()
        return self._cells <= BROADCAST_CELLS

    def local(self) -> Block:
        """The log as one block, if it is small (driver)."""
        if not self.small:
            raise ValueError(f"{self._cells} events are more than {BROADCAST_CELLS}")
        if self._local is None:
            rows = self.variants.select("seq", "freq").toArrow()
            self._local = Block(rows.column("seq").to_pylist(), rows.column("freq").to_pylist(), len(self.labels))
        return self._local

    def _each(self, fn, schema: str, *columns: str) -> DataFrame:
        """``fn(Block)`` on each batch of variants; it returns a dict of columns."""
        n = len(self.labels)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if len(batch):
                    yield pa.RecordBatch.from_pydict(fn(_block(batch, n)))

        return self.variants.select("seq", "freq", *columns).mapInArrow(run, schema)

    def counts(self, places: list[Place]) -> np.ndarray:
        """fit, under, over, unbalanced of a bounded list of places (driver)."""
        if self.small:
            return self.local().counts(places)
        out = np.zeros((len(places), 4), np.int64)
        for j in range(0, len(places), CHUNK):
            for r in self._partial(places[j : j + CHUNK]).collect():
                out[j + r["place"]] = [r[c] for c in COUNTS]
        return out

    def _partial(self, places: list[Place]) -> DataFrame:
        shared = self.variants.sparkSession.sparkContext.broadcast(places)
        n = len(self.labels)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros((len(shared.value), 4), np.int64)
            for batch in batches:
                total += _block(batch, n).counts(shared.value)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), *[pa.array(total[:, c]) for c in range(4)]], names=["place", *COUNTS])

        return self.variants.select("seq", "freq").mapInArrow(run, _SCHEMA).groupBy("place").agg(*[F.sum(c).alias(c) for c in COUNTS])

    def support(self, places: list[Place]) -> int:
        """Traces that fit all places (V6)."""
        if not places:
            return self.total
        if self.small:
            return self.local().support(places)
        return int(self._each(lambda b: {"n": [b.support(places)]}, "n long").agg(F.sum("n")).first()[0] or 0)

    def first_unfit(self, places: list[Place]) -> set[int]:
        """Positions of places that are the first misfit of some variant; one aggregation of distinct positions."""
        if not places:
            return set()
        if self.small:
            return self.local().first_unfit(places)
        return {r["i"] for r in self._each(lambda b: {"i": sorted(b.first_unfit(places))}, "i long").distinct().collect()}

    def beside(self, place: Place, others: list[Place]) -> tuple[np.ndarray, np.ndarray]:
        """For each of ``others`` whether it never holds more tokens than ``place``, and whether it never holds fewer."""
        if self.small:
            return self.local().beside(place, others)
        below = self.dominance([place, *others])
        return below[0, 1:], below[1:, 0]

    def dominance(self, places: list[Place], scope: str = "all") -> np.ndarray:
        if self.small:
            return self.local().dominance(places, scope)
        n = len(places)
        lost = self._each(lambda b: {"i": np.flatnonzero(~b.dominance(places, scope).ravel()).tolist()}, "i long").distinct().collect()
        out = np.ones(n * n, bool)
        out[[r["i"] for r in lost]] = False
        return out.reshape(n, n)

    def misfits(self, place: Place, given: list[Place]) -> int:
        """Traces that fit all of ``given`` but not ``place``."""
        return self.support(given) - self.support([*given, place])


def _fractions(counts: DataFrame, total) -> DataFrame:
    return counts.withColumn("n_total", F.lit(total).cast("long") if not hasattr(total, "alias") else total).withColumns({c: F.col(f"n_{c}") / F.col("n_total") for c in ("fit", "under", "over")})


def fitness(log: SparkLog, places: DataFrame, engine: str = "auto", chunk: int = CHUNK) -> DataFrame:
    """``places`` (place_id, pre, post as arrays of activity ids, ...) with the counts and fractions."""
    if engine == "auto":
        engine = "frontier" if log.small else "arrow"
    total = log.total
    if engine == "frontier":
        return _fractions(_frontier(log, places), total)
    if engine == "sql":
        state = trace_state("seq", "pre", "post")
        # The theta join has no key: every place meets every variant, which is the work asked for.
        each = log.variants.select("seq", "freq").join(F.broadcast(places.select("place_id", "pre", "post"))).select("place_id", "freq", state.alias("s"))
        sums = each.groupBy("place_id").agg(*[F.sum(F.when(F.col(f"s.{c[2:]}"), F.col("freq")).otherwise(0)).alias(c) for c in COUNTS])
        return _fractions(places.join(sums, "place_id"), total)
    if engine == "window":
        rows = log.variants.select("variant_id", "freq", F.posexplode("seq").alias("pos", "act")).join(F.broadcast(places.select("place_id", "pre", "post")))
        w = W.partitionBy("place_id", "variant_id").orderBy("pos")
        made = F.sum(F.array_contains("pre", F.col("act")).cast("int")).over(w.rowsBetween(W.unboundedPreceding, -1))
        used = F.sum(F.array_contains("post", F.col("act")).cast("int")).over(w.rowsBetween(W.unboundedPreceding, 0))
        slack = rows.select("place_id", "variant_id", "freq", (F.coalesce(made, F.lit(0)) - used).alias("slack"), (F.array_contains("pre", F.col("act")).cast("int") - F.array_contains("post", F.col("act")).cast("int")).alias("net"))
        ends = slack.groupBy("place_id", "variant_id").agg(F.first("freq").alias("freq"), F.min("slack").alias("least"), F.sum("net").alias("final"))
        tests = {"n_fit": "least >= 0 AND final = 0", "n_under": "least < 0", "n_over": "final > 0", "n_unbalanced": "final <> 0"}
        sums = ends.groupBy("place_id").agg(*[F.sum(F.when(F.expr(t), F.col("freq")).otherwise(0)).alias(c) for c, t in tests.items()])
        return _fractions(places.join(sums, "place_id"), total)
    if engine != "arrow":
        raise ValueError(f"unknown engine {engine}")
    # Chunks of places pass through the driver one at a time; never the whole frontier.
    spark, out, held = places.sparkSession, None, []

    def flush() -> None:
        nonlocal out
        part = log._partial([(tuple(r["pre"]), tuple(r["post"])) for r in held])
        ids = spark.createDataFrame([(i, r["place_id"]) for i, r in enumerate(held)], "place long, place_id string")
        named = part.join(F.broadcast(ids), "place").drop("place")
        out = named if out is None else out.union(named)
        held.clear()

    for r in places.select("place_id", "pre", "post").toLocalIterator():
        held.append(r)
        if len(held) == chunk:
            flush()
    if held or out is None:
        flush()
    return _fractions(places.join(out, "place_id"), total)


def _frontier(log: SparkLog, places: DataFrame) -> DataFrame:
    b = log.local()
    shared = places.sparkSession.sparkContext.broadcast(([s.tolist() for s in b.seqs], b.freq.tolist(), b.n_acts))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Block(*shared.value)
        for batch in batches:
            n = own.counts([(tuple(i), tuple(o)) for i, o in zip(batch.column("pre").to_pylist(), batch.column("post").to_pylist())])
            for c, name in enumerate(COUNTS):
                batch = batch.append_column(name, pa.array(n[:, c]))
            yield batch

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in places.schema.fields) + ", " + ", ".join(f"{c} long" for c in COUNTS)
    return places.mapInArrow(run, schema)


def decide(log: SparkLog, places: list[Place], tau: float, head_mass: float = 0.5) -> dict[Place, tuple[bool, str]]:
    """Whether each place reaches ``tau``, and on which part of the log that was known (V5, driver for a bounded list).

    The heaviest variants are replayed first; places whose misfits there already exceed what ``tau`` allows are settled.
    """
    from .log import subset

    head = SparkLog(subset(log.variants, top_mass=head_mass), log.labels)
    n = log.total
    allowed = n - -(-round(tau * 1_000_000) * n // 1_000_000)
    seen = head.total
    first = head.counts(places)
    out: dict[Place, tuple[bool, str]] = {}
    rest = []
    for p, c in zip(places, first):
        if seen - c[0] > allowed:
            out[p] = (False, "head")
        else:
            rest.append(p)
    if rest:
        for p, c in zip(rest, log.counts(rest)):
            out[p] = (bool(c[0] >= n - allowed), "all")
    return out


def counts_projected(log: SparkLog, places: list[Place], width: int = 12) -> np.ndarray:
    """Counts of a bounded list of places, each chunk of them on the log restricted to its activities (at most ``width`` where
    places allow) and compressed again: variants that differ elsewhere fall together, which helps where most traces are unique."""
    from .log import project

    order = sorted(range(len(places)), key=lambda i: places[i])
    chunks: list[tuple[set[int], list[int]]] = []
    for i in order:
        acts = {*places[i][0], *places[i][1]}
        if chunks and len(chunks[-1][0] | acts) <= max(width, len(acts)):
            chunks[-1][0].update(acts)
            chunks[-1][1].append(i)
        else:
            chunks.append((acts, [i]))
    out = np.zeros((len(places), 4), np.int64)
    for acts, members in chunks:
        part = SparkLog(project(log.variants, sorted(acts)), log.labels)
        out[members] = part.counts([places[i] for i in members])
    return out


def relative_fitness(log: SparkLog, places: list[Place]) -> DataFrame:
    """place, n_touching, n_fit_touching: fitness among the traces that hold an adjacent activity."""

    def one(b: Block) -> dict:
        touch, fit = b.touching(places), b.fits(places)
        return {"place": list(range(len(places))), "n_touching": (b.freq @ touch).tolist(), "n_fit_touching": (b.freq @ (touch & fit)).tolist()}

    return log._each(one, "place long, n_touching long, n_fit_touching long").groupBy("place").agg(F.sum("n_touching").alias("n_touching"), F.sum("n_fit_touching").alias("n_fit_touching"))


def token_series(log: SparkLog, places: DataFrame) -> DataFrame:
    """place_id, variant_id, tokens after each event (V7)."""
    return log.variants.select("variant_id", "seq").join(F.broadcast(places.select("place_id", "pre", "post"))).select("place_id", "variant_id", _token_series("seq", "pre", "post").alias("tokens"))


def set_support(log: SparkLog, places: list[Place]) -> DataFrame:
    """n_fit, n_total, share of traces that fit every place (V6)."""
    n, total = log.support(places), log.total
    return log.variants.sparkSession.createDataFrame([(n, total, n / total)], "n_fit long, n_total long, share double")


def sampled_fitness(log: SparkLog, places: list[Place], fraction: float, seed: int = 0) -> list[tuple[float, float]]:
    """Estimate and standard error of the fit of each place from a sample of variants; never used for cuts."""
    from .log import subset

    part = SparkLog(subset(log.variants, fraction=fraction, seed=seed), log.labels)
    n, c = part.total, part.counts(places)
    return [(float(f) / n, float(np.sqrt(max(f / n * (1 - f / n), 0) / n))) for f in c[:, 0]]
