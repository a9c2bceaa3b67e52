"""Events, timings and progress of a run."""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Callable
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

LEVELS = ("off", "reduced", "full")


@dataclass
class Supervisor:
    """``off`` records nothing, ``reduced`` counts and times, ``full`` also keeps accepted places with their time."""

    run_id: str = "run"
    level: str = "reduced"
    on_place: Callable[[tuple, float], None] | None = None
    started: float = field(default_factory=time.time)
    events: Counter = field(default_factory=Counter)
    timings: list[tuple[str, float]] = field(default_factory=list)
    curve: list[tuple[float, int, int]] = field(default_factory=list)
    depth: int = 0
    visited: int = 0
    considered: int = 0
    space: int = 0

    def count(self, component: str, event: str, n: int = 1) -> None:
        if self.level != "off" and n:
            self.events[component, event] += n

    @contextmanager
    def timed(self, task: str):
        t = time.time()
        yield
        if self.level != "off":
            self.timings.append((task, time.time() - t))

    def accepted(self, place: tuple, evaluated: int, size: int) -> None:
        if self.level == "full":
            self.curve.append((time.time() - self.started, evaluated, size))
        if self.on_place:
            self.on_place(place, time.time() - self.started)

    def progress(self) -> dict:
        """Visited share, share considered with what cuts removed, deepest level, seconds (S3)."""
        s = max(1, self.space)
        return {"visited": self.visited / s, "considered": (self.visited + self.considered) / s, "depth": self.depth, "seconds": time.time() - self.started}

    def event_table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(self.run_id, c, e, n) for (c, e), n in sorted(self.events.items())], "run_id string, component string, event string, n long")

    def timing_table(self, spark: SparkSession) -> DataFrame:
        """Mean, least, most and number of timings of each task."""
        from pyspark.sql import functions as F

        rows = spark.createDataFrame([(self.run_id, t, s) for t, s in self.timings], "run_id string, task string, seconds double")
        return rows.groupBy("run_id", "task").agg(F.avg("seconds").alias("mean_s"), F.min("seconds").alias("min_s"), F.max("seconds").alias("max_s"), F.count("seconds").alias("n"))
