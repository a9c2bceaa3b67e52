"""Incremental logs and online conformance. The same code runs on static tables."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import ArrayType, IntegerType, LongType, StringType, StructField, StructType

from ..functions.places import END, START


def read_events(spark: SparkSession, path: str, schema: StructType, late: str = "1 day", files: int = 1) -> DataFrame:
    """Events of a folder as a stream, with a watermark on ``ts``; repeated event_ids within it are dropped (T-6)."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    return prepared(raw, late)


def prepared(raw: DataFrame, late: str = "1 day") -> DataFrame:
    timed = raw.withColumn("ts", F.col("ts").cast("timestamp"))
    if raw.isStreaming:
        return timed.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return timed.dropDuplicates(["event_id"])


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """user_id, start, seq of closed sessions (T-1); events inside are sorted by time and id, whatever order they came in (T-4)."""
    closed = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("es"))
    body = F.transform("es", lambda e: e["event_type"])
    return closed.select("user_id", F.col("w.start").alias("start"), F.concat(F.array(F.lit(START)), body, F.array(F.lit(END))).alias("seq"))


def windowed_counts(events: DataFrame, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """Activity counts per tumbling or sliding window (T-2)."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def windowed_follows(closed: DataFrame, length: str = "1 day") -> DataFrame:
    """Directly-follows counts per window of the session's start (T-2); ``closed`` comes from :func:`sessions`."""
    steps = F.zip_with(F.slice("seq", F.lit(1), F.size("seq") - 1), F.slice("seq", F.lit(2), F.size("seq") - 1), lambda a, b: F.struct(a.alias("src"), b.alias("dst")))
    rows = closed.select("start", F.explode(steps).alias("s"))
    return rows.groupBy(F.window("start", length).alias("w"), F.col("s.src").alias("src"), F.col("s.dst").alias("dst")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "src", "dst", "n")


ALERTS = "case_id string, place int, kind string, n_events long"


def replay_case(places: list[tuple[tuple[str, ...], tuple[str, ...]]], tokens: list[int], activities: list[str]) -> tuple[list[int], list[int]]:
    """Tokens after more events, and the places that starved on the way."""
    tokens, starved = list(tokens), []
    for a in activities:
        for j, (pre, post) in enumerate(places):
            tokens[j] -= a in post
            if tokens[j] < 0 and j not in starved:
                starved.append(j)
            tokens[j] += a in pre
    return tokens, starved


class Conformance(StatefulProcessor):
    """State of a case: a token count a place, the places already reported, the number of events.

    Starved places are reported at once, left-over tokens when a case ends with an event of ``end_activity`` or has been quiet for
    ``timeout_ms`` of event time.
    """

    def __init__(self, places: list, end_activity: str | None, timeout_ms: int):
        self.places, self.end_activity, self.timeout_ms = places, end_activity, timeout_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.state = handle.getValueState("case", StructType([StructField("tokens", ArrayType(IntegerType())), StructField("told", ArrayType(IntegerType())), StructField("n", LongType()), StructField("last", LongType())]))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        events = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        if self.state.exists():
            tokens, told, n, last = self.state.get()
            tokens, told = list(tokens), list(told)
        else:
            tokens, _ = replay_case(self.places, [0] * len(self.places), [START])
            told, n, last = [], 0, 0
        out = []
        done = False
        for a in events["event_type"]:
            tokens, starved = replay_case(self.places, tokens, [a])
            n += 1
            for j in starved:
                if j not in told:
                    told.append(j)
                    out.append((key[0], j, "underfed", n))
            if self.end_activity is not None and a == self.end_activity:
                out += self._finish(key[0], tokens, told, n)
                done = True
                break
        if done:
            self.state.clear()
        else:
            at = int(events["ts"].max().timestamp() * 1000)
            self.state.update((tokens, told, n, max(last, at)))
            self.handle.registerTimer(max(last, at) + self.timeout_ms)
        yield pd.DataFrame(out, columns=["case_id", "place", "kind", "n_events"])

    def _finish(self, case: str, tokens: list[int], told: list[int], n: int) -> list[tuple]:
        tokens, starved = replay_case(self.places, tokens, [END])
        out = [(case, j, "underfed", n) for j in starved if j not in told]
        return out + [(case, j, "overfed", n) for j, t in enumerate(tokens) if t > 0]

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        rows = []
        if self.state.exists():
            tokens, told, n, last = self.state.get()
            if expiredTimerInfo.getExpiryTimeInMs() >= last + self.timeout_ms:
                rows = self._finish(key[0], list(tokens), list(told), n)
                self.state.clear()
        yield pd.DataFrame(rows, columns=["case_id", "place", "kind", "n_events"])

    def close(self) -> None:
        pass


def conformance_stream(events: DataFrame, places: list, end_activity: str | None = None, timeout_ms: int = 6 * 3600 * 1000) -> DataFrame:
    """Alerts (case_id, place, kind, n_events) of a stream of events (case_id, ts, event_id, event_type) (T-3)."""
    schema = StructType([StructField("case_id", StringType()), StructField("place", IntegerType()), StructField("kind", StringType()), StructField("n_events", LongType())])
    return events.groupBy("case_id").transformWithStateInPandas(Conformance(places, end_activity, timeout_ms), schema, "Append", "eventTime")


def conformance_batch(events: DataFrame, places: list, case: str = "case_id") -> DataFrame:
    """What the stream reports once all cases have ended, from a static table (T-7)."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        told, rows, tokens = [], [], replay_case(places, [0] * len(places), [START])[0]
        for k, a in enumerate(pdf.sort_values(["ts", "event_id"])["event_type"], 1):
            tokens, starved = replay_case(places, tokens, [a])
            for j in starved:
                if j not in told:
                    told.append(j)
                    rows.append((pdf[case].iloc[0], j, "underfed", k))
        n = len(pdf)
        tokens, starved = replay_case(places, tokens, [END])
        rows += [(pdf[case].iloc[0], j, "underfed", n) for j in starved if j not in told]
        rows += [(pdf[case].iloc[0], j, "overfed", n) for j, t in enumerate(tokens) if t > 0]
        return pd.DataFrame(rows, columns=["case_id", "place", "kind", "n_events"])

    return events.groupBy(case).applyInPandas(run, ALERTS)


class Rediscovery:
    """Counts of variants across micro-batches, and places evaluated anew on each (T-5).

    Counts add up, so each batch's closed traces are evaluated alone; when a place crosses the threshold ``on_cross`` is called.
    Use ``batch`` with foreachBatch; a batch id is counted once however often it is retried.
    """

    def __init__(self, places: list, tau: float, on_cross=None):
        self.places, self.tau, self.on_cross = places, tau, on_cross
        self.counts: dict[int, tuple[list[int], int]] = {}

    def batch(self, traces: DataFrame, batch_id: int) -> None:
        from ..functions.replay import place_fits

        fits = [F.count_if(place_fits("seq", F.array(*map(F.lit, pre)), F.array(*map(F.lit, post)))).alias(f"f{j}") for j, (pre, post) in enumerate(self.places)]
        row = traces.agg(F.count(F.lit(1)).alias("n"), *fits).first()
        before = self.passing()
        self.counts[batch_id] = ([row[f"f{j}"] for j in range(len(self.places))], row["n"])
        crossed = before ^ self.passing()
        if crossed and self.on_cross and len(self.counts) > 1:
            self.on_cross(sorted(crossed))

    def passing(self) -> set[int]:
        n = sum(t for _, t in self.counts.values())
        return {j for j in range(len(self.places)) if n and sum(f[j] for f, _ in self.counts.values()) >= self.tau * n}
