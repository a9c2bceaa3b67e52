"""Mixing sources to target weights by Sainte-Lague apportionment (op 10).

Each source's documents are laid end to end in a seeded order and cut into blocks of equal token
counts. Quotas of blocks go to the sources one at a time, each to the highest quotient
``target / (2 * given + 1)``; consecutive stretches of that sequence are the integer quotas of the
output shards (the rule is house-monotone, so quotas of a prefix never shrink). A source's blocks are
then taken in a seeded order, going round again where the quota exceeds them, at most ``limit`` times.

Targets: the weights 5, 2, 1 repeat over the sources by code point, null last, and share all tokens;
a source above ``limit`` times its size stays there and the excess is shared again by weight.

Only per-source sums (one row a source) and the block plan (at most ``max_blocks`` + sources rows)
meet on the driver; more than ``SOURCES`` sources are refused. Running positions come from slices of the seeded order, so a source with a third
of all rows is spread over as many tasks as there are slices. Edge cases: a null or blank text has
size 0 and is never taken; very long texts are counted whole; an empty table gives an empty result; equal rows are placed side by side;
a row without a doc_id is a document by its source and text; other columns, whatever their names, are not read by :func:`mix` and kept by :func:`mixed`.
"""

from __future__ import annotations

import hashlib
import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import WORD, checkpointed, draw, partitions

CYCLE = (5, 2, 1)
LIMIT = 3
#: Sources that the driver apportions at most; rows of the plan that are broadcast at most (about 20 MB).
SOURCES = 500_000
STEPS = 100_000
#: Documents of a slice, about, within which whole documents settle what others leave over.
ROWS = 2000


def named():
    """The key of a document: its doc_id, or else its source and text."""
    own = F.concat_ws("|", F.lit("null"), F.coalesce("source", F.lit("")), F.xxhash64("text").cast("string"))
    return F.coalesce(F.col("doc_id").cast("string"), own)


def targets(sizes: dict[str | None, int], cycle: tuple[int, ...] = CYCLE, limit: int = LIMIT) -> dict[str | None, float]:
    """Tokens wanted of each source (driver)."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: cycle[i % len(cycle)] for i, s in enumerate(order)}
    left, open_, out = float(sum(sizes.values())), list(order), {}
    while open_:
        total = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / total > limit * sizes[s]]
        if not over:
            out |= {s: left * weight[s] / total for s in open_}
            break
        for s in over:
            out[s] = float(limit * sizes[s])
        left -= sum(out[s] for s in over)
        open_ = [s for s in open_ if s not in out]
    return {s: out[s] for s in order}


def quotas(wanted: dict[str | None, float], most: dict[str | None, int], blocks: int, shards: int) -> list[dict[str | None, int]]:
    """Blocks of each source in each output shard, by highest quotients (driver)."""
    given = dict.fromkeys(wanted, 0)
    rank = {s: i for i, s in enumerate(wanted)}
    heap = [(-t, rank[s], s) for s, t in wanted.items() if t > 0 and most[s] > 0]
    heapq.heapify(heap)
    ends = [round(blocks * (i + 1) / shards) for i in range(shards)]
    out, before, step = [], dict(given), 0
    for end in ends:
        while step < end and heap:
            _, _, s = heapq.heappop(heap)
            given[s] += 1
            step += 1
            if given[s] < most[s]:
                heapq.heappush(heap, (-wanted[s] / (2 * given[s] + 1), rank[s], s))
        out.append({s: given[s] - before[s] for s in given})
        before = dict(given)
    return out


def _order(seed: str, source: str | None, n: int) -> np.ndarray:
    """A seeded permutation of a source's blocks."""
    key = int.from_bytes(hashlib.blake2b(f"{seed}|{source!r}".encode(), digest_size=8).digest(), "big")
    return np.random.Generator(np.random.PCG64(key)).permutation(n)


def plan(sizes: dict[str | None, int], *, seed: str = "mix-1", max_blocks: int = 16384, shards: int = 8) -> tuple[int, dict, list[tuple]]:
    """Tokens a block, targets, and rows (source, block, times, quota of each shard) (driver)."""
    total = sum(sizes.values())
    block = max(1, math.ceil(total / max_blocks))
    wanted = targets(sizes)
    have = {s: math.ceil(n / block) for s, n in sizes.items()}
    # A short last block makes a turn shorter than its blocks suggest, so quotas count turns of the real size.
    most = {s: LIMIT * n for s, n in have.items()}
    per_turn = {s: wanted[s] / sizes[s] * have[s] if sizes[s] else 0.0 for s in sizes}
    parts = quotas(per_turn, most, round(sum(per_turn.values())), shards)
    rows = []
    for s, n in have.items():
        if not n:
            continue
        turn = _order(seed, s, n)
        times, by_shard, at = np.zeros(n, dtype=np.int64), [[0] * shards for _ in range(n)], 0
        for k, part in enumerate(parts):
            for i in range(at, at + part[s]):
                b = int(turn[i % n])
                times[b] += 1
                by_shard[b][k] += 1
            at += part[s]
        rows += [(s, b, int(times[b]), by_shard[b]) for b in range(n)]
    return block, wanted, rows


def mix(docs: DataFrame, *, seed: str = "mix-1", max_blocks: int = 16384, shards: int = 8) -> DataFrame:
    """doc_id, size, source, source_size, target, taken, the words each output shard takes of the document (``by_shard``), and its key and draw."""
    spark = docs.sparkSession
    sized = docs.select(
        "doc_id", "source",
        F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
        F.crc32("text").alias("__crc"),
        named().alias("__key"),
    ).withColumn("__u", draw(seed, F.col("__key")))
    slices = partitions(spark)
    cut = sized.withColumn("__slice", F.floor(F.col("__u") * slices).cast("int"))
    sums = cut.groupBy("source", "__slice").agg(F.sum("size").alias("__n"))
    before = W.partitionBy("source").orderBy("__slice").rowsBetween(W.unboundedPreceding, -1)
    offsets = sums.select(F.col("source").alias("__source"), F.col("__slice").alias("__part"), F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__before"))
    sizes = {r["source"]: int(r["n"]) for r in sums.groupBy("source").agg(F.sum("__n").alias("n")).limit(SOURCES + 1).collect()}
    if len(sizes) > SOURCES:
        raise ValueError(f"more than {SOURCES} sources")
    block, wanted, rows = plan(sizes, seed=seed, max_blocks=max_blocks, shards=shards)

    inside = W.partitionBy("source", "__slice").orderBy("__u", "doc_id", "__crc", "size").rowsBetween(W.unboundedPreceding, -1)
    placed = cut.join(offsets, cut["source"].eqNullSafe(offsets["__source"]) & (cut["__slice"] == offsets["__part"])).select(
        "doc_id", "__key", "__u", "source", "size", (F.col("__before") + F.coalesce(F.sum("size").over(inside), F.lit(0))).alias("__start")
    )
    # What is taken of a document is the difference of the taken tokens before its end and before its start.
    cumulative, at = [], {}
    for s, b, times, by_shard in [*rows, *[(s, math.ceil(n / block), 0, [0] * shards) for s, n in sizes.items()]]:
        total, each = at.get(s, (0, [0] * shards))
        cumulative.append((s, b, times, total, by_shard, each))
        at[s] = (total + times * block, [x + y * block for x, y in zip(each, by_shard)])
    steps = spark.createDataFrame(cumulative, "b_source string, b_block long, b_times long, b_total long, b_shards array<long>, b_totals array<long>")

    bounded = F.broadcast if len(cumulative) <= STEPS else lambda df: df

    def before_position(df: DataFrame, position: str, name: str) -> DataFrame:
        block_of = F.floor(F.col(position) / block)
        into = F.col(position) - block_of * block
        hit = df.join(bounded(steps), df["source"].eqNullSafe(steps["b_source"]) & (block_of == steps["b_block"]))
        return hit.withColumn(name, F.col("b_total") + into * F.col("b_times")).withColumn(
            name + "_by", F.array(*[F.col("b_totals")[k] + into * F.col("b_shards")[k] for k in range(shards)])
        ).drop("b_source", "b_block", "b_times", "b_total", "b_shards", "b_totals")

    ranged = before_position(before_position(placed.withColumn("__end", F.col("__start") + F.col("size")), "__start", "__from"), "__end", "__to")
    facts = spark.createDataFrame([(s, sizes[s], float(wanted[s])) for s in sizes], "t_source string, source_size long, target double")
    return ranged.join(bounded(facts), ranged["source"].eqNullSafe(facts["t_source"])).select(
        "doc_id", "size", "source", "source_size", "target", "__key", "__u",
        (F.col("__to") - F.col("__from")).cast("long").alias("taken"),
        F.array(*[F.col("__to_by")[k] - F.col("__from_by")[k] for k in range(shards)]).alias("by_shard"),
    )


def _whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Whole times for documents in order: what rounding leaves over or owes is carried to the next one of the slice."""
    group, owed = None, 0
    for batch in batches:
        times = []
        for source, part, size, taken in zip(*(batch.column(c).to_pylist() for c in ("source", "__slice", "size", "taken"))):
            if (source, part) != group:
                group, owed = (source, part), 0
            owed += taken
            n = min(LIMIT, max(0, (2 * owed + size) // (2 * size))) if size else 0
            owed -= n * size
            times.append(n)
        yield pa.RecordBatch.from_arrays([batch.column("__key"), pa.array(times, pa.int32())], names=["__id", "__times"])


def mixed(docs: DataFrame, *, seed: str = "mix-1", **options) -> DataFrame:
    """The rows of ``docs``, each a whole number of times, with the columns of ``docs``; a source's words stay near its target.

    Within each slice of a source the documents come from large to small, and each is taken as often as its share
    and what earlier ones left over say, so that the small ones settle the rest. Rows that repeat a doc_id are one document.
    """
    slices = partitions(docs.sparkSession)
    one = mix(docs, seed=seed, **options).groupBy("__key", "__u").agg(F.sum("taken").alias("taken"), F.sum("size").alias("size"), F.min("source").alias("source"))
    # A small source is one slice, so that what one document leaves over meets another of them; one row a source is bounded by ``SOURCES``.
    one = checkpointed(one)
    cut = one.groupBy(F.col("source").alias("__source")).agg(F.least(F.lit(slices), F.ceil(F.count(F.lit(1)) / ROWS)).alias("__slices"))
    sliced = one.join(F.broadcast(cut), one["source"].eqNullSafe(cut["__source"])).withColumn("__slice", F.floor(F.col("__u") * F.col("__slices")).cast("int"))
    line = sliced.repartition(slices, "source", "__slice")
    order = ["source", "__slice", F.desc("size"), "__u", "__key"]
    times = line.sortWithinPartitions(*order).select("__key", "source", "__slice", "size", "taken").mapInArrow(_whole, "__id string, __times int")
    kept = docs.withColumn("__id", named()).join(times.where("__times > 0"), "__id")
    return kept.withColumn("__turn", F.explode(F.sequence(F.lit(1), F.col("__times")))).select(*docs.columns)
