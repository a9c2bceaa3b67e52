"""Connected components of a graph of long identifiers, without collecting it anywhere.

Edge cases: null ends and loops are left out, repeated edges count once, an empty graph has no node. A node with very many edges (the centre of a star)
meets its neighbours by a broadcast of a bounded number of such nodes, never in one task.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed


#: Edges that one task of a round writes at least; nodes that a task holds before it writes their stars.
EDGES_PER_FILE = 100_000
HELD = 1_000_000
#: A key is hot with more than ``HOT`` rows and more than one of ``SHARE`` of all rows: there are fewer than ``SHARE`` hot keys.
HOT = 100_000
SHARE = 10_000


def spread_join(big: DataFrame, small: DataFrame, key: str, times: str, least: int | None = None) -> DataFrame:
    """``big`` joined to ``small``, a held table that has each key once with the number ``times`` of its rows in ``big``.

    The few hot keys (more than ``least`` rows, ``HOT`` by default; fewer than ``SHARE``, whatever the input) are broadcast, so that their rows stay where they are; all others are shuffled.
    """
    facts = small.agg(F.sum(times).alias("rows"), F.max(times).alias("most")).first()
    limit = max(HOT if least is None else least, (facts["rows"] or 0) // SHARE)
    if (facts["most"] or 0) <= limit:
        return big.join(small, key)
    hot = small.sparkSession.createDataFrame(small.where(F.col(times) > limit).collect(), small.schema)
    rest = big.join(F.broadcast(hot.select(key)), key, "left_anti").join(small, key)
    return big.join(F.broadcast(hot), key).unionByName(rest)


def _forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A task's edges as stars around the least node of each of its components, ``HELD`` nodes at a time."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while (p := parent.setdefault(x, x)) != x:
            parent[x] = parent[p]
            x = p
        return x

    def stars() -> Iterator[pa.RecordBatch]:
        pairs = [(x, r) for x in list(parent) if (r := root(x)) != x]
        for i in range(0, len(pairs), 100_000):
            u, v = zip(*pairs[i : i + 100_000])
            yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], names=["u", "v"])

    for batch in batches:
        for a, b in zip(batch.column("u").to_pylist(), batch.column("v").to_pylist()):
            a, b = root(a), root(b)
            if a != b:
                parent[max(a, b)] = min(a, b)
        if len(parent) > HELD:
            yield from stars()
            parent.clear()
    yield from stars()


def connected(edges: DataFrame, limit: int = 60) -> DataFrame:
    """(node, root) for every node of the edges (u, v); the root is the least node of the component.

    Each round hangs every larger neighbour of a node under the least of its neighbours, then every
    smaller one (two small-key aggregations and joins), until nothing changes. Where a node has more than ``HOT`` edges, such nodes are joined apart.
    """
    edges = edges.where("u IS NOT NULL AND v IS NOT NULL AND u <> v").select("u", "v")
    now = checkpointed(edges.mapInArrow(_forest, "u long, v long").distinct())
    state = None
    for _ in range(limit):
        fresh = now.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v") % (1 << 40)).alias("h")).first()
        if not fresh["n"] or fresh == state:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select("v", "v").distinct())
        state = fresh
        both = now.union(now.select("v", "u"))
        least = both.groupBy("u").agg(F.min(F.least("u", "v")).alias("m"), F.count(F.lit(1)).alias("times"))
        # No node has more edges than there are, nor more rows after the first join than edges before it.
        hot = fresh["n"] > HOT and least.agg(F.max("times")).first()[0] > HOT
        join = spread_join if hot else (lambda big, few, key, _: big.join(few.drop("times"), key))
        held = (lambda df: checkpointed(df.coalesce(files(2 * fresh["n"])))) if hot else (lambda df: df)
        large = join(both.where("v > u"), held(least), "u", "times").select(F.col("v").alias("u"), F.col("m").alias("v"))
        down = held(large.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("times")))
        small = join(large, down, "u", "times").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(down.select("u", "m"))
        # A round has no more edges than the last; few edges are written as few files.
        now = checkpointed(small.distinct().coalesce(files(fresh["n"])))
    raise RuntimeError("components did not settle")


def files(rows: int) -> int:
    return max(8, rows // EDGES_PER_FILE)
