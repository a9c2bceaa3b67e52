"""Sharding by a hierarchical weighted hash tree (op 4, native).

Shards are leaves under racks under regions. A row descends from the root: at each level every
child makes an exponential draw ``-ln(u) / weight`` keyed by the row's key and the child's path, and
the smallest draw wins. A child's chance is its share of the weight, and raising the weight of one
child can only pull rows into it, so a change of weights moves rows only inside the subtrees whose
weights change. A new shard opens in a rack and region of its own once the last ones are full, so
going from ``n`` to ``n + 1`` shards at a region boundary (24 is one) takes rows only into the new shard.

Defined edge cases: a null text has size 8 and crc 0; very long texts are read whole; a null key is placed as the string ``null``,
and slots follow the text as well, so that many rows of one key or none are numbered in many tasks;
repeated rows get the same shard and slots next to each other; an empty table gives an empty result;
extra columns, whatever their names, are ignored by :func:`assign` and carried by :func:`place`.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import draw, partitions

#: Rows of offsets that are broadcast at most.
OFFSETS = 1 << 20


@dataclass(frozen=True)
class Tree:
    """Regions of racks of shards; ``weights`` has one positive number per shard."""

    weights: tuple[float, ...]
    shards_per_rack: int = 4
    racks_per_region: int = 3
    seed: str = "tree-1"

    @staticmethod
    def even(n: int, **kw) -> Tree:
        return Tree((1.0,) * n, **kw)

    def regions(self) -> list[list[list[int]]]:
        n, rack = len(self.weights), self.shards_per_rack
        racks = [list(range(i, min(n, i + rack))) for i in range(0, n, rack)]
        return [racks[i : i + self.racks_per_region] for i in range(0, len(racks), self.racks_per_region)]

    def grown(self, weight: float = 1.0) -> Tree:
        return Tree((*self.weights, weight), self.shards_per_rack, self.racks_per_region, self.seed)


def _least(children: list[tuple[float, Column | None, Column]]) -> Column:
    """The value of the child with the smallest draw; ties go to the first child."""
    if len(children) == 1:
        return children[0][2]
    best = F.array_min(F.array(*[F.struct((d / F.lit(w)).alias("d"), F.lit(i).alias("i")) for i, (w, d, _) in enumerate(children)]))["i"]
    out = children[-1][2]
    for i in reversed(range(len(children) - 1)):
        out = F.when(best == i, children[i][2]).otherwise(out)
    return out


def place(df: DataFrame, key: str, tree: Tree, name: str = "shard", grown_name: str | None = None) -> DataFrame:
    """Add the shard of each row, and with ``grown_name`` its shard in a tree of one more shard.

    Draws are columns of their own, so each is evaluated once and both trees share them.
    """
    k = F.coalesce(F.col(key).cast("string"), F.lit("null"))

    def named(path: str) -> str:
        return "__draw_" + path.replace("/", "_")

    trees = [(name, tree)] + ([(grown_name, tree.grown())] if grown_name else [])
    paths: dict[str, None] = {}
    for _, t in trees:
        for i, region in enumerate(rs := t.regions()):
            if len(rs) > 1:
                paths[f"r{i}"] = None
            for j, rack in enumerate(region):
                if len(region) > 1:
                    paths[f"r{i}/k{j}"] = None
                if len(rack) > 1:
                    paths.update({f"r{i}/k{j}/s{s}": None for s in rack})
    drawn = df.withColumns({named(p): -F.log(draw(tree.seed, p, k)) for p in paths})

    def at(path: str) -> Column:
        return F.col(named(path)) if path in paths else F.lit(0.0)

    def choice(t: Tree) -> Column:
        w = t.weights
        return _least([
            (sum(w[s] for rack in region for s in rack), at(f"r{i}"), _least([
                (sum(w[s] for s in rack), at(f"r{i}/k{j}"), _least([(w[s], at(f"r{i}/k{j}/s{s}"), F.lit(s)) for s in rack]))
                for j, rack in enumerate(region)
            ]))
            for i, region in enumerate(t.regions())
        ])

    return drawn.withColumns({n: choice(t).cast("int") for n, t in trees}).drop(*map(named, paths))


def number(df: DataFrame, group: str, order: list[str], draw_col: str, name: str = "slot", groups: int = 24) -> DataFrame:
    """Gapless numbers from 0 within each group, in the order of ``draw_col`` (in (0, 1)) and then ``order``.

    A group is cut into as many slices of the draw as there are shuffle partitions; the slices' counts
    (at most ``OFFSETS`` rows of a few numbers, so that they may be broadcast) give their offsets, so no task sees a whole group.
    """
    slices = max(1, min(partitions(df.sparkSession), OFFSETS // max(1, groups)))
    cut = df.withColumn("__slice", F.floor(F.col(draw_col) * slices).cast("int"))
    counts = cut.groupBy(group, "__slice").agg(F.count(F.lit(1)).alias("__n"))
    before = W.partitionBy(group).orderBy("__slice").rowsBetween(W.unboundedPreceding, -1)
    offsets = counts.select(group, "__slice", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__before"))
    inside = W.partitionBy(group, "__slice").orderBy(draw_col, *order)
    return cut.join(F.broadcast(offsets), [group, "__slice"]).withColumn(name, (F.col("__before") + F.row_number().over(inside) - 1).cast("long")).drop("__slice", "__before")


def assign(docs: DataFrame, shards: int = 24, tree: Tree | None = None) -> DataFrame:
    """One row per row of ``docs``: doc_id, size, text_crc32, law, shard, slot, grown_shard."""
    tree = tree or Tree.even(shards)
    sized = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 8).cast("long").alias("size"),
        F.coalesce(F.crc32("text"), F.lit(0)).cast("long").alias("text_crc32"),
    ).withColumn("__u", draw(tree.seed, "slot", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.col("text_crc32").cast("string")))
    placed = number(place(sized, "doc_id", tree, "shard", "grown_shard"), "shard", ["doc_id", "text_crc32", "size"], "__u", groups=len(tree.weights))
    return placed.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def write_shards(docs: DataFrame, path: str, tree: Tree, key: str = "doc_id") -> None:
    """Write whole rows into one folder per shard."""
    place(docs, key, tree).write.partitionBy("shard").parquet(path)


def oracle(shards: int = 24, view: str = "documents") -> str:
    """The same assignment in DuckDB SQL."""
    tree = Tree.even(shards)
    seed, grown = tree.seed, tree.grown()

    def uniform(path: str, more: str = "") -> str:
        return f"((CAST(('0x' || substr(md5('{seed}|{path}|' || coalesce(CAST(doc_id AS VARCHAR), 'null'){more}), 1, 12)) AS BIGINT) + 0.5) / 281474976710656.0)"

    def u(path: str) -> str:
        return f"-ln({uniform(path)})"

    def pick(options: list[tuple[float, str, str]]) -> str:
        if len(options) == 1:
            return options[0][2]
        out = options[-1][2]
        for i in reversed(range(len(options) - 1)):
            rest = " AND ".join(f"{options[i][1]} / {options[i][0]} <= {o[1]} / {o[0]}" for o in options[i + 1 :])
            out = f"CASE WHEN {rest} THEN {options[i][2]} ELSE {out} END"
        return out

    paths: dict[str, str] = {}

    def at(path: str) -> str:
        return paths.setdefault(path, f"p{len(paths)}")

    def choice(t: Tree) -> str:
        w, rs = t.weights, t.regions()
        return pick([
            (sum(w[s] for k in r for s in k), at(f"r{i}") if len(rs) > 1 else "0", pick([
                (sum(w[s] for s in k), at(f"r{i}/k{j}") if len(r) > 1 else "0", pick([(w[s], at(f"r{i}/k{j}/s{s}") if len(k) > 1 else "0", str(s)) for s in k]))
                for j, k in enumerate(r)
            ]))
            for i, r in enumerate(rs)
        ])

    a, b = choice(tree), choice(grown)
    # CRC-32 has no function there: the byte table follows from its polynomial, and each text is folded over it.
    return f"""
    WITH k AS (SELECT list(list_reduce(range(0, 8), lambda x, y: CASE WHEN x & 1 = 1 THEN xor(x >> 1, 3988292384) ELSE x >> 1 END, n) ORDER BY n) AS crc FROM range(0, 256) t(n)),
    bytes AS (SELECT *, list_filter(list_transform(string_split(regexp_replace(hex(coalesce(text, '')), '(..)', '\\1,', 'g'), ','), lambda h: try_cast('0x' || h AS BIGINT)), lambda z: z IS NOT NULL) AS bs FROM {view}),
    d AS (SELECT doc_id, len(bs) AS n, xor(list_reduce(bs, lambda x, z: xor(x >> 8, crc[xor(x & 255, z) + 1]), 4294967295), 4294967295) AS crc32, {", ".join(f"{u(p)} AS {n}" for p, n in paths.items())} FROM bytes, k),
    s AS (SELECT doc_id, CAST(n + 8 AS BIGINT) AS size, CAST(crc32 AS BIGINT) AS text_crc32, CAST({a} AS INTEGER) AS shard, CAST({b} AS INTEGER) AS grown_shard, {uniform("slot", " || '|' || CAST(crc32 AS VARCHAR)")} AS u FROM d)
    SELECT doc_id, size, text_crc32, 'key' AS law, shard, CAST(row_number() OVER (PARTITION BY shard ORDER BY u, doc_id, text_crc32, size) - 1 AS BIGINT) AS slot, grown_shard FROM s
    """
