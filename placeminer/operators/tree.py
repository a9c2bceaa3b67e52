"""The tree of candidate places.

Nodes are pairs of increasing rank tuples. Children add one activity that ranks above all of its side: the root and
places without a postset grow there first; a place of one arc grows a preset; a place with one postset activity
grows on both sides; one with more grows only its postset. So every place has exactly one parent. With
``prefer="pre"`` the sides swap roles.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import comb

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

Node = tuple[tuple[int, ...], tuple[int, ...]]


@dataclass(frozen=True)
class Tree:
    """Ordered activities of both sides and a depth limit."""

    pre: tuple[str, ...]
    post: tuple[str, ...]
    max_depth: int
    prefer: str = "post"

    def ids(self, node: Node, labels: list[str]) -> Node:
        """The place of a node as activity ids."""
        at = {a: i for i, a in enumerate(labels)}
        return tuple(sorted(at[self.pre[i]] for i in node[0])), tuple(sorted(at[self.post[i]] for i in node[1]))

    def names(self, node: Node) -> tuple[tuple[str, ...], tuple[str, ...]]:
        return tuple(sorted(self.pre[i] for i in node[0])), tuple(sorted(self.post[i] for i in node[1]))

    def extensions(self, node: Node, side: str) -> list[Node]:
        """All direct expansions of a side by larger activities; an empty side takes any."""
        i, o = node
        if side == "post":
            return [(i, (*o, k)) for k in range(o[-1] + 1 if o else 0, len(self.post))]
        return [((*i, k), o) for k in range(i[-1] + 1 if i else 0, len(self.pre))]

    def children(self, node: Node, cut_post: bool = False, cut_pre: bool = False) -> list[Node]:
        """Children in order, the leading side first; a cut removes that side's subtrees."""
        if len(node[0]) + len(node[1]) >= self.max_depth:
            return []
        lead, other = ("post", "pre") if self.prefer == "post" else ("pre", "post")
        main, minor = (node[1], node[0]) if lead == "post" else (node[0], node[1])
        cut = {"post": cut_post, "pre": cut_pre}
        out: list[Node] = []
        if not main:
            return [] if cut[lead] else self.extensions(node, lead)
        if minor and not cut[lead]:
            out += self.extensions(node, lead)
        if len(main) == 1 and not cut[other]:
            out += self.extensions(node, other)
        return out

    def parent(self, node: Node) -> Node | None:
        """The closed form of the one parent (C4)."""
        i, o = node
        main, minor = (o, i) if self.prefer == "post" else (i, o)
        if len(main) > 1:
            main = main[:-1]
        elif minor:
            minor = minor[:-1]
        elif main:
            main = ()
        else:
            return None
        return (minor, main) if self.prefer == "post" else (main, minor)

    def path(self, node: Node) -> tuple[int, ...]:
        """Sort key: the choices that lead from the root to a node."""
        steps, now = [], node
        while (up := self.parent(now)) is not None:
            post = len(now[1]) > len(up[1])
            lead = post == (self.prefer == "post")
            steps.append((0 if lead else 1 << 20) + (now[1][-1] if post else now[0][-1]))
            now = up
        return tuple(reversed(steps))

    def subtree(self, node: Node = ((), ())) -> list[Node]:
        """All nodes below and with ``node`` (C19; exponential, for tests and small trees)."""
        out, level = [], [node]
        while level:
            out += level
            level = [c for x in level for c in self.children(x)]
        return out

    def space(self) -> dict[int, int]:
        """Through places by depth, exactly."""
        n, m = len(self.pre), len(self.post)
        return {d: sum(comb(n, i) * comb(m, d - i) for i in range(1, d) if i <= n and d - i <= m) for d in range(2, self.max_depth + 1)}

    def cut_mass(self, node: Node, rule: str) -> int:
        """Descendants that a cut removes (C23): places under the post children, or under the pre children."""
        i, o = node
        left = self.max_depth - len(i) - len(o)
        if left <= 0:
            return 0
        free_post = len(self.post) - 1 - (o[-1] if o else -1)
        free_pre = len(self.pre) - 1 - (i[-1] if i else -1)
        if self.prefer == "pre":
            i, o, free_pre, free_post, rule = o, i, free_post, free_pre, {"post": "pre", "pre": "post"}[rule]
        if rule == "post":
            return sum(comb(free_post, k) for k in range(1, left + 1))
        # A grown preset may still grow its postset, from one activity on.
        return sum(comb(free_pre, k) * sum(comb(free_post, j) for j in range(0, left - k + 1)) for k in range(1, left + 1)) if len(o) == 1 else 0

    def seeds(self, spark: SparkSession) -> DataFrame:
        """The frontier of depth two: every pair of activities, with paths."""
        shift = 1 << 20
        pre = spark.range(len(self.pre)).select(F.col("id").cast("int").alias("i"))
        post = spark.range(len(self.post)).select(F.col("id").cast("int").alias("o"))
        lead, other = (F.col("o"), F.col("i")) if self.prefer == "post" else (F.col("i"), F.col("o"))
        pairs = pre.join(F.broadcast(post))  # |pre| x |post| seeds by definition
        return pairs.select(F.array("i").alias("pre"), F.array("o").alias("post"), F.lit(2).alias("depth"), F.array(lead, other + shift).alias("path"))

    def spread(self, frontier: DataFrame) -> DataFrame:
        """Children of a frontier (pre, post, depth, path, cut_post, cut_pre); no shuffle, no duplicates."""
        n, m, shift = len(self.pre), len(self.post), 1 << 20
        open_ = frontier.where(F.col("depth") < self.max_depth)

        def grow(side: str, size: int, lead: bool) -> DataFrame:
            last = F.element_at(side, -1)
            more = open_.where(~F.col(f"cut_{side}") & (last < size - 1))
            if not lead:
                more = more.where(F.size("post" if self.prefer == "post" else "pre") == 1)
            grown = more.withColumn("k", F.explode(F.sequence(last + 1, F.lit(size - 1))))
            side_of = {s: (F.concat(s, F.array("k")) if s == side else F.col(s)) for s in ("pre", "post")}
            return grown.select(side_of["pre"].alias("pre"), side_of["post"].alias("post"), (F.col("depth") + 1).alias("depth"), F.concat("path", F.array(F.col("k") + (0 if lead else shift))).alias("path"))

        return grow("post", m, self.prefer == "post").unionByName(grow("pre", n, self.prefer == "pre"))


def tree_of(labels: list[str], max_depth: int, pre: list[str] | None = None, post: list[str] | None = None, blacklist: tuple[str, ...] = (), prefer: str = "post") -> Tree:
    """The tree over inner labels in order; S is the least of presets and E the greatest of postsets unless sides are given."""
    from .log import sides

    a, b = sides(labels, pre, post, blacklist)
    return Tree(tuple(a), tuple(b), max_depth, prefer)
