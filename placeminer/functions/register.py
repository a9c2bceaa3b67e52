"""SQL surface: expressions, functions and table functions.

``sql_place_state`` and ``sql_place_fits`` give SQL text made of built-in functions only; ``register`` adds the table
functions ``place_children`` and ``discover_places`` and Arrow functions of the same names as the expressions.
"""

from __future__ import annotations

import json
import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from ..operators.compose import Collect, Implicit, Threshold
from ..operators.kernel import Block
from ..operators.lp import universal_place
from ..operators.tree import Tree, tree_of
from .places import END, START


def sql_place_state(seq: str, pre: str, post: str) -> str:
    """A SQL expression of replay over arrays of labels or ids."""
    has = lambda side: f"CAST(array_contains({side}, a) AS INT)"
    return (
        f"aggregate({seq}, named_struct('tokens', 0, 'slack', 0), "
        f"(s, a) -> named_struct('tokens', s.tokens - {has(post)} + {has(pre)}, 'slack', least(s.slack, s.tokens - {has(post)})), "
        "s -> named_struct('fit', s.slack >= 0 AND s.tokens = 0, 'under', s.slack < 0, 'over', s.tokens > 0, 'unbalanced', s.tokens <> 0, 'min_slack', s.slack, 'final', s.tokens))"
    )


def sql_place_fits(seq: str, pre: str, post: str) -> str:
    return f"({sql_place_state(seq, pre, post)}).fit"


def place_fits(seq: pd.Series, pre: pd.Series, post: pd.Series) -> pd.Series:
    def one(s, i, o) -> bool:
        i, o, tokens = set(i), set(o), 0
        for a in s:
            tokens -= a in o
            if tokens < 0:
                return False
            tokens += a in i
        return tokens == 0

    return pd.Series([one(*row) for row in zip(seq, pre, post)], dtype=bool)


@udtf(returnType="pre array<int>, post array<int>, depth int")
class PlaceChildren:
    """Children of a node given as ranks: ``place_children(pre, post, n_pre, n_post, max_depth)``."""

    def eval(self, pre: list, post: list, n_pre: int, n_post: int, max_depth: int):
        tree = Tree(tuple(map(str, range(n_pre))), tuple(map(str, range(n_post))), max_depth)
        for i, o in tree.children((tuple(pre), tuple(post))):
            yield list(i), list(o), len(i) + len(o)


def search_small(seqs: list[list[str]], freqs: list[int], tau: float, max_depth: int, oracle: str | None = None) -> list[tuple[list[str], list[str], int, int]]:
    """The whole search of a small log inside one task: (pre, post, n_fit, n_total) of the result, in order."""
    from ..plans.propose import walk

    first: dict[str, tuple[int, int]] = {}
    for s, f in zip(seqs, freqs):
        at: dict[str, int] = {}
        for k, a in enumerate(s):
            at.setdefault(a, k + 1)
        for a, k in at.items():
            n, w = first.get(a, (0, 0))
            first[a] = (n + k * f, w + f)
    inner = sorted((a for a in first if a not in (START, END)), key=lambda a: (first[a][0] / first[a][1], a))
    labels = [START, *inner, END]
    ids = {a: i for i, a in enumerate(labels)}
    log = Block([[ids[a] for a in s] for s in seqs], freqs, len(labels))
    kept = Collect()
    c = Threshold(Implicit(kept, log, oracle, universal=universal_place(len(labels), 0, len(labels) - 1)) if oracle else kept, tau)
    walk(log, labels, tree_of(inner, max_depth), tau, c)
    return [(sorted(labels[i] for i in a), sorted(labels[i] for i in b), kept.places[a, b].counts[0], log.total) for a, b in c.accepted]


@udtf(returnType="segment string, pre array<string>, post array<string>, n_fit bigint, n_total bigint")
class DiscoverPlaces:
    """``discover_places(TABLE(log) PARTITION BY (segment), options)`` over rows (segment, seq array<string>, freq): the small log of
    each segment is searched inside one Python worker. Options is JSON with tau, max_depth, oracle."""

    def __init__(self):
        self.rows: list = []
        self.options = "{}"

    def eval(self, row: Row, options: str):
        self.options = options
        self.rows.append((row["segment"], list(row["seq"]), int(row["freq"])))

    def terminate(self):
        o = json.loads(self.options)
        found = search_small([s for _, s, _ in self.rows], [f for _, _, f in self.rows], o.get("tau", 1.0), o.get("max_depth", 3), o.get("oracle"))
        for pre, post, n, total in found:
            yield self.rows[0][0], pre, post, n, total


def discover_segments(log, tau: float, max_depth: int, oracle: str | None = None):
    """segment, pre, post, n_fit, n_total: one small search per segment of a log (segment, seq, freq)."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = search_small([list(s) for s in pdf["seq"]], [int(f) for f in pdf["freq"]], tau, max_depth, oracle)
        return pd.DataFrame([(pdf["segment"].iloc[0], *r) for r in rows], columns=["segment", "pre", "post", "n_fit", "n_total"])

    return log.groupBy("segment").applyInPandas(run, "segment string, pre array<string>, post array<string>, n_fit long, n_total long")


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL."""
    spark.udf.register("place_fits", pandas_udf(place_fits, "boolean"))
    spark.udtf.register("place_children", PlaceChildren)
    spark.udtf.register("discover_places", DiscoverPlaces)


def as_views(found, spark: SparkSession, prefix: str = "") -> None:
    """Register the result of a discovery as the views places and arcs."""
    from ..operators.model import arcs_table

    places = found.table(spark)
    places.createOrReplaceTempView(f"{prefix}places")
    arcs_table(places.select("place_id", F.col("pre"), F.col("post"))).createOrReplaceTempView(f"{prefix}arcs")
