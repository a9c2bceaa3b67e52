"""The proposal, evaluation and composition cycle.

``discover`` walks level by level: the frontier is a DataFrame, one evaluation per level gives counts and local cuts as
columns, only candidates that reach the threshold come to the composer, in path order. Cuts depend on a node alone, so
the order of the walk does not change what is proposed unless a budget or pairwise constraints end it early.
``walk`` takes one node, one batch or (breadth first) one level at a time on the driver, for small logs and for the orders that
need it. Breadth first the two agree in every option: composers meet the candidates that reach the threshold, in path
order; further cuts are asked of those; constraints are asked of through places, and what violates one goes with its
subtree; levels end, wired pairs hold and budgets but for seconds are checked at the end of each level.
"""

from __future__ import annotations

import heapq
import time
from collections.abc import Iterator
from dataclasses import dataclass, field
from fractions import Fraction

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.compose import Budget, Candidate, Collect, Composer, Threshold, cut_columns, cuts, reaches
from ..operators.constraints import Constraint
from ..operators.evaluate import SparkLog, fitness
from ..operators.kernel import Block, Place
from ..operators.tree import Node, Tree
from .supervise import Supervisor


@dataclass
class Discovery:
    """What a run found: places as activity ids over ``labels``."""

    labels: list[str]
    places: list[Place]
    proposed: int
    stopped: str | None
    complete: bool
    supervisor: Supervisor
    seconds: float
    #: Rows (pre, post as ranks, depth, path, counts, cut flags) of every evaluated candidate, if asked for.
    evaluated: DataFrame | None = None
    by_depth: dict[int, tuple[int, int]] = field(default_factory=dict)

    def names(self) -> list[tuple[tuple[str, ...], tuple[str, ...]]]:
        return [(tuple(sorted(self.labels[i] for i in a)), tuple(sorted(self.labels[i] for i in b))) for a, b in self.places]

    def table(self, spark: SparkSession) -> DataFrame:
        rows = [(f"{','.join(a)}>{','.join(b)}", list(a), list(b), len(a) + len(b), i) for i, (a, b) in enumerate(self.names())]
        return spark.createDataFrame(rows, "place_id string, pre array<string>, post array<string>, depth int, position int")


def _with_ids(frontier: DataFrame, tree: Tree, labels: list[str]) -> DataFrame:
    """A frontier with its places as arrays of activity ids (``pre``/``post``), ranks kept as ``pre_rank``/``post_rank``."""
    at = {a: i for i, a in enumerate(labels)}
    pre, post = (F.array(*[F.lit(at[a]) for a in side]) for side in (tree.pre, tree.post))
    out = frontier.withColumnsRenamed({"pre": "pre_rank", "post": "post_rank"})
    ids = lambda table, c: F.array_sort(F.transform(c, lambda r: F.get(table, r)))
    return out.withColumn("pre", ids(pre, "pre_rank")).withColumn("post", ids(post, "post_rank")).withColumn("place_id", F.concat(F.concat_ws(",", F.col("pre").cast("array<string>")), F.lit(">"), F.concat_ws(",", F.col("post").cast("array<string>"))))


def _named(df: DataFrame, labels: list[str], constraint: Constraint) -> DataFrame:
    """Rows whose places satisfy a constraint on labels; one without a column is asked in the tasks, as it is at this level."""
    if constraint.make is None:

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                places = zip(b.column("pre").to_pylist(), b.column("post").to_pylist())
                yield b.filter(pa.array([constraint.holds(tuple(tuple(sorted(labels[x] for x in side)) for side in p)) for p in places], pa.bool_()))

        return df.mapInArrow(run, df.schema)
    table = F.array(*map(F.lit, labels))
    names = {s: F.transform(f"__{s}", lambda i: F.get(table, i)) for s in ("pre", "post")}
    kept = df.withColumnsRenamed({"pre": "__pre", "post": "__post"}).withColumns(names).where(constraint.column)
    return kept.drop("pre", "post").withColumnsRenamed({"__pre": "pre", "__post": "post"})


def _mass(done: DataFrame, tree: Tree) -> int:
    """Descendants that the cuts of a level remove; they depend on sizes and last ranks alone, so that few groups are added up."""
    last = {f"last_{s}": F.element_at(f"{s}_rank", -1) for s in ("pre", "post")}
    size = {f"size_{s}": F.size(f"{s}_rank") for s in ("pre", "post")}
    groups = done.where("cut_post OR cut_pre").withColumns({**last, **size}).groupBy(*last, *size).agg(F.count_if("cut_post").alias("post"), F.count_if("cut_pre").alias("pre"))
    total = 0
    for g in groups.toLocalIterator():
        node = ((0,) * (g["size_pre"] - 1) + (g["last_pre"],), (0,) * (g["size_post"] - 1) + (g["last_post"],))
        total += sum(g[rule] * tree.cut_mass(node, rule) for rule in ("post", "pre") if g[rule])
    return total


def discover(
    log: SparkLog, tree: Tree, tau: float, composer: Composer | None = None, *, cut_mode: str = "paper", budget: Budget | None = None, initial: list[Constraint] = (), roots: DataFrame | None = None,
    engine: str = "auto", supervisor: Supervisor | None = None, keep_evaluated: bool = False,
) -> Discovery:
    """Level-by-level discovery (C7, C8). ``roots`` (pre, post, depth, path as ranks) starts from disjoint subtrees instead of the seeds."""
    from ..checkpoints import checkpointed

    spark = log.variants.sparkSession
    sup, budget, began = supervisor or Supervisor(), budget or Budget(), time.time()
    composer = composer or Threshold(Collect(), tau)
    labels, total = log.labels, log.total
    n, m = len(tree.pre), len(tree.post)
    sup.space = sum(tree.space().values())
    frontier = roots if roots is not None else tree.seeds(spark)
    stopped, proposed, by_depth, kept = None, 0, {}, None
    depth = 2
    pairs: set[tuple[int, int]] = set()
    while tree.max_depth >= 2:
        level = _with_ids(frontier, tree, labels)
        for constraint in initial:
            level = _named(level, labels, constraint)
        if pairs:
            wire = F.array(*[F.lit(a * len(labels) + b) for a, b in sorted(pairs)])
            own = F.flatten(F.transform("pre", lambda a: F.transform("post", lambda b: a * len(labels) + b)))
            level = level.where(~F.arrays_overlap(own, wire))
        if budget.max_candidates is not None:
            level = level.orderBy("path").limit(max(0, budget.max_candidates - proposed))
        last_post = F.element_at("post_rank", -1) == m - 1
        last_pre = F.element_at("pre_rank", -1) == n - 1
        if tree.prefer == "pre":  # the mirrored tree mirrors the rules
            cut_pre, cut_post = cut_columns(total, tau, last_pre, cut_mode, "n_over", "n_under")
        else:
            cut_post, cut_pre = cut_columns(total, tau, last_post, cut_mode)
        with sup.timed("evaluate"):
            done = checkpointed(fitness(log, level, engine).withColumns({"cut_post": cut_post, "cut_pre": cut_pre}))
        facts = done.agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("cut_post").cast("long")).alias("a"), F.sum(F.col("cut_pre").cast("long")).alias("b")).first()
        if not facts["n"]:
            break
        proposed += facts["n"]
        sup.visited, sup.depth = proposed, depth
        sup.count("evaluate", "cut_post", facts["a"])
        sup.count("evaluate", "cut_pre", facts["b"])
        keep = done.select("pre_rank", "post_rank", "pre", "post", "depth", "path", "n_fit", "n_under", "n_over", "n_unbalanced", "cut_post", "cut_pre") if keep_evaluated else None
        kept = keep if kept is None else kept.union(keep) if keep_evaluated else kept
        passing = done.where(F.col("n_fit") * F.lit(1_000_000).cast("long") >= F.lit(round(tau * 1_000_000) * total).cast("long")).orderBy("path")
        before, passed, extra = set(composer.accepted), 0, []
        with sup.timed("compose"):
            # Only places that reach the threshold come here, a level at a time.
            for r in passing.select("place_id", "pre", "post", "n_fit", "n_under", "n_over", "n_unbalanced", "path").toLocalIterator():
                passed += 1
                c = Candidate((tuple(r["pre"]), tuple(r["post"])), (r["n_fit"], r["n_under"], r["n_over"], r["n_unbalanced"]), total, (depth, *r["path"]))
                verdict = composer.consume(c)
                sup.count("compose", verdict)
                if verdict == "accepted":
                    sup.accepted(c.place, proposed, len(composer.accepted))
                if any(more := composer.extra_cuts(c)):
                    extra.append((r["place_id"], *more))
            composer.end_of_level()
        sup.count("compose", "unfit", facts["n"] - passed)
        if extra:
            # No more rows than places came to the composer; none of them was cut yet, since they reach the threshold.
            sup.count("evaluate", "cut_post", sum(x[1] for x in extra))
            sup.count("evaluate", "cut_pre", sum(x[2] for x in extra))
            more = spark.createDataFrame(extra, "place_id string, more_post boolean, more_pre boolean")
            done = done.join(more, "place_id", "left").withColumns({f"cut_{s}": F.col(f"cut_{s}") | F.coalesce(f"more_{s}", F.lit(False)) for s in ("post", "pre")}).drop("more_post", "more_pre")
        if sup.level != "off":
            sup.considered += _mass(done, tree)
        by_depth[depth] = (facts["n"], passed)
        stopped = budget.spent(time.time() - began, proposed, len(composer.accepted), set(composer.accepted) != before)
        if stopped or depth >= tree.max_depth:
            break
        pairs = composer.wired_pairs
        frontier = tree.spread(done.select(F.col("pre_rank").alias("pre"), F.col("post_rank").alias("post"), "depth", "path", "cut_post", "cut_pre"))
        depth += 1
    composer.finish()
    whole = stopped is None and composer.complete and all(c.monotone for c in initial)
    return Discovery(labels, composer.accepted, proposed, stopped, whole, sup, time.time() - began, kept, by_depth)


class Stepper:
    """One node at a time on the driver (C6, C9, C10): ``bfs``, ``dfs`` or ``best`` by a heuristic on label names.

    Active nodes wait in a heap; ``next(k)`` takes the k best that satisfy the constraints of now; ``visit`` hands back a node's cuts and
    its children become active. Nodes are forgotten once their children are.
    """

    def __init__(self, tree: Tree, strategy: str = "bfs", heuristic=None, constraints: list[Constraint] = (), roots: list[Node] | None = None):
        self.tree, self.strategy, self.heuristic = tree, strategy, heuristic
        self.constraints = list(constraints)
        self.heap: list = []
        self.pruned = 0
        for r in roots if roots is not None else [((), ())]:
            self._push(r)

    def _key(self, node: Node):
        path = self.tree.path(node)
        if self.strategy == "bfs":
            return (len(path), path)
        if self.strategy == "dfs":
            return (path,)
        return (self.heuristic(self.tree.names(node)) if node[0] and node[1] else float("-inf"), path)

    def _push(self, node: Node) -> None:
        heapq.heappush(self.heap, (self._key(node), node))

    def next(self, k: int = 1) -> list[Node]:
        """Up to ``k`` through places; the layers before them are opened on the way."""
        out: list[Node] = []
        while self.heap and len(out) < k:
            node = heapq.heappop(self.heap)[1]
            if node[0] and node[1] and not all(c.holds(self.tree.names(node)) for c in self.constraints):
                self.pruned += 1
                continue
            if not (node[0] and node[1]):
                for child in self.tree.children(node):
                    self._push(child)
                continue
            out.append(node)
        return out

    def visit(self, node: Node, cut_post: bool = False, cut_pre: bool = False) -> None:
        for child in self.tree.children(node, cut_post, cut_pre):
            self._push(child)


def walk(
    log: SparkLog | Block, labels: list[str], tree: Tree, tau: float, composer: Composer | None = None, *, strategy: str = "bfs", heuristic=None, constraints: list[Constraint] = (), batch: int = 256,
    budget: Budget | None = None, cut_mode: str = "paper", roots: list[Node] | None = None, supervisor: Supervisor | None = None, observe=None,
) -> Discovery:
    """Discovery by a stepper, ``batch`` candidates an evaluation (a level, breadth first); strict order at a batch of one.
    ``observe`` sees every evaluated candidate, the composer those that reach ``tau``."""
    sup, budget, began = supervisor or Supervisor(), budget or Budget(), time.time()
    composer = composer or Threshold(Collect(), tau)
    steps = Stepper(tree, strategy, heuristic, list(constraints), roots)
    total, proposed, stopped, by_depth = log.total, 0, None, {}
    if total == 0:
        raise ValueError("the log is empty")
    sup.space = sum(tree.space().values())
    at = {a: i for i, a in enumerate(labels)}
    level = 0
    wired: set[tuple[int, int]] = set()
    while nodes := steps.next(batch):
        if strategy == "bfs":  # a level is a batch
            d = len(nodes[0][0]) + len(nodes[0][1])
            while steps.heap and len(steps.tree.path(steps.heap[0][1])) <= d and (more := steps.next(1)):
                if len(more[0][0]) + len(more[0][1]) != d:
                    steps._push(more[0])
                    break
                nodes += more
        if wired:
            nodes = [x for x in nodes if not any((at[tree.pre[i]], at[tree.post[o]]) in wired for i in x[0] for o in x[1])]
        if budget.max_candidates is not None:
            nodes = nodes[: max(0, budget.max_candidates - proposed)]
        if not nodes:
            if strategy == "bfs":
                break
            continue
        places = [tree.ids(x, labels) for x in nodes]
        with sup.timed("evaluate"):
            counts = log.counts(places)
        before = set(composer.accepted)
        for node, place, c in zip(nodes, places, counts):
            proposed += 1
            d = len(node[0]) + len(node[1])
            level = max(level, d)
            seen, passed = by_depth.get(d, (0, 0))
            ok = reaches(int(c[0]), total, tau)
            by_depth[d] = (seen + 1, passed + ok)
            candidate = Candidate(place, tuple(int(x) for x in c), total, (d, *tree.path(node)))
            if observe is not None:
                observe(candidate)
            verdict = composer.consume(candidate) if ok else "unfit"
            more = composer.extra_cuts(candidate) if ok else (False, False)
            sup.count("compose", verdict)
            if verdict == "accepted":
                sup.accepted(place, proposed, len(composer.accepted))
            can_post, can_pre = bool(tree.extensions(node, "post")), bool(tree.extensions(node, "pre"))
            if tree.prefer == "pre":
                cut_pre, cut_post = cuts(int(c[2]), int(c[1]), total, tau, d, can_pre, can_post, cut_mode)
            else:
                cut_post, cut_pre = cuts(int(c[1]), int(c[2]), total, tau, d, can_post, can_pre, cut_mode)
            cut_post, cut_pre = cut_post or more[0], cut_pre or more[1]
            for rule, cut in (("post", cut_post), ("pre", cut_pre)):
                if cut:
                    sup.count("evaluate", f"cut_{rule}")
                    sup.considered += tree.cut_mass(node, rule)
            steps.visit(node, cut_post, cut_pre)
        if strategy == "bfs":
            composer.end_of_level()
        sup.visited, sup.depth = proposed, max(sup.depth, level)
        wired = composer.wired_pairs
        stopped = budget.spent(time.time() - began, proposed, len(composer.accepted), set(composer.accepted) != before)
        if stopped:
            break
    if strategy != "bfs":
        composer.end_of_level()
    composer.finish()
    whole = stopped is None and composer.complete and all(c.monotone for c in constraints)
    return Discovery(labels, composer.accepted, proposed, stopped, whole, sup, time.time() - began, None, by_depth)


def restart(log, labels: list[str], tree: Tree, tau: float, make, times: int, **options) -> Discovery:
    """Walk again with what a composer kept (C22): useful where released pairs opened subtrees that were passed."""
    out = walk(log, labels, tree, tau, composer := make(), **options)
    for _ in range(times):
        seen = set(composer.accepted)
        again = walk(log, labels, tree, tau, composer, **options)
        out.places, out.proposed = again.places, out.proposed + again.proposed
        if set(composer.accepted) == seen:
            break
    return out


def regrid(rows: list[dict], tree: Tree, total: int, tau: float, depth: int, mode: str = "both") -> list[dict]:
    """The candidates that a walk at (tau, depth) evaluates, out of those of a walk in mode ``both`` at a lower or equal tau and
    a larger or equal depth: exactly the rows all of whose ancestors leave them open (grid sharing)."""
    known = {(tuple(r["pre"]), tuple(r["post"])): r for r in rows}
    alive: dict[Node, bool] = {}

    def open_(node: Node) -> bool:
        if node not in alive:
            up = tree.parent(node)
            if up is None or not (up[0] and up[1]):
                alive[node] = True
            elif up not in known or not open_(up):
                alive[node] = False
            else:
                r = known[up]
                can_post, can_pre = bool(tree.extensions(up, "post")), bool(tree.extensions(up, "pre"))
                cut_post, cut_pre = cuts(r["n_under"], r["n_over"], total, tau, len(up[0]) + len(up[1]), can_post, can_pre, mode)
                alive[node] = not (cut_post if len(node[1]) > len(up[1]) else cut_pre)
        return alive[node]

    return [r for r in rows if r["depth"] <= depth and open_((tuple(r["pre"]), tuple(r["post"])))]


def share(n: int, total: int) -> float:
    return float(Fraction(n, total))
