"""The experiment workloads over the given tables, each as a query, and their DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .checkpoints import checkpointed
from .functions import places as pl
from .functions.places import END, START
from .functions.replay import trace_state
from .operators import conformance, heuristics, log as logs, order, post, stats
from .operators.baselines import alpha as alpha_miner
from .operators.baselines import brute, cuts as cut_miner, dfg as graph, region as region_miner
from .operators.compose import Budget, Candidate, Collect, Delta, Implicit, Postponing, Threshold, Uniwired, beam, reaches, support_score
from .operators.evaluate import counts_projected, fitness, relative_fitness
from .operators.implicit import agreement, dominance_fold, log_language_kept
from .operators.lp import lp_implicit
from .operators.model import arcs_table, explored, to_net
from .operators.suite import EvaluatorSuite, adds_something, at_most_arcs, reaches_threshold
from .operators.tree import Tree
from .plans.config import PRESETS, Config
from .plans.experiment import DEPTHS, TAUS, grid
from .plans.propose import _with_ids, discover, walk
from .plans.run import RUNS, Prepared, prepare, run, tree
from .plans.supervise import Supervisor
from .sources.logs import SQL as LOG_SQL
from .sources.logs import events
from .sources.spec import LogSpec

Query = Callable[[SparkSession, str], DataFrame]

#: Fixed micro-logs: (trace without markers, frequency).
MICRO = {
    "fitness_example": [("a b", 4), ("a a", 6)],
    "replay_example": [("a b a b", 1)],
    "longterm": [("o d d i", 1), ("vo d d d vi", 1)],
}
#: Places asked of the day log and of the orders of two types.
EXAMPLES = [
    ("events_day", (START,), ("view",)), ("events_day", (START, "view"), ("view", END)), ("events_day", ("view",), ("purchase",)),
    ("order_types", ("o",), ("i",)), ("order_types", ("vo",), ("vi",)), ("order_types", ("d", "o", "vo"), ("d", "i", "vi")), ("order_types", ("o",), ("vi",)),
]
#: Orders of these priorities are of one type (o, invoiced by i), all others of another (vo, vi); deliveries are d.
URGENT = ("1-URGENT", "2-HIGH")
_URGENT_SQL = "o_orderpriority IN (" + ", ".join(f"'{p}'" for p in URGENT) + ")"
OWN_SQL = {
    "order_types": f"""SELECT CAST(o_orderkey AS VARCHAR) AS case_id, CASE WHEN {_URGENT_SQL} THEN 'o' ELSE 'vo' END AS activity, 0 AS o1, 0 AS o2, 0 AS o3, 0 AS o4 FROM orders
        UNION ALL SELECT CAST(o_orderkey AS VARCHAR), CASE WHEN {_URGENT_SQL} THEN 'i' ELSE 'vi' END, 2, 0, 0, 0 FROM orders
        UNION ALL SELECT CAST(l_orderkey AS VARCHAR), 'd', 1, 0, 0, 0 FROM lineitem""",
}
#: A place set over the lifecycle log.
PRIORITIES = ("place:1-URGENT", "place:2-HIGH", "place:3-MEDIUM", "place:4-NOT SPECIFIED", "place:5-LOW")
CLOSES = ("close:F", "close:O", "close:P")
SHIPS = ("ship:A", "ship:N", "ship:R")
LIFECYCLE_SET = [((START,), PRIORITIES), (PRIORITIES, CLOSES), ((*PRIORITIES, *SHIPS), (*CLOSES, *SHIPS)), (("place:1-URGENT",), ("close:O",))]
CONV_SET = [((START,), (END,)), ((START, "assistant"), ("user", END)), ((START, "user"), (END, "user"))]
LOOPS = [(("a", "b"), ("b", "c")), (("a", "d"), ("c", "d")), (("a",), ("c",)), (("a", "x"), ("b",)), (("e",), ("f", "g")), (("a", "e"), ("b", "f"))]


def order_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders of two types with their deliveries: what an order starts with decides how it ends, however many deliveries lie between."""
    orders, lines = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("orders", "lineitem"))
    either = lambda a, b: F.when(F.col("o_orderpriority").isin(*URGENT), a).otherwise(b)
    rows = [(orders, "o_orderkey", 0, either("o", "vo")), (orders, "o_orderkey", 2, either("i", "vi")), (lines, "l_orderkey", 1, F.lit("d"))]
    placed, closed, shipped = (t.select(F.col(k).alias("k"), F.lit(stage).alias("stage"), a.alias("activity")) for t, k, stage, a in rows)
    return LogSpec("order_types", ("k",), "activity", ("stage",)).events(placed.union(closed).union(shipped))


def _events(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return order_types(spark, sf_dir) if name == "order_types" else events(spark, sf_dir, name)


def names_log(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Variants of a log with labels; micro-logs by name."""
    if name in MICRO:
        return spark.createDataFrame([([START, *t.split(), END], n) for t, n in MICRO[name]], "seq array<string>, freq long").select(F.xxhash64("seq").alias("variant_id"), "seq", "freq")
    return logs.variants(logs.traces(_events(spark, sf_dir, name)))


def ready(spark: SparkSession, sf_dir: str, name: str, how: str = "first_index") -> Prepared:
    if name in MICRO:
        rows = [(f"{t}#{k}", (i,), a) for t, n in MICRO[name] for k in range(n) for i, a in enumerate(t.split())]
        return prepare(spark.createDataFrame(rows, "case_id string, ord struct<o0:int>, activity string"), how)
    return prepare(_events(spark, sf_dir, name), how)


def joined(column: str):
    return F.concat_ws(",", F.array_sort(column))


# --- logs ---------------------------------------------------------------------------------------------------------


def log_overview(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for name in LOG_SQL:
        one = logs.overview(names_log(spark, d, name)).select(F.lit(name).alias("log"), "*")
        out = one if out is None else out.union(one)
    return out


def variants_of(name: str) -> Query:
    return lambda spark, d: names_log(spark, d, name).select(F.concat_ws(">", F.slice("seq", F.lit(2), F.size("seq") - 2)).alias("variant"), "freq")


def trace_lengths(spark: SparkSession, d: str) -> DataFrame:
    return names_log(spark, d, "events_day").groupBy((F.size("seq") - 2).cast("long").alias("len")).agg(F.sum("freq").alias("n"))


def activity_scores(spark: SparkSession, d: str) -> DataFrame:
    return order.scores(names_log(spark, d, "events_day")).select("activity", F.round("mean_first", 6).alias("mean_first"), "n_cases", "n_events")


def sessions_events(spark: SparkSession, d: str) -> DataFrame:
    return names_log(spark, d, "events_sess").groupBy((F.size("seq") - 2).cast("long").alias("len")).agg(F.sum("freq").alias("n"))


def dfg_of(name: str) -> Query:
    return lambda spark, d: graph.dfg(names_log(spark, d, name)).where(~F.col("src").isin(START) & ~F.col("dst").isin(END))


def footprint_of(name: str) -> Query:
    return lambda spark, d: graph.footprint(names_log(spark, d, name))


def eventually(spark: SparkSession, d: str) -> DataFrame:
    return heuristics.interest(names_log(spark, d, "events_day")).where(f"pre_act <> '{START}' AND post_act <> '{END}'").select(F.col("pre_act").alias("src"), F.col("post_act").alias("dst"), F.col("n").alias("n_cases"))


def segment_dfg(spark: SparkSession, d: str) -> DataFrame:
    rows = events(spark, d, "cust_prio")
    customers = spark.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").cast("string").alias("case_id"), F.col("c_mktsegment").alias("seg"))
    by = logs.by_segment(rows.join(customers, "case_id"), "seg")
    steps = F.zip_with(F.slice("seq", F.lit(2), F.size("seq") - 3), F.slice("seq", F.lit(3), F.size("seq") - 3), lambda a, b: F.struct(a.alias("src"), b.alias("dst")))
    return by.where(F.size("seq") > 3).select("segment", "freq", F.explode(steps).alias("s")).groupBy("segment", "s.src", "s.dst").agg(F.sum("freq").alias("n"))


def cube_log_stats(spark: SparkSession, d: str) -> DataFrame:
    o = spark.read.parquet(f"{d}/orders.parquet").select("o_orderpriority", "o_orderstatus")
    return o.cube("o_orderpriority", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


def ordering_ablation(spark: SparkSession, d: str) -> DataFrame:
    """Rank of each activity under the orders that SQL can repeat."""
    named = checkpointed(names_log(spark, d, "events_day"))
    out = None
    for how in ("first_index", "lexicographic", "frequency", "trace_frequency", "mean_occurrences"):
        one = order.rank(named, how).select(F.lit(how).alias("strategy"), "activity", "rank")
        out = one if out is None else out.union(one)
    return out


# --- places -------------------------------------------------------------------------------------------------------


def _counts(p: Prepared, table: DataFrame) -> DataFrame:
    """Fitness of a place table of ids with names instead."""
    names = F.array(*map(F.lit, p.labels))
    label = lambda c: F.concat_ws(",", F.array_sort(F.transform(c, lambda i: F.get(names, i))))
    return fitness(p.log, table).select(label("pre").alias("pre"), label("post").alias("post"), "n_fit", "n_under", "n_over", "n_total")


def _pairs(p: Prepared, depth: int = 2) -> DataFrame:
    t = tree(Config(max_depth=depth), p)
    frontier = t.seeds(p.spark).withColumn("cut_post", F.lit(False)).withColumn("cut_pre", F.lit(False))
    for _ in range(2, depth):
        frontier = t.spread(frontier).withColumn("cut_post", F.lit(False)).withColumn("cut_pre", F.lit(False))
    return _with_ids(frontier, t, p.labels)


def place_fitness_pairs(name: str) -> Query:
    return lambda spark, d: _counts(p := ready(spark, d, name), _pairs(p))


def place_fitness_depth3(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "events_day")
    return _counts(p, _pairs(p, 3))


def planted_dependency(spark: SparkSession, d: str) -> DataFrame:
    """On the log whose closing label repeats the priority: the pairs that every trace fits tie each order to its own closing."""
    return place_fitness_pairs("lifecycle_planted")(spark, d).where("n_fit = n_total")


def projected_counts(spark: SparkSession, d: str) -> DataFrame:
    """The pair counts of a log of mostly unique traces, from the log restricted to each chunk's activities."""
    p = ready(spark, d, "lineflags")
    t = tree(Config(max_depth=2), p)
    places = [t.ids(n, p.labels) for n in t.subtree() if n[0] and n[1]]
    c = counts_projected(p.log, places, 4)
    return _rows(p, places, lambda i, _: (*map(int, c[i][:3]), p.log.total), "n_fit long, n_under long, n_over long, n_total long")


def evaluator_suite(spark: SparkSession, d: str) -> DataFrame:
    """How many places each evaluator of a suite has to judge, cheap ones first."""
    p = ready(spark, d, "conv")
    t = tree(Config(max_depth=4), p)
    suite = EvaluatorSuite([reaches_threshold(0.5), at_most_arcs(3), adds_something()])
    left = suite.passing(p.log, [t.ids(n, p.labels) for n in t.subtree() if n[0] and n[1]], [(tuple([p.start]), tuple([p.end]))])
    return spark.createDataFrame([*suite.asked.items(), ("passing", len(left))], "evaluator string, n long")


def passing_by_tau(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for name in ("conv", "events_day", "lineflags", "lifecycle", "tags_core"):
        c = place_fitness_pairs(name)(spark, d)
        for tau in (1000, 900, 800, 700, 600, 500):
            one = c.agg(F.count_if(F.col("n_fit") * 1000 >= tau * F.col("n_total")).alias("n_passing")).select(F.lit(name).alias("log"), F.lit(tau).alias("tau_permille"), "n_passing")
            out = one if out is None else out.union(one)
    return out


def cuts_depth2(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "events_day")
    found = discover(p.log, tree(Config(max_depth=2), p), 0.5, keep_evaluated=True)
    names = F.array(*map(F.lit, p.labels))
    return found.evaluated.select(F.get(names, F.get("pre", 0)).alias("pre"), F.get(names, F.get("post", 0)).alias("post"), "cut_post", "cut_pre")


def pruning_ablation(spark: SparkSession, d: str) -> DataFrame:
    """Candidates evaluated down to depth three under each way to cut, at a threshold of 0.8."""
    p = ready(spark, d, "events_day")
    rows = []
    for mode in ("none", "under", "over", "paper", "both"):
        found = walk(p.log, p.labels, tree(Config(max_depth=3), p), 0.8, cut_mode=mode)
        rows += [(mode, depth, n, k) for depth, (n, k) in sorted(found.by_depth.items())]
    return spark.createDataFrame(rows, "mode string, depth long, n_evaluated long, n_passing long")


def candidate_counts_by_depth(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "events_day")
    return spark.createDataFrame([(depth, n) for depth, n in tree(Config(max_depth=6), p).space().items()], "depth long, n_candidates long")


def _passing(p: Prepared, tau: float, depth: int = 2) -> list[Candidate]:
    kept: list[Candidate] = []
    walk(p.log, p.labels, tree(Config(max_depth=depth), p), tau, observe=lambda c: kept.append(c) if reaches(c.counts[0], c.total, tau) else None)
    return sorted(kept, key=lambda c: c.order)


def _named(p: Prepared, place) -> tuple[str, str]:
    return tuple(",".join(sorted(p.labels[i] for i in s)) for s in place)


def _rows(p: Prepared, places: list, extra=lambda i, q: (), columns: str = "") -> DataFrame:
    return p.spark.createDataFrame([(*_named(p, q), *extra(i, q)) for i, q in enumerate(places)], "pre string, post string" + (f", {columns}" if columns else ""))


def log_language_kept_query(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "events_day")
    ordered = [c.place for c in _passing(p, 0.5)]
    kept = log_language_kept(p.log, ordered, 0.5)
    return _rows(p, [ordered[i] for i in kept], lambda k, _: (kept[k] + 1,), "rank long")


def set_support_lifecycle(spark: SparkSession, d: str) -> DataFrame:
    v = names_log(spark, d, "lifecycle")
    both = lambda ps: [trace_state("seq", F.array(*map(F.lit, i)), F.array(*map(F.lit, o)))["fit"] for i, o in ps]
    out = None
    for k in range(1, len(LIFECYCLE_SET) + 1):
        fit = F.lit(True)
        for c in both(LIFECYCLE_SET[:k]):
            fit = fit & c
        one = v.agg(F.sum(F.when(fit, F.col("freq")).otherwise(0)).alias("n_fit"), F.sum("freq").alias("n_total")).select(F.lit(k).cast("long").alias("n_places"), "n_fit", "n_total")
        out = one if out is None else out.union(one)
    return out


def perfect_fit_share(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "conv")
    places = [c.place for c in _passing(p, 0.5)]
    n, total = p.log.support(places), p.log.total
    return spark.createDataFrame([(len(places), n, total)], "n_places long, n_fit long, n_total long")


def selfloop_merge(spark: SparkSession, d: str) -> DataFrame:
    table = spark.createDataFrame([(list(i), list(o)) for i, o in LOOPS], "pre array<string>, post array<string>")
    return post.merge_selfloops(table).select(joined("pre").alias("pre"), joined("post").alias("post"), "merged")


def uniwired_conflicts(spark: SparkSession, d: str) -> DataFrame:
    table = spark.createDataFrame([(k, list(i), list(o)) for k, (i, o) in enumerate(LOOPS)], "k long, pre array<string>, post array<string>")
    w = table.select("k", F.explode(pl.wires("pre", "post")).alias("w"))
    a, b = w.alias("a"), w.alias("b")
    return a.join(b, (F.col("a.w") == F.col("b.w")) & (F.col("a.k") < F.col("b.k"))).groupBy(F.col("a.k").alias("first"), F.col("b.k").alias("second")).agg(F.count(F.lit(1)).alias("n"))


def net_arcs_lifecycle(spark: SparkSession, d: str) -> DataFrame:
    c = place_fitness_pairs("lifecycle")(spark, d).where("n_fit * 10 >= n_total * 7")
    return arcs_table(c.select(F.concat("pre", F.lit(">"), "post").alias("place_id"), F.array("pre").alias("pre"), F.array("post").alias("post")))


def _ids(p: Prepared, places) -> list:
    at = {a: i for i, a in enumerate(p.labels)}
    return [(tuple(sorted(at[a] for a in i)), tuple(sorted(at[a] for a in o))) for i, o in places]


def etc_precision_conv(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "conv")
    return conformance.etc_precision(p.log, _ids(p, CONV_SET), p.start, p.end).select("enabled", "escaping", F.round("precision", 6).alias("precision"))


def micro_examples(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for name in dict.fromkeys(n for n, _, _ in EXAMPLES):
        # All places of a log in one pass over its variants.
        asked = [(i, o, trace_state("seq", F.array(*map(F.lit, i)), F.array(*map(F.lit, o)))) for n, i, o in EXAMPLES if n == name]
        states = F.array(*[F.struct(F.lit(",".join(sorted(i))).alias("pre"), F.lit(",".join(sorted(o))).alias("post"), *[s[x].alias(x) for x in ("fit", "under", "over")]) for i, o, s in asked])
        c = names_log(spark, d, name).select("freq", F.explode(states).alias("s")).groupBy("s.pre", "s.post").agg(*[F.sum(F.when(F.col(f"s.{x}"), F.col("freq")).otherwise(0)).alias(f"n_{x}") for x in ("fit", "under", "over")], F.sum("freq").alias("n_total"))
        one = c.select(F.lit(name).alias("log"), "*")
        out = one if out is None else out.union(one)
    return out


def candidate_tree_example(spark: SparkSession, d: str) -> DataFrame:
    """The subtree under ({start}, {first}) of the tree over the activities of the day log in their order: places by depth."""
    inner = order.ordered(checkpointed(names_log(spark, d, "events_day")))
    t = Tree((START, *inner), (*inner, END), 2 * len(inner) + 2)
    rows = [(len(i) + len(o), ",".join(sorted(t.pre[x] for x in i)), ",".join(sorted(t.post[x] for x in o))) for i, o in t.subtree(((0,), (0,)))]
    return spark.createDataFrame(rows, "depth long, pre string, post string")


# --- composition --------------------------------------------------------------------------------------------------


def _compose(p: Prepared, make, tau: float, depth: int) -> DataFrame:
    c = Threshold(make(p), tau)
    found = walk(p.log, p.labels, tree(Config(max_depth=depth), p), tau, c)
    counts = p.log.counts(found.places) if found.places else []
    return _rows(p, found.places, lambda i, _: (int(counts[i][0]), p.log.total), "n_fit long, n_total long")


def composed(name: str, make, tau: float, depth: int) -> Query:
    return lambda spark, d: _compose(ready(spark, d, name), make, tau, depth)


COMPOSERS = {
    "base_compose_conv": ("conv", lambda p: Collect(), 0.8, 4),
    "uniwired_compose_conv": ("conv", lambda p: Uniwired(Collect()), 0.5, 4),
    "delta_compose_conv": ("conv", lambda p: Delta(Collect(), p.log, 0.2, 0.3), 0.5, 4),
    "delta_growing_compose_conv": ("conv", lambda p: Delta(Collect(), p.log, 0.2, 0.3, "linear", 4), 0.5, 4),
    "postponing_compose_conv": ("conv", lambda p: Postponing(Uniwired(Collect()), lambda c: c.depth), 0.5, 4),
    "dominance_compose_conv": ("conv", lambda p: Implicit(Collect(), p.log, "token_dominance", True), 0.5, 4),
    "lp_compose_conv": ("conv", lambda p: Implicit(Collect(), p.log, "lp", universal=p.universal), 0.5, 4),
    "log_language_compose_conv": ("conv", lambda p: Implicit(Collect(), p.log, "log_language"), 0.5, 4),
    "nested_compose_conv": ("conv", lambda p: Uniwired(Implicit(Collect(), p.log, "lp", universal=p.universal)), 0.5, 4),
}


def dominance_kept(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "conv")
    fold = dominance_fold(p.log, [c.place for c in _passing(p, 0.5, 4)])
    return _rows(p, [q for q, _, _ in fold], lambda i, _: (fold[i][1],), "verdict string")


def lp_kept(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "conv")
    places = [c.place for c in _passing(p, 0.5, 4)]
    verdicts = [lp_implicit(q, [r for r in places if r != q], universal=p.universal) for q in places]
    return _rows(p, places, lambda i, _: (verdicts[i].implicit, len(verdicts[i].weights)), "implicit boolean, n_weights long")


def oracle_agreement(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "conv")
    found = agreement(p.log, [c.place for c in _passing(p, 0.5, 4)], 0.5, p.universal)
    return spark.createDataFrame([(*k, n) for k, n in sorted(found.items())], "log_language boolean, token_dominance boolean, lp boolean, n long")


def longterm_dependency(spark: SparkSession, d: str) -> DataFrame:
    """The base miner on the orders of two types: order and invoice types are tied, deliveries loop."""
    return _compose(ready(spark, d, "order_types"), lambda p: Implicit(Collect(), p.log, "lp", universal=p.universal), 1.0, 6)


def beam_conv(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "conv")
    return _rows(p, beam(p.log, _passing(p, 0.5, 3), 4, support_score(0.05)))


def brute_sets_conv(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "conv")
    best, score = brute.brute_sets(p.log, [c.place for c in _passing(p, 0.5, 3)], support_score(0.05), 2)
    return _rows(p, list(best), lambda i, _: (float(score),), "score double")


def brute_conv(spark: SparkSession, d: str) -> DataFrame:
    """Exhaustive search beside the pruned one: the same places, more evaluations."""
    p = ready(spark, d, "conv")
    t = tree(Config(max_depth=5), p)
    every, n = brute.brute(p.log, p.labels, t, 0.8)
    found = walk(p.log, p.labels, t, 0.8)
    return spark.createDataFrame([("brute", n, len(every), True), ("pruned", found.proposed, len(found.places), set(found.places) == set(every))], "search string, n_evaluated long, n_places long, same boolean")


def search_orders(spark: SparkSession, d: str) -> DataFrame:
    """Places found within a budget of candidates by breadth, depth and best first."""
    p = ready(spark, d, "events_day")
    rows = []
    for strategy, h in (("bfs", None), ("dfs", None), ("best", p.context.get("eventually")), ("best_size", p.context.get("size"))):
        for budget in (40, 80, 160):
            found = walk(p.log, p.labels, tree(Config(max_depth=4), p), 0.5, strategy=strategy.split("_")[0], heuristic=h, batch=8, budget=Budget(max_candidates=budget))
            rows.append((strategy, budget, found.proposed, len(found.places)))
    return spark.createDataFrame(rows, "strategy string, budget long, n_evaluated long, n_places long")


# --- models and quality -------------------------------------------------------------------------------------------


def alignment_fitness_conv(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "conv")
    a = conformance.alignment(p.log, _ids(p, CONV_SET), p.start, p.end)
    return a.groupBy("cost").agg(F.sum("freq").alias("n"), F.avg("fitness").alias("fitness"))


def replay_fitness_conv(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "conv")
    return conformance.replay_fitness(p.log, _ids(p, CONV_SET)).withColumn("fitness", F.round("fitness", 6))


def relative_fitness_events(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "events_day")
    places = [c.place for c in _passing(p, 0.0)]
    names = spark.createDataFrame([(i, *_named(p, q)) for i, q in enumerate(places)], "place long, pre string, post string")
    return relative_fitness(p.log, places).join(F.broadcast(names), "place").select("pre", "post", "n_touching", "n_fit_touching")


def best_model(name: str, tau: float, depth: int) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        p = ready(spark, d, name)
        out = run(Config(log=name, tau=tau, max_depth=depth, oracle="lp"), p)
        counts = p.log.counts(out.places) if out.places else []
        return _rows(p, out.places, lambda i, _: (int(counts[i][0]), p.log.total, out.fitness, out.precision), "n_fit long, n_total long, fitness double, precision double")

    return query


def dead_activities_lifecycle(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "lifecycle")
    out = run(Config(log="lifecycle", tau=0.7, max_depth=3, oracle="lp"), p, quality=False)
    found = conformance.activity_status(p.log, out.places, p.start, p.end)
    return spark.createDataFrame(list(found.items()), "activity string, status string")


def deadlocks_longterm(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "order_types")
    out = run(Config(log="order_types", tau=1.0, max_depth=6, oracle="lp"), p, quality=False)
    found, whole = explored(to_net(out.names(), p.labels), 2000)
    return spark.createDataFrame([(len(out.places), len(found), whole)], "n_places long, n_deadlocks long, complete boolean")


def stagnation_curve(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "tags_core")
    sup = Supervisor(run_id="tags_core", level="full")
    found = walk(p.log, p.labels, tree(Config(max_depth=4), p), 0.9, Threshold(Implicit(Collect(), p.log, "lp", universal=p.universal), 0.9), supervisor=sup)
    curve = spark.createDataFrame([("tags_core", s, e, n, found.seconds) for s, e, n in sup.curve], "run_id string, seconds double, evaluated long, size long, end_seconds double")
    return stats.stagnation(curve).withColumn("n_evaluated", F.lit(found.proposed))


def grid_of(name: str, taus=(1.0, 0.8, 0.6), depths=(2, 3, 4)) -> Query:
    return lambda spark, d: grid(ready(spark, d, name), Config(log=name), taus, depths)


GRID_LOGS = (("conv", (1.0, 0.9, 0.8, 0.7, 0.6, 0.5), (2, 3, 4, 5)), ("tags_core", (1.0, 0.9, 0.8, 0.7), (2, 3, 4)), ("events_day", (1.0, 0.8, 0.6, 0.5), (2, 3, 4)), ("lifecycle_planted", (1.0, 0.9, 0.8), (2, 3)))


def grids(spark: SparkSession, d: str) -> DataFrame:
    """The runs of all grids; rows of shared evaluation left out."""
    out = None
    for name, taus, depths in GRID_LOGS:
        one = grid_of(name, taus, depths)(spark, d).where("oracle <> 'shared'")
        out = one if out is None else out.union(one)
    return out


def grid_correlations(spark: SparkSession, d: str) -> DataFrame:
    """Controlled rank correlations of threshold and depth with fitness and precision over our own grids."""
    runs, out = grids(spark, d), None
    for x, other in (("tau", "depth"), ("depth", "tau")):
        for y in ("fitness", "precision", "f1"):
            one = stats.controlled_spearman(runs, x, y, [other, "oracle"]).select("log", F.lit(x).alias("x"), F.lit(y).alias("y"), F.round("rho", 4).alias("rho"), "groups", "constant")
            out = one if out is None else out.union(one)
    return out


def grid_tables(spark: SparkSession, d: str) -> DataFrame:
    """Runtimes and place medians of our own grids, one row a log."""
    runs = grids(spark, d)
    return stats.runtimes(runs).join(stats.place_medians(runs), "log")


def segments_discovery(spark: SparkSession, d: str) -> DataFrame:
    from .functions.register import discover_segments

    rows = events(spark, d, "events_day").withColumn("seg", F.concat(F.lit("user"), F.pmod(F.split("case_id", r"\|")[0].cast("long"), F.lit(4)).cast("string")))
    return discover_segments(logs.by_segment(rows, "seg"), 0.5, 3).select("segment", joined("pre").alias("pre"), joined("post").alias("post"), "n_fit", "n_total")


def alpha_conv(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame([(",".join(i), ",".join(o)) for i, o in alpha_miner.alpha(names_log(spark, d, "conv"))], "pre string, post string")


def cuts_conv(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame([(n, cut_miner.cuts(names_log(spark, d, n)).text()) for n in ("conv", "longterm", "fitness_example")], "log string, tree string")


def region_conv(spark: SparkSession, d: str) -> DataFrame:
    rows = [(n, ",".join(i), ",".join(o)) for n in ("conv", "longterm") for i, o in region_miner.region(names_log(spark, d, n))]
    return spark.createDataFrame(rows, "log string, pre string, post string")


def presets_conv(spark: SparkSession, d: str) -> DataFrame:
    """Every preset on one log: what it collects and keeps."""
    p = ready(spark, d, "conv")
    rows = []
    for name, c in sorted(PRESETS.items()):
        out = run(replace(c, tau=min(c.tau, 0.8), max_depth=3), p, quality=False)
        rows.append((name, out.discovery.proposed, len(out.discovery.places), len(out.places), out.discovery.complete))
    return spark.createDataFrame(rows, "preset string, proposed long, collected long, after_post long, complete boolean")


# --- runs ---------------------------------------------------------------------------------------------------------


def fixed_runs() -> list[tuple]:
    """A small stored runs table by rule, the same for Spark and SQL."""
    out = []
    for li, log in enumerate(("alpha", "beta")):
        for ti, tau in enumerate((1.0, 0.8, 0.6)):
            for depth in (2, 3, 4):
                for oi, oracle in enumerate(("lp", "token_dominance")):
                    k = 7 * li + 5 * ti + 3 * depth + oi
                    fit, prec = (50 + (k * 13) % 47) / 100, (40 + (k * 29) % 59) / 100
                    out.append((log, tau, depth, oracle, 100 * depth + k, 10 * depth + k % 9, 4 + k % 7, fit, prec, 2 * fit * prec / (fit + prec), depth**3 + k % 5 + 0.5, k % 3 + 0.25, depth == 4 and k % 4 == 0, k % 8 == 0))
    return out


def _runs(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(fixed_runs(), RUNS)


#: Settings of the runs over the events table, and its logs.
TABLE_LOGS = ("events_day", "events_sess")
TABLE_TAUS, TABLE_DEPTHS, TABLE_RULES = (800, 700, 600, 500, 400, 300), (2, 3, 4), ("all", "loopfree")
#: Budgets of those runs, in candidates and in places.
TABLE_BUDGET = (500, 40)


def table_runs(spark: SparkSession, d: str) -> DataFrame:
    """Runs of the exhaustive search over the day and session logs of the events table, one a threshold, depth and rule.

    A run collects the places down to its depth that reach its threshold and keeps all of them, or those without a self-loop. Its fitness is
    the share of traces that fit a kept place, on average; its precision the share of all pairs of a preset and a postset activity that
    the kept places wire; its times are work, so that they can be repeated: millions of events replayed for all candidates and for the collected ones.
    """
    places = None
    for name in TABLE_LOGS:
        p = ready(spark, d, name)
        asked = _pairs(p, TABLE_DEPTHS[0])
        for depth in TABLE_DEPTHS[1:]:
            asked = asked.unionByName(_pairs(p, depth))
        cells = p.log.variants.agg(F.sum(F.col("freq") * F.size("seq"))).first()[0]
        wires = F.flatten(F.transform("pre", lambda a: F.transform("post", lambda b: a * len(p.labels) + b)))
        facts = (F.lit(name).alias("log"), F.lit(cells).cast("long").alias("cells"), F.lit((len(p.labels) - 1) ** 2).alias("pairs"))
        one = fitness(p.log, asked).select(*facts, (F.size("pre") + F.size("post")).alias("size"), F.arrays_overlap("pre", "post").alias("looped"), wires.alias("wires"), "n_fit", "n_total")
        places = one if places is None else places.union(one)
    settings = spark.createDataFrame([(t, k, r) for t in TABLE_TAUS for k in TABLE_DEPTHS for r in TABLE_RULES], "tau long, depth int, oracle string")
    each = places.join(F.broadcast(settings), F.col("size") <= F.col("depth")).withColumn("ok", F.col("n_fit") * 1000 >= F.col("tau") * F.col("n_total"))
    each = each.withColumn("kept", F.col("ok") & ((F.col("oracle") == "all") | ~F.col("looped")))
    of_kept = lambda c: F.when(F.col("kept"), F.col(c))
    sums = each.groupBy("log", "tau", "depth", "oracle", "cells", "pairs").agg(
        F.count(F.lit(1)).alias("proposed"), F.count_if("ok").alias("collected"), F.count_if("kept").alias("after_post"),
        (F.sum(of_kept("n_fit")) / F.sum(of_kept("n_total"))).alias("fitness"), F.size(F.array_distinct(F.flatten(F.collect_list(of_kept("wires"))))).alias("wired"),
    )
    scored = sums.withColumn("tau", F.col("tau") / 1000).withColumn("precision", F.when(F.col("after_post") > 0, F.col("wired") / F.col("pairs")))
    timed = scored.withColumns({
        "f1": 2 * F.col("fitness") * F.col("precision") / (F.col("fitness") + F.col("precision")), "t_search": F.col("proposed") * F.col("cells") / 1e6, "t_post": F.col("collected") * F.col("cells") / 1e6,
        "stopped_search": F.col("proposed") > TABLE_BUDGET[0], "dnf": F.col("collected") > TABLE_BUDGET[1],
    })
    return checkpointed(timed.select(*[c.split()[0] for c in RUNS.split(", ")]))


def _round(df: DataFrame) -> DataFrame:
    return df.select(*[F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


RUN_QUERIES: dict[str, Query] = {
    "runtime_table": lambda s, d: _round(stats.runtimes(_runs(s))),
    "collected_places": lambda s, d: _round(stats.place_medians(table_runs(s, d))),
    "pareto_fit_prec": lambda s, d: _round(stats.pareto(table_runs(s, d), "fitness", "precision")),
    "pareto_fit_size": lambda s, d: _round(stats.pareto(table_runs(s, d), "fitness", "after_post", less_y=True)),
    "pareto_prec_size": lambda s, d: _round(stats.pareto(_runs(s), "precision", "after_post", less_y=True)),
    "fastest_top_decile": lambda s, d: _round(stats.fastest_top(table_runs(s, d), "f1")),
    "min_depth_at_max": lambda s, d: _round(stats.min_depth(table_runs(s, d), "fitness")),
    "controlled_spearman": lambda s, d: _round(stats.controlled_spearman(table_runs(s, d), "tau", "fitness", ["depth", "oracle"])),
    "controlled_spearman_depth": lambda s, d: _round(stats.controlled_spearman(table_runs(s, d), "depth", "precision", ["tau", "oracle"])),
    "cube_runs": lambda s, d: stats.cube(table_runs(s, d)),
}


def measured(what) -> Query:
    """A statistic of the 60 measured runs of the full grid on the conversation log."""
    return lambda spark, d: _round(what(grid_of("conv", TAUS, DEPTHS)(spark, d).where("oracle <> 'shared'")))


MEASURED: dict[str, Query] = {
    "measured_runtimes_conv": measured(stats.runtimes),
    "measured_pareto_conv": measured(lambda r: stats.pareto(r, "fitness", "precision")),
    "measured_fastest_conv": measured(lambda r: stats.fastest_top(r.where("f1 IS NOT NULL"), "f1")),
    "measured_min_depth_conv": measured(lambda r: stats.min_depth(r, "precision")),
    "measured_spearman_conv": measured(lambda r: stats.controlled_spearman(r, "tau", "precision", ["depth", "oracle"])),
}


def queries() -> dict[str, Query]:
    return {
        "place_fitness_pairs_events_day": place_fitness_pairs("events_day"),
        "log_overview": log_overview,
        **{f"variants_{n}": variants_of(n) for n in ("conv", "tags", "lifecycle", "events_day", "lineflags")},
        "trace_lengths": trace_lengths,
        "activity_scores": activity_scores,
        "sessions_events": sessions_events,
        **{f"dfg_{n}": dfg_of(n) for n in ("conv", "lifecycle", "events_day")},
        "footprint_conv": footprint_of("conv"),
        "eventually_follows_events_day": eventually,
        "segment_dfg_by_mktsegment": segment_dfg,
        "cube_log_stats": cube_log_stats,
        "ordering_ablation": ordering_ablation,
        **{f"place_fitness_pairs_{n}": place_fitness_pairs(n) for n in ("conv", "lifecycle", "tags_core", "lineflags")},
        "place_fitness_depth3_events_day": place_fitness_depth3,
        "planted_dependency": planted_dependency,
        "projected_counts_lineflags": projected_counts,
        "footprint_matrix_conv": lambda s, d: graph.footprint_matrix(names_log(s, d, "conv"), ["assistant", "system", "user", START, END]),
        "evaluator_suite_conv": evaluator_suite,
        "passing_by_tau": passing_by_tau,
        "cuts_depth2_events_day": cuts_depth2,
        "pruning_ablation": pruning_ablation,
        "candidate_counts_by_depth": candidate_counts_by_depth,
        "log_language_kept_events_day": log_language_kept_query,
        "set_support_lifecycle": set_support_lifecycle,
        "perfect_fit_share": perfect_fit_share,
        "selfloop_merge": selfloop_merge,
        "uniwired_conflicts": uniwired_conflicts,
        "net_arcs_lifecycle": net_arcs_lifecycle,
        "etc_precision_conv": etc_precision_conv,
        "micro_examples": micro_examples,
        "candidate_tree_example": candidate_tree_example,
        **{k: composed(*v) for k, v in COMPOSERS.items()},
        "dominance_kept_conv": dominance_kept,
        "lp_kept_conv": lp_kept,
        "oracle_agreement": oracle_agreement,
        "longterm_dependency": longterm_dependency,
        "beam_conv": beam_conv,
        "brute_conv": brute_conv,
        "brute_sets_conv": brute_sets_conv,
        "search_orders": search_orders,
        "alignment_fitness_conv": alignment_fitness_conv,
        "replay_fitness_conv": replay_fitness_conv,
        "relative_fitness_events_day": relative_fitness_events,
        "best_model_tags": best_model("tags_core", 0.8, 4),
        "best_model_lifecycle": best_model("lifecycle_planted", 1.0, 3),
        "dead_activities": dead_activities_lifecycle,
        "deadlocks_longterm": deadlocks_longterm,
        "stagnation_curve": stagnation_curve,
        **{f"grid_{n}": grid_of(n, TAUS, DEPTHS) for n in ("conv", "events_day")},
        "grid_tags_core": grid_of("tags_core"),
        **MEASURED,
        "grid_lifecycle": grid_of("lifecycle", (1.0, 0.8), (2, 3)),
        "grid_correlations": grid_correlations,
        "grid_tables": grid_tables,
        "tags_wide_depth2": place_fitness_pairs("tags"),
        "segments_discovery": segments_discovery,
        "baseline_alpha_conv": alpha_conv,
        "baseline_cuts_conv": cuts_conv,
        "baseline_region_conv": region_conv,
        "presets_conv": presets_conv,
        **RUN_QUERIES,
    }


# --- DuckDB -------------------------------------------------------------------------------------------------------


def _with(name: str) -> str:
    """Common tables of a log: traces t(case_id, seq), variants v(vid, seq, freq), events ev(vid, freq, act, pos), acts(act)."""
    raw = LOG_SQL.get(name, OWN_SQL.get(name))
    if raw is None:
        rows = ", ".join(f"({k}, {[START, *t.split(), END]!r}, {n})" for k, (t, n) in enumerate(MICRO[name]))
        v = f"v AS (SELECT * FROM (VALUES {rows}) x(vid, seq, freq))"
    else:
        v = f"""t AS (SELECT case_id, ['{START}'] || list(activity ORDER BY o1, o2, o3, o4) || ['{END}'] AS seq FROM ({raw}) GROUP BY case_id),
        v AS (SELECT row_number() OVER () AS vid, seq, count(*) AS freq FROM t GROUP BY seq)"""
    return f"""WITH {v}, ev AS (SELECT vid, freq, unnest(seq) AS act, generate_subscripts(seq, 1) AS pos FROM v),
    acts AS (SELECT DISTINCT act FROM ev), tot AS (SELECT CAST(sum(freq) AS BIGINT) AS n FROM v)"""


_SIDES = f"pre_acts AS (SELECT act FROM acts WHERE act <> '{END}'), post_acts AS (SELECT act FROM acts WHERE act <> '{START}')"
_PAIRS = f"{_SIDES}, pl AS (SELECT a.act || '>' || b.act AS pid, [a.act] AS pre, [b.act] AS post FROM pre_acts a, post_acts b)"
#: From pl(pid, pre, post) to st(pid, vid, freq, least, fin) of touched variants and fc(pid, pre, post, counts).
_FIT = """touch AS (SELECT pid, vid, freq, pos, CAST(list_contains(pre, act) AS INT) AS made, CAST(list_contains(post, act) AS INT) AS used FROM ev, pl WHERE list_contains(pre, act) OR list_contains(post, act)),
    run AS (SELECT pid, vid, freq, made - used AS net, coalesce(sum(made) OVER (PARTITION BY pid, vid ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) - sum(used) OVER (PARTITION BY pid, vid ORDER BY pos ROWS UNBOUNDED PRECEDING) AS slack FROM touch),
    st AS (SELECT pid, vid, any_value(freq) AS freq, least(min(slack), 0) AS least, sum(net) AS fin FROM run GROUP BY pid, vid),
    bad AS (SELECT pid, sum(CASE WHEN least < 0 OR fin <> 0 THEN freq ELSE 0 END) AS b, sum(CASE WHEN least < 0 THEN freq ELSE 0 END) AS u, sum(CASE WHEN fin > 0 THEN freq ELSE 0 END) AS o FROM st GROUP BY pid),
    fc AS (SELECT pl.pid, array_to_string(list_sort(pre), ',') AS pre, array_to_string(list_sort(post), ',') AS post, CAST(n - coalesce(b, 0) AS BIGINT) AS n_fit, CAST(coalesce(u, 0) AS BIGINT) AS n_under, CAST(coalesce(o, 0) AS BIGINT) AS n_over, n AS n_total FROM pl CROSS JOIN tot LEFT JOIN bad ON pl.pid = bad.pid)"""
_COUNTS = "SELECT pre, post, n_fit, n_under, n_over, n_total FROM fc"
_RANKS = f"""firsts AS (SELECT act, vid, any_value(freq) AS freq, min(pos) AS f, count(*) AS k FROM ev GROUP BY act, vid),
    sc AS (SELECT act, sum(f * freq) / sum(freq) AS mean_first, sum(freq) AS n_cases, sum(k * freq) AS n_events FROM firsts GROUP BY act),
    rk AS (SELECT act, row_number() OVER (ORDER BY CASE act WHEN '{START}' THEN 0 WHEN '{END}' THEN 2 ELSE 1 END, mean_first, act) AS r FROM sc)"""


def _pairs_sql(name: str) -> str:
    return f"{_with(name)}, {_PAIRS}, {_FIT} {_COUNTS}"


def _list(values) -> str:
    return "[" + ", ".join("'" + v.replace("'", "''") + "'" for v in values) + "]"


def _runs_sql() -> str:
    lit = lambda x: "TRUE" if x is True else "FALSE" if x is False else repr(x) if not isinstance(x, float) else f"CAST({x!r} AS DOUBLE)"
    return "runs AS (SELECT * FROM (VALUES " + ", ".join("(" + ", ".join(map(lit, r)) + ")" for r in fixed_runs()) + ") x(log, tau, depth, oracle, proposed, collected, after_post, fitness, precision, f1, t_search, t_post, stopped_search, dnf))"


def _table_runs_sql() -> str:
    from .repeatable import _all

    value = lambda xs: ", ".join(f"({x!r})" for x in xs)
    logs_ = " UNION ALL ".join(
        f"""SELECT * FROM ({_all(n, max(TABLE_DEPTHS))} SELECT '{n}' AS log, (SELECT CAST(sum(freq * len(seq)) AS BIGINT) FROM v) AS cells, (SELECT (count(*) - 1) * (count(*) - 1) FROM rk) AS pairs, depth AS size, list_has_any(pr, qr) AS looped,
        flatten(list_transform(pr, lambda x: list_transform(qr, lambda y: 100 * x + y))) AS wires, n_fit, n_total FROM fx)""" for n in TABLE_LOGS
    )
    return f"""pf AS ({logs_}), ts AS (SELECT * FROM (VALUES {value(TABLE_TAUS)}) x(t)), ds AS (SELECT * FROM (VALUES {value(TABLE_DEPTHS)}) x(d)), rs AS (SELECT * FROM (VALUES {value(TABLE_RULES)}) x(oracle)),
    ea AS (SELECT *, n_fit * 1000 >= t * n_total AS ok, n_fit * 1000 >= t * n_total AND (oracle = 'all' OR NOT looped) AS kept FROM pf JOIN ds ON size <= d CROSS JOIN ts CROSS JOIN rs),
    wd AS (SELECT log, t, d, oracle, count(DISTINCT w) AS wired FROM (SELECT log, t, d, oracle, unnest(wires) AS w FROM ea WHERE kept) GROUP BY log, t, d, oracle),
    sm AS (SELECT log, t, d, oracle, any_value(cells) AS cells, any_value(pairs) AS pairs, count(*) AS proposed, count(*) FILTER (ok) AS collected, count(*) FILTER (kept) AS after_post,
        CAST(sum(n_fit) FILTER (kept) AS DOUBLE) / CAST(sum(n_total) FILTER (kept) AS DOUBLE) AS fitness FROM ea GROUP BY log, t, d, oracle),
    sc AS (SELECT sm.*, CAST(wired AS DOUBLE) / CAST(pairs AS DOUBLE) AS precision FROM sm LEFT JOIN wd USING (log, t, d, oracle)),
    runs AS (SELECT log, CAST(t AS DOUBLE) / 1000 AS tau, CAST(d AS INTEGER) AS depth, oracle, proposed, collected, after_post, fitness, precision, 2 * fitness * precision / (fitness + precision) AS f1,
        CAST(proposed * cells AS DOUBLE) / 1e6 AS t_search, CAST(collected * cells AS DOUBLE) / 1e6 AS t_post, proposed > {TABLE_BUDGET[0]} AS stopped_search, collected > {TABLE_BUDGET[1]} AS dnf FROM sc)"""


def _pareto_sql(x: str, y: str, sign: int, given: bool = False) -> str:
    return f"""WITH {_table_runs_sql() if given else _runs_sql()}, best AS (SELECT DISTINCT log, {x} AS x, {sign} * {y} AS y FROM (SELECT *, percent_rank() OVER (PARTITION BY log ORDER BY f1 DESC) AS q FROM runs{" WHERE f1 IS NOT NULL" if given else ""}) WHERE q <= 0.25)
    SELECT log, round(x, 6) AS {x}, {"round(y, 6)" if sign > 0 else f"CAST({sign} * y AS BIGINT)"} AS {y} FROM best a WHERE NOT EXISTS (SELECT 1 FROM best b WHERE b.log = a.log AND b.x >= a.x AND b.y >= a.y AND (b.x > a.x OR b.y > a.y))"""


def _spearman_sql(x: str, y: str, control: str, given: bool = False) -> str:
    avg = lambda c: f"rank() OVER (PARTITION BY log, {control} ORDER BY {c}) + (count(*) OVER (PARTITION BY log, {control}, {c}) - 1) / 2.0"
    made = f"{_table_runs_sql() if given else _runs_sql()}, "
    return f"""WITH {made}r AS (SELECT log, {control}, {avg(x)} AS rx, {avg(y)} AS ry FROM runs{f" WHERE {x} IS NOT NULL AND {y} IS NOT NULL" if given else ""}),
    g AS (SELECT log, {control}, CASE WHEN min(rx) = max(rx) OR min(ry) = max(ry) THEN NULL ELSE corr(rx, ry) END AS rho FROM r GROUP BY log, {control})
    SELECT log, round(avg(rho), 6) AS rho, count(rho) AS groups, count(*) - count(rho) AS constant FROM g GROUP BY log"""


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    out["log_overview"] = " UNION ALL ".join(
        f"SELECT '{n}' AS log, (SELECT count(*) FROM t_{n}) AS n_cases, (SELECT count(DISTINCT seq) FROM t_{n}) AS n_variants, (SELECT count(DISTINCT activity) FROM r_{n}) AS n_activities, (SELECT count(*) FROM r_{n}) AS n_events" for n in LOG_SQL
    )
    out["log_overview"] = "WITH " + ", ".join(f"r_{n} AS ({sql}), t_{n} AS (SELECT case_id, string_agg(activity, '>' ORDER BY o1, o2, o3, o4) AS seq FROM r_{n} GROUP BY case_id)" for n, sql in LOG_SQL.items()) + " " + out["log_overview"]
    for n in ("conv", "tags", "lifecycle", "events_day", "lineflags"):
        out[f"variants_{n}"] = f"{_with(n)} SELECT array_to_string(list_slice(seq, 2, len(seq) - 1), '>') AS variant, freq FROM v"
    for key, n in (("trace_lengths", "events_day"), ("sessions_events", "events_sess")):
        out[key] = f"{_with(n)} SELECT CAST(len(seq) - 2 AS BIGINT) AS len, CAST(sum(freq) AS BIGINT) AS n FROM v GROUP BY 1"
    out["activity_scores"] = f"{_with('events_day')}, {_RANKS} SELECT act AS activity, round(mean_first, 6) AS mean_first, CAST(n_cases AS BIGINT) AS n_cases, CAST(n_events AS BIGINT) AS n_events FROM sc"
    step = "nx AS (SELECT vid, freq, act AS src, lead(act) OVER (PARTITION BY vid ORDER BY pos) AS dst FROM ev)"
    for n in ("conv", "lifecycle", "events_day"):
        out[f"dfg_{n}"] = f"{_with(n)}, {step} SELECT src, dst, CAST(sum(freq) AS BIGINT) AS n FROM nx WHERE src <> '{START}' AND dst <> '{END}' GROUP BY src, dst"
    out["footprint_conv"] = f"""{_with("conv")}, {step}, e AS (SELECT DISTINCT src, dst FROM nx WHERE dst IS NOT NULL)
    SELECT a.act AS src, b.act AS dst, CASE WHEN x.src IS NOT NULL AND y.src IS NOT NULL THEN '||' WHEN x.src IS NOT NULL THEN '->' WHEN y.src IS NOT NULL THEN '<-' ELSE '#' END AS relation
    FROM acts a CROSS JOIN acts b LEFT JOIN e x ON x.src = a.act AND x.dst = b.act LEFT JOIN e y ON y.src = b.act AND y.dst = a.act"""
    out["eventually_follows_events_day"] = f"""{_with("events_day")}, m AS (SELECT vid, act, any_value(freq) AS freq, min(pos) AS lo, max(pos) AS hi FROM ev GROUP BY vid, act)
    SELECT x.act AS src, y.act AS dst, CAST(sum(x.freq) AS BIGINT) AS n_cases FROM m x JOIN m y ON x.vid = y.vid AND x.lo < y.hi WHERE x.act <> '{START}' AND y.act <> '{END}' GROUP BY x.act, y.act"""
    out["segment_dfg_by_mktsegment"] = """WITH nx AS (SELECT o_custkey, o_orderpriority AS src, lead(o_orderpriority) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS dst FROM orders)
    SELECT c_mktsegment AS segment, src, dst, count(*) AS n FROM nx JOIN customer ON o_custkey = c_custkey WHERE dst IS NOT NULL GROUP BY 1, 2, 3"""
    out["cube_log_stats"] = "SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY CUBE (o_orderpriority, o_orderstatus)"
    keys = {"first_index": "mean_first", "lexicographic": "0", "frequency": "n_events", "trace_frequency": "n_cases", "mean_occurrences": "n_events / n_cases"}
    out["ordering_ablation"] = f"{_with('events_day')}, {_RANKS} " + " UNION ALL ".join(f"SELECT '{k}' AS strategy, act AS activity, CAST(row_number() OVER (ORDER BY {s}, act) - 1 AS INTEGER) AS rank FROM sc" for k, s in keys.items())
    for n in ("conv", "events_day", "lifecycle", "tags_core", "lineflags"):
        out[f"place_fitness_pairs_{n}"] = _pairs_sql(n)
    three = f"""{_SIDES}, pl AS (SELECT a.act || ',' || c.act || '>' || b.act AS pid, [a.act, c.act] AS pre, [b.act] AS post FROM pre_acts a, pre_acts c, post_acts b WHERE a.act < c.act
        UNION ALL SELECT a.act || '>' || b.act || ',' || c.act, [a.act], [b.act, c.act] FROM pre_acts a, post_acts b, post_acts c WHERE b.act < c.act)"""
    out["place_fitness_depth3_events_day"] = f"{_with('events_day')}, {three}, {_FIT} {_COUNTS}"
    tau = "(VALUES (1000), (900), (800), (700), (600), (500)) q(tau)"
    out["planted_dependency"] = f"SELECT * FROM ({_pairs_sql('lifecycle_planted')}) WHERE n_fit = n_total"
    out["projected_counts_lineflags"] = _pairs_sql("lineflags")
    out["passing_by_tau"] = " UNION ALL ".join(
        f"SELECT * FROM ({_with(n)}, {_PAIRS}, {_FIT} SELECT '{n}' AS log, tau AS tau_permille, count(*) FILTER (n_fit * 1000 >= tau * n_total) AS n_passing FROM fc CROSS JOIN {tau} GROUP BY tau)" for n in ("conv", "events_day", "lineflags", "lifecycle", "tags_core")
    )
    flags = f"cu AS (SELECT *, 1000 * n_under > {{0}} * n_total AS under, post = '{END}' AND 1000 * n_over > {{0}} * n_total AS over_ FROM fc)"
    out["cuts_depth2_events_day"] = f"{_with('events_day')}, {_PAIRS}, {_FIT}, {flags.format(500)} SELECT pre, post, under AS cut_post, over_ AND NOT under AS cut_pre FROM cu"
    modes = {"none": ("FALSE", "FALSE"), "under": ("under", "FALSE"), "over": ("FALSE", "over_"), "paper": ("under", "over_ AND NOT under"), "both": ("under", "over_")}
    # Depth three by the parent in closed form: a larger postset activity, or a larger preset one beside a single postset one.
    kids = " UNION ALL ".join(
        f"""SELECT '{k}' AS mode, 'x' AS kind, a.pre AS p1, NULL AS p2, a.post AS o1, z.act AS o2 FROM cu a JOIN rk rb ON rb.act = a.post JOIN rk z ON z.r > rb.r WHERE NOT ({cp}) AND z.act <> '{START}'
        UNION ALL SELECT '{k}', 'y', a.pre, z.act, a.post, NULL FROM cu a JOIN rk ra ON ra.act = a.pre JOIN rk z ON z.r > ra.r WHERE NOT ({cq}) AND z.act <> '{END}'""" for k, (cp, cq) in modes.items()
    )
    out["pruning_ablation"] = f"""{_with("events_day")}, {_RANKS}, {_PAIRS}, {_FIT}, {flags.format(200)}, kids AS ({kids}),
    three AS ({_with("events_day")}, {three}, {_FIT} {_COUNTS}),
    k3 AS (SELECT mode, array_to_string(list_sort(list_filter([p1, p2], lambda x: x IS NOT NULL)), ',') AS pre, array_to_string(list_sort(list_filter([o1, o2], lambda x: x IS NOT NULL)), ',') AS post FROM kids)
    SELECT mode, CAST(2 AS BIGINT) AS depth, count(*) AS n_evaluated, count(*) FILTER (10 * n_fit >= 8 * n_total) AS n_passing FROM fc CROSS JOIN (SELECT DISTINCT mode FROM kids) GROUP BY mode
    UNION ALL SELECT mode, CAST(3 AS BIGINT), count(*), count(*) FILTER (10 * n_fit >= 8 * n_total) FROM k3 JOIN three USING (pre, post) GROUP BY mode"""
    out["candidate_counts_by_depth"] = f"""{_with("events_day")}, k AS (SELECT CAST(power(2, count(*) - 1) AS BIGINT) AS top FROM acts), m AS (SELECT unnest(range(1, top)) AS i FROM k)
    SELECT CAST(bit_count(a.i) + bit_count(b.i) AS BIGINT) AS depth, count(*) AS n_candidates FROM m a, m b GROUP BY 1 HAVING depth <= 6"""
    out["log_language_kept_events_day"] = f"""{_with("events_day")}, {_RANKS}, {_PAIRS}, {_FIT},
    ok AS (SELECT fc.pid, fc.pre, fc.post, row_number() OVER (ORDER BY b.r, a.r) AS rank FROM fc JOIN rk a ON a.act = fc.pre JOIN rk b ON b.act = fc.post WHERE 10 * n_fit >= 5 * n_total),
    f AS (SELECT vid, min(rank) AS rank FROM st JOIN ok USING (pid) WHERE least < 0 OR fin <> 0 GROUP BY vid)
    SELECT DISTINCT ok.pre, ok.post, CAST(ok.rank AS BIGINT) AS rank FROM ok JOIN f ON ok.rank = f.rank"""
    sets = ", ".join(f"('{k}', {_list(i)}, {_list(o)})" for k, (i, o) in enumerate(LIFECYCLE_SET, 1))
    out["set_support_lifecycle"] = f"""{_with("lifecycle")}, pl AS (SELECT * FROM (VALUES {sets}) x(pid, pre, post)), {_FIT},
    worst AS (SELECT vid, any_value(freq) AS freq, min(CAST(pid AS INTEGER)) AS k FROM st WHERE least < 0 OR fin <> 0 GROUP BY vid)
    SELECT CAST(q.k AS BIGINT) AS n_places, CAST(n - coalesce((SELECT sum(freq) FROM worst WHERE worst.k <= q.k), 0) AS BIGINT) AS n_fit, n AS n_total FROM tot CROSS JOIN (SELECT unnest(range(1, {len(LIFECYCLE_SET) + 1})) AS k) q"""
    out["perfect_fit_share"] = f"""{_with("conv")}, {_PAIRS}, {_FIT}, ok AS (SELECT pid FROM fc WHERE 10 * n_fit >= 5 * n_total), un AS (SELECT DISTINCT vid, freq FROM st JOIN ok USING (pid) WHERE least < 0 OR fin <> 0)
    SELECT (SELECT count(*) FROM ok) AS n_places, CAST(n - (SELECT coalesce(sum(freq), 0) FROM un) AS BIGINT) AS n_fit, n AS n_total FROM tot"""
    loops = ", ".join(f"({k}, {_list(i)}, {_list(o)})" for k, (i, o) in enumerate(LOOPS))
    lt = f"pl AS (SELECT * FROM (VALUES {loops}) x(k, pre, post))"
    out["selfloop_merge"] = f"""WITH {lt}, s AS (SELECT k, list_sort(list_filter(pre, lambda x: NOT list_contains(post, x))) AS gain, list_sort(list_filter(post, lambda x: NOT list_contains(pre, x))) AS loss, list_filter(pre, lambda x: list_contains(post, x)) AS loops FROM pl),
    g AS (SELECT gain, loss, list_distinct(flatten(list(loops))) AS loops, count(*) AS merged FROM s GROUP BY gain, loss)
    SELECT array_to_string(list_sort(list_concat(gain, loops)), ',') AS pre, array_to_string(list_sort(list_concat(loss, loops)), ',') AS post, merged FROM g"""
    out["uniwired_conflicts"] = f"""WITH {lt}, w AS (SELECT k, a, unnest(post) AS b FROM (SELECT k, unnest(pre) AS a, post FROM pl))
    SELECT CAST(x.k AS BIGINT) AS first, CAST(y.k AS BIGINT) AS second, count(*) AS n FROM w x JOIN w y ON x.a = y.a AND x.b = y.b AND x.k < y.k GROUP BY 1, 2"""
    out["net_arcs_lifecycle"] = f"""{_with("lifecycle")}, {_PAIRS}, {_FIT}, ok AS (SELECT pre, post, pre || '>' || post AS pid FROM fc WHERE n_fit * 10 >= n_total * 7)
    SELECT pre AS src, pid AS dst, 'produce' AS kind FROM ok UNION ALL SELECT pid, post, 'consume' FROM ok UNION ALL SELECT 'source', '{START}', 'consume' UNION ALL SELECT '{END}', 'sink', 'produce'"""
    conv = ", ".join(f"({k}, {_list(i)}, {_list(o)})" for k, (i, o) in enumerate(CONV_SET))
    out["etc_precision_conv"] = f"""{_with("conv")}, pl AS (SELECT * FROM (VALUES {conv}) x(pid, pre, post)),
    tk AS (SELECT pid, vid, freq, pos, post, CAST(list_contains(pre, act) AS INT) AS made, CAST(list_contains(post, act) AS INT) AS used FROM ev, pl),
    rn AS (SELECT pid, vid, freq, pos, post, sum(made - used) OVER (PARTITION BY pid, vid ORDER BY pos ROWS UNBOUNDED PRECEDING) AS tokens, coalesce(sum(made) OVER (PARTITION BY pid, vid ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) - sum(used) OVER (PARTITION BY pid, vid ORDER BY pos ROWS UNBOUNDED PRECEDING) AS slack FROM tk),
    ok AS (SELECT pid, vid, freq, pos, post, tokens, min(slack) OVER (PARTITION BY pid, vid ORDER BY pos ROWS UNBOUNDED PRECEDING) AS least FROM rn),
    pre_ok AS (SELECT vid, freq, pos FROM ok GROUP BY vid, freq, pos HAVING min(least) >= 0),
    sts AS (SELECT p.vid, p.pos, p.freq, list_slice(v.seq, 1, p.pos) AS prefix, v.seq[p.pos + 1] AS nxt FROM pre_ok p JOIN v ON p.vid = v.vid WHERE p.pos < len(v.seq)),
    dis AS (SELECT DISTINCT o.vid, o.pos, b.act FROM ok o, acts b WHERE list_contains(o.post, b.act) AND o.tokens < 1),
    en AS (SELECT DISTINCT s.prefix, b.act FROM sts s, acts b WHERE b.act <> '{START}' AND NOT EXISTS (SELECT 1 FROM dis WHERE dis.vid = s.vid AND dis.pos = s.pos AND dis.act = b.act)),
    wt AS (SELECT prefix, sum(freq) AS w FROM sts GROUP BY prefix), seen AS (SELECT DISTINCT prefix, nxt FROM sts),
    tt AS (SELECT CAST(sum(w) AS BIGINT) AS enabled, CAST(sum(CASE WHEN seen.nxt IS NULL THEN w ELSE 0 END) AS BIGINT) AS escaping FROM en JOIN wt USING (prefix) LEFT JOIN seen ON seen.prefix = en.prefix AND seen.nxt = en.act)
    SELECT enabled, escaping, round(1 - escaping / enabled, 6) AS precision FROM tt"""
    out["micro_examples"] = " UNION ALL ".join(
        f"SELECT * FROM ({_with(n)}, pl AS (SELECT 'p' AS pid, {_list(i)} AS pre, {_list(o)} AS post), {_FIT} SELECT '{n}' AS log, pre, post, n_fit, n_under, n_over, n_total FROM fc)" for n, i, o in EXAMPLES
    )
    # Bits of i: the activities after the first one of a side, by rank.
    subsets = lambda lo, hi: f"SELECT m.i, coalesce(list(k.act) FILTER (k.act IS NOT NULL), []) AS acts FROM m LEFT JOIN (SELECT act, CAST(r - {lo} AS INTEGER) AS b FROM rk, na WHERE r >= {lo} AND r <= {hi}) k ON (m.i >> k.b) & 1 = 1 GROUP BY m.i"
    out["candidate_tree_example"] = f"""{_with("events_day")}, {_RANKS}, na AS (SELECT count(*) AS n FROM rk), m AS (SELECT i FROM na, range(CAST(power(2, n - 2) AS BIGINT)) t(i)), a AS ({subsets(2, "n - 1")}), b AS ({subsets(3, "n")})
    SELECT CAST(2 + len(a.acts) + len(b.acts) AS BIGINT) AS depth, array_to_string(list_sort(list_concat(['{START}'], a.acts)), ',') AS pre, array_to_string(list_sort(list_concat([rk.act], b.acts)), ',') AS post FROM a, b, rk WHERE rk.r = 2"""
    q = lambda c, p: f"round(quantile_cont({c}, {p}), 6)"
    times = ", ".join(f"{q(c, 0.1)} AS {n}_p10, round(avg({c}), 6) AS {n}_mean, {q(c, 0.9)} AS {n}_p90, round(stddev_samp({c}), 6) AS {n}_std" for n, c in (("search", "t_search"), ("post", "t_post"), ("total", "t_search + t_post")))
    out["runtime_table"] = f"WITH {_runs_sql()} SELECT log, count(*) AS runs, round(100 * avg(CAST(stopped_search AS INT)), 6) AS search_timeouts, round(100 * avg(CAST(dnf AS INT)), 6) AS total_timeouts, {times} FROM runs GROUP BY log"
    out["collected_places"] = f"WITH {_table_runs_sql()} SELECT log, {q('collected', 0.5)} AS collected, {q('CASE WHEN dnf THEN collected END', 0.5)} AS collected_dnf, {q('CASE WHEN NOT dnf THEN after_post END', 0.5)} AS after_post FROM runs GROUP BY log"
    out["pareto_fit_prec"] = _pareto_sql("fitness", "precision", 1, True)
    out["pareto_fit_size"] = _pareto_sql("fitness", "after_post", -1, True)
    out["pareto_prec_size"] = _pareto_sql("precision", "after_post", -1)
    out["fastest_top_decile"] = f"""WITH {_table_runs_sql()}, r AS (SELECT log, percent_rank() OVER (PARTITION BY log ORDER BY f1 DESC) AS q, percent_rank() OVER (PARTITION BY log ORDER BY t_search + t_post) AS s FROM runs WHERE f1 IS NOT NULL)
    SELECT log, round(100 * min(s), 6) AS percentile FROM r WHERE q <= 0.1 GROUP BY log"""
    out["min_depth_at_max"] = f"""WITH {_table_runs_sql()}, m AS (SELECT log, oracle, tau, depth, fitness, max(fitness) OVER (PARTITION BY log, oracle, tau) AS top FROM runs), d AS (SELECT log, oracle, tau, min(depth) AS d FROM m WHERE fitness = top GROUP BY 1, 2, 3)
    SELECT log, oracle, round(avg(d), 6) AS mean_depth FROM d GROUP BY 1, 2"""
    out["controlled_spearman"] = _spearman_sql("tau", "fitness", "depth, oracle", True)
    out["controlled_spearman_depth"] = _spearman_sql("depth", "precision", "tau, oracle", True)
    out["cube_runs"] = f"WITH {_table_runs_sql()} SELECT log, tau, depth, count(*) AS n, CAST(sum(collected) AS BIGINT) AS collected FROM runs GROUP BY CUBE (log, tau, depth)"
    out["tags_wide_depth2"] = _pairs_sql("tags")
    return out
