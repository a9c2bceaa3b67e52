"""Workloads whose rows SQL can repeat step by step: composition, the tree and its cuts, budgets, constraints, engines, replay.

The DuckDB side lists all places of a log down to a depth as pairs of bit masks over the ordered activities, replays them, and
folds the composers' decisions over the candidates in path order with recursive queries.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .checkpoints import checkpointed
from .functions import places as pl
from .functions.places import END, START
from .functions.replay import token_replay, token_series
from .operators import heuristics, log as logs, order
from .operators.baselines import dfg as graph
from .operators.compose import Budget, Collect, Delta, Implicit, Threshold, Uniwired
from .operators.constraints import heuristic_below, max_post, not_anywhere
from .operators.evaluate import decide, fitness
from .operators.tree import tree_of
from .plans.config import Config
from .plans.experiment import DEPTHS, TAUS, evaluated
from .plans.propose import Discovery, discover, regrid, walk
from .plans.run import Prepared, search, tree
from .workloads import _FIT, _RANKS, _compose, _counts, _list, _pairs, _passing, _rows, _with, CONV_SET, Query, names_log, ready

BLACK = {"conv": "system", "events_day": "click"}


# --- queries ------------------------------------------------------------------------------------------------------


def _found(p: Prepared, found: Discovery) -> DataFrame:
    counts = p.log.counts(found.places) if found.places else []
    return _rows(p, found.places, lambda i, _: (int(counts[i][0]), p.log.total), "n_fit long, n_total long")


def distributed_walk(name: str, tau: float, depth: int, make=None) -> Query:
    """The places of the walk over DataFrames, whatever the size of the log."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        p = ready(spark, d, name)
        found = discover(p.log, tree(Config(max_depth=depth), p), tau, Threshold(make(p) if make else Collect(), tau), engine="arrow")
        return _found(p, found)

    return query


def distributed_levels(name: str, tau: float, depth: int) -> Query:
    """Candidates and passing places of each level of the walk over DataFrames."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        p = ready(spark, d, name)
        found = discover(p.log, tree(Config(max_depth=depth), p), tau, engine="arrow")
        return spark.createDataFrame([(k, n, m) for k, (n, m) in found.by_depth.items()], "depth long, n_evaluated long, n_passing long")

    return query


def budgeted(limit: int) -> Query:
    """The first candidates of the walk by levels on the log of mostly short sessions, by the driver's and by the distributed search."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        p = ready(spark, d, "events_day")
        rows = []
        for how in (False, True):
            out = search(Config(tau=0.5, max_depth=4, max_candidates=limit, seconds=None), p, distributed=how)
            rows += [("distributed" if how else "driver", depth, n, k) for depth, (n, k) in out.by_depth.items()]
        return spark.createDataFrame(rows, "search string, depth long, n_evaluated long, n_passing long")

    return query


def constrained(name: str, tau: float, depth: int) -> Query:
    """Places without one activity, with at most two activities after them and at most three in all."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        p = ready(spark, d, name)
        guards = [not_anywhere(BLACK[name]), max_post(2), heuristic_below("size", heuristics.place_size, 3.0, True)]
        return _found(p, walk(p.log, p.labels, tree(Config(max_depth=depth), p), tau, constraints=guards))

    return query


def blacklisted(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "events_day")
    t = tree(Config(max_depth=2, blacklist=(BLACK["events_day"],)), p)
    from .plans.propose import _with_ids

    return _counts(p, _with_ids(t.seeds(spark), t, p.labels))


def prefer_pre(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "conv")
    return _found(p, walk(p.log, p.labels, tree(Config(max_depth=4, prefer="pre"), p), 0.5))


def grid_counts(name: str, depths=DEPTHS) -> Query:
    """Candidates and passing places of every threshold and depth of the full grid, from one shared walk."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        p = ready(spark, d, name)
        top = Config(tau=min(TAUS), max_depth=max(depths))
        table, t, total = evaluated(p, top), tree(top, p), p.log.total
        rows = []
        for tau in TAUS:
            for depth in depths:
                part = regrid(table, t, total, tau, depth)
                rows.append((round(1000 * tau), depth, len(part), sum(r["n_fit"] * 1000 >= round(1000 * tau) * total for r in part)))
        return spark.createDataFrame(rows, "tau_permille long, depth long, n_evaluated long, n_passing long")

    return query


def orders_compared(spark: SparkSession, d: str) -> DataFrame:
    """What single wiring leaves and how many candidates a walk evaluates under each order of the activities."""
    named = checkpointed(names_log(spark, d, "events_day"))
    rows = []
    for how in ("first_index", "lexicographic", "frequency", "trace_frequency", "mean_occurrences"):
        labels = [START, *order.ordered(named, how), END]
        from .operators.evaluate import SparkLog

        log = SparkLog(logs.encode(named, labels), labels)
        found = walk(log, labels, tree_of(labels[1:-1], 3), 0.5, Threshold(Uniwired(Collect()), 0.5))
        free = walk(log, labels, tree_of(labels[1:-1], 3), 0.5)
        rows.append((how, len(found.places), free.proposed, len(free.places)))
    return spark.createDataFrame(rows, "strategy string, uniwired_places long, n_evaluated long, n_places long")


def engines(spark: SparkSession, d: str) -> DataFrame:
    """The pair counts by each fitness engine."""
    p = ready(spark, d, "conv")
    table, out = checkpointed(_pairs(p)), None
    names = F.array(*map(F.lit, p.labels))
    label = lambda c: F.concat_ws(",", F.array_sort(F.transform(c, lambda i: F.get(names, i))))
    for engine in ("sql", "window", "arrow", "frontier"):
        one = fitness(p.log, table, engine).select(F.lit(engine).alias("engine"), label("pre").alias("pre"), label("post").alias("post"), "n_fit", "n_under", "n_over")
        out = one if out is None else out.union(one)
    return out


def early_decisions(spark: SparkSession, d: str) -> DataFrame:
    p = ready(spark, d, "events_day")
    t = tree(Config(max_depth=2), p)
    places = [t.ids(n, p.labels) for n in t.subtree() if n[0] and n[1]]
    found = decide(p.log, places, 0.5)
    return _rows(p, places, lambda i, q: (found[q][0],), "reaches boolean")


def token_lines(spark: SparkSession, d: str) -> DataFrame:
    """Tokens of one place after each event, by variant."""
    sides = [F.array(*map(F.lit, s)) for s in CONV_SET[1]]
    return names_log(spark, d, "conv").select(F.concat_ws(">", "seq").alias("variant"), F.concat_ws(",", token_series("seq", *sides).cast("array<string>")).alias("tokens"))


def token_totals(spark: SparkSession, d: str) -> DataFrame:
    """Produced, consumed, missing and remaining tokens of each place of a set over all traces."""
    out = None
    for i, o in CONV_SET:
        s = token_replay("seq", F.array(*map(F.lit, i)), F.array(*map(F.lit, o)))
        sums = [F.sum(F.col(f"s.{c}") * F.col("freq")).alias(c) for c in ("produced", "consumed", "missing", "remaining")]
        one = names_log(spark, d, "conv").select("freq", s.alias("s")).agg(*sums).select(F.lit(",".join(sorted(i))).alias("pre"), F.lit(",".join(sorted(o))).alias("post"), "*")
        out = one if out is None else out.union(one)
    return out


def place_facts(spark: SparkSession, d: str) -> DataFrame:
    """What places over three activities are: self-loops, sizes, effect, and how many direct expansions they have among themselves."""
    t = tree_of(["a", "b", "c"], 4)
    rows = [tuple(list(s) for s in t.names(n)) for n in t.subtree() if n[0] and n[1]]
    p = spark.createDataFrame(rows, "pre array<string>, post array<string>").withColumn("pid", pl.place_id("pre", "post"))
    q = p.select(*[F.col(c).alias(f"q_{c}") for c in ("pre", "post", "pid")])
    grown = p.join(F.broadcast(q), pl.is_pre_expansion("q_pre", "q_post", "pre", "post", True) | pl.is_post_expansion("q_pre", "q_post", "pre", "post", True)).groupBy("pid").agg(F.count(F.lit(1)).alias("n_direct"))
    text = lambda c: F.concat_ws(",", c)
    e = pl.effect("pre", "post")
    return p.join(grown, "pid", "left").select("pid", text(pl.selfloops("pre", "post")).alias("loops"), pl.depth("pre", "post").cast("long").alias("depth"), pl.support_size("pre", "post").cast("long").alias("support"), text(e["gain"]).alias("gain"), text(e["loss"]).alias("loss"), F.coalesce("n_direct", F.lit(0)).alias("n_direct"))


def top_mass(spark: SparkSession, d: str) -> DataFrame:
    """The most frequent variants that make up half of the traces."""
    return logs.subset(names_log(spark, d, "events_day"), top_mass=0.5).select(F.concat_ws(">", "seq").alias("variant"), "freq")


def directly_interest(spark: SparkSession, d: str) -> DataFrame:
    found = heuristics.interest(names_log(spark, d, "conv"), "directly")
    return found.select(F.col("pre_act").alias("src"), F.col("post_act").alias("dst"), F.round("score", 6).alias("score"), "n")


def filtered_follows(spark: SparkSession, d: str) -> DataFrame:
    return graph.dfg(names_log(spark, d, "events_day")).where("n >= 20")


def two_taus(p: Prepared):
    return Implicit(Collect(), p.log, "log_language")


QUERIES: dict[str, Query] = {
    "distributed_walk_events_day": distributed_walk("events_day", 0.5, 3),
    "distributed_walk_lifecycle": distributed_walk("lifecycle", 0.7, 2),
    "distributed_levels_events_day": distributed_levels("events_day", 0.5, 4),
    "distributed_uniwired_events_day": distributed_walk("events_day", 0.5, 3, lambda p: Uniwired(Collect())),
    "distributed_delta_conv": distributed_walk("conv", 0.5, 4, lambda p: Delta(Collect(), p.log, 0.2, 0.3)),
    "budget_walks_events_day": budgeted(70),
    "uniwired_compose_events_day": lambda s, d: _compose(ready(s, d, "events_day"), lambda p: Uniwired(Collect()), 0.5, 3),
    "delta_compose_events_day": lambda s, d: _compose(ready(s, d, "events_day"), lambda p: Delta(Collect(), p.log, 0.2, 0.3), 0.5, 3),
    "log_language_compose_events_day": lambda s, d: _compose(ready(s, d, "events_day"), two_taus, 0.5, 3),
    "constrained_walk_conv": constrained("conv", 0.5, 4),
    "constrained_walk_events_day": constrained("events_day", 0.5, 3),
    "blacklist_pairs_events_day": blacklisted,
    "prefer_pre_conv": prefer_pre,
    "grid_counts_conv": grid_counts("conv"),
    "grid_counts_events_day": grid_counts("events_day", (2, 3, 4)),
    "orders_compared": orders_compared,
    "engines_conv": engines,
    "early_decisions_events_day": early_decisions,
    "token_lines_conv": token_lines,
    "token_totals_conv": token_totals,
    "place_facts": place_facts,
    "top_mass_events_day": top_mass,
    "directly_interest_conv": directly_interest,
    "filtered_follows_events_day": filtered_follows,
}


def queries() -> dict[str, Query]:
    return dict(QUERIES)


# --- DuckDB -------------------------------------------------------------------------------------------------------


def _places(depth: int) -> str:
    """pl(pid, pre, post, pr, qr, depth, parent): all places down to a depth, with ranks and masks of their sides, and their parent."""
    return f"""na AS (SELECT CAST(count(*) AS INTEGER) AS n FROM rk),
    sets AS (SELECT i, list(act ORDER BY r) AS acts, list(r ORDER BY r) AS rs, CAST(count(*) AS INTEGER) AS k FROM (SELECT i FROM na, range(1, CAST(power(2, n) AS BIGINT)) t(i) WHERE bit_count(i) < {depth}), rk WHERE (i >> CAST(r - 1 AS INTEGER)) & 1 = 1 GROUP BY i),
    pl AS (SELECT a.i || '>' || b.i AS pid, a.acts AS pre, b.acts AS post, a.rs AS pr, b.rs AS qr, a.k + b.k AS depth, list_last(b.rs) = n AS at_end,
        CASE WHEN b.k > 1 THEN a.i || '>' || (b.i - (1 << CAST(list_last(b.rs) - 1 AS INTEGER))) WHEN a.k > 1 THEN (a.i - (1 << CAST(list_last(a.rs) - 1 AS INTEGER))) || '>' || b.i END AS parent, b.k > 1 AS by_post
        FROM sets a, sets b, na WHERE a.i < (1 << (n - 1)) AND b.i % 2 = 0 AND a.k + b.k <= {depth})"""


def _all(name: str, depth: int) -> str:
    """Common tables down to fx: every place with its counts, ranks and path."""
    return f"""{_with(name)}, {_RANKS}, {_places(depth)}, {_FIT},
    fx AS (SELECT fc.*, pl.pr, pl.qr, pl.depth, pl.parent, pl.by_post, pl.at_end, list_concat([CAST(pl.depth AS BIGINT), qr[1]], list_transform(pr, lambda x: x + 1000), list_slice(qr, 2, len(qr))) AS ord FROM fc JOIN pl ON fc.pid = pl.pid)"""


def _passing_sql(tau: int, where: str = "TRUE") -> str:
    return f"cand AS (SELECT row_number() OVER (ORDER BY ord) AS rn, * FROM fx WHERE 1000 * n_fit >= {tau} * n_total AND {where})"


_KEPT = "SELECT pre, post, n_fit, n_total FROM cand WHERE rn IN (SELECT unnest(acc) FROM (SELECT acc FROM rec ORDER BY rn DESC LIMIT 1))"


def uniwired_sql(name: str, tau: int, depth: int) -> str:
    return f"""{_all(name, depth).replace("WITH ", "WITH RECURSIVE ", 1)}, {_passing_sql(tau)},
    wc AS (SELECT rn, flatten(list_transform(pr, lambda x: list_transform(qr, lambda y: 100 * x + y))) AS ws FROM cand),
    rec AS (SELECT CAST(0 AS BIGINT) AS rn, CAST([] AS BIGINT[]) AS taken, CAST([] AS BIGINT[]) AS acc
        UNION ALL SELECT wc.rn, CASE WHEN list_has_any(taken, ws) THEN taken ELSE list_concat(taken, ws) END, CASE WHEN list_has_any(taken, ws) THEN acc ELSE list_append(acc, wc.rn) END FROM rec JOIN wc ON wc.rn = rec.rn + 1)
    {_KEPT}"""


def _bad(name: str, tau: int, depth: int) -> str:
    """Candidates with the variants that do not fit them, and the variants' frequencies as one list."""
    return f"""{_all(name, depth).replace("WITH ", "WITH RECURSIVE ", 1)}, {_passing_sql(tau)},
    un AS (SELECT pid, list(vid) AS bad FROM st WHERE least < 0 OR fin <> 0 GROUP BY pid),
    bc AS (SELECT rn, depth, coalesce(bad, CAST([] AS BIGINT[])) AS bad FROM cand LEFT JOIN un ON cand.pid = un.pid),
    fr AS (SELECT list(freq ORDER BY vid) AS f, list(vid ORDER BY vid) AS vids FROM v)"""


def log_language_sql(name: str, tau: int, depth: int) -> str:
    return f"""{_bad(name, tau, depth)},
    rec AS (SELECT CAST(0 AS BIGINT) AS rn, vids AS alive, CAST([] AS BIGINT[]) AS acc FROM fr
        UNION ALL SELECT bc.rn, CASE WHEN list_has_any(alive, bad) THEN list_filter(alive, lambda x: NOT list_contains(bad, x)) ELSE alive END, CASE WHEN list_has_any(alive, bad) THEN list_append(acc, bc.rn) ELSE acc END FROM rec JOIN bc ON bc.rn = rec.rn + 1)
    {_KEPT}"""


def delta_sql(name: str, tau: int, depth: int, growing: bool = False) -> str:
    allowed = f"(200000 * bc.depth // {depth})" if growing else "200000"
    return f"""{_bad(name, tau, depth)},
    rec AS (SELECT CAST(0 AS BIGINT) AS rn, vids AS alive, CAST(list_sum(f) AS BIGINT) AS w, CAST([] AS BIGINT[]) AS acc FROM fr
        UNION ALL SELECT rn, CASE WHEN ok THEN rest ELSE alive END, CASE WHEN ok THEN wr ELSE w END, CASE WHEN ok THEN list_append(acc, rn) ELSE acc END FROM (
            SELECT *, wr * 1000000 >= 300000 * n AND (w - wr) * 1000000 <= allowed * n AS ok FROM (
                SELECT rn, alive, w, acc, rest, allowed, n, CAST(coalesce(list_sum(list_transform(rest, lambda x: f[x])), 0) AS BIGINT) AS wr FROM (
                    SELECT bc.rn, alive, w, acc, list_filter(alive, lambda x: NOT list_contains(bad, x)) AS rest, {allowed} AS allowed FROM rec JOIN bc ON bc.rn = rec.rn + 1) CROSS JOIN fr CROSS JOIN tot)))
    {_KEPT}"""


def _cut(tau: str, both: bool = False) -> str:
    """Whether the candidate al cuts its child c, by the rule that tries overfed traces only where underfed ones do not cut, or by ``both``; ``tau`` in permille."""
    under = f"1000 * al.n_under > (1000 - {tau}) * al.n_total"
    return f"CASE WHEN c.by_post THEN {under} ELSE al.at_end AND 1000 * al.n_over > (1000 - {tau}) * al.n_total AND {"TRUE" if both else f"NOT ({under})"} END"


def walk_sql(name: str, tau: int, depth: int, select: str) -> str:
    cut = _cut(str(tau))
    return f"""{_all(name, depth).replace("WITH ", "WITH RECURSIVE ", 1)},
    al AS (SELECT * FROM fx WHERE depth = 2 UNION ALL SELECT c.* FROM al JOIN fx c ON c.parent = al.pid WHERE NOT ({cut}))
    {select}"""


def grid_sql(name: str, depths) -> str:
    taus = ", ".join(f"({round(1000 * t)})" for t in TAUS)
    cut = _cut("al.tau", True)
    return f"""{_all(name, max(depths)).replace("WITH ", "WITH RECURSIVE ", 1)}, q AS (SELECT * FROM (VALUES {taus}) x(tau)),
    al AS (SELECT q.tau, fx.* FROM fx, q WHERE depth = 2 UNION ALL SELECT al.tau, c.* FROM al JOIN fx c ON c.parent = al.pid WHERE NOT ({cut})),
    ds AS (SELECT * FROM (VALUES {", ".join(f"({d})" for d in depths)}) y(d))
    SELECT CAST(tau AS BIGINT) AS tau_permille, CAST(d AS BIGINT) AS depth, count(*) AS n_evaluated, count(*) FILTER (1000 * n_fit >= tau * n_total) AS n_passing FROM al JOIN ds ON al.depth <= ds.d GROUP BY tau, d"""


def orders_sql(name: str, tau: int, depth: int) -> str:
    keys = {"first_index": "mean_first", "lexicographic": "0", "frequency": "n_events", "trace_frequency": "n_cases", "mean_occurrences": "n_events / n_cases"}
    one = uniwired_sql(name, tau, depth)
    body = one[: one.rindex(_KEPT)]
    out = []
    for how, key in keys.items():
        ranked = body.replace(_RANKS, _RANKS.replace("ELSE 1 END, mean_first, act)", f"ELSE 1 END, {key}, act)"))
        out.append(f"""SELECT * FROM ({ranked}, al AS (SELECT * FROM fx WHERE depth = 2 UNION ALL SELECT c.* FROM al JOIN fx c ON c.parent = al.pid WHERE NOT ({_cut(str(tau))}))
        SELECT '{how}' AS strategy, (SELECT CAST(len(acc) AS BIGINT) FROM rec ORDER BY rn DESC LIMIT 1) AS uniwired_places, count(*) AS n_evaluated, count(*) FILTER (1000 * n_fit >= {tau} * n_total) AS n_places FROM al)""")
    return " UNION ALL ".join(out)


def _kept_sql(name: str, tau: int, depth: int, where: str = "TRUE") -> str:
    return f"{_all(name, depth)} SELECT pre, post, n_fit, n_total FROM fx WHERE 1000 * n_fit >= {tau} * n_total AND {where}"


def _guard(name: str) -> str:
    return f"NOT list_contains(string_split(pre || ',' || post, ','), '{BLACK[name]}') AND len(qr) <= 2 AND len(list_distinct(list_concat(pr, qr))) <= 3"


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    out["base_compose_conv"] = _kept_sql("conv", 800, 4)
    out["uniwired_compose_conv"] = out["postponing_compose_conv"] = uniwired_sql("conv", 500, 4)
    out["log_language_compose_conv"] = log_language_sql("conv", 500, 4)
    out["delta_compose_conv"] = out["distributed_delta_conv"] = delta_sql("conv", 500, 4)
    out["delta_growing_compose_conv"] = delta_sql("conv", 500, 4, True)
    out["uniwired_compose_events_day"] = out["distributed_uniwired_events_day"] = uniwired_sql("events_day", 500, 3)
    out["delta_compose_events_day"] = delta_sql("events_day", 500, 3)
    out["log_language_compose_events_day"] = log_language_sql("events_day", 500, 3)
    out["distributed_walk_events_day"] = _kept_sql("events_day", 500, 3)
    out["distributed_walk_lifecycle"] = _kept_sql("lifecycle", 700, 2)
    levels = "SELECT CAST(depth AS BIGINT) AS depth, count(*) AS n_evaluated, count(*) FILTER (2 * n_fit >= n_total) AS n_passing FROM al GROUP BY depth"
    out["distributed_levels_events_day"] = walk_sql("events_day", 500, 4, levels)
    out["budget_walks_events_day"] = walk_sql(
        "events_day", 500, 4, ", first AS (SELECT * FROM (SELECT *, row_number() OVER (ORDER BY ord) AS rn FROM al) WHERE rn <= 70) SELECT search, CAST(depth AS BIGINT) AS depth, count(*) AS n_evaluated, count(*) FILTER (2 * n_fit >= n_total) AS n_passing FROM first, (VALUES ('driver'), ('distributed')) z(search) GROUP BY search, depth"
    )
    for n, depth in (("conv", 4), ("events_day", 3)):
        out[f"constrained_walk_{n}"] = _kept_sql(n, 500, depth, _guard(n))
    black = BLACK["events_day"]
    out["blacklist_pairs_events_day"] = f"{_all('events_day', 2)} SELECT pre, post, n_fit, n_under, n_over, n_total FROM fx WHERE pre <> '{black}' AND post <> '{black}'"
    out["prefer_pre_conv"] = _kept_sql("conv", 500, 4)
    out["grid_counts_conv"] = grid_sql("conv", DEPTHS)
    out["grid_counts_events_day"] = grid_sql("events_day", (2, 3, 4))
    out["orders_compared"] = orders_sql("events_day", 500, 3)
    out["engines_conv"] = f"{_all('conv', 2)} SELECT engine, pre, post, n_fit, n_under, n_over FROM fx, (VALUES ('sql'), ('window'), ('arrow'), ('frontier')) z(engine)"
    out["early_decisions_events_day"] = f"{_all('events_day', 2)} SELECT pre, post, 2 * n_fit >= n_total AS reaches FROM fx"
    i, o = CONV_SET[1]
    out["token_lines_conv"] = f"""{_with("conv")}, tk AS (SELECT vid, pos, sum(CAST(list_contains({_list(i)}, act) AS INTEGER) - CAST(list_contains({_list(o)}, act) AS INTEGER)) OVER (PARTITION BY vid ORDER BY pos ROWS UNBOUNDED PRECEDING) AS t FROM ev)
    SELECT array_to_string(any_value(seq), '>') AS variant, string_agg(CAST(CAST(t AS BIGINT) AS VARCHAR), ',' ORDER BY pos) AS tokens FROM tk JOIN v USING (vid) GROUP BY vid"""
    sets = ", ".join(f"('{k}', {_list(a)}, {_list(b)})" for k, (a, b) in enumerate(CONV_SET))
    replay = f"""{_with("conv")}, pl AS (SELECT * FROM (VALUES {sets}) x(pid, pre, post)),
    tk AS (SELECT pid, vid, freq, pos, CAST(list_contains(pre, act) AS INT) AS made, CAST(list_contains(post, act) AS INT) AS used FROM ev, pl),
    rn AS (SELECT *, sum(used) OVER w - coalesce(sum(made) OVER (PARTITION BY pid, vid ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS lack FROM tk WINDOW w AS (PARTITION BY pid, vid ORDER BY pos ROWS UNBOUNDED PRECEDING)),
    one AS (SELECT pid, vid, any_value(freq) AS freq, sum(made) AS p, sum(used) AS c, greatest(max(lack), 0) AS m FROM rn GROUP BY pid, vid),
    by_place AS (SELECT pid, CAST(sum(freq * p) AS BIGINT) AS produced, CAST(sum(freq * c) AS BIGINT) AS consumed, CAST(sum(freq * m) AS BIGINT) AS missing, CAST(sum(freq * (p - c + m)) AS BIGINT) AS remaining FROM one GROUP BY pid)"""
    out["token_totals_conv"] = f"{replay} SELECT array_to_string(list_sort(pre), ',') AS pre, array_to_string(list_sort(post), ',') AS post, produced, consumed, missing, remaining FROM by_place JOIN pl USING (pid)"
    out["replay_fitness_conv"] = f"""{replay}, s AS (SELECT CAST(sum(produced) AS BIGINT) AS produced, CAST(sum(consumed) AS BIGINT) AS consumed, CAST(sum(missing) AS BIGINT) AS missing, CAST(sum(remaining) AS BIGINT) AS remaining FROM by_place)
    SELECT *, round(0.5 * (1 - missing / consumed) + 0.5 * (1 - remaining / produced), 6) AS fitness FROM s"""
    out["relative_fitness_events_day"] = f"""{_all("events_day", 2)}, tc AS (SELECT pid, sum(freq) AS t, sum(CASE WHEN least >= 0 AND fin = 0 THEN freq ELSE 0 END) AS f FROM st GROUP BY pid)
    SELECT pre, post, CAST(coalesce(t, 0) AS BIGINT) AS n_touching, CAST(coalesce(f, 0) AS BIGINT) AS n_fit_touching FROM fx LEFT JOIN tc USING (pid)"""
    rel = "CASE WHEN x.src IS NOT NULL AND y.src IS NOT NULL THEN '||' WHEN x.src IS NOT NULL THEN '->' WHEN y.src IS NOT NULL THEN '<-' ELSE '#' END"
    foot = f"""{_with("conv")}, nx AS (SELECT vid, act AS src, lead(act) OVER (PARTITION BY vid ORDER BY pos) AS dst FROM ev), e AS (SELECT DISTINCT src, dst FROM nx WHERE dst IS NOT NULL),
    fp AS (SELECT a.act AS src, b.act AS dst, {rel} AS relation FROM acts a CROSS JOIN acts b LEFT JOIN e x ON x.src = a.act AND x.dst = b.act LEFT JOIN e y ON y.src = b.act AND y.dst = a.act)"""
    columns = ", ".join(f"""max(CASE WHEN dst = '{a}' THEN relation END) AS "{a}\"""" for a in ("assistant", "system", "user", START, END))
    out["footprint_matrix_conv"] = f"{foot} SELECT src, {columns} FROM fp GROUP BY src"
    out["baseline_alpha_conv"] = f"""{foot}, ids AS (SELECT act, CAST(row_number() OVER (ORDER BY act) - 1 AS INTEGER) AS k FROM acts), num AS (SELECT count(*) AS n FROM ids),
    ss AS (SELECT i, list(act ORDER BY act) AS acts FROM (SELECT i FROM num, range(1, CAST(power(2, n) AS BIGINT)) t(i)), ids WHERE (i >> k) & 1 = 1 GROUP BY i),
    sm AS (SELECT i, unnest(acts) AS act FROM ss),
    free AS (SELECT i, acts FROM ss WHERE NOT EXISTS (SELECT 1 FROM sm x JOIN sm y ON x.i = y.i JOIN fp ON fp.src = x.act AND fp.dst = y.act WHERE x.i = ss.i AND relation <> '#')),
    pairs AS (SELECT a.i AS a, b.i AS b, a.acts AS pre, b.acts AS post FROM free a, free b WHERE NOT EXISTS (SELECT 1 FROM sm x, sm y, fp WHERE x.i = a.i AND y.i = b.i AND fp.src = x.act AND fp.dst = y.act AND relation <> '->'))
    SELECT array_to_string(pre, ',') AS pre, array_to_string(post, ',') AS post FROM pairs p WHERE NOT EXISTS (SELECT 1 FROM pairs q WHERE (p.a <> q.a OR p.b <> q.b) AND p.a & q.a = p.a AND p.b & q.b = p.b)"""
    out["evaluator_suite_conv"] = f"""{_all("conv", 4)}, e1 AS (SELECT * FROM fx WHERE depth <= 3), e2 AS (SELECT * FROM e1 WHERE 2 * n_fit >= n_total),
    ok AS (SELECT vid FROM v WHERE vid NOT IN (SELECT vid FROM st JOIN fx USING (pid) WHERE fx.pre = '{START}' AND fx.post = '{END}' AND (least < 0 OR fin <> 0))),
    e3 AS (SELECT DISTINCT e2.pid FROM e2 JOIN st USING (pid) JOIN ok USING (vid) WHERE least < 0 OR fin <> 0)
    SELECT 'arcs<=3' AS evaluator, (SELECT count(*) FROM fx) AS n UNION ALL SELECT 'fit>=0.5', (SELECT count(*) FROM e1) UNION ALL SELECT 'adds_something', (SELECT count(*) FROM e2) UNION ALL SELECT 'passing', (SELECT count(*) FROM e3)"""
    out["brute_conv"] = walk_sql("conv", 800, 5, "SELECT 'brute' AS search, count(*) AS n_evaluated, count(*) FILTER (10 * n_fit >= 8 * n_total) AS n_places, TRUE AS same FROM fx UNION ALL SELECT 'pruned', count(*), count(*) FILTER (10 * n_fit >= 8 * n_total), count(*) FILTER (10 * n_fit >= 8 * n_total) = (SELECT count(*) FROM fx WHERE 10 * n_fit >= 8 * n_total) FROM al")
    out["top_mass_events_day"] = f"""{_with("events_day")}, m AS (SELECT freq, sum(freq) AS m FROM v GROUP BY freq), c AS (SELECT freq, coalesce(sum(m) OVER (ORDER BY freq DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM m)
    SELECT array_to_string(seq, '>') AS variant, v.freq FROM v JOIN c ON v.freq = c.freq CROSS JOIN tot WHERE 2 * before < n"""
    out["directly_interest_conv"] = f"""{_with("conv")}, nx AS (SELECT vid, freq, act AS src, lead(act) OVER (PARTITION BY vid ORDER BY pos) AS dst FROM ev), p AS (SELECT DISTINCT vid, freq, src, dst FROM nx WHERE dst IS NOT NULL),
    oc AS (SELECT act, sum(freq) AS o FROM (SELECT DISTINCT vid, freq, act FROM ev) GROUP BY act)
    SELECT src, dst, round(sum(freq) / greatest(any_value(a.o), any_value(b.o)), 6) AS score, CAST(sum(freq) AS BIGINT) AS n FROM p JOIN oc a ON a.act = src JOIN oc b ON b.act = dst GROUP BY src, dst"""
    out["filtered_follows_events_day"] = f"{_with('events_day')}, nx AS (SELECT vid, freq, act AS src, lead(act) OVER (PARTITION BY vid ORDER BY pos) AS dst FROM ev) SELECT src, dst, CAST(sum(freq) AS BIGINT) AS n FROM nx WHERE dst IS NOT NULL GROUP BY src, dst HAVING sum(freq) >= 20"
    out["place_facts"] = f"""WITH b AS (SELECT unnest(range(1, 16)) AS i), s AS (SELECT i, list_filter([CASE WHEN i & 1 > 0 THEN '{START}' END, CASE WHEN i & 2 > 0 THEN 'a' END, CASE WHEN i & 4 > 0 THEN 'b' END, CASE WHEN i & 8 > 0 THEN 'c' END], lambda x: x IS NOT NULL) AS pre,
        list_filter([CASE WHEN i & 1 > 0 THEN 'a' END, CASE WHEN i & 2 > 0 THEN 'b' END, CASE WHEN i & 4 > 0 THEN 'c' END, CASE WHEN i & 8 > 0 THEN '{END}' END], lambda x: x IS NOT NULL) AS post FROM b),
    p AS (SELECT x.i AS a, y.i AS b, list_sort(x.pre) AS pre, list_sort(y.post) AS post, bit_count(x.i) + bit_count(y.i) AS d FROM s x, s y WHERE bit_count(x.i) + bit_count(y.i) <= 4),
    g AS (SELECT p.a, p.b, count(*) AS n FROM p JOIN p q ON (q.b = p.b AND q.a & p.a = p.a AND bit_count(q.a) = bit_count(p.a) + 1) OR (q.a = p.a AND q.b & p.b = p.b AND bit_count(q.b) = bit_count(p.b) + 1) GROUP BY p.a, p.b)
    SELECT array_to_string(pre, ',') || '>' || array_to_string(post, ',') AS pid, array_to_string(list_sort(list_intersect(pre, post)), ',') AS loops, CAST(d AS BIGINT) AS depth, len(list_distinct(list_concat(pre, post))) AS support,
        array_to_string(list_filter(pre, lambda x: NOT list_contains(post, x)), ',') AS gain, array_to_string(list_filter(post, lambda x: NOT list_contains(pre, x)), ',') AS loss, coalesce(n, 0) AS n_direct FROM p LEFT JOIN g ON p.a = g.a AND p.b = g.b"""
    return out
