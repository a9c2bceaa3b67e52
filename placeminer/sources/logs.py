"""The logs that are derived from the given tables, in Spark and as DuckDB SQL for the oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .spec import LogSpec

#: Tags of the small tag log; fixed values.
CORE_TAGS = ("<nav", "</nav", "<ul", "</ul", "<li", "</li", "<b", "<br", "<body", "</body")
TAG = r"</?[a-zA-Z][a-zA-Z0-9]*"
SESSION_GAP_SECONDS = 6 * 3600


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _simple(table: str, spec: LogSpec):
    return lambda spark, d: spec.events(_table(spark, d, table))


def _tags(spark: SparkSession, d: str, keep: tuple[str, ...] | None = None) -> DataFrame:
    found = _table(spark, d, "pages").select("page_id", F.posexplode(F.regexp_extract_all("html", F.lit(TAG), F.lit(0))).alias("pos", "tag"))
    found = found.withColumn("tag", F.lower("tag"))
    found = found.where(F.col("tag").isin(*keep)) if keep else found
    return LogSpec("tags", ("page_id",), "tag", ("pos",)).events(found)


def _lifecycle(spark: SparkSession, d: str, planted: bool = False) -> DataFrame:
    orders, lines = _table(spark, d, "orders"), _table(spark, d, "lineitem")
    no_date, no_int = F.lit(None).cast("timestamp_ntz"), F.lit(None).cast("long")
    row = lambda key, stage, activity, date=no_date, a=no_int, b=no_int: (
        F.col(key).alias("k"), F.lit(stage).alias("stage"), date.cast("timestamp_ntz").alias("d"), a.cast("long").alias("a"), b.cast("long").alias("b"), activity.alias("activity")
    )
    placed = orders.select(*row("o_orderkey", 0, F.concat(F.lit("place:"), "o_orderpriority")))
    closed = orders.select(*row("o_orderkey", 2, F.concat(F.lit("close:"), "o_orderpriority" if planted else "o_orderstatus")))
    shipped = lines.select(*row("l_orderkey", 1, F.concat(F.lit("ship:"), "l_returnflag"), F.col("l_shipdate"), F.col("l_linenumber"), F.col("l_partkey")))
    return LogSpec("lifecycle", ("k",), "activity", ("stage", "d", "a", "b")).events(placed.union(closed).union(shipped))


def _sessions(spark: SparkSession, d: str) -> DataFrame:
    """A new session where the gap to the user's last event is above six hours."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp"))
    marked = _table(spark, d, "events").select("user_id", "ts", "event_id", "event_type", (F.coalesce(gap, F.lit(0)) > SESSION_GAP_SECONDS * 1_000_000).cast("int").alias("fresh"))
    numbered = marked.withColumn("session", F.sum("fresh").over(w.rowsBetween(W.unboundedPreceding, 0)))
    return LogSpec("events_sess", ("user_id", "session"), "event_type", ("ts", "event_id")).events(numbered)


def _cust_lines(spark: SparkSession, d: str) -> DataFrame:
    lines = _table(spark, d, "lineitem").select("l_orderkey", "l_returnflag", "l_linestatus", "l_shipdate", "l_linenumber", "l_partkey")
    joined = lines.join(_table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return LogSpec("cust_lines", ("o_custkey",), "concat(l_returnflag, l_linestatus)", ("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey")).events(joined)


def _doc_steps(spark: SparkSession, d: str) -> DataFrame:
    docs = _table(spark, d, "documents").select("doc_id", "lang", "source").join(_table(spark, d, "labels"), "doc_id", "left")
    steps = F.array(*[F.when(F.col(c).isNotNull(), F.struct(F.lit(i).alias("stage"), F.concat(F.lit(f"{n}:"), F.col(c).cast("string")).alias("activity"))) for i, (n, c) in enumerate((("lang", "lang"), ("src", "source"), ("quality", "quality"), ("toxic", "toxic")))])
    exploded = docs.select("doc_id", F.explode(steps).alias("s")).where("s IS NOT NULL").select("doc_id", "s.stage", "s.activity")
    return LogSpec("doc_steps", ("doc_id",), "activity", ("stage",)).events(exploded)


LOGS = {
    "conv": _simple("conversations", LogSpec("conv", ("conv_id",), "role", ("turn",))),
    "tags": _tags,
    "tags_core": lambda spark, d: _tags(spark, d, CORE_TAGS),
    "lifecycle": _lifecycle,
    "lifecycle_planted": lambda spark, d: _lifecycle(spark, d, True),
    "events_day": _simple("events", LogSpec("events_day", ("user_id", "to_date(ts)"), "event_type", ("ts", "event_id"))),
    "events_sess": _sessions,
    "events_user": _simple("events", LogSpec("events_user", ("user_id",), "event_type", ("ts", "event_id"))),
    "lineflags": _simple("lineitem", LogSpec("lineflags", ("l_orderkey",), "concat(l_returnflag, l_linestatus)", ("l_linenumber", "l_shipdate", "l_partkey"))),
    "cust_prio": _simple("orders", LogSpec("cust_prio", ("o_custkey",), "o_orderpriority", ("o_orderdate", "o_orderkey"))),
    "cust_lines": _cust_lines,
    "doc_steps": _doc_steps,
}

_TAG_SQL = "SELECT page_id, t AS activity, i AS o1 FROM (SELECT page_id, unnest(regexp_extract_all(html, '</?[a-zA-Z][a-zA-Z0-9]*')) AS raw, generate_subscripts(regexp_extract_all(html, '</?[a-zA-Z][a-zA-Z0-9]*'), 1) AS i, lower(raw) AS t FROM pages)"
#: For each log: case_id, activity, o1..o4.
SQL = {
    "conv": "SELECT CAST(conv_id AS VARCHAR) AS case_id, role AS activity, turn AS o1, 0 AS o2, 0 AS o3, 0 AS o4 FROM conversations",
    "tags": f"SELECT CAST(page_id AS VARCHAR) AS case_id, activity, o1, 0 AS o2, 0 AS o3, 0 AS o4 FROM ({_TAG_SQL})",
    "tags_core": f"SELECT CAST(page_id AS VARCHAR) AS case_id, activity, o1, 0 AS o2, 0 AS o3, 0 AS o4 FROM ({_TAG_SQL}) WHERE activity IN ({', '.join(repr(t) for t in CORE_TAGS)})",
    "lifecycle": """SELECT CAST(o_orderkey AS VARCHAR) AS case_id, 'place:' || o_orderpriority AS activity, 0 AS o1, TIMESTAMP '1900-01-01' AS o2, 0 AS o3, 0 AS o4 FROM orders
        UNION ALL SELECT CAST(o_orderkey AS VARCHAR), 'close:' || o_orderstatus, 2, TIMESTAMP '1900-01-01', 0, 0 FROM orders
        UNION ALL SELECT CAST(l_orderkey AS VARCHAR), 'ship:' || l_returnflag, 1, l_shipdate, l_linenumber, l_partkey FROM lineitem""",
    "lifecycle_planted": """SELECT CAST(o_orderkey AS VARCHAR) AS case_id, 'place:' || o_orderpriority AS activity, 0 AS o1, TIMESTAMP '1900-01-01' AS o2, 0 AS o3, 0 AS o4 FROM orders
        UNION ALL SELECT CAST(o_orderkey AS VARCHAR), 'close:' || o_orderpriority, 2, TIMESTAMP '1900-01-01', 0, 0 FROM orders
        UNION ALL SELECT CAST(l_orderkey AS VARCHAR), 'ship:' || l_returnflag, 1, l_shipdate, l_linenumber, l_partkey FROM lineitem""",
    "events_day": "SELECT user_id || '|' || CAST(CAST(ts AS DATE) AS VARCHAR) AS case_id, event_type AS activity, ts AS o1, event_id AS o2, 0 AS o3, 0 AS o4 FROM events",
    "events_sess": """SELECT user_id || '|' || sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS case_id, event_type AS activity, ts AS o1, event_id AS o2, 0 AS o3, 0 AS o4 FROM
        (SELECT *, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) > 21600000000 THEN 1 ELSE 0 END AS fresh FROM events)""",
    "events_user": "SELECT CAST(user_id AS VARCHAR) AS case_id, event_type AS activity, ts AS o1, event_id AS o2, 0 AS o3, 0 AS o4 FROM events",
    "lineflags": "SELECT CAST(l_orderkey AS VARCHAR) AS case_id, l_returnflag || l_linestatus AS activity, l_linenumber AS o1, l_shipdate AS o2, l_partkey AS o3, 0 AS o4 FROM lineitem",
    "cust_prio": "SELECT CAST(o_custkey AS VARCHAR) AS case_id, o_orderpriority AS activity, o_orderdate AS o1, o_orderkey AS o2, 0 AS o3, 0 AS o4 FROM orders",
    "cust_lines": "SELECT CAST(o_custkey AS VARCHAR) AS case_id, l_returnflag || l_linestatus AS activity, l_shipdate AS o1, l_orderkey AS o2, l_linenumber AS o3, l_partkey AS o4 FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "doc_steps": """SELECT CAST(doc_id AS VARCHAR) AS case_id, activity, o1, 0 AS o2, 0 AS o3, 0 AS o4 FROM (
        SELECT doc_id, 'lang:' || lang AS activity, 0 AS o1 FROM documents UNION ALL SELECT doc_id, 'src:' || source, 1 FROM documents
        UNION ALL SELECT d.doc_id, 'quality:' || quality, 2 FROM documents d JOIN labels l ON d.doc_id = l.doc_id
        UNION ALL SELECT d.doc_id, 'toxic:' || toxic, 3 FROM documents d JOIN labels l ON d.doc_id = l.doc_id) WHERE activity IS NOT NULL""",
}


def events(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return LOGS[name](spark, sf_dir)
