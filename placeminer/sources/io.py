"""Readers and writers of logs and results."""

from __future__ import annotations

from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import model
from .spec import LogSpec

#: Types of the attributes that an XES event or trace may hold; fixed values.
_KV = "array<struct<_key:string,_value:string>>"
XES_SCHEMA = f"string {_KV}, event array<struct<string:{_KV},date:{_KV},int:{_KV},float:{_KV},boolean:{_KV}>>"


def read_log(spark: SparkSession, path: str, spec: LogSpec, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Events of a file or folder: ``parquet``, ``orc``, ``csv`` and ``json`` (with a schema), ``xes``, or ``table``."""
    if fmt == "table":
        return spec.events(spark.table(path))
    if fmt == "xes":
        return read_xes(spark, path)
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} logs need a schema")
    reader = spark.read.format(fmt).options(**({"header": "true"} if fmt == "csv" else {}), **options)
    return spec.events((reader.schema(schema) if schema else reader).load(path))


def read_xes(spark: SparkSession, path: str, classifier: str = "concept:name") -> DataFrame:
    """case_id, ord, activity, attrs of an XES file: one row tag a trace, events in document order."""
    raw = spark.read.format("xml").option("rowTag", "trace").schema(XES_SCHEMA).load(path)
    value = lambda entries, key: F.element_at(F.transform(F.filter(entries, lambda e: e["_key"] == key), lambda e: e["_value"]), 1)
    events = raw.select(F.get(F.transform(F.filter("string", lambda e: e["_key"] == "concept:name"), lambda e: e["_value"]), 0).alias("case_id"), F.posexplode("event").alias("pos", "e"))
    entries = F.coalesce(F.col("e.string"), F.array().cast(_KV))
    attrs = F.map_from_entries(F.transform(F.filter(entries, lambda x: x["_key"].isNotNull()), lambda x: F.struct(x["_key"], x["_value"])))
    return events.select("case_id", F.struct(F.col("pos").alias("o0")).alias("ord"), F.try_element_at(attrs, F.lit(classifier)).alias("activity"), attrs.alias("attrs")).where("activity IS NOT NULL")


def write_xes(log: DataFrame, path: str) -> None:
    """Traces (case_id, seq with markers) as XES through the XML writer."""
    kv = lambda k, v: F.array(F.struct(F.lit(k).alias("_key"), v.alias("_value")))
    inner = F.slice("seq", F.lit(2), F.greatest(F.size("seq") - 2, F.lit(0)))
    rows = log.select(kv("concept:name", F.col("case_id")).alias("string"), F.transform(inner, lambda a: F.struct(kv("concept:name", a).alias("string"))).alias("event"))
    rows.write.format("xml").option("rootTag", "log").option("rowTag", "trace").mode("overwrite").save(path)


def write_table(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] = (), mode: str = "overwrite") -> None:
    df.write.format(fmt).mode(mode).partitionBy(*partition_by).save(path)


def save_bucketed(events: DataFrame, table: str, buckets: int) -> None:
    """Events bucketed by case, so that building traces again needs no shuffle."""
    events.write.bucketBy(buckets, "case_id").sortBy("case_id").mode("overwrite").saveAsTable(table)


def write_net(net: model.Net, path: str, config: dict | None = None) -> None:
    """A small net as PNML, DOT or JSON by the file's ending (driver)."""
    text = {"pnml": lambda: model.to_pnml(net), "dot": lambda: model.to_dot(net), "json": lambda: model.to_json(net, config)}[path.rpartition(".")[2]]()
    Path(path).write_text(text, encoding="utf-8")


def as_of(events: DataFrame, facts: DataFrame, key: str, at: str, fact_at: str, columns: list[str]) -> DataFrame:
    """Each event with the latest fact of its key at or before it: a union and a running last value, one shuffle."""
    from pyspark.sql import Window as W

    left = events.select(F.col(key).alias("__k"), F.col(at).alias("__t"), F.lit(1).alias("__side"), F.struct(*events.columns).alias("__row"), *[F.lit(None).cast(facts.schema[c].dataType).alias(c) for c in columns])
    right = facts.select(F.col(key).alias("__k"), F.col(fact_at).alias("__t"), F.lit(0).alias("__side"), F.lit(None).cast(left.schema["__row"].dataType).alias("__row"), *columns)
    w = W.partitionBy("__k").orderBy("__t", "__side").rowsBetween(W.unboundedPreceding, 0)
    last = left.unionByName(right).withColumns({c: F.last(c, ignorenulls=True).over(w) for c in columns})
    return last.where("__side = 1").select("__row.*", *columns)
