"""Rule bitmask ledger (op 3): every rule is evaluated once, policies are masks over its bits.

``ledger`` keeps a document's measurements and one ``bits`` number whose bit *i* is set if rule *i*
fails. A policy is a named, versioned mask; a document is kept if no bit of the mask is set. What dropping
a rule from a policy would bring back (``ablation``) is read from counts per bit pattern, without a
second look at any text.

Edge cases: a null or empty text has no words and fails ``few_words`` alone; very long texts are
measured whole; repeated rows and a null doc_id have rows of their own; only doc_id and text are read, so other columns cannot clash; an empty table
gives an empty ledger.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .words import WordHashes, windows

SYMBOLS = b"#*$%&|<>"
#: Name and failing condition of each rule, over the measurements; the position is the bit.
RULES: list[tuple[str, str]] = [
    ("few_words", "n_words < 10"),
    ("repeated_words", "100 * n_repeat_words > 20 * n_words"),
    ("symbols", "100 * n_symbols > 40 * n_words"),
    ("repeated_lines", "n_dup_lines > 2 AND 100 * n_dup_lines > 40 * n_lines"),
    ("long_words", "word_chars > 20 * n_words"),
    ("short_words", "word_chars < 2 * n_words"),
    ("shouting", "100 * n_shouted > 60 * n_words"),
]
BIT = {name: i for i, (name, _) in enumerate(RULES)}
#: Versioned policies: the rules that each one enforces.
POLICIES: dict[str, tuple[str, ...]] = {
    "base-1": ("few_words", "repeated_words"),
    "clean-1": ("few_words", "repeated_words", "symbols", "repeated_lines", "long_words", "short_words"),
    "strict-1": tuple(name for name, _ in RULES),
}
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_shouted")


def mask(policy: str) -> int:
    return sum(1 << BIT[name] for name in POLICIES[policy])


def measure(text: str | None, hashes: WordHashes) -> tuple[int, ...]:
    """The measurements of one text, in the order of MEASURES."""
    if not text:
        return (0,) * len(MEASURES)
    raw = text.encode()
    words = raw.split()
    n = len(words)
    # Continuation bytes are no characters of their own.
    joined = b"".join(words)
    chars = len(joined) if len(raw) == len(text) else len(joined.decode())
    symbols = len(raw) - len(raw.translate(None, SYMBOLS))
    lines = [line for line in raw.split(b"\n") if line.split(None, 1)]
    repeated = 0
    if n > 5:
        w = windows(hashes.of(words))
        order = np.argsort(w, kind="stable")
        same = w[order][1:] == w[order][:-1]
        if same.any():
            twice = np.zeros(len(w) + 1, bool)
            twice[order[1:][same]] = twice[order[:-1][same]] = True
            starts = np.flatnonzero(twice)
            covered = np.zeros(n + 1, np.int64)
            np.add.at(covered, starts, 1)
            np.add.at(covered, starts + 5, -1)
            repeated = int(np.count_nonzero(np.cumsum(covered)[:n]))
    shouted = sum(map(bytes.isupper, words))
    return n, chars, symbols, len(lines) - len(set(lines)), repeated, len(lines), shouted


def ledger(docs: DataFrame) -> DataFrame:
    """doc_id, the measurements and ``bits`` of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            rows = [measure(t, hashes) for t in batch.column("text").to_pylist()]
            columns = [pa.array(c, pa.int64()) for c in zip(*rows)] or [pa.array([], pa.int64())] * len(MEASURES)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), *columns], names=["doc_id", *MEASURES])

    measured = docs.select("doc_id", "text").mapInArrow(run, "doc_id long, " + ", ".join(f"{m} long" for m in MEASURES))
    bits = sum((F.when(F.expr(test), F.lit(1 << i)).otherwise(F.lit(0)) for i, (_, test) in enumerate(RULES)), F.lit(0))
    return measured.withColumn("bits", bits.cast("long"))


def fails(policy: str, bits: str = "bits") -> Column:
    return F.col(bits).bitwiseAND(F.lit(mask(policy))) != 0


def verdicts(docs: DataFrame, policy: str = "clean-1") -> DataFrame:
    """The ledger with base_failed and kept."""
    return ledger(docs).withColumn("base_failed", fails("base-1")).withColumn("kept", ~(fails("base-1") | fails(policy)))


def stored(docs: DataFrame, path: str) -> DataFrame:
    """The ledger written to a shared folder and read again: policies and ablations to come look at it and at no text."""
    ledger(docs).write.mode("overwrite").parquet(path)
    return docs.sparkSession.read.parquet(path)


def ablation(book: DataFrame) -> DataFrame:
    """policy, rule, n_failed, n_only (failed by this rule alone), n_kept_without: one row a policy and rule.

    The bit patterns are counted first (at most 2**rules rows), the rest is bit arithmetic on those.
    """
    patterns = book.groupBy("bits").agg(F.count(F.lit(1)).alias("n"))
    pairs = book.sparkSession.createDataFrame([(p, r, mask(p), 1 << BIT[r]) for p, rules in POLICIES.items() for r in rules], "policy string, rule string, mask long, bit long")
    hit = F.col("bits").bitwiseAND(F.col("mask"))
    each = patterns.join(F.broadcast(pairs))
    total = lambda c: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0)).alias
    return each.groupBy("policy", "rule").agg(
        total(F.col("bits").bitwiseAND(F.col("bit")) != 0)("n_failed"), total(hit == F.col("bit"))("n_only"), total(hit.bitwiseAND(F.bitwise_not("bit")) == 0)("n_kept_without")
    )


def oracle(view: str = "documents", policy: str = "clean-1") -> str:
    """The thin query's rows in DuckDB SQL."""
    tests = " OR ".join(f"({test})" for name, test in RULES if name in POLICIES[policy])
    return f"""{_measured(view)}
    SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
           (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed,
           NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words OR {tests}) AS kept FROM m
    """


def ablation_oracle(view: str = "documents") -> str:
    """The ablation of every policy in DuckDB SQL, rule by rule from the measurements."""
    test = dict(RULES)
    rows = []
    for p, rules in POLICIES.items():
        for r in rules:
            others = " OR ".join(f"({test[x]})" for x in rules if x != r) or "FALSE"
            rows.append(f"SELECT '{p}' AS policy, '{r}' AS rule, count(*) FILTER ({test[r]}) AS n_failed, count(*) FILTER (({test[r]}) AND NOT ({others})) AS n_only, count(*) FILTER (NOT ({others})) AS n_kept_without FROM m")
    return f"{_measured(view)} " + " UNION ALL ".join(rows)


def _measured(view: str) -> str:
    """The measurements m of every document."""
    word = r"[^\x20\x09-\x0D]+"
    return f"""
    WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS text FROM {view}),
    w AS (SELECT rid, doc_id, text, regexp_extract_all(text, '{word}') AS ws FROM d),
    pos AS (SELECT rid, ws, unnest(range(1, greatest(len(ws) - 3, 1))) AS i FROM w WHERE len(ws) >= 5),
    win AS (SELECT rid, i, list_slice(ws, i, i + 4) AS s FROM pos),
    twice AS (SELECT rid, i, count(*) OVER (PARTITION BY rid, s) AS c FROM win),
    rep AS (SELECT rid, count(DISTINCT p) AS n FROM (SELECT rid, unnest(range(i, i + 5)) AS p FROM twice WHERE c > 1) GROUP BY rid),
    ln AS (SELECT rid, count(*) AS n_lines, count(*) - count(DISTINCT l) AS n_dup FROM (SELECT rid, unnest(string_split(text, chr(10))) AS l FROM d) WHERE regexp_matches(l, '{word}') GROUP BY rid),
    m AS (SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
                 CAST(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
                 CAST(coalesce(n_dup, 0) AS BIGINT) AS n_dup_lines, CAST(coalesce(rep.n, 0) AS BIGINT) AS n_repeat_words, coalesce(n_lines, 0) AS n_lines,
                 len(list_filter(ws, lambda x: regexp_matches(x, '[A-Z]') AND NOT regexp_matches(x, '[a-z]'))) AS n_shouted
          FROM w LEFT JOIN rep ON w.rid = rep.rid LEFT JOIN ln ON w.rid = ln.rid)
    """
