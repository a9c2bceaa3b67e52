"""Mixing, quality features and the pipeline held against plain versions."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np

from placeminer.llm import hashtree, mixing, quality, tiling

from .test_operators import components_of, shingles
from .test_tiling import greedy

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def uniform(*parts):
    return (int(hashlib.md5("|".join(parts).encode()).hexdigest()[:12], 16) + 0.5) / (1 << 48)


def plain_mix(rows, max_blocks, seed="mix-1"):
    """taken of every row (doc_id, text, source), counted word by word."""
    size = lambda t: len(WORD.findall(t or ""))
    sizes = Counter()
    for _, t, s in rows:
        sizes[s] += size(t)
    total = sum(sizes.values())
    block = max(1, math.ceil(total / max_blocks))
    # Targets by the contract, then quotas one at a time by the highest quotient.
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    target, free, left = {}, list(order), total
    while free:
        shares = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        full = [s for s in free if shares[s] > 3 * sizes[s]]
        if not full:
            target |= shares
            break
        for s in full:
            target[s] = 3 * sizes[s]
            left -= target[s]
            free.remove(s)
    have = {s: math.ceil(sizes[s] / block) for s in order}
    turn = {s: target[s] / sizes[s] * have[s] if sizes[s] else 0.0 for s in order}
    given = dict.fromkeys(order, 0)
    for _ in range(round(sum(turn.values()))):
        able = [s for s in order if turn[s] > 0 and given[s] < 3 * have[s]]
        if not able:
            break
        best = max(able, key=lambda s: turn[s] / (2 * given[s] + 1) if given[s] else turn[s])
        given[best] += 1
    times = {}
    for s in order:
        if have[s]:
            key = int.from_bytes(hashlib.blake2b(f"{seed}|{s!r}".encode(), digest_size=8).digest(), "big")
            line = np.random.Generator(np.random.PCG64(key)).permutation(have[s])
            times[s] = Counter(int(line[i % have[s]]) for i in range(given[s]))
    out = {}
    for s in order:
        at = 0
        for d, t, _ in sorted((r for r in rows if r[2] == s), key=lambda r: (uniform(seed, str(r[0])), r[0], zlib.crc32((r[1] or "").encode()))):
            n = size(t)
            out[d] = sum(times[s][(at + k) // block] for k in range(n)) if n else 0
            at += n
    return out, target


def test_mixing_word_by_word(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "source").where("doc_id < 120")
    rows = [tuple(r) for r in docs.collect()]
    for blocks in (16384, 300, 40):
        got = {r["doc_id"]: (r["taken"], r["target"]) for r in mixing.mix(docs, max_blocks=blocks).collect()}
        want, target = plain_mix(rows, blocks)
        assert {d: t for d, (t, _) in got.items()} == want
        assert all(abs(got[d][1] - target[s]) < 1e-6 * max(1, target[s]) for d, _, s in rows)


def test_mixing_many_rows_without_a_name(spark):
    rows = [(None, f"word{i} " * (i % 7), "a" if i % 2 else None) for i in range(200)] + [(None, "same text", "a")] * 5
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    kept = mixing.mixed(df)
    assert kept.columns == df.columns and len({r["text"] for r in kept.collect()}) > 60
    assert hashtree.assign(df).select("slot").distinct().count() == 205


def test_quality_features_one_word_at_a_time():
    rng = np.random.Generator(np.random.PCG64(1))
    words, shapes = rng.normal(size=(quality.WORD_SLOTS, quality.WIDTH)).astype(np.float32), rng.normal(size=(quality.SHAPE_SLOTS, quality.WIDTH)).astype(np.float32)
    index, slots = quality.index_vectors(quality.WORD_SLOTS, 1), quality.Slots()
    for text in ("", "One two, THREE 4-5 six one two, THREE x", "w " * 70_000, "ünï cödé\tΩ \n 1"):
        at = slots.of(text)
        got = quality.pooled(at, words, shapes, index)
        tokens = text.encode().split()
        assert len(at) == len(tokens)
        if not tokens:
            assert not got.any()
            continue
        pairs = [divmod(slots[w], quality.SHAPE_SLOTS) for w in tokens]
        mean = lambda rows: np.mean([r.astype(np.float64) for r in rows], axis=0)
        trigrams = [tuple(tokens[i : i + 3]) for i in range(len(tokens) - 2)]
        want = np.concatenate((mean([words[w] for w, _ in pairs]), mean([shapes[s] for _, s in pairs]), [np.linalg.norm(mean([index[w] for w, _ in pairs])), np.log1p(len(tokens)), len(set(trigrams)) / len(trigrams) if trigrams else 1.0]))
        assert np.allclose(got, want, rtol=1e-4, atol=1e-5)


def test_the_pipeline_stage_by_stage(spark, sf):
    import corpus_pipeline

    stages = dict(corpus_pipeline.STAGES)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = stages["quality"](spark, docs, sf)
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    left = {r["doc_id"] for r in kept.select("doc_id").collect()}
    known = [(d, q) for d, q in labels.items() if q in (0, 1)]
    assert sum((d in left) == (q == 1) for d, q in known) >= 0.95 * len(known)

    rows = [(r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect()]
    one = {r["doc_id"] for r in stages["near_duplicates"](spark, docs, sf).select("doc_id").collect()}
    assert one == {c for _, _, c in components_of(rows)}

    items = [tiling.normal(r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    grams = [set(zip(*(i[k:] for k in range(tiling.MIN_TILE)))) for i in items]
    clean = {r["doc_id"] for r in stages["decontamination"](spark, docs, sf).select("doc_id").collect()}
    for d, t in rows:
        words = tiling.normal(t)
        own = set(zip(*(words[k:] for k in range(tiling.MIN_TILE))))
        # Trying everything is for pairs that share seeds enough to matter.
        foul = any(i and len(own & g) * tiling.MIN_TILE >= tiling.THRESHOLD * len(i) and sum(n for _, _, n in greedy(words, i, tiling.MIN_TILE)) >= tiling.THRESHOLD * len(i) for i, g in zip(items, grams))
        assert (d in clean) == (not foul)

    out = [tuple(r) for r in stages["sharding"](spark, docs, sf).select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard").collect()]
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    assert sorted(out) == sorted(con.execute(hashtree.oracle()).fetchall())


def test_the_pipeline_takes_its_stages_in_turn(spark, sf):
    """Every later row comes from a row that all stages kept, and words stay near the targets of what the mix was given."""
    import corpus_pipeline

    docs, rows = spark.read.parquet(f"{sf}/documents.parquet"), None
    given = docs
    for _, stage in corpus_pipeline.STAGES[:3]:
        given = stage(spark, given, sf)
    given = spark.createDataFrame(given.collect(), docs.schema)
    rows = corpus_pipeline.run(spark, sf).collect()
    sizes = {r["doc_id"]: (r["source"], len(WORD.findall(r["text"] or ""))) for r in given.collect()}
    taken, copies = defaultdict(int), Counter(r["doc_id"] for r in rows)
    assert set(copies) <= set(sizes) and max(copies.values()) <= mixing.LIMIT
    for d, n in copies.items():
        taken[sizes[d][0]] += n * sizes[d][1]
    total = Counter()
    for s, n in sizes.values():
        total[s] += n
    for s, want in mixing.targets(dict(total)).items():
        # Documents are whole: what is left over or owed is less than half of one of them.
        assert abs(taken[s] - want) <= max(n for x, n in sizes.values() if x == s) / 2 + 0.01 * want
    for shard in {r["shard"] for r in rows}:
        assert sorted(r["slot"] for r in rows if r["shard"] == shard) == list(range(sum(r["shard"] == shard for r in rows)))
