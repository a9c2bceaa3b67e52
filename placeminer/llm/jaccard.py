"""N-gram Jaccard join by multiple global token orders (op 6).

Tokens are hashes of five-word shingles; documents of equal sets share a signature and are one node. Two
nodes link when 100 * intersection >= 80 * union. Under any fixed order of all tokens, linked nodes share one of the
first ``n - ceil(0.8 n) + 1`` tokens of both. Three orders are used, all with rare tokens first and ties
broken by different hashes: candidates meet on the first order and must also share a prefix token under
the second and third, before the intersection is counted.

Steps
1. Shingle every text once and deal (token, signature) pairs by token as packed blobs. Buckets follow the size of the
   input (``BUCKET_BYTES`` each), and a token that ``HEAVY`` nodes of one chunk share sends its number instead: its pairs stay in
   blobs of their task, so that no task meets all documents that hold a very common shingle.
2. Count in how many nodes each token occurs. Tokens of one node (most of all) end here. The counts of heavy tokens go
   back to the blobs that asked for them.
3. Gather the shared tokens of each node. Unshared tokens come first in every order, so a node whose
   prefixes hold nothing else has no partner and leaves; what stays is small.
4. Contract: sort the candidates by minhashes, verify neighbours, and form components of the links found.
5. Exact rest: prefix tokens whose nodes lie in more than one component are joined, only across
   components, under size, order and bitmap bounds that no link can break; survivors are verified
   exactly. So no link between components is lost, and no pairs inside a group are listed.
6. Components of all links give each document the least doc_id that it reaches.

Copies count once in every step; their rows meet again only in the last join. Edge cases: texts without words and
null texts have no shingles and no partner; fewer than five words are one shingle; very long texts are
whole; repeated rows get the same component; rows with a null doc_id get a null component and join no group; an
empty table gives an empty result. Signatures have 64 bits: a collision among a billion distinct sets has a chance of
about 3 percent and would merge two groups. Tokens have 48 bits where they are compared: two documents of
a thousand words count one token too many with a chance of 4e-9.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import checkpointed, partitions, written
from .components import connected, spread_join
from .words import MULTIPLIERS, WordHashes, mixed, shingles, slices, tidy

#: Tokens that a task holds before it deals them out, at least and at most; signatures that it remembers.
CHUNK = 300_000
MOST = 1 << 24
SEEN = 100_000
#: Copies from which a set's documents are joined to its component where they are.
COPIES = 1000
#: Bytes of input a bucket, and the most buckets; tokens that a chunk deals to a bucket, about.
BUCKET_BYTES = 4 << 20
BUCKETS = 1 << 18
DEAL = 64
#: Nodes of one chunk that must share a token for it to be dealt as a number.
HEAVY = 64
#: Tokens of candidates that are sent on at once.
SEND = 500_000
#: Words of 64 bits of a bitmap of tokens, and of a mask of prefix tokens.
BITMAP = 16
MASK = 4
NEIGHBOURS = 4
ROUNDS = 3


def needed(n: np.ndarray | int):
    """Tokens of a prefix that two linked sets must share one of."""
    return n - (4 * n + 4) // 5 + 1


def linked(shared, a, b):
    """100 * shared >= 80 * (a + b - shared)."""
    return 9 * shared >= 4 * (a + b)


def signature(tokens: np.ndarray) -> int:
    with np.errstate(over="ignore"):
        total = mixed(tokens ^ MULTIPLIERS[0]).sum(dtype=np.uint64) + np.uint64(len(tokens)) * MULTIPLIERS[1]
    return int(mixed(np.array([total], np.uint64)).view(np.int64)[0])


def narrow(tokens: np.ndarray) -> bytes:
    """Tokens of 48 bits as six bytes each."""
    return (tokens >> np.uint64(16)).astype(np.uint32).tobytes() + tokens.astype(np.uint16).tobytes()


def wide(blob: bytes) -> np.ndarray:
    n = len(blob) // 6
    return (np.frombuffer(blob, np.uint32, n).astype(np.uint64) << np.uint64(16)) | np.frombuffer(blob, np.uint16, n, 4 * n)


def input_bytes(df: DataFrame) -> int:
    """Size of the relations that a plan reads, as the planner knows it, without reading them; relations of unknown size count as none."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    sizes = [int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size())]
    return sum(x for x in sizes if x < 1 << 60)


def bucketed(df: DataFrame) -> int:
    """Buckets for the tokens of a table; results do not depend on them."""
    return max(partitions(df.sparkSession), min(BUCKETS, input_bytes(df) // BUCKET_BYTES))


def encoded(tok: np.ndarray, node: np.ndarray, sigs: np.ndarray) -> dict[str, bytes]:
    """Tokens whose nodes stand together: a node's signature is written once, with their number."""
    runs = np.concatenate(([0], np.flatnonzero(np.diff(node)) + 1, [len(node)]))
    return {"tok": narrow(tok), "sig": sigs[node[runs[:-1]]].tobytes(), "runs": np.diff(runs).astype(np.uint32).tobytes()}


def decoded(tok: bytes, sig: bytes, runs: bytes) -> tuple[np.ndarray, np.ndarray]:
    return wide(tok), np.repeat(np.frombuffer(sig, np.int64), np.frombuffer(runs, np.uint32))


def bucket_of(tok: np.ndarray, buckets: int) -> np.ndarray:
    return ((tok >> np.uint64(17)) % np.uint64(buckets)).astype(np.int32)


def spans(at: np.ndarray) -> list[tuple[int, int]]:
    """Stretches of equal values."""
    ends = np.flatnonzero(np.diff(at)) + 1
    return list(zip([0, *ends.tolist()], [*ends.tolist(), len(at)])) if len(at) else []


#: What rows of the first shuffle hold: pairs, numbers of heavy tokens, pairs of heavy tokens, documents.
PAIRS, NUMBERS, HELD, DOCS = range(4)
DEALT = {"what": pa.int32(), "bucket": pa.int32(), "blob": pa.int64(), "tok": pa.binary(), "sig": pa.binary(), "runs": pa.binary()}


def _dealt(buckets: int):
    """Texts to blobs: tokens with their signatures by token, documents anywhere."""
    chunk = min(MOST, max(CHUNK, DEAL * buckets))

    def rows_of(rows: list[dict]) -> Iterator[pa.RecordBatch]:
        for i in range(0, len(rows), 64):
            yield pa.RecordBatch.from_pydict({k: pa.array([r.get(k) for r in rows[i : i + 64]], t) for k, t in DEALT.items()})

    def by_bucket(tok: np.ndarray, what: int, blob: int | None, write) -> Iterator[pa.RecordBatch]:
        at = bucket_of(tok, buckets)
        order = np.argsort(at, kind="stable")
        yield from rows_of([{"what": what, "bucket": int(at[order[b]]), "blob": blob} | write(order[b:e]) for b, e in spans(at[order])])

    def flush(docs: list, parts: list, turn: int, blob: int) -> Iterator[pa.RecordBatch]:
        if docs:
            ids, ns, sigs = zip(*docs)
            known = np.array([i is not None for i in ids])
            one = {"tok": np.array([i or 0 for i in ids], np.int64), "sig": np.array(sigs, np.int64), "runs": np.array(ns, np.int64)}
            yield from rows_of([{"what": DOCS, "bucket": turn % buckets} | {k: v[known].tobytes() for k, v in one.items()}])
        if parts:
            # 48 bits of a token travel: enough to tell the tokens of two documents apart.
            tok = np.concatenate([t for _, t in parts]) >> np.uint64(16)
            sigs = np.array([s for s, _ in parts], np.int64)
            node = np.repeat(np.arange(len(sigs)), [len(t) for _, t in parts])
            each = np.sort(tok)
            often = np.unique(each[: -HEAVY + 1][each[HEAVY - 1 :] == each[: -HEAVY + 1]]) if len(each) >= HEAVY else each[:0]
            if len(often):
                times = np.searchsorted(each, often, "right") - np.searchsorted(each, often, "left")
                yield from by_bucket(often, NUMBERS, blob, lambda x: {"tok": narrow(often[x]), "runs": times[x].astype(np.uint32).tobytes()})
                held = often[np.minimum(np.searchsorted(often, tok), len(often) - 1)] == tok
                yield from rows_of([{"what": HELD, "bucket": blob % buckets, "blob": blob} | encoded(tok[held], node[held], sigs)])
                tok, node = tok[~held], node[~held]
            yield from by_bucket(tok, PAIRS, None, lambda x: encoded(tok[x], node[x], sigs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # Blobs are named by the task's partition and their number, the same if it runs again.
        first = TaskContext.get().partitionId() << 32
        words, seen = WordHashes(), set()
        docs, parts, held, turn = [], [], 0, 0
        for batch in (part for whole in batches for part in slices(whole)):
            for d, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()):
                tokens = shingles(words.of(text.encode().lower().split())) if text else np.empty(0, np.uint64)
                s = signature(tokens) if len(tokens) else 0
                docs.append((d, len(tokens), s))
                # Rows without a doc_id join no group: their tokens would belong to no node.
                if len(tokens) and d is not None and s not in seen:
                    parts.append((s, tokens))
                    held += len(tokens)
                    if len(seen) < SEEN:
                        seen.add(s)
                if held > chunk or len(docs) > chunk:
                    yield from flush(docs, parts, (first >> 32) + turn, first + turn)
                    docs, parts, held, turn = [], [], 0, turn + 1
        yield from flush(docs, parts, (first >> 32) + turn, first + turn)

    return run, "what int, bucket int, blob long, tok binary, sig binary, runs binary"


#: What rows after the count hold: documents, sizes of nodes, shared tokens, counts of heavy tokens by blob, pairs of heavy tokens.
ROWS, SIZES, SHARED, COUNTS, WAITING = range(5)
COUNTED = {"kind": pa.int32(), "doc_id": pa.int64(), "n": pa.int64(), "sig": pa.int64(), "bucket": pa.int32(), "s": pa.binary(), "a": pa.binary(), "b": pa.binary()}
COUNTED_SCHEMA = "kind int, doc_id long, n long, sig long, bucket int, s binary, a binary, b binary"


def _packed(kind: int, at: np.ndarray, *arrays: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Three arrays as blobs by bucket."""
    order = np.argsort(at, kind="stable")
    at, arrays = at[order].astype(np.int64), [v[order] for v in arrays]
    cut = spans(at)
    for i in range(0, len(cut), 64):
        some, n = cut[i : i + 64], len(cut[i : i + 64])
        own = {"kind": pa.array([kind] * n, pa.int32()), "bucket": pa.array([int(at[x]) for x, _ in some], pa.int32())}
        own |= {k: pa.array([v[x:y].tobytes() for x, y in some], pa.binary()) for k, v in zip("sab", arrays)}
        yield pa.RecordBatch.from_pydict({k: own.get(k, pa.nulls(n, t)) for k, t in COUNTED.items()})


def _of_signature(sigs: np.ndarray, buckets: int) -> np.ndarray:
    return (sigs.view(np.uint64) >> np.uint64(33)) % np.uint64(buckets)


def _counted(buckets: int):
    """A partition's tokens to those that several nodes have, dealt by signature; documents as rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        toks, sigs, nodes, asked = [], [], [], []
        for batch in batches:
            for what, bucket, blob, tok, sig, runs in zip(*(batch.column(c).to_pylist() for c in DEALT)):
                if what == PAIRS:
                    t, s = decoded(tok, sig, runs)
                    toks.append(t), sigs.append(s)
                elif what == NUMBERS:
                    t = wide(tok)
                    asked.append((t, np.frombuffer(runs, np.uint32).astype(np.int64), np.full(len(t), blob, np.int64)))
                elif what == HELD:
                    one = {"kind": [WAITING], "n": [blob], "bucket": [bucket], "s": [sig], "a": [tok], "b": [runs]}
                    yield pa.RecordBatch.from_pydict({k: pa.array(one.get(k, [None]), t) for k, t in COUNTED.items()})
                else:
                    d, n, s = (np.frombuffer(x, np.int64) for x in (tok, runs, sig))
                    one = {"kind": pa.array(np.full(len(d), ROWS, np.int32)), "doc_id": pa.array(d), "n": pa.array(n), "sig": pa.array(s)}
                    yield pa.RecordBatch.from_pydict({k: one.get(k, pa.nulls(len(d), t)) for k, t in COUNTED.items()})
                    s, first = np.unique(s, return_index=True)
                    nodes.append((s[n[first] > 0], n[first][n[first] > 0]))
        if nodes:
            s, first = np.unique(np.concatenate([x for x, _ in nodes]), return_index=True)
            n = np.concatenate([x for _, x in nodes])[first]
            yield from _packed(SIZES, _of_signature(s, buckets), s, n, n)
        if not toks and not asked:
            return
        tok, sig = np.concatenate([np.empty(0, np.uint64), *toks]), np.concatenate([np.empty(0, np.int64), *sigs])
        del toks, sigs
        heavy, number, blob = (np.concatenate([x[i] for x in asked]) if asked else np.empty(0, t) for i, t in enumerate((np.uint64, np.int64, np.int64)))
        listed, back = np.unique(heavy, return_inverse=True)
        numbers = np.bincount(back, number, len(listed)).astype(np.int64) if len(listed) else np.empty(0, np.int64)
        order = np.argsort(tok)
        tok, sig = tok[order], sig[order]
        del order
        same = tok[1:] == tok[:-1]
        several = np.concatenate(([False], same)) | np.concatenate((same, [False])) if len(tok) else np.empty(0, bool)
        several |= np.isin(tok, listed)
        tok, sig = tok[several], sig[several]
        order = np.lexsort((sig, tok))
        tok, sig = tok[order], sig[order]
        fresh = np.ones(len(tok), bool)
        fresh[1:] = (tok[1:] != tok[:-1]) | (sig[1:] != sig[:-1])
        tok, sig = tok[fresh], sig[fresh]
        known, where, n = np.unique(tok, return_inverse=True, return_counts=True)
        if len(listed):
            # One count for each token, whichever way its pairs went; copies in several blobs may count twice, which no order minds.
            at = np.searchsorted(listed, known)
            n = n + np.where(listed[np.minimum(at, len(listed) - 1)] == known, numbers[np.minimum(at, len(listed) - 1)], 0)
            at = np.searchsorted(known, listed)
            total = np.where(known[np.minimum(at, len(known) - 1)] == listed, n[np.minimum(at, len(known) - 1)], numbers) if len(known) else numbers
            yield from _packed(COUNTS, (blob % buckets).astype(np.int64), blob, heavy.view(np.int64), total[back])
        n = n[where]
        yield from _packed(SHARED, _of_signature(sig[n > 1], buckets), sig[n > 1], tok[n > 1].view(np.int64), n[n > 1].astype(np.int64))

    return run, COUNTED_SCHEMA


def _answered(buckets: int):
    """Counts of heavy tokens to the pairs that wait for them, dealt by signature."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, waiting = [], []
        for batch in batches:
            for kind, n, s, a, b in zip(*(batch.column(c).to_pylist() for c in ("kind", "n", "s", "a", "b"))):
                (counts if kind == COUNTS else waiting).append(tuple(np.frombuffer(x, np.int64) for x in (s, a, b)) if kind == COUNTS else (n, s, a, b))
        if not waiting:
            return
        blob, tok, n = (np.concatenate([c[i] for c in counts]) for i in range(3))
        order = np.lexsort((tok.view(np.uint64), blob))
        blob, tok, n = blob[order], tok[order].view(np.uint64), n[order]
        for name, s, a, b in waiting:
            t, sig = decoded(a, s, b)
            lo, hi = np.searchsorted(blob, name, "left"), np.searchsorted(blob, name, "right")
            count = n[lo:hi][np.searchsorted(tok[lo:hi], t)]
            yield from _packed(SHARED, _of_signature(sig, buckets), sig, t.view(np.int64), count)

    return run, COUNTED_SCHEMA


def mask(tokens: np.ndarray, words: int) -> np.ndarray:
    """Bits of tokens, set."""
    out = np.zeros(words, np.uint64)
    np.bitwise_or.at(out, (tokens >> np.uint64(6)).astype(np.int64) % words, np.uint64(1) << (tokens & np.uint64(63)))
    return out


def bitmap(tokens: np.ndarray, words: int = BITMAP) -> np.ndarray:
    """Parity of tokens by bit: bits that differ between two bitmaps are no more than tokens that differ."""
    out = np.zeros(words, np.uint64)
    h = mixed(tokens)
    np.bitwise_xor.at(out, (h >> np.uint64(6)).astype(np.int64) % words, np.uint64(1) << (h & np.uint64(63)))
    return out


def orders(tokens: np.ndarray, counts: np.ndarray) -> list[np.ndarray]:
    """Positions of the tokens under each global order."""
    rough = np.log2(counts).astype(np.int64)
    return [np.lexsort((tokens, counts)), np.lexsort((mixed(tokens ^ MULTIPLIERS[2]), rough)), np.lexsort((mixed(tokens ^ MULTIPLIERS[3]), rough))]


def _gathered():
    """Shared tokens by signature to candidates: nodes with a shared token in their prefixes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sizes, parts = [], []
        for batch in batches:
            for kind, s, a, b in zip(*(batch.column(c).to_pylist() for c in ("kind", "s", "a", "b"))):
                (sizes if kind == SIZES else parts).append(tuple(np.frombuffer(x, np.int64) for x in (s, a, b)))
        if not parts:
            return
        node, first = np.unique(np.concatenate([s for s, _, _ in sizes]), return_index=True)
        size = np.concatenate([n for _, n, _ in sizes])[first]
        sig, tok, n = (np.concatenate([p[i] for p in parts]) for i in range(3))
        del parts
        order = np.lexsort((tok, sig))
        order = order[np.concatenate(([True], (np.diff(sig[order]) != 0) | (np.diff(tok[order]) != 0)))]
        sig, tok, n = sig[order], tok[order].view(np.uint64), n[order]
        rows, held = [], 0
        for b, e in spans(sig):
            total = int(size[np.searchsorted(node, sig[b])])
            left = int(needed(total)) - (total - (e - b))
            if left <= 0:
                continue
            t, c = tok[b:e], n[b:e]
            prefixes = [t[o[:left]] for o in orders(t, c)]
            keys = [np.array([mixed(t ^ MULTIPLIERS[(r + i) % 5] ^ np.uint64(r)).min() for i in range(3)], np.uint64) for r in range(ROUNDS)]
            rows.append((int(sig[b]), total, np.sort(t), *prefixes, mask(prefixes[1], MASK), mask(prefixes[2], MASK), bitmap(t), *keys))
            held += len(t)
            if held >= SEND:
                yield batch_of(rows)
                rows, held = [], 0
        if rows:
            yield batch_of(rows)

    lists = ["toks", "p1", "p2", "p3", "m2", "m3", "bits", *[f"k{r}" for r in range(ROUNDS)]]

    def batch_of(rows: list[tuple]) -> pa.RecordBatch:
        def column(i: int) -> pa.ListArray:
            values = [r[i] for r in rows]
            return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, values)]), pa.int32()), pa.array(np.concatenate(values).view(np.int64)))

        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), *[column(i) for i in range(2, 2 + len(lists))]], names=["sig", "n", *lists])

    return run, "sig long, n long, " + ", ".join(f"{x} array<long>" for x in lists)


def _neighbours(key: str):
    """Links among rows that stand near one another in the sorted order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        near: list[tuple] = []
        for batch in batches:
            a, b = [], []
            lists = batch.column("toks")
            tokens, ends = lists.values.to_numpy(), lists.offsets.to_numpy()
            first = batch.column(key).values.to_numpy()[batch.column(key).offsets.to_numpy()[:-1]]
            for i, (sig, n) in enumerate(zip(batch.column("sig").to_pylist(), batch.column("n").to_pylist())):
                row = (sig, n, first[i], tokens[ends[i] : ends[i + 1]].copy())
                near = [x for x in near if x[2] == row[2]][-NEIGHBOURS:]
                for other in near:
                    low, high = sorted((row[1], other[1]))
                    if 5 * low >= 4 * high and linked(len(np.intersect1d(row[3], other[3], assume_unique=True)), row[1], other[1]):
                        a.append(other[0]), b.append(row[0])
                near.append(row)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["u", "v"])

    return run, "u long, v long"


def _bits_differ(words: int) -> Column:
    """A lower bound of the shared tokens in which two nodes differ."""
    return sum((F.bit_count(F.col("a.bits")[i].bitwiseXOR(F.col("b.bits")[i])) for i in range(words)), F.lit(0))


def _meet(name: str) -> Column:
    """Whether two masks share a bit, without which no prefix token is shared."""
    out = F.lit(False)
    for i in range(MASK):
        out = out | (F.col(f"a.{name}")[i].bitwiseAND(F.col(f"b.{name}")[i]) != 0)
    return out


def verified(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """The pairs (u, v, ...) that share prefix tokens under the later orders and are linked."""
    side = lambda s: nodes.select(F.col("sig").alias(s), *[F.col(c).alias(f"{s}_{c}") for c in ("n", "toks", "p2", "p3")])
    both = pairs.join(side("u"), "u").join(side("v"), "v").where(F.arrays_overlap("u_p2", "v_p2") & F.arrays_overlap("u_p3", "v_p3"))
    return both.where(linked(F.size(F.array_intersect("u_toks", "v_toks")), F.col("u_n"), F.col("v_n"))).select(pairs.columns)


def _sized(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Shingles of rows without a doc_id."""
    words = WordHashes()
    for batch in (part for whole in batches for part in slices(whole)):
        n = [len(shingles(words.of(t.encode().lower().split()))) if t else 0 for t in batch.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.nulls(len(n), pa.int64()), pa.array(n, pa.int64()), pa.nulls(len(n), pa.int64())], names=["doc_id", "n_shingles", "component_id"])


def groups(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    parts, buckets = partitions(docs.sparkSession), bucketed(docs)
    deal, deal_schema = _dealt(buckets)
    count, count_schema = _counted(buckets)
    answer, _ = _answered(buckets)
    gather, gather_schema = _gathered()
    dealt = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(tidy(deal), deal_schema)
    counted = written(dealt.repartitionById(buckets, "bucket").mapInArrow(tidy(count), count_schema))
    rows = counted.where(f"kind = {ROWS}").select("doc_id", "n", "sig")
    blobs = ["kind", "n", "bucket", "s", "a", "b"]
    answered = counted.where(f"kind IN ({COUNTS}, {WAITING})").select(blobs).repartitionById(buckets, "bucket").mapInArrow(tidy(answer), count_schema)
    shared = counted.where(f"kind IN ({SIZES}, {SHARED})").select(blobs).union(answered.select(blobs))
    nodes = written(shared.repartitionById(buckets, "bucket").mapInArrow(tidy(gather), gather_schema))

    # From here on a node is named by the least doc_id of its copies, so that the root of a component is its answer.
    least = checkpointed(rows.where("n > 0").groupBy("sig").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("copies")))
    names = checkpointed(nodes.select("sig").join(least, "sig"))
    of = lambda s, n: names.select(F.col("sig").alias(s), F.col("least").alias(n))

    near = None
    for r in range(ROUNDS):
        compare, link_schema = _neighbours(f"k{r}")
        key = [F.col(f"k{r}")[i] for i in range(3)]
        line = nodes.select("sig", "n", "toks", f"k{r}").repartitionByRange(parts, *key, "sig").sortWithinPartitions(*key, "sig")
        found = line.mapInArrow(tidy(compare), link_schema)
        near = found if near is None else near.union(found)
    first = connected(near.distinct().join(of("u", "a"), "u").join(of("v", "b"), "v").select(F.col("a").alias("u"), F.col("b").alias("v")))

    comp = names.join(first, F.col("least") == F.col("node"), "left").select("sig", F.coalesce("root", "least").alias("comp"))
    held = nodes.select("sig", "n", F.size("toks").alias("r"), "p1", "m2", "m3", "bits").join(comp, "sig")
    spread = checkpointed(held.select(F.explode("p1").alias("tok"), "sig", "n", "r", "m2", "m3", "bits", "comp"))
    across = spread.groupBy("tok").agg(F.min("comp").alias("x"), F.max("comp").alias("y")).where("x <> y").select("tok")
    open_ = spread.join(across, "tok", "left_semi")
    size = (5 * F.col("a.n") >= 4 * F.col("b.n")) & (5 * F.col("b.n") >= 4 * F.col("a.n"))
    bound = 9 * (F.col("a.r") + F.col("b.r") - _bits_differ(BITMAP)) >= 8 * (F.col("a.n") + F.col("b.n"))
    pairs = open_.alias("a").join(open_.alias("b"), (F.col("a.tok") == F.col("b.tok")) & (F.col("a.comp") < F.col("b.comp")) & size & _meet("m2") & _meet("m3") & bound)
    pairs = pairs.select(F.col("a.sig").alias("u"), F.col("b.sig").alias("v"), F.col("a.comp").alias("cu"), F.col("b.comp").alias("cv")).distinct()
    second = connected(verified(pairs, nodes).select(F.col("cu").alias("u"), F.col("cv").alias("v")).distinct())

    # The second graph joins components of the first; its roots are the answers of the nodes in it.
    moved = comp.join(second, F.col("comp") == F.col("node")).select("sig", F.col("root").alias("top"))
    answer = comp.join(moved, "sig", "left").select("sig", F.coalesce("top", "comp").alias("component_id"))
    of_sig = checkpointed(least.join(answer, "sig", "left").select("sig", F.coalesce("component_id", "least").alias("component_id"), "copies"))
    full = spread_join(rows.where("n > 0"), of_sig, "sig", "copies", COPIES).select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    nameless = docs.where(F.col("doc_id").isNull()).select("text").mapInArrow(_sized, "doc_id long, n_shingles long, component_id long")
    return full.union(rows.where("n = 0").select("doc_id", "n", "doc_id")).union(nameless)


def representatives(docs: DataFrame) -> DataFrame:
    """One row of each group, with the columns of ``docs``: the one whose doc_id names the component.

    Of rows that repeat a doc_id the one with the least text hash stays; a null doc_id has no group and stays.
    """
    keep = groups(docs).where("doc_id = component_id").select("doc_id").distinct()
    one = W.partitionBy("doc_id").orderBy(F.xxhash64("text"))
    kept = docs.join(keep, "doc_id", "left_semi").withColumn("__copy", F.row_number().over(one)).where("__copy = 1").select(*docs.columns)
    return kept.unionByName(docs.where(F.col("doc_id").isNull()))


def oracle(view: str = "documents") -> str:
    """The thin query's rows in DuckDB SQL, by joining all documents that share a shingle; for small tables."""
    word = r"[^\x20\x09-\x0D]+"
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    return f"""
    WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{upper}', '{lower}'), '{word}') AS ws FROM {view}),
    sh AS (SELECT DISTINCT doc_id, array_to_string(list_slice(ws, i, i + 4), ' ') AS s FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 2))) AS i FROM d WHERE len(ws) > 0)),
    n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
    both_ AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM sh a JOIN sh b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY 1, 2),
    link AS (SELECT x, y FROM both_ JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * c >= 80 * (p.n + q.n - c)),
    way AS (SELECT x, y FROM link UNION ALL SELECT y, x FROM link),
    reach AS (SELECT x AS doc_id, y AS c FROM way UNION SELECT reach.doc_id, way.y FROM reach JOIN way ON reach.c = way.x)
    SELECT d.doc_id, CAST(coalesce(any_value(n.n), 0) AS BIGINT) AS n_shingles, CAST(least(d.doc_id, coalesce(min(reach.c), d.doc_id)) AS BIGINT) AS component_id
    FROM d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN reach ON reach.doc_id = d.doc_id GROUP BY d.doc_id
    """
