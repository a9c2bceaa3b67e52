"""Quality classifier (op 5): random-indexing word vectors, pooled, then a two-layer network.

Every word has a sparse random index vector made from its hash. The vector of a word is the sum of the
index vectors of its neighbours over the training texts, kept in a fixed number of slots; the same is done for
word shapes (runs of letters, capitals, digits and each other character). A document is the mean of the
vectors of its words and shapes, with the length of the mean index vector (large if few words
repeat), the log length and the share of distinct three-word windows. A two-layer numpy network
gives a logit; a temperature fitted on rows set aside turns it into a calibrated probability.

The fit reads at most about ``max_rows`` labelled rows (a documented bound, picked by a hash of doc_id); scores
cover every row and whole texts. Edge cases: null and empty texts are the zero document and get its score;
repeated rows get equal scores; columns beside doc_id and text are only carried along, whatever their names;
labels that are null or neither 0 nor 1 are ignored; several labels of one document count as their
least; without labels of both kinds everything scores the share of ones (0.5 without any).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed
from .words import MEMO, MULTIPLIERS, SHORT, slices, tidy

WIDTH = 32
ENTRIES = 4
WORD_SLOTS = 1 << 16
SHAPE_SLOTS = 1 << 11
REACH = 2
FEATURES = 2 * WIDTH + 3
#: Tasks of the fit, which reads a bounded sample; slots of word vectors that are added up together.
FIT_TASKS = 8
BLOCK = 1 << 10
#: Words of a text that are pooled at once.
STRIDE = 1 << 16


def index_vectors(slots: int, salt: int) -> np.ndarray:
    """A sparse ternary vector for each slot; made anew wherever it is needed, never sent."""
    rng = np.random.Generator(np.random.PCG64(salt))
    out = np.zeros((slots, WIDTH), np.float32)
    where = rng.integers(0, WIDTH, (slots, ENTRIES))
    sign = rng.integers(0, 2, (slots, ENTRIES)) * 2.0 - 1.0
    np.add.at(out, (np.arange(slots)[:, None], where), sign)
    return out


class Slots(dict):
    """word -> word slot and shape slot in one number, memoised within a bound."""

    def __init__(self):
        super().__init__()
        self.fold = [(regex.compile(rb"[a-z\x80-\xff]+"), b"a"), (regex.compile(rb"[A-Z]+"), b"A"), (regex.compile(rb"[0-9]+"), b"9")]

    def shape(self, word: bytes) -> bytes:
        for pattern, sign in self.fold:
            word = pattern.sub(sign, word)
        return word

    def __missing__(self, word: bytes) -> int:
        n = xxhash.xxh64_intdigest(word) % WORD_SLOTS * SHAPE_SLOTS + xxhash.xxh64_intdigest(self.shape(word)) % SHAPE_SLOTS
        if len(self) < MEMO and len(word) <= SHORT:
            self[word] = n
        return n

    def of(self, text: str | None) -> np.ndarray:
        words = text.encode().split() if text else []
        return np.fromiter(map(self.__getitem__, words), np.int64, len(words))


def pooled(at: np.ndarray, words: np.ndarray, shapes: np.ndarray, index: np.ndarray) -> np.ndarray:
    """The features of one document from the slots of its words."""
    out, n = np.zeros(FEATURES, np.float64), len(at)
    if not n:
        return out
    mean_index = np.zeros(WIDTH)
    for i in range(0, n, STRIDE):
        w, s = np.divmod(at[i : i + STRIDE], SHAPE_SLOTS)
        out[:WIDTH] += words[w].sum(axis=0, dtype=np.float64)
        out[WIDTH : 2 * WIDTH] += np.bincount(s, minlength=SHAPE_SLOTS) @ shapes
        mean_index += index[w].sum(axis=0, dtype=np.float64)
    out[: 2 * WIDTH] /= n
    out[-3] = np.linalg.norm(mean_index / n)
    out[-2] = np.log1p(n)
    h = at.astype(np.uint64)
    if n >= 3:
        h = h[:-2] * MULTIPLIERS[0] + h[1:-1] * MULTIPLIERS[1] + h[2:] * MULTIPLIERS[2]
    out[-1] = len(np.unique(h)) / len(h)
    return out


@dataclass
class Network:
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float = 1.0

    def logits(self, x: np.ndarray) -> np.ndarray:
        return np.tanh(((x - self.mean) / self.scale) @ self.w1 + self.b1) @ self.w2 + self.b2

    def scores(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x) / self.temperature, -40, 40)))


def train(x: np.ndarray, y: np.ndarray, hidden: int = 24, epochs: int = 400, seed: int = 7) -> Network:
    """Fit the network by Adam on the whole matrix, then its temperature on a fifth that was set aside (driver)."""
    rng = np.random.Generator(np.random.PCG64(seed))
    net = Network(x.mean(axis=0) if len(x) else np.zeros(FEATURES), (x.std(axis=0) if len(x) else np.ones(FEATURES)) + 1e-6, np.zeros((x.shape[1], hidden)), np.zeros(hidden), np.zeros(hidden), 0.0)
    share = float(y.mean()) if len(y) else 0.5
    if share in (0.0, 1.0) or not len(y):
        net.b2 = float(np.clip(np.log((share + 1e-3) / (1 - share + 1e-3)), -7, 7)) if len(y) else 0.0
        return net
    aside = rng.random(len(y)) < 0.2
    if len(set(y[aside])) < 2 or len(set(y[~aside])) < 2:
        aside[:] = False
    z, t = (x[~aside] - net.mean) / net.scale, y[~aside]
    p = [rng.normal(0, 1 / np.sqrt(x.shape[1]), net.w1.shape), np.zeros(hidden), rng.normal(0, 1 / np.sqrt(hidden), hidden), np.zeros(1)]
    m, v = [np.zeros_like(a) for a in p], [np.zeros_like(a) for a in p]
    for step in range(1, epochs + 1):
        h = np.tanh(z @ p[0] + p[1])
        g = (1 / (1 + np.exp(-np.clip(h @ p[2] + p[3], -40, 40))) - t) / len(t)
        back = np.outer(g, p[2]) * (1 - h * h)
        for i, grad in enumerate((z.T @ back + 1e-4 * p[0], back.sum(axis=0), h.T @ g + 1e-4 * p[2], np.array([g.sum()]))):
            m[i] = 0.9 * m[i] + 0.1 * grad
            v[i] = 0.999 * v[i] + 0.001 * grad * grad
            p[i] -= 0.02 * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.999**step)) + 1e-8)
    net.w1, net.b1, net.w2, net.b2 = p[0], p[1], p[2], float(p[3][0])
    if aside.any():
        l, t = net.logits(x[aside]), y[aside]
        grid = np.geomspace(0.25, 8, 61)
        net.temperature = float(grid[np.argmin([np.mean(np.logaddexp(0, np.where(t == 1, -l, l) / k)) for k in grid])])
    return net


@dataclass
class Model:
    words: np.ndarray
    shapes: np.ndarray
    network: Network


def training_rows(docs: DataFrame, labels: DataFrame, max_rows: int) -> DataFrame:
    """(doc_id, text, y) of at most about ``max_rows`` labelled documents; that bound also bounds what is broadcast."""
    known = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.min("quality").cast("double").alias("y"))
    n = known.count()
    if n > max_rows:
        known = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < int((1 << 20) * max_rows / n))
    return docs.select("doc_id", "text").join(F.broadcast(known), "doc_id")


def fit(docs: DataFrame, labels: DataFrame, max_rows: int = 20000) -> Model:
    rows = checkpointed(training_rows(docs, labels, max_rows).repartition(FIT_TASKS))

    def context(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slots = Slots()
        index, shape_index = index_vectors(WORD_SLOTS, 1), index_vectors(SHAPE_SLOTS, 2)
        words, shapes = np.zeros((WORD_SLOTS, WIDTH), np.float32), np.zeros((SHAPE_SLOTS, WIDTH), np.float32)
        seen = 0
        for batch in batches:
            for text in batch.column("text").to_pylist():
                w, s = np.divmod(slots.of(text), SHAPE_SLOTS)
                for d in range(1, REACH + 1):
                    np.add.at(words, w[d:], index[w[:-d]])
                    np.add.at(words, w[:-d], index[w[d:]])
                    np.add.at(shapes, s[d:], shape_index[s[:-d]])
                    np.add.at(shapes, s[:-d], shape_index[s[d:]])
                seen += 1
        if seen:
            for i in range(0, WORD_SLOTS, BLOCK):
                yield pa.RecordBatch.from_pydict({"block": [i], "sums": [words[i : i + BLOCK].tobytes()]})
            yield pa.RecordBatch.from_pydict({"block": [-1], "sums": [shapes.tobytes()]})

    def added(group: pa.Table) -> pa.Table:
        # Whole numbers, so that any order gives the same sums.
        total = np.sum([np.frombuffer(b, np.float32) for b in group.column("sums").to_pylist()], axis=0, dtype=np.float64)
        return pa.table({"block": group.column("block")[:1], "sums": pa.array([total.astype(np.float32).tobytes()], pa.binary())})

    def directions(total: np.ndarray) -> np.ndarray:
        total /= np.maximum(np.linalg.norm(total, axis=1, keepdims=True), 1e-6)
        return total

    words, shapes = np.zeros((WORD_SLOTS, WIDTH), np.float32), np.zeros((SHAPE_SLOTS, WIDTH), np.float32)
    # Tasks add up blocks of slots, so that one matrix comes to the driver, whatever the number of tasks.
    parts = rows.select("text").mapInArrow(tidy(context), "block long, sums binary").groupBy("block").applyInArrow(added, "block long, sums binary")
    for r in parts.toLocalIterator():
        sums = np.frombuffer(r["sums"], np.float32).reshape(-1, WIDTH)
        if r["block"] < 0:
            shapes[:] = sums
        else:
            words[r["block"] : r["block"] + BLOCK] = sums
    model = Model(directions(words), directions(shapes), None)
    sample = _features(rows, model, ["y"], "y double").toArrow().sort_by([("doc_id", "ascending"), ("y", "ascending")])
    x = np.frombuffer(b"".join(sample.column("x").to_pylist()), np.float64).reshape(-1, FEATURES)
    model.network = train(x, sample.column("y").to_numpy())
    return model


def _features(rows: DataFrame, model: Model, keep: list[str], schema: str) -> DataFrame:
    shared = rows.sparkSession.sparkContext.broadcast((model.words, model.shapes))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slots, index = Slots(), index_vectors(WORD_SLOTS, 1)
        for batch in batches:
            for part in slices(batch):
                x = np.array([pooled(slots.of(t), *shared.value, index) for t in part.column("text").to_pylist()])
                blob = pa.FixedSizeBinaryArray.from_buffers(pa.binary(8 * FEATURES), len(part), [None, pa.py_buffer(x.tobytes())]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), *map(part.column, keep), blob], names=["doc_id", *keep, "x"])

    return rows.select("doc_id", "text", *keep).mapInArrow(tidy(run), f"doc_id long, {schema}, x binary")


def scores(docs: DataFrame, model: Model, keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` (doc_id by default) of every row, with its score from the whole text."""
    keep = keep or ["doc_id"]
    shared = docs.sparkSession.sparkContext.broadcast((model.words, model.shapes, model.network))
    kept = docs.select(*{c: None for c in [*keep, "text"]})
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema if f.name in keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slots, index = Slots(), index_vectors(WORD_SLOTS, 1)
        words, shapes, network = shared.value
        for batch in (part for whole in batches for part in slices(whole)):
            x = np.array([pooled(slots.of(t), words, shapes, index) for t in batch.column("text").to_pylist()]).reshape(-1, FEATURES)
            yield pa.RecordBatch.from_arrays([*map(batch.column, keep), pa.array(network.scores(x), pa.float64())], names=[*keep, "score"])

    return kept.mapInArrow(tidy(run), f"{schema}, score double")


def filtered(docs: DataFrame, model: Model, threshold: float = 0.5) -> DataFrame:
    """The rows that the model accepts, with the columns of ``docs``."""
    return scores(docs, model, docs.columns).where(F.col("score") >= threshold).select(*docs.columns)
