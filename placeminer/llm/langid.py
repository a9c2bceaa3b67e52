"""Language identification by language bitmasks of n-grams (op 2).

Training counts hashed character n-grams per language over labelled texts (exact sums over every
labelled row given, in a fixed number of hash cells) and keeps for a language the n-grams whose rate there is
at least ``share`` of the highest rate among the languages. The filter is a bit-sliced Bloom filter: one row
of bits per cell, one column per language, so that the AND of an n-gram's probed rows is the mask of
all languages that contain it. A text's hits per language are popcounts of those mask columns over its
n-grams, corrected for the column's false-positive chance, weighted by length, and normalised to a score.

The training rows may be bounded (``max_rows``, a documented parameter), which bounds the counts on the driver too; every
language among them is learned, with as many mask words as they need (16 MB for each 64). Prediction reads whole texts.
Edge cases: repeated rows count as often as they stand there and get equal results; other columns, whatever their names, are not
read; a null text or one without a letter is ``und`` with score 0; a text without any known n-gram
falls back to the most frequent language with score 0; without training rows everything is ``und``; ties go
to the language first by code point. Only doc_id, text and, for training, lang are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .words import slices, tidy

#: n-gram lengths; cells of the counting table; rows and probes of the Bloom filter.
LENGTHS = (2, 3, 4)
CELLS = 1 << 20
ROWS = 1 << 21
PROBES = 2
#: n-grams that are looked up at once.
STRIDE = 1 << 18
#: Languages that one word of a mask holds; more languages take more words.
WORD = 64


def letter_table() -> np.ndarray:
    """True for each code point that is a letter."""
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


def codes(text: str) -> np.ndarray:
    return np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)


def spread(x: np.ndarray, salt: int) -> np.ndarray:
    x = (x ^ np.uint64(salt)) * np.uint64(0x9E3779B97F4A7C15)
    return (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)


def pieces(text: str, letters: np.ndarray) -> Iterator[np.ndarray]:
    """Hashes of all n-grams of the letters of a text, every other run of characters being one blank; none without letters.

    They come at most ``STRIDE`` at a time, so that the memory of a very long text is a few times its own.
    """
    c = codes(text)
    is_letter = letters[c]
    if not is_letter.any():
        return
    c = np.where(is_letter, c, np.uint32(32))
    keep = np.ones(len(c), bool)
    keep[1:] = (c[1:] != 32) | (c[:-1] != 32)
    blank = np.full(1, 32, np.uint32)
    c = np.concatenate((blank, c[keep], blank))
    for n in LENGTHS:
        for at in range(0, len(c) - n + 1, STRIDE):
            part = c[at : at + STRIDE + n - 1].astype(np.uint64)
            h = part[: len(part) - n + 1].copy()
            for i in range(1, n):
                h = (h << np.uint64(16)) ^ (h >> np.uint64(48)) ^ part[i : len(part) - n + 1 + i]
            yield spread(h, 0)


def grams(text: str, letters: np.ndarray) -> np.ndarray:
    """All of them at once."""
    return np.concatenate([np.empty(0, np.uint64), *pieces(text, letters)])


@dataclass
class Model:
    languages: list[str]
    #: For each word of languages, ROWS masks with a bit for each of them.
    table: list[np.ndarray]
    #: Chance that an absent n-gram passes, by language.
    false: np.ndarray
    default: str

    def masks(self, g: np.ndarray) -> list[np.ndarray]:
        """Languages of each n-gram, by word."""
        c = cell(g)
        out = [word[probe(c, 1)] for word in self.table]
        for p in range(2, PROBES + 1):
            at = probe(c, p)
            for m, word in zip(out, self.table):
                m &= word[at]
        return out

    def hits(self, g: np.ndarray) -> np.ndarray:
        """Popcount of each language's column over the n-grams."""
        out = []
        for w, m in enumerate(self.masks(g)):
            distinct, n = np.unique(m, return_counts=True)
            out += [int(n[(distinct >> i) & 1 == 1].sum()) for i in range(min(WORD, len(self.languages) - w * WORD))]
        return np.array(out, float)

    def predict(self, text: str | None, letters: np.ndarray) -> tuple[str, float]:
        hits, n = np.zeros(len(self.languages)), 0
        for g in pieces(text, letters) if text else ():
            hits += self.hits(g)
            n += len(g)
        if not n or not self.languages:
            return "und", 0.0
        true = np.clip((hits - n * self.false) / (1 - self.false), 0, None)
        if true.max() <= 0:
            return self.default, 0.0
        best = int(true.argmax())
        others = np.delete(true, best)
        return self.languages[best], float(min(1.0, max(0.0, 1 - (others.max() if len(others) else 0) / true[best])))


def build(languages: list[str], cells: list[np.ndarray], counts: list[np.ndarray], rows: np.ndarray, share: float = 0.34) -> Model:
    """The filter from the cells of each language and their counts (driver; one array of CELLS rates at a time)."""
    if not languages:
        return Model([], [], np.zeros(0), "und")
    top = np.zeros(CELLS)
    rates = [n / max(1, n.sum()) for n in counts]
    for at, rate in zip(cells, rates):
        np.maximum.at(top, at, rate)
    table, false = [], []
    every = np.arange(CELLS, dtype=np.uint64)
    for w in range(0, len(languages), WORD):
        some = range(w, min(w + WORD, len(languages)))
        kind = next(k for k in (np.uint8, np.uint16, np.uint32, np.uint64) if len(some) <= 8 * np.dtype(k).itemsize)
        word = np.zeros(ROWS, kind)
        for bit, i in enumerate(some):
            member = cells[i][(counts[i] > 0) & (rates[i] >= share * top[cells[i]])].astype(np.uint64)
            for p in range(1, PROBES + 1):
                np.bitwise_or.at(word, probe(member, p), kind(1 << bit))
        passing = np.bitwise_and.reduce([word[probe(every, p)] for p in range(1, PROBES + 1)])
        # An absent n-gram falls into any cell alike, and passes if that cell's rows all have the bit.
        false += [float(np.mean((passing >> kind(bit)) & kind(1))) for bit in range(len(some))]
        table.append(word)
    return Model(languages, table, np.minimum(np.array(false), 0.99), languages[int(rows.argmax())])


def probe(cells: np.ndarray, salt: int) -> np.ndarray:
    return (spread(cells, salt) >> np.uint64(64 - 21)).astype(np.int64)


def cell(g: np.ndarray) -> np.ndarray:
    return g >> np.uint64(64 - 20)


def fit(labelled: DataFrame, max_rows: int = 40000, share: float = 0.34) -> Model:
    """Learn from rows (doc_id, text, lang) with a lang; of more than ``max_rows`` rows, a hash of doc_id picks about that many.

    Tasks send sums per language and cell, added up before they reach the driver.
    """
    rows = labelled.where(F.col("lang").isNotNull() & F.col("text").isNotNull())
    n = rows.count()
    if n > max_rows:
        rows = rows.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < int((1 << 20) * max_rows / n))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        letters = letter_table()
        sums: dict[str, np.ndarray] = {}
        seen: dict[str, int] = {}
        for batch in (part for whole in batches for part in slices(whole)):
            for text, lang in zip(batch.column("text").to_pylist(), batch.column("lang").to_pylist()):
                if lang not in sums:
                    sums[lang] = np.zeros(CELLS, np.int64)
                for g in pieces(text, letters) if text else ():
                    at, c = np.unique(cell(g).astype(np.int64), return_counts=True)
                    sums[lang][at] += c
                seen[lang] = seen.get(lang, 0) + 1
        for lang, s in sums.items():
            at = np.flatnonzero(s)
            yield pa.RecordBatch.from_pydict({"lang": [lang] * (len(at) + 1), "cell": [*at.tolist(), -1], "n": [*s[at].tolist(), seen[lang]]})

    summed = rows.select("text", "lang").mapInArrow(tidy(run), "lang string, cell long, n long").groupBy("lang", "cell").agg(F.sum("n").alias("n"))
    found = summed.toArrow()
    at, n = found.column("cell").to_numpy(), found.column("n").to_numpy()
    coded = found.column("lang").combine_chunks().dictionary_encode() if len(at) else pa.array([], pa.string()).dictionary_encode()
    names, which = coded.dictionary.to_pylist(), coded.indices.to_numpy()
    order = sorted(range(len(names)), key=lambda i: names[i])
    cells, counts, seen = [], [], []
    for i in order:
        own = which == i
        cells.append(at[own & (at >= 0)]), counts.append(n[own & (at >= 0)]), seen.append(int(n[own & (at < 0)].sum()))
    return build([names[i] for i in order], cells, counts, np.array(seen), share)


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred, score of every row; the filter (ROWS numbers) is broadcast."""
    shared = docs.sparkSession.sparkContext.broadcast((model.languages, model.table, model.false, model.default))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, letters = Model(*shared.value), letter_table()
        for batch in (part for whole in batches for part in slices(whole)):
            found = [own.predict(t, letters) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").cast(pa.int64()), pa.array([x for x, _ in found], pa.string()), pa.array([s for _, s in found], pa.float64())], names=["doc_id", "lang_pred", "score"]
            )

    return docs.select("doc_id", "text").mapInArrow(tidy(run), "doc_id long, lang_pred string, score double")


def held_out(mod: int, rest: int, doc_id: str = "doc_id") -> Column:
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string")), F.lit(mod)) == rest, F.lit(False))
