"""Token counts by heap-and-linked-list byte-pair merging (op 9).

A pre-token starts as one symbol a byte, the last with the end-of-word mark. The symbols form a linked
list; a heap holds the adjacent pairs that merge, by rank and then position; the lowest is popped,
merged if both ends still stand, and its new neighbours are pushed. The count of tokens is the number of
symbols less the number of merges, and no identifier is made. Counts of pre-tokens are memoised per task
within a bound.

Special tokens found in a text count one each and cut the text, as the library does by default. Edge
cases: a null or empty text has no tokens; no length is refused; repeated rows and clashing columns are
of no effect, since only doc_id and text are read.
"""

from __future__ import annotations

import heapq
import json
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
import public_tokenizers
import regex
from pyspark.sql import DataFrame

#: Fixed values of the tokenizer family: words are split by this pattern after NFC and lower case.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: Letters whose lower case there differs from str.lower().
LOWER = (("\u03a3", "\u03c3"), ("\ua7cb", "\u0264"), ("\ua7dc", "\u019b"))
#: Memoised pre-tokens per task.
MEMO = 1 << 20
SHORT = 64


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte: printable Latin-1 stands for itself, the rest follow from U+0100 on."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = iter(range(0x100, 0x200))
    return [chr(b) if b in plain else chr(next(rest)) for b in range(256)]


def merged_count(symbols: list[str], ranks: dict[tuple[str, str], int]) -> int:
    """Symbols left after all merges."""
    n = len(symbols)
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = [(r, i, symbols[i], symbols[i + 1]) for i in range(n - 1) if (r := ranks.get((symbols[i], symbols[i + 1]))) is not None]
    heapq.heapify(heap)
    merges = 0
    while heap:
        _, i, left, right = heapq.heappop(heap)
        j = after[i]
        if symbols[i] != left or j >= n or symbols[j] != right:
            continue  # one end has been merged since
        symbols[i], symbols[j] = left + right, ""
        merges += 1
        k = after[i] = after[j]
        if k < n:
            before[k] = i
            if (r := ranks.get((symbols[i], symbols[k]))) is not None:
                heapq.heappush(heap, (r, i, symbols[i], symbols[k]))
        if (h := before[i]) >= 0 and (r := ranks.get((symbols[h], symbols[i]))) is not None:
            heapq.heappush(heap, (r, h, symbols[h], symbols[i]))
    return n - merges


class Counter:
    """Token counts of texts for one vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.ranks = {tuple(m) if isinstance(m, list) else tuple(m.split(" ")): i for i, m in reversed(list(enumerate(spec["model"]["merges"])))}
        self.suffix = spec["model"]["end_of_word_suffix"] or ""
        special = [t["content"] for t in spec["added_tokens"]]
        self.special = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None
        self.split = regex.compile(PATTERN).findall
        self.bytes = byte_symbols()
        self.memo: dict[str, int] = {}

    def word(self, word: str) -> int:
        symbols = [self.bytes[b] for b in word.encode()]
        symbols[-1] += self.suffix
        n = merged_count(symbols, self.ranks)
        if len(self.memo) < MEMO and len(word) <= SHORT:
            self.memo[word] = n
        return n

    def count(self, text: str) -> int:
        if self.special is not None and "<|" in text and self.special.search(text):
            parts = self.special.split(text)
            return len(parts) - 1 + sum(map(self._plain, parts))
        return self._plain(text)

    def _plain(self, text: str) -> int:
        if not text.isascii():
            # The library lowers each character on its own, without the final form of sigma.
            text = unicodedata.normalize("NFC", text)
            for upper, lower in LOWER:
                text = text.replace(upper, lower)
        words = self.split(text.lower())
        known = list(map(self.memo.get, words))
        if None in known:
            known = [n if n is not None else m if (m := self.memo.get(w)) is not None else self.word(w) for w, n in zip(words, known)]
        return sum(known)


def counts(docs: DataFrame, path: str | None = None, limit: int = 2048) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit (n_tokens > limit) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = Counter(path or public_tokenizers.path("word_bpe_49k.json"))
        for batch in batches:
            texts = [t or "" for t in batch.column("text").to_pylist()]
            tokens = [counter.count(t) for t in texts]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").cast(pa.int64()), pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array(tokens, pa.int64()), pa.array([n > limit for n in tokens], pa.bool_())],
                names=["doc_id", "n_bytes", "n_tokens", "over_limit"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
