"""Replay of many places over many variants in numpy; runs in tasks on batches, and on whole small logs.

A place is a pair of tuples of activity ids. Per event, tokens first fall by the postset, the least value is
kept, then they rise by the preset.
"""

from __future__ import annotations

import numpy as np

Place = tuple[tuple[int, ...], tuple[int, ...]]
#: Cells of the token matrix that are alive at once.
CELLS = 1 << 18
#: Cells that a block keeps between calls.
HELD = 1 << 27


def pack(places: list[Place], n_acts: int, kind=np.int16) -> tuple[np.ndarray, np.ndarray]:
    """Activity x place matrices of presets and postsets; the last activity is padding."""
    pre, post = np.zeros((n_acts + 1, len(places)), kind), np.zeros((n_acts + 1, len(places)), kind)
    for j, (i, o) in enumerate(places):
        pre[list(i), j] = 1
        post[list(o), j] = 1
    return pre, post


class Block:
    """Variants with frequencies."""

    def __init__(self, seqs: list, freqs, n_acts: int):
        order = sorted(range(len(seqs)), key=lambda i: len(seqs[i]))
        self.order = np.array(order, np.int64)
        self.n_acts = n_acts
        self.lengths = np.array([len(seqs[i]) for i in order], np.int64)
        self.seqs = [np.asarray(seqs[i], np.int64) for i in order]
        self.freq = np.array([freqs[i] for i in order], np.int64)
        self.total = int(self.freq.sum())
        self._padded: list | None = None
        self._prefixes: np.ndarray | None = None
        self._fit: dict[Place, np.ndarray] = {}

    def __len__(self) -> int:
        return len(self.seqs)

    def padded(self) -> list[tuple[int, int, np.ndarray]]:
        """Slices of variants of similar length as padded matrices, made once; a very long variant shares with none that is much shorter."""
        if self._padded is None:
            self._padded, at = [], 0
            kind = np.int16 if self.n_acts < 32767 else np.int32
            while at < len(self.seqs):
                end = int(np.searchsorted(self.lengths, 4 * self.lengths[at] + 16, "right"))
                out = np.full((end - at, max(1, int(self.lengths[end - 1]))), self.n_acts, kind)
                out[np.arange(out.shape[1]) < self.lengths[at:end, None]] = np.concatenate(self.seqs[at:end])
                self._padded.append((at, end, out))
                at = end
        return self._padded

    def chunks(self, width: int):
        """Parts of the padded matrices for ``width`` places at once."""
        step = max(1, CELLS // max(1, width))
        for at, end, acts in self.padded():
            for i in range(at, end, step):
                part = acts[i - at : i - at + step]
                yield i, min(end, i + step), part[:, : max(1, int(self.lengths[min(end, i + step) - 1]))]

    def states(self, places: list[Place]):
        """(first, last, least tokens, final tokens) per slice of variants."""
        packed: dict = {}
        for at, end, acts in self.chunks(len(places)):
            # Counters are as narrow as the longest variant allows.
            kind = np.int8 if acts.shape[1] < 127 else np.int16 if acts.shape[1] < 32767 else np.int32
            if kind not in packed:
                packed[kind] = pack(places, self.n_acts, kind)
            pre, post = packed[kind]
            tokens = np.zeros((len(acts), len(places)), kind)
            least = np.zeros_like(tokens)
            for k in range(acts.shape[1]):
                tokens -= post[acts[:, k]]
                np.minimum(least, tokens, out=least)
                tokens += pre[acts[:, k]]
            yield at, end, least, tokens

    def counts(self, places: list[Place]) -> np.ndarray:
        """fit, under, over, unbalanced traces of each place."""
        if not places:
            return np.zeros((0, 4), np.int64)
        width = 4096
        if len(places) > width:
            return np.concatenate([self.counts(places[j : j + width]) for j in range(0, len(places), width)])
        out = np.zeros((len(places), 4), np.int64)
        for at, end, least, final in self.states(places):
            f, under = self.freq[at:end], least < 0
            # All sums of these whole numbers are exact in the float that is used.
            kind = np.float32 if f.sum() < 1 << 24 else np.float64
            f = f.astype(kind)
            for c, m in enumerate((~under & (final == 0), under, final > 0, final != 0)):
                out[:, c] += (f @ m.astype(kind)).astype(np.int64)
        return out

    def fits(self, places: list[Place]) -> np.ndarray:
        """variant x place: whether the variant fits; variants in the order of this block."""
        out = np.zeros((len(self), len(places)), bool)
        for j in range(0, len(places), 4096):
            for at, end, least, final in self.states(places[j : j + 4096]):
                out[at:end, j : j + 4096] = (least >= 0) & (final == 0)
        return out

    def support(self, places: list[Place]) -> int:
        """Traces that fit all places."""
        if not places:
            return self.total
        if fresh := [p for p in dict.fromkeys(places) if p not in self._fit]:
            if (len(self._fit) + len(fresh)) * len(self) > HELD:
                self._fit.clear()
                fresh = list(dict.fromkeys(places))
            if len(fresh) * len(self) > HELD:
                return int(self.freq[self.fits(fresh).all(axis=1)].sum())
            self._fit |= zip(fresh, np.ascontiguousarray(self.fits(fresh).T))
        fit = self._fit[places[0]]
        for p in places[1:]:
            fit = fit & self._fit[p]
        return int(self.freq[fit].sum())

    def first_unfit(self, places: list[Place]) -> set[int]:
        """Positions of places that are the first one that some variant does not fit."""
        if not places or not len(self):
            return set()
        bad = ~self.fits(places)
        return set(bad.argmax(axis=1)[bad.any(axis=1)].tolist())

    def token_states(self, places: list[Place], fitting: bool = False) -> np.ndarray:
        """Distinct rows of tokens after events; with ``fitting`` only of variants that fit each place (others count as zero)."""
        pre, post = pack(places, self.n_acts)
        found = np.zeros((1, len(places)), np.int16)
        fits = self.fits(places) if fitting else None
        for at, end, acts in self.chunks(len(places)):
            tokens = np.zeros((end - at, len(places)), np.int16)
            rows = []
            for k in range(acts.shape[1]):
                tokens = tokens - post[acts[:, k]] + pre[acts[:, k]]
                alive = self.lengths[at:end] > k
                rows.append(np.unique((tokens * fits[at:end] if fitting else tokens)[alive], axis=0))
            found = np.unique(np.concatenate([found, *rows]), axis=0)
        return found

    def prefixes(self) -> np.ndarray:
        """Distinct rows of how often each activity came until some event, made once; tokens of every place depend on these alone."""
        if self._prefixes is None:
            kind = np.int16 if not len(self) or self.lengths[-1] < 32767 else np.int32
            found = np.zeros((1, self.n_acts), kind)
            for at, end, acts in self.chunks(self.n_acts + 1):
                seen, rows = np.zeros((end - at, self.n_acts + 1), kind), []
                for k in range(acts.shape[1]):
                    seen[np.arange(end - at), acts[:, k]] += 1
                    rows.append(np.unique(seen[self.lengths[at:end] > k, :-1], axis=0))
                found = np.unique(np.concatenate([found, *rows]), axis=0)
            self._prefixes = found
        return self._prefixes

    def _tokens(self, places: list[Place]) -> np.ndarray:
        """Tokens of places after events, each state of them at least once."""
        if int(self.lengths.sum()) * self.n_acts > HELD:
            return self.token_states(places)
        pre, post = pack(places, self.n_acts, np.float64)
        return self.prefixes() @ (pre - post)[:-1]

    def beside(self, place: Place, others: list[Place]) -> tuple[np.ndarray, np.ndarray]:
        """For each of ``others`` whether it never holds more tokens than ``place``, and whether it never holds fewer."""
        t = self._tokens([place, *others])
        return (t[:, 1:] <= t[:, :1]).all(axis=0), (t[:, 1:] >= t[:, :1]).all(axis=0)

    def dominance(self, places: list[Place], scope: str = "all") -> np.ndarray:
        """p x q: whether q holds at most as many tokens as p after every event of every variant in scope (``all``, or those that both fit)."""
        n = len(places)
        out = np.ones((n, n), bool)
        if scope == "all":
            t = self._tokens(places)
            for p in range(n):
                out[p] = (t <= t[:, p : p + 1]).all(axis=0)
            return out
        pre, post = pack(places, self.n_acts)
        fits = self.fits(places)
        for at, end, acts in self.chunks(n * 8):
            tokens = np.zeros((end - at, n), np.int16)
            for k in range(acts.shape[1]):
                tokens = tokens - post[acts[:, k]] + pre[acts[:, k]]
                alive = (self.lengths[at:end] > k)[:, None]
                for p in range(n):
                    out[p] &= ~((tokens > tokens[:, p : p + 1]) & fits[at:end] & fits[at:end, p : p + 1] & alive).any(axis=0)
        return out

    def touching(self, places: list[Place]) -> np.ndarray:
        """variant x place: whether the variant holds an adjacent activity."""
        pre, post = pack(places, self.n_acts)
        near = (pre + post) > 0
        out = np.zeros((len(self), len(places)), bool)
        for at, end, acts in self.chunks(len(places)):
            for k in range(acts.shape[1]):
                out[at:end] |= near[acts[:, k]]
        return out
