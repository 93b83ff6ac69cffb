"""A compressed full-text index of word sequences: wavelet matrix over the Burrows-Wheeler
transform, with vectorised backward search.

The index holds many short segments, each ended by its own sentinel.  `smaller_matches` streams
all segments through the index at once and finds their longest stretches that also occur in a
document with a smaller id: the matching statistics above a threshold.
"""

from __future__ import annotations

import numpy as np


class Bits:
    """A bit vector with constant-time rank, 1 bit a position plus 1/2 bit of counts."""

    def __init__(self, bits: np.ndarray):
        n = len(bits)
        padded = np.zeros((n // 64 + 1) * 64, np.uint8)
        padded[:n] = bits
        self.words = np.packbits(padded, bitorder="little").view(np.uint64)
        self.before = np.concatenate([[0], np.cumsum(np.bitwise_count(self.words), dtype=np.int64)])[:-1].astype(np.int32)

    def rank1(self, i: np.ndarray) -> np.ndarray:
        """Ones among the first i bits."""
        w = i >> 6
        return self.before[w] + np.bitwise_count(self.words[w] & ((np.uint64(1) << (i & 63).astype(np.uint64)) - np.uint64(1)))


class Wavelet:
    """Rank of any symbol in a sequence over 0..sigma-1."""

    def __init__(self, symbols: np.ndarray, sigma: int):
        self.levels: list[tuple[int, Bits, int]] = []
        for shift in range(max(1, int(sigma - 1).bit_length()) - 1, -1, -1):
            bit = (symbols >> shift & 1).astype(np.uint8)
            self.levels.append((shift, Bits(bit), int(len(bit) - bit.sum())))
            symbols = np.concatenate([symbols[bit == 0], symbols[bit == 1]])
        self.base = None

    def rank(self, c: np.ndarray, i: np.ndarray) -> np.ndarray:
        """How many c are among the first i symbols, plus where c's block begins in the last level."""
        for shift, bits, zeros in self.levels:
            ones = bits.rank1(i)
            i = np.where(c >> shift & 1, zeros + ones, i - ones)
        return i


class Least:
    """Range minimum by doubling."""

    def __init__(self, values: np.ndarray):
        self.rows = [values.astype(np.int32)]
        h = 1
        while 2 * h <= len(values):
            last = self.rows[-1]
            self.rows.append(np.minimum(last[:-h], last[h:]))
            h *= 2
        self.flat = np.concatenate(self.rows)
        self.at = np.cumsum([0, *map(len, self.rows)])[:-1]

    def __call__(self, l: np.ndarray, r: np.ndarray) -> np.ndarray:
        """min values[l:r], r > l."""
        k = np.frexp((r - l).astype(np.float64))[1] - 1
        return np.minimum(self.flat[self.at[k] + l], self.flat[self.at[k] + r - (1 << k)])


class Index:
    """`words`: all segments' word codes joined; `starts`: where each begins; `docs`: their ids."""

    def __init__(self, words: np.ndarray, starts: np.ndarray, docs: np.ndarray):
        lengths = np.diff(np.append(starts, len(words)))
        alphabet, codes = np.unique(words, return_inverse=True)
        self.n = len(words) + len(starts)
        self.text = np.zeros(self.n, np.int64)  # 0 is the sentinel
        self.start = starts + np.arange(len(starts))
        self.end = self.start + lengths  # the sentinel's place
        inner = np.ones(self.n, bool)
        inner[self.end] = False
        self.text[inner] = codes + 1
        owner = np.repeat(np.arange(len(starts)), lengths + 1)
        self.doc = np.unique(docs, return_inverse=True)[1].astype(np.int64)
        order = self._sorted_suffixes(int(lengths.max(initial=0)), self.end[owner])
        self.sigma = len(alphabet) + 1
        self.last = Wavelet(self.text[order - 1], self.sigma)
        counts = np.bincount(self.text, minlength=self.sigma)
        self.first = np.concatenate([[0], np.cumsum(counts)])[:-1]
        # Wavelet.rank counts from where the symbol's block begins: rank of zero occurrences
        zero = np.zeros(self.sigma, np.int64)
        self.shift = self.first - self.last.rank(np.arange(self.sigma), zero)
        self.least = Least(self.doc[owner][order])

    def _sorted_suffixes(self, longest: int, stop: np.ndarray) -> np.ndarray:
        """Suffixes within their segments, by prefix doubling; equal ones stay in text order."""
        at, h = np.arange(self.n), 1
        rank = self.text
        if int(rank.max()) < 1 << 20:  # the first three words fit one number
            for i in (1, 2):
                rank = rank << 21 | np.where(at + i <= stop, self.text[np.minimum(at + i, self.n - 1)], 0)
            rank, h = np.unique(rank, return_inverse=True)[1], 3
        while h <= longest:
            after = np.where(at + h <= stop, rank[np.minimum(at + h, self.n - 1)], 0)
            key = rank * (int(rank.max()) + 1) + after
            _, rank = np.unique(key, return_inverse=True)
            h *= 2
            if int(rank.max()) == self.n - 1:
                break
        return np.argsort(rank, kind="stable")

    def extend(self, c: np.ndarray, l: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """One step of backward search: the suffixes that begin with c and go on as those in [l, r)."""
        both = self.last.rank(np.concatenate([c, c]), np.concatenate([l, r]))
        return self.shift[c] + both[: len(c)], self.shift[c] + both[len(c) :]

    def smaller_matches(self, least: int, asked: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(segment, from, to): stretches of `least` words or more, within the segment, that occur
        in a smaller document; together they cover every window of `least` words that does.
        Only `asked` segments are streamed (all by default).

        Each segment is read backwards from its end.  A match that cannot grow is reported if it
        is long enough, and reading starts again at the next window that is still open.  After a
        short match, half of it is tried: if that fails at the same word, all windows over that
        half are settled at once."""
        k = len(self.start)
        e, p = self.end.copy(), self.end.copy()
        l, r = np.zeros(k, np.int64), np.full(k, self.n, np.int64)
        probe = np.full(k, -1, np.int64)  # the word that ended the longer match, while half of it is tried
        back = np.zeros(k, np.int64)
        live = np.flatnonzero((self.end - self.start >= least) & (True if asked is None else asked))
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        while len(live):
            nl, nr = self.extend(self.text[p[live] - 1], l[live], r[live])
            many = nr - nl > 1  # one is the segment itself
            ok = np.zeros(len(live), bool)
            ok[many] = self.least(nl[many], nr[many]) < self.doc[live[many]]
            go = live[ok]
            p[go] -= 1
            l[go], r[go] = nl[ok], nr[ok]
            whole = (p[go] == self.start[go]) & (probe[go] < 0)
            past = go[(probe[go] >= 0) & (p[go] <= probe[go])]
            e[past] = back[past] - 1
            stuck = live[~ok]
            tried = stuck[probe[stuck] >= 0]
            e[tried] -= 1
            plain = stuck[probe[stuck] < 0]
            long_ = e[plain] - p[plain] >= least
            hit = np.concatenate([plain[long_], go[whole & (e[go] - self.start[go] >= least)]])
            found.append((hit, p[hit] - self.start[hit], e[hit] - self.start[hit]))
            a, b = plain[long_], plain[~long_]
            e[a] = p[a] - 1 + least
            half = (e[b] - p[b]) // 2
            deep = b[half >= 2]
            probe[past], probe[tried] = -1, -1
            probe[deep], back[deep] = p[deep] - 1, e[deep]
            e[deep] = p[deep] + half[half >= 2]
            flat = b[half < 2]
            e[flat] -= 1
            again = np.concatenate([past, stuck])
            p[again], l[again], r[again] = e[again], 0, self.n
            done = np.zeros(k, bool)
            done[go[whole]] = True
            done[again[(probe[again] < 0) & (e[again] - self.start[again] < least)]] = True
            live = live[~done[live]]
        return tuple(np.concatenate(x) for x in zip(*found)) if found else (np.zeros(0, np.int64),) * 3
