"""Words and word shingles of whole texts as 64-bit fingerprints, computed on byte buffers with numpy.

A word is a run of bytes other than space, tab, line feed, vertical tab, form feed and carriage return, with A-Z
lower-cased. Its fingerprint is a polynomial over its bytes (modulo 2^64) and its length, then mixed. Texts are
worked through in pieces of at most ``PIECE`` bytes cut between words, so memory doesn't grow with a text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

PIECE = 1 << 21
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective finaliser on uint64: every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class WordReader:
    """Holds the power tables, which grow to the longest piece seen."""

    def __init__(self) -> None:
        self.powers = self.inverses = np.ones(0, np.uint64)
        fold = np.arange(256, dtype=np.uint8)
        fold[65:91] += 32
        self.values = fold.astype(np.uint64) + np.uint64(1)
        self.blank = np.zeros(256, bool)
        self.blank[[32, 9, 10, 11, 12, 13]] = True

    def _tables(self, n: int) -> None:
        if len(self.powers) < n:
            n = max(n, PIECE + 1)
            steps = np.full(n, _BASE, np.uint64)
            back = np.full(n, _INVERSE, np.uint64)
            steps[0] = back[0] = 1
            self.powers, self.inverses = np.cumprod(steps), np.cumprod(back)

    def piece(self, data: np.ndarray, breaks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Fingerprints and start positions of the words in ``data``; ``breaks``: positions where a text begins."""
        n = len(data)
        if n == 0:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        self._tables(n + 1)
        inside = ~self.blank[data]
        first = inside.copy()
        first[1:] &= ~inside[:-1]
        begins = breaks[breaks < n]
        first[begins] = inside[begins]
        last = inside.copy()
        last[:-1] &= ~inside[1:] | first[1:]
        starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum(self.values[data] * self.powers[:n], out=sums[1:])
        raw = (sums[ends] - sums[starts]) * self.inverses[starts]
        return mix64(raw + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)), starts

    def texts(self, column: pa.Array) -> Iterator[tuple[int, np.ndarray]]:
        """(row, word fingerprints) for each row of a string column, in order; a null is an empty text."""
        column = column.cast(pa.large_string()) if column.type != pa.large_string() else column
        size = len(column)
        if size == 0:
            return
        ends = np.frombuffer(column.buffers()[1], np.int64, size + 1, column.offset * 8)
        held = column.buffers()[2]
        data = np.frombuffer(held, np.uint8) if held is not None else np.zeros(0, np.uint8)
        valid = column.is_valid().to_numpy(zero_copy_only=False)
        row = 0
        while row < size:
            if ends[row + 1] - ends[row] > PIECE:
                yield row, self._long(data[ends[row] : ends[row + 1]]) if valid[row] else np.zeros(0, np.uint64)
                row += 1
                continue
            stop = max(row + 1, int(np.searchsorted(ends, ends[row] + PIECE, "right")) - 1)
            offsets = ends[row : stop + 1] - ends[row]
            words, starts = self.piece(data[ends[row] : ends[stop]], offsets[:-1])
            cuts = np.searchsorted(starts, offsets)
            for k in range(row, stop):
                got = words[cuts[k - row] : cuts[k - row + 1]]
                yield k, got if valid[k] else got[:0]
            row = stop

    def _long(self, data: np.ndarray) -> np.ndarray:
        out, at = [], 0
        while at < len(data):
            end = min(len(data), at + PIECE)
            if end < len(data):  # back to a blank, or on to the next one
                gaps = np.flatnonzero(self.blank[data[at:end]])
                if len(gaps):
                    end = at + int(gaps[-1]) + 1
                else:
                    step = end
                    while step < len(data) and not self.blank[data[step : step + PIECE]].any():
                        step += PIECE
                    gaps = np.flatnonzero(self.blank[data[step : step + PIECE]]) if step < len(data) else []
                    end = step + int(gaps[0]) + 1 if len(gaps) else len(data)
            out.append(self.piece(data[at:end], np.zeros(1, np.int64))[0])
            at = end
        return np.concatenate(out) if out else np.zeros(0, np.uint64)


_ODD = np.array([0x8CB92BA72F3D8DD7, 0xA24BAED4963EE407, 0x9FB21C651E98DF25, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9], np.uint64)


def shingle_set(words: np.ndarray, width: int = 5) -> np.ndarray:
    """Sorted distinct fingerprints of the word ``width``-grams; fewer words count as one shingle, none as none."""
    n = len(words)
    if n == 0:
        return words
    take, lots = (width, n - width + 1) if n >= width else (n, 1)
    total = np.zeros(lots, np.uint64)
    for k in range(take):
        total += words[k : k + lots] * _ODD[k % 5] + np.uint64(k // 5 + take)
        total = (total << np.uint64(7)) | (total >> np.uint64(57))
    return np.unique(mix64(total))
