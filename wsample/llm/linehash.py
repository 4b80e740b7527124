"""Hashes of lines and of what is left of them without one unit, for whole batches of texts at once.

A line is what stands between line feeds; its words are what ASCII white space leaves.  The unit of an edit is a word for
lines of WORDS or more words, and a character for shorter ones, whose words one space joins.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa

#: From so many words on a line's units are words.
WORDS = 3
#: One character of a short line is at most a fifth of it: lines below this length have no near ones.
LEAST_CHARS = 5

_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_TABLE = np.random.Generator(np.random.Philox(20)).integers(0, 2**64, 65536, np.uint64)  # by place in the word and byte
_BASE = 0x9E3779B97F4A7C15
_BACK = pow(_BASE, -1, 2**64)
_SHORT = np.uint64(1 << 40)  # added to the lengths of lines that are counted in characters


def _powers(base: int, n: int) -> np.ndarray:
    return np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full(max(n, 1) - 1, base, np.uint64)]))


def mixed(x: np.ndarray, n) -> np.ndarray:
    x = x + np.asarray(n).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(29))


def within_runs(lengths: np.ndarray) -> np.ndarray:
    """0, 1, ... anew in each run."""
    return np.arange(lengths.sum()) - np.repeat(np.cumsum(lengths) - lengths, lengths)


@dataclass
class Lines:
    """The lines of a batch that are not blank.

    text and number: row and line; start and end: bytes from the first word to the last; size: units; check: a hash of the words.
    Units of line i: first[i] on in ``sums``, running sums of their hashes times powers.
    """

    data: np.ndarray
    text: np.ndarray
    number: np.ndarray
    start: np.ndarray
    end: np.ndarray
    check: np.ndarray
    size: np.ndarray
    short: np.ndarray
    first: np.ndarray
    sums: np.ndarray
    back: np.ndarray

    def piece(self, i: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Hash of the units lo to hi of lines i, wherever they stand in the line."""
        at = self.first[i]
        return (self.sums[at + hi] - self.sums[at + lo]) * self.back[at + lo]

    def lengths(self) -> np.ndarray:
        return self.size.astype(np.uint64) + self.short * _SHORT

    def whole(self) -> np.ndarray:
        every = np.arange(len(self.size))
        return mixed(self.piece(every, np.zeros_like(self.size), self.size), self.lengths())

    def comparable(self) -> np.ndarray:
        """Lines that may have near ones."""
        return ~self.short | (self.size >= LEAST_CHARS)

    def halves(self, i: np.ndarray) -> np.ndarray:
        """Four keys of each of the lines i; two lines one unit apart share one.

        Of lengths n and n, or n and n + 1: the first n // 2 units or the last n - n // 2 are untouched.
        """
        n, zero, out = self.size[i], np.zeros(len(i), np.int64), np.empty((len(i), 4), np.uint64)
        for k, less in enumerate((n - 1, n)):  # the other line may be the shorter one, or not
            tag = (less.astype(np.uint64) + self.short[i] * _SHORT) * np.uint64(4)
            out[:, 2 * k] = mixed(self.piece(i, zero, less // 2), tag + np.uint64(1))
            out[:, 2 * k + 1] = mixed(self.piece(i, n - (less - less // 2), n), tag + np.uint64(2))
        return out

    def rests(self, i: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(of, place, hash): what is left of lines i without each of their units, as the hash of a line."""
        n = self.size[i]
        of, place = np.repeat(np.arange(len(i)), n), within_runs(n)
        at = self.first[i][of]
        upto, after = self.sums[at + place] - self.sums[at], self.sums[at + n[of]] - self.sums[at + place + 1]
        return of, place, mixed((upto + after * np.uint64(_BACK)) * self.back[at], self.lengths()[i][of] - np.uint64(1))

    def texts(self, i: np.ndarray) -> pa.Array:
        data = self.data.tobytes()
        return pa.array([data[a:b] for a, b in zip(self.start[i].tolist(), self.end[i].tolist(), strict=True)], pa.binary()).cast(pa.string())


def _bytes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all texts, and where each starts and the last ends."""
    kind = np.int64 if pa.types.is_large_string(texts.type) else np.int32
    buffers = texts.buffers()
    edges = np.frombuffer(buffers[1], kind)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64) if len(texts) else np.zeros(1, np.int64)
    data = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None and buffers[2].size else np.zeros(0, np.uint8)
    return data[edges[0] : edges[-1]], edges - edges[0]


def _cut(data: np.ndarray, edges: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(starts, lengths, hashes, text) of the words."""
    full = ~_BLANK[data]
    before = np.concatenate([[False], full[:-1]]) if len(data) else full
    inner = edges[:-1][edges[:-1] < len(data)]
    if len(data):
        before[inner] = False  # a text starts a word, whatever the one before ends with
    solid = np.flatnonzero(full)
    rank = np.flatnonzero(~before[solid])
    starts = solid[rank]
    lengths = np.diff(np.concatenate([rank, [len(solid)]]))
    place = within_runs(lengths)
    value = _TABLE[(place & 255) << 8 | data[solid]]
    if len(place) and lengths.max() > 256:
        value = value * (2 * (place >> 8) + 1).astype(np.uint64)
    words = mixed(np.add.reduceat(value, rank), lengths) if len(rank) else np.zeros(0, np.uint64)
    held = np.diff(np.searchsorted(starts, edges))
    return starts, lengths, words, held


def shingles_of(texts: pa.Array, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the k-word shingles of texts with A-Z lower-cased, repeats included, and how many each text has; fewer words make one."""
    data, edges = _bytes(texts)
    _, _, words, held = _cut(_LOWER[data], edges)
    powers, back = _powers(_BASE, len(words) + 1), _powers(_BACK, len(words) + 1)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(words * powers[:-1], dtype=np.uint64)])
    counts = np.where(held > 0, np.maximum(held - k + 1, 1), 0)
    at = np.repeat(np.cumsum(held) - held, counts) + within_runs(counts)
    size = np.repeat(np.minimum(held, k), counts)
    return mixed((sums[at + size] - sums[at]) * back[at], size), counts


def lines_of(texts: pa.Array) -> Lines:
    """The lines of texts without nulls."""
    data, edges = _bytes(texts)
    starts, lengths, words, held = _cut(data, edges)
    breaks = np.flatnonzero(data == 10)
    text = np.repeat(np.arange(len(held)), held)
    passed = np.cumsum(np.bincount(np.searchsorted(starts, breaks), minlength=len(starts) + 1)[: len(starts)])
    number = passed - np.repeat(np.searchsorted(breaks, edges[:-1]), held)
    new = np.ones(len(starts), bool)
    new[1:] = (text[1:] != text[:-1]) | (number[1:] != number[:-1])
    first = np.flatnonzero(new)
    count = np.diff(np.concatenate([first, [len(starts)]]))
    check = np.add.reduceat(mixed(words, within_runs(count) + 1), first) if len(first) else np.zeros(0, np.uint64)
    start, end = starts[first], (starts + lengths)[first + count - 1] if len(first) else first
    short = count < WORDS
    size, units = count.astype(np.int64), words
    if short.any():
        units, size = _with_characters(data, words, first, count, short, starts, lengths)
    at = np.cumsum(size) - size
    powers = _powers(_BASE, len(units) + 1)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(units * powers[:-1], dtype=np.uint64)])
    return Lines(data, text[first], number[first], start, end, mixed(check, count), size, short, at, sums, _powers(_BACK, len(units) + 1))


def _with_characters(data, words, first, count, short, starts, lengths) -> tuple[np.ndarray, np.ndarray]:
    """Unit hashes and sizes, the short lines' units being characters."""
    raw, pieces, sizes, last = data.tobytes(), [], count.astype(np.int64), 0
    for i in np.flatnonzero(short).tolist():
        w = range(int(first[i]), int(first[i] + count[i]))
        line = b" ".join(raw[starts[k] : starts[k] + lengths[k]] for k in w).decode()
        points = np.frombuffer(line.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
        pieces += [words[last : first[i]], mixed(points, 77)]
        sizes[i], last = len(points), int(first[i] + count[i])
    return np.concatenate([*pieces, words[last:]]), sizes
