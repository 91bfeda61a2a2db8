"""Words of many texts at once, straight from Arrow string buffers.

All separators used here are ASCII, so a word of code points is a run of UTF-8 bytes and needs no decoding.
A word's hash is a polynomial over its bytes modulo 2^64, read off one prefix sum per batch; upper-case
A-Z hash as lower-case. Hashes are 64 bits wide: two words share one with probability about 2^-63.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

U64 = np.uint64
_BASE = U64(0x9E3779B97F4A7C15 | 1)
_BASE_INVERSE = U64(pow(int(_BASE), -1, 1 << 64))
#: Bytes handled together; a longer text makes a longer step of its own.
STEP_BYTES = 256 << 10

_CODES = np.random.default_rng(20240229).integers(1, 1 << 63, 256, dtype=np.uint64)
_CODES[65:91] = _CODES[97:123]

SPACES = np.zeros(256, bool)
SPACES[[0x20, *range(0x09, 0x0E)]] = True
NON_WORD = np.zeros(256, bool)
NON_WORD[:0x80] = True
for _c in b"0123456789abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ":
    NON_WORD[_c] = False

_powers = np.ones(1, U64)
_inverses = np.ones(1, U64)


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers, _inverses
    if len(_powers) < n:
        size = max(n, 1 << 16)
        for name, base in (("_powers", _BASE), ("_inverses", _BASE_INVERSE)):
            steps = np.full(size, base, U64)
            steps[0] = 1
            globals()[name] = np.multiply.accumulate(steps)
    return _powers, _inverses


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection that spreads every input bit over the 64 output bits."""
    h = h ^ (h >> U64(30))
    h = h * U64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> U64(27))
    h = h * U64(0x94D049BB133111EB)
    return h ^ (h >> U64(31))


class Step:
    """Bytes of consecutive texts, with the prefix sum their spans are hashed from."""

    def __init__(self, data: np.ndarray, bounds: np.ndarray):
        self.data, self.bounds = data, bounds
        powers, self._inverse = _power_tables(len(data) + 1)
        self.sums = np.zeros(len(data) + 1, U64)
        np.cumsum(_CODES[data] * powers[: len(data)], out=self.sums[1:])

    def span_hash(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * self._inverse[start])

    def words(self, separators: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Start and end byte of each word, and for each text the index of its first word (n + 1 numbers)."""
        inside = np.zeros(len(self.data) + 2, np.int8)
        inside[1:-1] = ~separators[self.data]
        edge = np.diff(inside)
        start, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        # texts are laid out with a separator byte between them, so no word crosses from one into the next
        return start, end, np.searchsorted(start, self.bounds)


def steps(column: pa.Array | pa.ChunkedArray, size: int = STEP_BYTES):
    """Yields (first row, Step) over a string column; null counts as an empty text."""
    chunks = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    first = 0
    for chunk in chunks:
        wide = pa.types.is_large_string(chunk.type)
        kind = np.int64 if wide else np.int32
        n = len(chunk)
        if not n:
            continue
        buffers = chunk.buffers()
        offsets = np.frombuffer(buffers[1], kind)[chunk.offset : chunk.offset + n + 1].astype(np.int64)
        lengths = np.diff(offsets)
        if chunk.null_count:
            lengths = np.where(np.asarray(chunk.is_null()), 0, lengths)
        raw = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None else np.zeros(0, np.uint8)
        at = 0
        while at < n:
            upto = max(at + 1, int(np.searchsorted(np.cumsum(lengths[at:] + 1), size, "right")) + at)
            own = lengths[at:upto]
            bounds = np.zeros(len(own) + 1, np.int64)
            np.cumsum(own + 1, out=bounds[1:])
            data = np.full(int(bounds[-1]), 0x20, np.uint8)
            for k in range(len(own)):
                o = offsets[at + k]
                data[bounds[k] : bounds[k] + own[k]] = raw[o : o + own[k]]
            yield first + at, Step(data, bounds)
            at = upto
        first += n


def hash_word(word: str) -> int:
    """The hash that ``Step`` gives the same word."""
    data = np.frombuffer(word.encode(), np.uint8)
    return int(Step(data, np.array([0, len(data)])).span_hash(np.array([0]), np.array([len(data)]))[0])


def per_text_sum(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sum of ``values`` (one per word) over each text."""
    total = np.zeros((len(values) + 1, *values.shape[1:]), np.float64)
    np.cumsum(values, axis=0, out=total[1:])
    return total[first[1:]] - total[first[:-1]]


def position_of(table: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Index of each key in a sorted table, or -1."""
    if not len(table):
        return np.full(len(keys), -1, np.int64)
    at = np.minimum(np.searchsorted(table, keys), len(table) - 1)
    return np.where(table[at] == keys, at, -1)
