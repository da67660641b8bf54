"""Vectorised text kernels over Arrow string columns.

Every kernel works on the UTF-8 bytes of a slice of rows at once, so the cost of
the Python interpreter is paid per slice and not per word.  Hashes are only used
to find candidates; the operators confirm them on the words themselves or with a
cryptographic digest.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

#: Bytes of text that one kernel call handles (a longer single text is still handled whole).
SLICE_BYTES = 2 << 20

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_STEP = 0xD1342543DE82EF95 | 1


class _Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, _U)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, 1 << 12)
            for name, b in (("up", self.base), ("down", self.inverse)):
                table = np.full(size, b, _U)
                table[0] = 1
                setattr(self, name, np.multiply.accumulate(table))
        return self.up[:n], self.down[:n]


_CACHE: dict[int, _Powers] = {}


def powers(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    if base not in _CACHE:
        _CACHE[base] = _Powers(base)
    return _CACHE[base].upto(n)


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijective finaliser, so that all bits of a hash depend on all its input bits."""
    h = h ^ (h >> _U(30))
    h = h * _U(0xBF58476D1CE4E5B9)
    h ^= h >> _U(27)
    h = h * _U(0x94D049BB133111EB)
    h ^= h >> _U(31)
    return h


def rolling(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, base: int) -> np.ndarray:
    """Polynomial hash of values[start:end] for every pair, in O(len(values) + pairs)."""
    up, down = powers(base, len(values) + 1)
    total = np.zeros(len(values) + 1, _U)
    np.cumsum(values * up[:-1], out=total[1:])
    return (total[ends] - total[starts]) * down[starts]


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts of a column end to end, and where each begins; null is empty."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    column = column.fill_null("").cast(pa.large_binary()) if column.type != pa.large_binary() else column
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    if data is None or not len(column):
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    return np.frombuffer(data, np.uint8)[offs[0] : offs[-1]], offs - offs[0]


def slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES):
    """Cut a batch into runs of rows with about `limit` bytes of text."""
    if not batch.num_rows:
        return
    lengths = np.diff(text_bytes(batch.column(column))[1])
    part = (np.cumsum(lengths) - lengths) // limit
    cuts = np.flatnonzero(np.diff(part)) + 1
    for a, b in zip([0, *cuts], [*cuts, batch.num_rows], strict=True):
        yield batch.slice(int(a), int(b - a))


class Words:
    """Where the words of a slice begin and end, document by document."""

    def __init__(self, data: np.ndarray, offs: np.ndarray, wordly: np.ndarray, fold: np.ndarray):
        self.data, self.offs = fold[data], offs
        inside = wordly[data]
        n = len(data)
        change = np.zeros(n + 1, bool)
        if n:
            change[0], change[-1] = inside[0], inside[-1]
            change[1:-1] = inside[1:] != inside[:-1]
        before = np.zeros(n + 1, bool)
        before[1:] = inside
        starts = np.zeros(n + 1, bool)
        starts[:-1] = inside & ~before[:-1]
        ends = before & ~np.append(inside, False)
        edge = offs[(offs > 0) & (offs < n)]
        both = edge[inside[edge] & inside[edge - 1]]
        starts[both] = ends[both] = True
        self.starts, self.ends = np.flatnonzero(starts), np.flatnonzero(ends)
        #: Index of the first word of each document, and one past the last.
        self.first = np.searchsorted(self.starts, offs)

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def hashes(self) -> np.ndarray:
        h = rolling(self.data.astype(_U) + _U(1), self.starts, self.ends, _BASE)
        return mixed(h + (self.ends - self.starts).astype(_U) * _U(_STEP))

    def runs(self, length: int, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(start word, hash) of each run of `length` words that stays inside a document."""
        n = len(hashes)
        if n < length:
            return np.zeros(0, np.int64), np.zeros(0, _U)
        begin = np.arange(n - length + 1)
        end_of = np.repeat(self.first[1:], self.counts)
        begin = begin[begin + length <= end_of[begin]]
        return begin, mixed(rolling(hashes, begin, begin + length, _STEP))


def table(inside, lower: bool) -> tuple[np.ndarray, np.ndarray]:
    """Lookup tables over byte values: is it part of a word, and its folded value."""
    fold = np.arange(256, dtype=np.uint8)
    if lower:
        fold[0x41:0x5B] += 32
    return np.array([bool(inside(int(b))) for b in fold]), fold


#: Letters, digits and everything beyond ASCII, lower-cased.
ALNUM = table(lambda b: 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80, True)
#: Everything between ASCII white space, unchanged.
SPACED = table(lambda b: b != 0x20 and not 0x09 <= b <= 0x0D, False)


def alnum_words(data: np.ndarray, offs: np.ndarray) -> Words:
    return Words(data, offs, *ALNUM)


def spaced_words(data: np.ndarray, offs: np.ndarray) -> Words:
    return Words(data, offs, *SPACED)


def minimizers(hashes: np.ndarray, gram: int, window: int) -> np.ndarray:
    """For each run of `window` words, the first word of its smallest run of `gram` words.

    `hashes` are word hashes.  Equal runs of words give equal choices relative to
    their start, wherever they stand: order is by the upper half of the gram's hash
    and then by position.  Runs across documents are given too; callers drop them.
    """
    n = len(hashes) - gram + 1
    width = window - gram + 1
    m = n - width + 1
    if m <= 0:
        return np.zeros(0, np.int64)
    begin = np.arange(n)
    keys = mixed(rolling(hashes, begin, begin + gram, _BASE)) & ~_U(0xFFFFFFFF) | begin.astype(_U)
    blocks = -(-n // width)
    padded = np.full(blocks * width, np.iinfo(np.uint64).max, _U)
    padded[:n] = keys
    grid = padded.reshape(blocks, width)
    left = np.minimum.accumulate(grid, axis=1).ravel()
    right = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    best = np.minimum(right[:m], left[width - 1 : width - 1 + m])
    return (best & _U(0xFFFFFFFF)).astype(np.int64)


class Probe:
    """Which of many hashes are in a sorted set: a bit table first, then a search."""

    def __init__(self, members: np.ndarray, bits: int = 22):
        self.members, self.shift = members, _U(64 - bits)
        self.seen = np.zeros(1 << bits, bool)
        self.seen[(members >> self.shift).astype(np.int64)] = True

    def find(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(indexes into hashes, indexes into members) of all that are members."""
        at = np.flatnonzero(self.seen[(hashes >> self.shift).astype(np.int64)])
        if not len(at):
            return at, at
        where = np.minimum(np.searchsorted(self.members, hashes[at]), len(self.members) - 1)
        good = self.members[where] == hashes[at]
        return at[good], where[good]
